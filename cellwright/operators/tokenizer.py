"""Tokenizer: word counts, byte-pair merges on what the domain pre-tokenizer leaves over, vocabulary, ids, diagnostics."""

from __future__ import annotations

import functools
import heapq
from collections import Counter, defaultdict

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellwright.functions import lexing
from cellwright.functions.dialect import SPARK

SPECIALS = ("<pad>", "<eos>", "<unk>", "<mask>")
MARKS = list("()[]{},;:!\"'#$%&*+-/<=>?@\\^_`|~. \t\n")


def word_counts(df: DataFrame, text: str, lowercase: bool = True, times: str | None = None) -> DataFrame:
    """word, freq of the letter runs that BPE sees. Partial counts collapse frequent words before the shuffle. times: a
    column with the number of texts that a row stands for."""
    own = F.explode(F.expr(SPARK.rx_all(f"lower({text})" if lowercase else text, lexing.RUN))).alias("word")
    freq = (F.sum(times) if times else F.count(F.lit(1))).alias("freq")
    counted = df.select(own, *([times] if times else [])).groupBy("word").agg(freq)
    return counted.where(F.expr(lexing.is_word(SPARK, "word")))


def spelled(words: DataFrame) -> DataFrame:
    """word, freq, w: the word with each symbol in angle brackets, so that merging a pair is a string replacement."""
    return words.withColumn("w", F.regexp_replace("word", "(?s:(.))", "<$1>"))


def pair_counts(state: DataFrame) -> DataFrame:
    """left, right, n: adjacent symbols, weighted by word frequency."""
    syms = F.expr("split(substring(w, 2, length(w) - 2), '><')")
    pairs = state.select("freq", syms.alias("s")).where("size(s) > 1").select("freq", F.explode(F.expr("transform(sequence(1, size(s) - 1), i -> struct(get(s, i - 1) as left, get(s, i) as right))")).alias("p"))
    return pairs.groupBy("p.left", "p.right").agg(F.sum("freq").alias("n"))


def bpe_rounds(words: DataFrame, rounds: int) -> list[tuple[str, str, int]]:
    """The first merges, one aggregate and one top row a round; for large vocabularies see bpe_train."""
    state, out = spelled(words), []
    for _ in range(rounds):
        top = pair_counts(state).orderBy(F.desc("n"), "left", "right").limit(1).collect()
        if not top:
            break
        a, b, n = top[0]["left"], top[0]["right"], top[0]["n"]
        out.append((a, b, n))
        state = state.withColumn("w", F.replace("w", F.lit(f"<{a}><{b}>"), F.lit(f"<{a}{b}>")))
    return out


def train_merges(words: list[tuple[str, int]], merges: int) -> list[tuple[str, str, int]]:
    """Merges over word types with frequencies: the most frequent pair first, ties to the smaller pair. Counts are kept up
    to date for the words that a merge touches; stale heap entries are dropped when met."""
    seqs = [list(w) for w, _ in words]
    count: dict = defaultdict(int)
    where: dict = defaultdict(set)
    for i, (s, (_, f)) in enumerate(zip(seqs, words)):
        for p in zip(s, s[1:]):
            count[p] += f
            where[p].add(i)
    heap = [(-n, p) for p, n in count.items()]
    heapq.heapify(heap)
    out = []
    while heap and len(out) < merges:
        n, pair = heapq.heappop(heap)
        if count.get(pair, 0) != -n or n == 0:
            continue
        out.append((*pair, -n))
        changed = set()
        for i in where.pop(pair, ()):
            s, f = seqs[i], words[i][1]
            for p in zip(s, s[1:]):
                count[p] -= f
                changed.add(p)
            k, new = 0, []
            while k < len(s):
                if k + 1 < len(s) and s[k] == pair[0] and s[k + 1] == pair[1]:
                    new.append(s[k] + s[k + 1])
                    k += 2
                else:
                    new.append(s[k])
                    k += 1
            seqs[i] = new
            for p in zip(new, new[1:]):
                count[p] += f
                where[p].add(i)
                changed.add(p)
        count.pop(pair, None)
        for p in changed:
            if count.get(p, 0) > 0:
                heapq.heappush(heap, (-count[p], p))
    return out


def train_merges_arrays(flat, lens, freq, merges: int) -> list[tuple[str, str, int]]:
    """As train_merges, over words as arrays: all characters one after another, characters a word, frequencies.

    A word keeps its place; what a merge shortens is filled up with -1, and one place after each word is -1 from the start,
    so a pair is found by comparing the whole array with itself shifted. Counts are taken anew for the words it touches."""
    import numpy as np

    from cellwright.llm.common import ragged_index

    lens, freq = np.asarray(lens, np.int64), np.asarray(freq, np.int64)
    letters, own = np.unique(flat, return_inverse=True)
    text = [chr(c) for c in letters.tolist()]
    number = {c: i for i, c in enumerate(text)}
    starts = np.cumsum(lens + 1) - lens - 1
    flat = np.full(int((lens + 1).sum()), -1, np.int32)
    flat[ragged_index(starts, lens)] = own
    del own
    count: dict = defaultdict(int)
    heap, out = [], []

    def change(seq, words, sign: int) -> set:
        """Adds the pairs of some words, their symbols one after another (-1 after each), to the counts."""
        codes = (seq[:-1].astype(np.int64) << 32) | seq[1:].astype(np.int64)
        inside = (seq[:-1] >= 0) & (seq[1:] >= 0)
        pairs, at = np.unique(codes[inside], return_inverse=True)
        n = np.bincount(at, freq[words[:-1][inside]], len(pairs))  # whole numbers below 2**53
        for p, x in zip(pairs.tolist(), n.tolist()):
            count[p] += sign * round(x)
        return set(pairs.tolist())

    def put(codes) -> None:
        for p in codes:
            if count[p] > 0:
                heapq.heappush(heap, (-count[p], (text[p >> 32], text[p & 0xFFFFFFFF]), p))

    for at in range(0, len(lens), 500_000):  # in parts, for memory
        rows = np.arange(at, min(at + 500_000, len(lens)))
        change(flat[starts[at] : starts[rows[-1]] + lens[rows[-1]] + 1], np.repeat(rows, lens[rows] + 1), 1)
    put(list(count))
    while heap and len(out) < merges:
        n, _, pair = heapq.heappop(heap)
        if count.get(pair, 0) != -n or n == 0:
            continue
        a, b = pair >> 32, pair & 0xFFFFFFFF
        out.append((text[a], text[b], -n))
        made = text[a] + text[b]
        new = number.setdefault(made, len(text))
        if new == len(text):
            text.append(made)
        hits = np.flatnonzero(flat == a)
        hits = hits[flat[hits + 1] == b]
        if a == b and len(hits):  # of a run, every other one from its left end
            first = np.concatenate([[True], np.diff(hits) != 1])
            hits = hits[(np.arange(len(hits)) - np.maximum.accumulate(np.where(first, np.arange(len(hits)), 0))) % 2 == 0]
        words = np.unique(np.searchsorted(starts, hits, side="right") - 1)
        size = lens[words]
        places = ragged_index(starts[words], size + 1)
        owner = np.repeat(words, size + 1)
        changed = change(flat[places], owner, -1)
        flat[hits] = new
        flat[hits + 1] = -2
        seq = flat[places]
        stay = seq != -2
        seq, owner = seq[stay], owner[stay]
        changed |= change(seq, owner, 1)
        lens[words] = np.bincount(np.searchsorted(words, owner), minlength=len(words)) - 1
        flat[places] = -1
        flat[ragged_index(starts[words], lens[words] + 1)] = seq
        count.pop(pair, None)
        put(changed - {pair})
    return out


def independent_head(pairs: list[tuple[str, str, int]]) -> int:
    """How many of the pairs, most frequent first (ties to the smaller pair), can be merged at once with the result of
    merging one after another, if the list holds all pairs of every count in it but the last.

    A merge changes the counts of pairs that share a symbol with it, and new pairs are no more frequent than those. So
    the head ends before a pair that shares a symbol with one before it; and where pairs of one count follow each other,
    before a count at which any pair shares a symbol with the head, as ties go by symbols that a merge makes longer."""
    taken, n, k = set(), 0, 0
    while k < len(pairs):
        end = k
        while end < len(pairs) and pairs[end][2] == pairs[k][2]:
            end += 1
        level = pairs[k:end]
        clash = any(a in taken or b in taken for a, b, _ in level)
        own = Counter(x for a, b, _ in level for x in {a, b})
        if clash or end == len(pairs) or any(c > 1 for c in own.values()):
            return n if n else 1
        taken.update(own)
        n += len(level)
        k = end
    return max(n, 1)


def bpe_train_distributed(words: DataFrame, merges: int, at_once: int = 2000, save=None) -> list[tuple[str, str, int]]:
    """Merges over any number of word types: pair counts are summed by Spark each round, and a round merges the head of the
    list that does not depend on itself. The result is that of train_merges. save: writes the words' state every few
    rounds, so that lineage stays short; a checkpoint in the shared folder by default."""
    state, out, rounds = spelled(words).select("freq", "w"), [], 0
    while len(out) < merges:
        top = pair_counts(state).where("n > 0").orderBy(F.desc("n"), "left", "right").limit(at_once + 1).collect()
        if not top:
            break
        pairs = [(r["left"], r["right"], r["n"]) for r in top]
        # what the limit cuts off may belong to the last count
        n = len(pairs) if len(pairs) == 1 else independent_head(pairs if len(pairs) > at_once else [*pairs, ("", "", 0)])
        head = pairs[: min(n, merges - len(out))]
        out += head
        for a, b, _ in head:
            state = state.withColumn("w", F.replace("w", F.lit(f"<{a}><{b}>"), F.lit(f"<{a}{b}>")))
        rounds += 1
        if rounds % 8 == 0:
            state = (save or (lambda x: x.checkpoint()))(state)
    return out


#: the published number of tokens
VOCABULARY = 16_000


def _symbols(words: list[str]):
    """Characters of all words as numbers, where a word begins, and the codes of neighbours (-1 across words)."""
    import numpy as np

    flat = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    ends = np.cumsum([len(w) for w in words])
    codes = (flat[:-1] << 32) | flat[1:]
    inner = ends[:-1]
    codes[inner[(inner > 0) & (inner < len(flat))] - 1] = -1
    return flat, ends, codes


def neighbours(words: DataFrame) -> dict[int, int]:
    """Code of two adjacent characters -> occurrences, weighted by word frequency; bounded by the alphabet."""

    def run(batches):
        import numpy as np
        import pandas as pd

        for b in batches:
            _, _, codes = _symbols(list(b["word"]))
            freq = np.repeat(b["freq"].to_numpy(np.int64), b["word"].str.len().to_numpy(np.int64))[: len(codes)]
            own, at = np.unique(codes, return_inverse=True)
            n = np.zeros(len(own), np.int64)
            np.add.at(n, at, freq)
            yield pd.DataFrame({"code": own[own >= 0], "n": n[own >= 0]})

    rows = words.select("word", "freq").mapInPandas(run, "code long, n long").groupBy("code").agg(F.sum("n").alias("n"))
    return {r["code"]: r["n"] for r in rows.collect()}


def cut_words(words: DataFrame, joined: set[int]) -> DataFrame:
    """word, freq: the words cut between all neighbours but those joined, pieces of one character left out, equal ones summed."""
    shared = words.sparkSession.sparkContext.broadcast(sorted(joined))

    def run(batches):
        import numpy as np
        import pandas as pd

        keep, held = np.array(shared.value, np.int64), Counter()
        for b in batches:
            texts = list(b["word"])
            flat, ends, codes = _symbols(texts)
            text = "".join(texts)
            cuts = np.flatnonzero(~np.isin(codes, keep)) + 1 if len(codes) else np.zeros(0, np.int64)
            starts, stops = np.concatenate([[0], cuts]), np.concatenate([cuts, [len(flat)]])
            long = stops - starts > 1
            starts, stops = starts[long], stops[long]
            freq = b["freq"].to_numpy(np.int64)[np.searchsorted(ends, starts, side="right")]
            for i, j, n in zip(starts.tolist(), stops.tolist(), freq.tolist()):
                held[text[i:j]] += n
            if len(held) > 200_000:
                yield pd.DataFrame({"word": list(held), "freq": list(held.values())})
                held.clear()
        if held:
            yield pd.DataFrame({"word": list(held), "freq": list(held.values())})

    return words.select("word", "freq").mapInPandas(run, "word string, freq long").groupBy("word").agg(F.sum("freq").alias("freq"))


def bpe_train(words: DataFrame, merges: int, in_one_task: int = 20_000_000, whole: int = 20_000) -> DataFrame:
    """rank, left, right, freq. Up to in_one_task word types are trained in one task, with counts kept up to date for each
    merge; beyond that, in rounds over distributed counts. Both read all types and give the same merges.

    More than `whole` types are cut first: a merge across two characters is no more frequent than these are beside each
    other, so where that is rarer than the last merge, no merge crosses. The bound is a guess, checked against the last
    merge and lowered until it holds; where cutting leaves over a quarter of the types, the whole words are trained."""
    schema = "rank int, left string, right string, freq long"
    words = words.where("word IS NOT NULL").persist()
    if (types := words.count()) > whole:
        beside = neighbours(words)
        levels = sorted(beside.values(), reverse=True)
        bound = levels[min(merges, len(levels)) - 1] if levels else 0
        while bound > 1:
            cut = cut_words(words, {c for c, n in beside.items() if n >= bound}).persist()
            pieces = cut.count()
            if pieces > types // 4:  # little is saved, and a lower bound cuts less still
                cut.unpersist()
                break
            got = _train(cut, merges, in_one_task, pieces, schema).orderBy("rank").collect()
            cut.unpersist()
            if len(got) == merges and got[-1]["freq"] >= bound:
                words.unpersist()
                return words.sparkSession.createDataFrame(got, schema)
            bound = min(bound - 1, max(bound // 3, got[-1]["freq"] if got and len(got) == merges else 0))
    return _train(words, merges, in_one_task, types, schema)


def _train(words: DataFrame, merges: int, in_one_task: int, types: int, schema: str) -> DataFrame:
    if types > in_one_task:
        return words.sparkSession.createDataFrame([(i, *m) for i, m in enumerate(bpe_train_distributed(words, merges))], schema)

    def run(table):
        import numpy as np
        import pyarrow as pa
        import pyarrow.compute as pc

        chars = [np.zeros(0, np.uint32)]
        for c in table.column("word").chunks:
            for at in range(0, len(c), 100_000):
                chars.append(np.frombuffer("".join(c.slice(at, 100_000).to_pylist()).encode("utf-32-le"), np.uint32))
        lens, freq = (x.to_numpy() for x in (pc.utf8_length(table.column("word")), table.column("freq")))
        rows = train_merges_arrays(np.concatenate(chars), lens, freq, merges)
        kinds = (pa.int32(), pa.string(), pa.string(), pa.int64())
        return pa.table({k: pa.array([(i, *r)[j] for i, r in enumerate(rows)], kind) for j, (k, kind) in enumerate(zip(("rank", "left", "right", "freq"), kinds))})

    return words.select("word", "freq").groupBy().applyInArrow(run, schema)


def _characters(column):
    """Characters of all texts of an Arrow column as numbers, and where each text ends; nulls left out."""
    import numpy as np
    import pyarrow as pa

    column = column.drop_null().cast(pa.large_string())
    if not len(column):
        return np.zeros(0, np.int32), np.zeros(0, np.int64)
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(data or b"", np.uint8)[offsets[0] : offsets[-1]]
    ends = offsets[1:] - offsets[0]
    if data.max(initial=0) < 128:
        return data.astype(np.int32), ends
    before = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])  # characters begun up to each byte
    return np.frombuffer(data.tobytes().decode().encode("utf-32-le"), np.int32), before[ends]


@functools.lru_cache(2)
def _powers(bits: int):
    """The first 2**bits powers modulo 2**64 of an odd number and of its inverse."""
    import numpy as np

    base = 0x9E3779B97F4A7C15
    return [np.multiply.accumulate(np.concatenate([np.ones(1, np.uint64), np.full((1 << bits) - 1, b, np.uint64)])) for b in (base, pow(base, -1, 1 << 64))]


def _tally(flat, starts, stops) -> Counter:
    """Text -> occurrences, of parts of one or more characters that follow each other. Parts are grouped by a polynomial hash
    of 64 bits, the difference of two running sums shifted to the part's start; each part is compared with the first one of
    its group, so that the counts are exact."""
    import numpy as np

    def text(i, j):
        return flat[i:j].astype("<u4").tobytes().decode("utf-32-le")

    if not len(starts):
        return Counter()
    up, down = _powers(len(flat).bit_length())
    sums = np.zeros(len(flat) + 1, np.uint64)
    np.cumsum((flat + 1).astype(np.uint64) * up[: len(flat)], out=sums[1:])
    hashed = (sums[stops] - sums[starts]) * down[starts]
    _, first, group, n = np.unique(hashed, return_index=True, return_inverse=True, return_counts=True)
    same = first[group]
    lens = stops - starts
    if (lens == lens[same]).all():
        ends = np.cumsum(lens)
        place = np.arange(ends[-1])
        own = flat if ends[-1] == len(flat) else flat[place + np.repeat(starts - ends + lens, lens)]
        if (own == flat[place + np.repeat(starts[same] - ends + lens, lens)]).all():
            return Counter({text(i, j): x for i, j, x in zip(starts[first].tolist(), stops[first].tolist(), n.tolist())})
    return Counter(map(text, starts.tolist(), stops.tolist()))


def text_counts(texts: DataFrame, merges: int, at_once: int = 2_000_000, slack: int = 2) -> DataFrame:
    """kind, text, n, cut: what BPE needs to know of whole texts (column word), in one pass that shuffles no text.

    pair: two adjacent characters. cut: whether texts were cut between them anywhere.
    piece: what is left of the texts, without pieces of one character. Each part of at_once characters is cut between its
    rarer neighbours, those below 1/slack of its merges-th pair; all counts are exact, whatever was cut.
    stem: a text with 0 for each run of digits. No letter run touches a digit: word_counts of stems are those of the texts."""

    def parts(batches):
        import numpy as np

        held, size = [], 0
        for b in batches:
            held.append(_characters(b.column(0)))
            size += len(held[-1][0])
            if size >= at_once:
                yield np.concatenate([f for f, _ in held]), np.concatenate([[len(f)] for f, _ in held]), [e for _, e in held]
                held, size = [], 0
        if held:
            yield np.concatenate([f for f, _ in held]), np.concatenate([[len(f)] for f, _ in held]), [e for _, e in held]

    def run(batches):
        import numpy as np
        import pyarrow as pa

        def out(kind, counts, cut=None):
            cut = [x in cut for x in counts] if cut is not None else [False] * len(counts)
            kinds = (pa.string(), pa.string(), pa.int64(), pa.bool_())
            return pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(([kind] * len(counts), list(counts), list(counts.values()), cut), kinds)], ["kind", "text", "n", "cut"])

        pairs, rare, held = Counter(), set(), {"piece": Counter(), "stem": Counter()}
        for flat, sizes, ends in parts(batches):
            ends = np.concatenate([e + at for e, at in zip(ends, np.cumsum(sizes) - sizes)])
            last = np.zeros(len(flat) + 1, bool)  # whether a text ends before a place
            last[ends] = True
            digit = (flat >= 48) & (flat <= 57)
            stay = np.ones(len(flat), bool)
            stay[1:] = ~digit[1:] | ~digit[:-1] | last[1:-1]
            stops = np.concatenate([[0], np.cumsum(stay)])[ends]
            starts = np.concatenate([[0], stops])[:-1]
            some = stops > starts
            held["stem"] += _tally(np.where(digit, 48, flat)[stay], starts[some], stops[some])

            seen = np.zeros(int(flat.max(initial=0)) + 1, bool)
            seen[flat] = True
            letters, own = np.flatnonzero(seen), (np.cumsum(seen) - 1)[flat]
            code, area = own[:-1] * len(letters) + own[1:], len(letters) ** 2
            code[last[1:-1]] = area  # no pair
            if area <= 1 << 22:
                known, n = np.arange(area + 1), np.bincount(code, minlength=area + 1)
            else:
                known, code = np.unique(code, return_inverse=True)
                n = np.bincount(code)
            n[known == area] = 0
            some = n > 0
            keep = n * slack >= (np.sort(n[some])[-min(merges, some.sum())] if some.any() else 1)
            cuts = np.flatnonzero(~keep[code]) + 1
            starts, stops = np.concatenate([[0], cuts]), np.concatenate([cuts, [len(flat)]])
            long = stops - starts > 1
            held["piece"] += _tally(flat, starts[long], stops[long])
            for c, x, k in zip(known[some].tolist(), n[some].tolist(), keep[some].tolist()):
                pair = chr(letters[c // len(letters)]) + chr(letters[c % len(letters)])
                pairs[pair] += x
                if not k:
                    rare.add(pair)
            for kind, counts in held.items():
                if len(counts) > 200_000:
                    yield out(kind, counts)
                    counts.clear()
        for kind, counts in held.items():
            yield out(kind, counts)
        yield out("pair", pairs, rare)

    counted = texts.select("word").mapInArrow(run, "kind string, text string, n long, cut boolean")
    return counted.groupBy("kind", "text").agg(F.sum("n").alias("n"), F.max("cut").alias("cut"))


def bpe_train_counted(texts: DataFrame, counts: DataFrame, merges: int) -> DataFrame:
    """As bpe_train over whole texts (column word), from their text_counts for as many merges. A merge across two characters
    is no more frequent than these are beside each other; so where the last merge is more frequent than all pairs that were
    cut, no merge crosses a cut. Where it is not, the texts themselves are counted and trained."""
    cut = counts.where("kind = 'pair' AND cut").agg(F.max("n")).first()[0] or 0
    pieces = counts.where("kind = 'piece'").select(F.col("text").alias("word"), F.col("n").alias("freq"))
    got = bpe_train(pieces, merges).orderBy("rank").collect()
    if cut == 0 or len(got) == merges and got[-1]["freq"] > cut:
        return texts.sparkSession.createDataFrame(got, "rank int, left string, right string, freq long")
    return bpe_train(texts.groupBy("word").agg(F.count(F.lit(1)).alias("freq")), merges)


def encode_word(word: str, rank: dict[tuple[str, str], int]) -> list[str]:
    s = list(word)
    while len(s) > 1:
        best = min(zip(s, s[1:]), key=lambda p: rank.get(p, 1 << 60))
        if best not in rank:
            break
        k, new = 0, []
        while k < len(s):
            hit = k + 1 < len(s) and (s[k], s[k + 1]) == best
            new.append(s[k] + s[k + 1] if hit else s[k])
            k += 1 + hit
        s = new
    return s


def bpe_encode(words: DataFrame, merges: DataFrame) -> DataFrame:
    """word, pieces for distinct words; join back, never encode an occurrence twice. Merges are bounded by the vocabulary."""
    rank = words.sparkSession.sparkContext.broadcast({(r["left"], r["right"]): r["rank"] for r in merges.collect()})

    def run(batches):
        import pyarrow as pa

        for b in batches:
            w = b.column(0)
            yield pa.RecordBatch.from_arrays([w, pa.array([encode_word(x, rank.value) for x in w.to_pylist()], pa.list_(pa.string()))], ["word", "pieces"])

    return words.select("word").distinct().mapInArrow(run, "word string, pieces array<string>")


def build_vocab(merges: DataFrame, letters: list[str], size: int = VOCABULARY) -> DataFrame:
    """id, token, class: specials, marks, digits, functions, letters, then merged pieces by rank; never above size."""
    spark = merges.sparkSession
    fixed = [(t, "special") for t in SPECIALS] + [(t, "mark") for t in MARKS] + [(str(i), "digit") for i in range(10)]
    fixed += [(f.lower(), "function") for f in lexing.FUNCTIONS] + [(c, "letter") for c in letters]
    seen, rows = set(), []
    for t, c in fixed + [(r["left"] + r["right"], "piece") for r in merges.orderBy("rank").collect()]:
        if t not in seen and len(rows) < size:
            seen.add(t)
            rows.append((len(rows), t, c))
    return spark.createDataFrame(rows, "id int, token string, class string")


def encode_ids(df: DataFrame, text: str, merges: DataFrame, vocab: DataFrame, key: str = "formula_id") -> DataFrame:
    """key, ids: pieces of each text in order; distinct words are encoded once and joined back."""
    pre = df.select(key, F.posexplode(F.expr(lexing.pretokens(SPARK, text))).alias("p", "word"))
    pre = pre.withColumn("is_word", F.expr(lexing.is_word(SPARK, "word")))
    pieces = bpe_encode(pre.where("is_word").select("word"), merges)
    joined = pre.join(pieces, "word", "left").select(key, "p", F.posexplode(F.when(F.col("is_word"), F.col("pieces")).otherwise(F.array("word"))).alias("q", "token"))
    unk = SPECIALS.index("<unk>")
    ids = joined.join(F.broadcast(vocab), "token", "left").select(key, "p", "q", F.coalesce("id", F.lit(unk)).alias("id"))
    return ids.groupBy(key).agg(F.expr("transform(array_sort(collect_list(struct(p, q, id))), x -> x.id)").alias("ids"))


def decode_ids(ids: DataFrame, vocab: DataFrame, key: str = "formula_id") -> DataFrame:
    """key, text."""
    flat = ids.select(key, F.posexplode("ids").alias("p", "id")).join(F.broadcast(vocab), "id", "left")
    return flat.groupBy(key).agg(F.expr("array_join(transform(array_sort(collect_list(struct(p, token))), x -> x.token), '')").alias("text"))


def tokenizer_report(df: DataFrame, text: str = "formula") -> DataFrame:
    """Tokens a formula, characters a token, share of BPE words, and their number."""
    t = df.select(F.length(text).alias("chars"), F.expr(lexing.pretokens(SPARK, text)).alias("t"))
    t = t.select("chars", F.size("t").alias("n"), F.expr(f"size(filter(t, y -> {lexing.is_word(SPARK, 'y')}))").alias("words"))
    return t.agg(F.count(F.lit(1)).alias("formulas"), F.sum("n").cast("long").alias("tokens"), F.round(F.avg("n"), 6).alias("tokens_each"), F.round(F.sum("chars") / F.sum("n"), 6).alias("chars_each"), F.round(F.sum("words") / F.sum("n"), 6).alias("word_share"))


def diagnostics(df: DataFrame, text: str = "formula") -> DataFrame:
    """Quantiles of the number of tokens, tokens that cross a mark (none by construction), share of single characters beyond
    the fixed tokens and letters, and characters for each token of the model's input."""
    t = lexing.with_tokens(df, text).select(F.length(text).alias("chars"), F.expr(lexing.pretokens(SPARK, text)).alias("p"), F.expr(lexing.model_tokens(SPARK, "tokens", "kinds")).alias("m"))
    crossing = F.expr(r"size(filter(p, x -> length(x) > 1 and x rlike '[\\p{L}0-9]' and x rlike '[^\\p{L}0-9]'))")
    unknown = F.expr("size(filter(p, x -> x rlike '^[^ -~]$'))")
    n = F.size("p")
    return t.select("chars", n.alias("n"), crossing.alias("x"), unknown.alias("u"), F.expr("size(flatten(m))").alias("m")).agg(
        F.count(F.lit(1)).alias("formulas"),
        F.expr("percentile_disc(0.5) within group (order by n)").cast("long").alias("half"),
        F.expr("percentile_disc(0.9) within group (order by n)").cast("long").alias("nine_tenths"),
        F.max("n").cast("long").alias("longest"),
        F.sum("x").cast("long").alias("crossing"),
        F.round(F.sum("u") / F.sum("n"), 6).alias("unknown"),
        F.round(F.sum("chars") / F.sum("m"), 6).alias("chars_each_model_token"),
    )


def case_fragmentation(df: DataFrame, text: str = "formula") -> DataFrame:
    """word (lower case), spellings: tokens that a case-sensitive vocabulary would keep apart."""
    w = df.select(F.explode(F.expr(lexing.pretokens(SPARK, text, False))).alias("t")).where(F.col("t").rlike("^[A-Za-z]"))
    return w.groupBy(F.lower("t").alias("word")).agg(F.countDistinct("t").alias("spellings"), F.count(F.lit(1)).alias("n"))
