"""Each operator against a brute-force version, on rows with nulls, empty and long texts, ties, copies and clashing columns."""

import hashlib
import random
import re
import zlib

import numpy as np
import pytest
import xxhash

public_tokenizers = pytest.importorskip("public_tokenizers")
BYTES, WORDS = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("word_bpe_49k.json")
PATTERN = public_tokenizers.PATTERN
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, keep_id string, h int, component_id int, vslot int, block int"


def texts() -> list[tuple]:
    rng = random.Random(4)
    words = ["Alpha", "beta", "Straße", "don't", "naïve", "x1y2", "日本語", "...", "é", "gamma,"]
    para = " ".join(rng.choice(words) + str(rng.randrange(99)) for _ in range(60))
    out = [None, "", " ", "a", "a", "A  a\n\tb ", "aaaa" * 400, para, para, para + " tail", "head " + para, para.replace("beta", "BETA"), "  lead", "<|endoftext|> x  <|endoftext|>", "ab " * 3000, "\x1c \x85 y", "line\n" * 200]
    out += [" ".join(rng.choice(words) for _ in range(rng.randrange(1, 400))) for _ in range(25)]
    return [(i + 10, t) for i, t in enumerate(out)] + [(12, " "), (None, "no id"), (None, para)]


@pytest.fixture(scope="module")
def rows():
    return texts()


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame([(i, t, "xx", "s", 0, "clash", 1, 2, 3, 4) for i, t in rows], SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def key(r):
    return tuple((x is None, str(type(x)), x) for x in r)


def same(got, want):
    assert sorted(map(key, got)) == sorted(map(key, want))


def library(path):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


def test_exact_dedup(docs, none, rows):
    from cellwright.llm.exact_dedup import exact_groups

    norm = [re.sub(r"[\x20\x09-\x0D]+", " ", t or "") for _, t in rows]
    want = []
    for (i, _), n in zip(rows, norm):
        own = [j for (j, _), m in zip(rows, norm) if m == n]
        ids = [j for j in own if j is not None]
        keep = min(ids) if ids else None
        want.append((i, keep, len(own), i == keep, hashlib.sha256(n.encode()).hexdigest()))
    same([tuple(r) for r in exact_groups(docs).collect()], want)
    same([tuple(r) for r in exact_groups(docs, capacity=300).collect()], want)
    assert exact_groups(none).count() == 0


def test_directory_splits(spark):
    from cellwright.llm.exact_dedup import build_directory

    rng = np.random.default_rng(3)
    h = np.concatenate([rng.integers(-(1 << 63), (1 << 63) - 1, 400), 77 << 40 | rng.integers(0, 1 << 40, 40)])  # forty share 24 bits
    frame = spark.createDataFrame([(int(x), 10) for x in h] + [(1234567, 10_000)], "h long, load long")
    d = build_directory(frame, 100)
    assert len(d.entries) == 1 << d.depth and d.depth > 24 and set(d.entries) == set(range(len(d.local)))
    assert np.bincount(d.buckets(h)).max() <= 10
    lead = h.view(np.uint64)
    assert all(int(lead[i]) >> (64 - d.local[b]) == d.prefix[b] for i, b in enumerate(d.buckets(h).tolist()))
    assert build_directory(frame.where("load < 0"), 100).depth == 0


def test_chain_keeps_colliding_texts_apart():
    import pyarrow as pa

    from cellwright.llm.exact_dedup import _own

    b = pa.RecordBatch.from_pydict({"h": [7, 7, 7], "doc_id": [3, 1, 2], "n": [1, 1, 5], "norm": ["x", "y", "x"]})
    got = [tuple(r.values()) for p in _own([b]) for r in p.to_pylist()]
    assert [(g[1], g[3], g[4]) for g in got] == [(0, 2, 6), (1, 1, 1)]


def fingerprint(t):
    w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate({c: c + 32 for c in range(65, 91)}))
    if not w:
        return 0
    sh = [" ".join(w[i : i + 4]) for i in range(len(w) - 3)] or [" ".join(w)]
    h = [xxhash.xxh64_intdigest(s, 42) for s in sh]
    return sum(1 << k for k in range(64) if sum(x >> k & 1 for x in h) * 2 > len(h))


def test_simhash(docs, none, rows):
    from cellwright.llm.simhash import near_groups

    f = [fingerprint(t) for _, t in rows]
    comp = list(range(len(f)))
    for _ in f:
        comp = [min(comp[b] for b in range(len(f)) if bin(f[a] ^ f[b]).count("1") <= 4) for a in range(len(f))]
    want = []
    for k, (i, _) in enumerate(rows):
        ids = [rows[j][0] for j in range(len(f)) if comp[j] == comp[k] and rows[j][0] is not None]
        want.append((i, f"{f[k]:016x}", min(ids) if ids else None))
    same([tuple(r)[:3] for r in near_groups(docs).collect()], want)
    assert near_groups(none).count() == 0


def test_simhash_lists_miss_no_pair():
    from cellwright.llm.simhash import forest, list_links, near, position_triples

    rng = np.random.default_rng(2)
    base = rng.integers(0, 1 << 63, 40, dtype=np.uint64)
    fps = np.unique(np.concatenate([base] + [base ^ np.bitwise_or.reduce(np.uint64(1) << rng.integers(0, 64, (4, 40)).astype(np.uint64), axis=0) for _ in range(6)]))
    pairs = {(int(a), int(b)) for i, a in enumerate(fps) for b in fps[i + 1 :] if near(np.array([a]), b)[0]}
    shared = {p for p in pairs for t in position_triples() if all((p[0] >> 8 * x) & 255 == (p[1] >> 8 * x) & 255 for x in t)}
    assert pairs == shared
    a, b = list_links(np.zeros(len(fps), np.int64), fps)
    assert len(forest(fps)) == len(a) and all(near(np.array([x]), y)[0] or True for x, y in zip(a, b))


def test_components_of_a_long_chain(spark):
    from cellwright.llm.simhash import components

    edges = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101)], "a long, b long")
    got = {r["node"]: r["root"] for r in components(edges).collect()}
    assert got == {**{i: 0 for i in range(1, 41)}, 101: 100}


def test_token_counts(docs, none, rows):
    from cellwright.llm.token_counts import token_counts

    tok = library(BYTES)
    want = [(i, len((t or "").encode()), n, n > 1024) for i, t in rows for n in [len(tok.encode(t or "", add_special_tokens=False).ids)]]
    same([tuple(r) for r in token_counts(docs, BYTES, PATTERN).collect()], want)
    assert token_counts(none, BYTES, PATTERN).count() == 0


def test_bpe_roundtrip(docs, none, rows):
    from cellwright.llm.chunk_bpe import encode_decode

    tok = library(WORDS)
    want = []
    for i, t in rows:
        ids = tok.encode(t or "", add_special_tokens=False).ids
        want.append((i, len(ids), np.array(ids, "<u4").tobytes(), tok.decode(ids, skip_special_tokens=False)))
    same([(r[0], r[1], bytes(r[2]), r[3]) for r in encode_decode(docs, WORDS).collect()], want)
    assert encode_decode(none, WORDS).count() == 0


@pytest.mark.parametrize("part_ids", [500_000, 100])
def test_token_files(spark, docs, none, rows, part_ids, monkeypatch):
    from cellwright.llm import token_files
    from cellwright.llm.token_files import FileWriter, pack_values, read_file, read_token_files, unpack_values, write_token_files

    v = np.array([0, 255, 256, 65535, 65536, 1 << 24, (1 << 32) - 1], np.uint64)
    c, d = pack_values(v)
    control, data = np.frombuffer(c, np.uint8), np.frombuffer(d, np.uint8)
    assert unpack_values(control, data, len(v))[0].tolist() == v.tolist()
    first, used = unpack_values(control, data, 5)
    assert first.tolist() == v[:5].tolist() and unpack_values(control[1:], data[used:], 2, 1)[0].tolist() == v[5:].tolist()
    monkeypatch.setattr(token_files, "PART_IDS", part_ids)
    rng = np.random.default_rng(1)
    n, rank = rng.integers(0, 900, 40), rng.permutation(5000).astype(np.uint32)
    ids, w, at = rng.integers(0, 5000, n.sum()), FileWriter(rank), 0
    for k in (7, 13, 20):
        m = n[at : at + k]
        w.add([None if i % 5 == 0 else i for i in range(at, at + k)], m, ids[n[:at].sum() : n[:at].sum() + m.sum()])
        at += k
    parts = list(read_file(b"".join(w.parts(3)), np.argsort(rank)))
    assert np.concatenate([p[4] for p in parts]).tolist() == ids.tolist() and [d for p in parts for d in p[1]] == [None if i % 5 == 0 else i for i in range(40)]
    assert np.concatenate([p[2] for p in parts]).tolist() == (np.cumsum(n) - n).tolist() and np.concatenate([p[3] for p in parts]).tolist() == n.tolist()
    tok = library(BYTES)
    got = [tuple(r) for r in read_token_files(spark, *write_token_files(docs, BYTES)).collect()]
    want = [(i, np.array(tok.encode(t or "", add_special_tokens=False).ids + [0], "<u4").tobytes()) for i, t in rows]
    same([(g[0], bytes(g[3])) for g in got], want)
    at = 0
    for g in sorted(got, key=lambda g: g[1]):
        assert g[1] == at and g[2] == len(g[3]) // 4
        at += g[2]
    order = [g[0] if g[0] is not None else -1 for g in sorted(got, key=lambda g: g[1])]
    assert order == sorted(order)
    assert read_token_files(spark, *write_token_files(none, BYTES)).count() == 0


def test_sharding(spark, docs, none, rows):
    from cellwright.llm import sharding as s

    out, m = s.shard(docs, 4)
    got = out.collect()
    same([(r["doc_id"], r["size"], r["text_crc32"]) for r in got], [(i, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t in rows])
    for k in range(4):
        own = sorted(r["slot"] for r in got if r["shard"] == k)
        assert own == list(range(len(own)))
    load = {k: 100 + k % 7 for k in range(200)}
    a = s.balanced(load, 5)
    held = s._held(a, load)
    assert max(held) - min(held) < 0.02 * sum(held)
    b = s.grown(a, load)
    assert all(b.shard_of[k] in (a.shard_of[k], 5) for k in load) and min(s._held(b, load)) > 0.8 * sum(held) / 6
    load[3] = 4000
    c = s.rebalanced(b, load)
    assert max(s._held(c, load)) <= max(s._held(b, load))
    path = a.save(spark)
    b.save(spark, path)
    assert s.SlotMap.load(spark, path) == b and s.SlotMap.load(spark, path, 1) == a
    assert s.shard(none)[0].count() == 0


def covered(rows):
    """Rows in the order of doc_id (null last); repeated ids in the order given."""
    seen, out = set(), {}
    for k in sorted(range(len(rows)), key=lambda k: (rows[k][0] is None, rows[k][0] or 0)):
        b = (rows[k][1] or "").encode()
        gone = np.zeros(len(b), bool)
        for i in range(len(b) - 99):
            w = b[i : i + 100]
            if w in seen:
                gone[i : i + 100] = True
            seen.add(w)
        out[k] = b, gone
    return out


def test_suffix_dedup(docs, none, rows):
    from cellwright.llm.suffix_dedup import remove_repeats

    own = [(i, t) for i, t in rows if i is not None]
    want = []
    for k, (b, gone) in covered(own).items():
        spans = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        want.append((own[k][0], len(b), int(gone.sum()), spans, np.frombuffer(b, np.uint8)[~gone].tobytes()))
    got = remove_repeats(docs.where("doc_id IS NOT NULL"), bucket_bytes=2000)
    same([(*r[:4], bytes(r[4])) for r in got.collect()], want)
    same([(*r[:4], bytes(r[4])) for r in remove_repeats(docs.where("doc_id IS NOT NULL"), many=0).collect()], want)
    kept = remove_repeats(docs, keep=True)
    assert set(docs.columns) <= set(kept.columns) and kept.count() == len(rows)
    assert remove_repeats(none).count() == 0 and remove_repeats(none, keep=True).count() == 0


@pytest.mark.parametrize("many", [0, 3, 1000])
def test_suffix_dedup_of_a_passage_in_many_texts(spark, many):
    """A passage at the edges of different texts, near copies, copies, periodic text, and a text above a slice of windows."""
    from cellwright.llm.suffix_dedup import SLICE, remove_repeats

    rng = random.Random(many)

    def prose(n):
        return " ".join("".join(rng.choice("abcdefgh") for _ in range(rng.randrange(2, 9))) for _ in range(n))

    passage, base = prose(45), prose(300)
    rows = [(i, prose(rng.randrange(5, 60)) + passage + prose(rng.randrange(5, 60))) for i in range(40)]
    rows += [(100 + i, base[: rng.randrange(len(base))] + prose(3) + base[rng.randrange(len(base)) :]) for i in range(15)]
    rows += [(200 + i, base) for i in range(5)] + [(300, "ab" * 400), (301, "xab" * 200 + "ab" * 100), (302, passage)]
    long = prose(SLICE // 5 + 20_000)
    assert len(long) > SLICE
    rows += [(400, long), (401, long[SLICE - 500 : SLICE + 700])]
    want = [(rows[k][0], len(b), int(g.sum()), np.frombuffer(b, np.uint8)[~g].tobytes()) for k, (b, g) in covered(rows).items()]
    frame = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    same([(r[0], r[1], r[2], bytes(r[4])) for r in remove_repeats(frame, many=many).collect()], want)


@pytest.mark.parametrize("seed", range(12))
def test_suffix_order(seed):
    from cellwright.llm.suffix_dedup import repeated_windows, suffix_order

    rng = np.random.default_rng(seed)
    base = rng.integers(97, 99 + seed % 3, 1500).astype(np.uint8)
    text = np.concatenate([base[a : a + rng.integers(120, 500)] for a in rng.integers(0, 1300, 8)] + ([np.full(300, 97, np.uint8)] if seed % 3 == 0 else []))
    starts = np.sort(rng.choice(len(text) - 99, 700, replace=False))
    raw, seen, want = text.tobytes(), set(), []
    for s in starts.tolist():
        want.append(raw[s : s + 100] in seen)
        seen.add(raw[s : s + 100])
    assert repeated_windows(text, starts).tolist() == want
    order = [raw[s : s + 100] for s in starts[suffix_order(text, starts)[0]].tolist()]
    assert order == sorted(order)


def test_packing(docs, none, rows):
    from cellwright.llm.packing import first_fit_decreasing, pack

    bins, offsets = first_fit_decreasing(np.array([5, 9, 3, 7, 1, 10]), 10)
    assert bins.tolist() == [3, 1, 2, 2, 1, 0] and offsets.tolist() == [0, 0, 7, 0, 9, 0]
    tok = library(BYTES)
    got = pack(docs, BYTES, group_pieces=16).collect()
    by = {}
    for r in got:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for spans in by.values():
        at = 0
        for o, n in sorted(spans):
            assert o == at
            at += n
        assert at <= 1024
    want = []
    for i, t in rows:
        ids = tok.encode(t or "", add_special_tokens=False).ids + [0]
        want += [(i, s, len(ids[s : s + 1024]), zlib.crc32(np.array(ids[s : s + 1024], "<u4").tobytes()), len(ids)) for s in range(0, len(ids), 1024)]
    same([tuple(r)[:5] for r in got], want)
    assert pack(none, BYTES).count() == 0


def test_additive_ann(spark):
    from cellwright.llm.additive_ann import exact_search, search

    rng = np.random.default_rng(1)
    x = rng.normal(size=(600, 16)).astype("float32")
    x[40:90] = x[40]
    data = [(i, v.tolist(), 0, "clash") for i, v in enumerate(x)] + [(601, None, 0, ""), (602, [0.0] * 16, 0, ""), (603, [float("nan")] + [1.0] * 15, 0, ""), (620, [1.0], 0, ""), (604, [None] + [1.0] * 15, 0, ""), (5, x[5].tolist(), 0, "")]
    frame = spark.createDataFrame(data, "vec_id long, embedding array<float>, rank int, score string")
    got, want = search(frame).collect(), exact_search(frame).collect()
    g, w = ({(r["query_id"], r["rank"]): (r["vec_id"], r["score"]) for r in rows} for rows in (got, want))
    assert g.keys() == w.keys()
    assert np.mean([g[k][0] == w[k][0] for k in w]) > 0.95 and all(abs(g[k][1] - w[k][1]) < 1e-9 for k in w if g[k][0] == w[k][0])
    assert search(frame.where("vec_id < 0")).count() == 0


def test_additive_ann_is_exact_in_a_hot_group(spark):
    from cellwright.llm.additive_ann import exact_search, search

    rng = np.random.default_rng(2)
    x = rng.normal(size=(4500, 16))
    x[::3] = x[0] + 1e-4 * rng.normal(size=(1500, 16))
    for scale in (1.0, 1e30):  # the second overflows single precision
        frame = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x * scale)], "vec_id long, embedding array<double>")
        got, want = ({(r["query_id"], r["rank"]): r["score"] / scale**2 for r in f(frame, every=100).collect()} for f in (search, exact_search))
        assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-9 for k in want)


def test_toxicity(spark, docs, none):
    from cellwright.llm.toxicity import fit, gradients, new_model, score, train

    rng = random.Random(3)
    calm = ["sun", "tree", "road", "house", "water", "stone"]

    def doc(bad):
        w = [rng.choice(calm) + str(rng.randrange(30)) for _ in range(rng.randrange(20, 120))]
        if bad:
            for _ in range(3):
                w[rng.randrange(len(w))] = "grumf" + rng.choice("abcdefgh")
        return " ".join(w)

    y = np.array([i % 3 == 0 for i in range(240)], int)
    data = [doc(b) for b in y]
    model = train(data, y)
    y2 = np.array([i % 2 for i in range(60)])
    p = model.scores([doc(b) for b in y2])
    assert ((p >= 0.5) == y2).mean() > 0.9
    m = new_model(["one two three"] * 9)
    m.weights = {k: v.astype(np.float64) for k, v in m.weights.items()}
    args = ([["one", "two"], ["three"]], np.array([0.5, 0.5]), np.array([1.0, 0.0]))
    _, g = gradients(m, *args)
    for k in ("char", "cf_u", "wf_w", "wb_u", "att_w", "att_v", "out_w"):
        i = np.unravel_index(np.abs(g[k]).argmax(), g[k].shape)
        old = m.weights[k][i]
        m.weights[k][i] = old + 1e-2
        a, _ = gradients(m, *args)
        m.weights[k][i] = old - 1e-2
        b, _ = gradients(m, *args)
        m.weights[k][i] = old
        assert abs((a - b) / 2e-2 - g[k][i]) < 0.05 * abs(g[k][i]) + 1e-4, k
    out = score(docs, model, keep=True)
    assert out.count() == docs.count() and out.columns == [*docs.columns, "__cw_score"]
    assert all(0 <= r["score"] <= 1 for r in score(docs, model).collect())
    assert score(none, model).count() == 0
    labels = spark.createDataFrame([(10, None), (None, 1)], "doc_id long, toxic int")
    assert all(r["score"] < 0.5 for r in score(docs, fit(docs, labels)).collect())


def test_toxicity_reads_whole_texts(spark):
    from cellwright.llm import toxicity

    run = "".join(chr(ord("a") + i % 26) for i in range(500))
    got = toxicity.tokens(f"{run} two_words_joined_by_underscores {'_' * 20} Short")
    assert max(map(len, got)) <= toxicity.CHARS and got[-1] == "short" and {"two", "words", "underscores"} <= set(got)
    assert all(any(run[a : a + 7] in w for w in got) for a in range(494))
    assert all("".join(p[-7 if i else 0 :] for i, p in enumerate(toxicity.tokens(run[:n]))).startswith(run[: min(n, 14)]) for n in range(1, 40))
    seen, train = [], toxicity.train
    long = " ".join(["calm"] * 9000) + " grumfa"
    docs = spark.createDataFrame([(i, long) for i in range(10)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, 1) for i in range(10)], "doc_id long, toxic int")
    try:
        toxicity.train = lambda texts, *a, **b: seen.extend(texts) or train(["x"], np.array([0]))
        toxicity.fit(docs, labels)
    finally:
        toxicity.train = train
    assert seen and all(t == long for t in seen)


def test_pipeline_stages(spark, docs, rows):
    """The four stages after the learned one, against brute force on what each was given."""
    import corpus_pipeline as c

    assert [n for n, _ in c.STAGES] == ["toxicity", "exact_dedup", "simhash", "suffix_dedup", "packing"]
    kept = sorted((r["text"] or "") for r in c.drop_exact_copies(spark, docs, "").where("doc_id IS NULL").collect())
    assert kept == ["no id"]  # the other row without an id has a copy with one
    once = docs.where("doc_id IS NOT NULL").dropDuplicates(["doc_id"])
    have = {r["doc_id"]: r["text"] or "" for r in once.collect()}
    a = c.drop_exact_copies(spark, once, "")
    b = c.drop_near_copies(spark, a, "")
    d = c.cut_repeats(spark, b, "")
    assert a.columns == b.columns == d.columns == docs.columns
    rows_ = [(1, "one two three four five six"), (1, "seven eight nine ten eleven twelve"), (0, "one two three four five six"), (None, "one two three four five six"), (None, "alone here")]
    left = c.drop_near_copies(spark, spark.createDataFrame(rows_, "doc_id long, text string"), "").collect()
    assert sorted((str(r["doc_id"]), r["text"]) for r in left) == [("0", rows_[0][1]), ("1", rows_[1][1]), ("None", "alone here")]
    norm = {}
    for i in sorted(have):
        norm.setdefault(re.sub(r"[\x20\x09-\x0D]+", " ", have[i]), i)
    ids = sorted(norm.values())
    assert sorted(r["doc_id"] for r in a.collect()) == ids
    f, group = {i: fingerprint(have[i]) for i in ids}, {i: i for i in ids}
    for _ in ids:
        group = {i: min(group[j] for j in ids if bin(f[i] ^ f[j]).count("1") <= 4) for i in ids}
    ids = [i for i in ids if group[i] == i]
    assert sorted(r["doc_id"] for r in b.collect()) == ids
    cut = {ids[k]: np.frombuffer(x, np.uint8)[~gone].tobytes().decode(errors="ignore") for k, (x, gone) in covered([(i, have[i]) for i in ids]).items()}
    assert {r["doc_id"]: r["text"] or "" for r in d.collect()} == cut
    tok = library(BYTES)
    got = {}
    for r in c.pack_sequences(spark, d, "").collect():
        got[r["doc_id"]] = got.get(r["doc_id"], 0) + r["length"]
    assert got == {i: len(tok.encode(t, add_special_tokens=False).ids) + 1 for i, t in cut.items()}
