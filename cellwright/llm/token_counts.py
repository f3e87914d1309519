"""Token counts by rank-synchronous merging in ragged numpy arrays.

All distinct pre-tokens of a batch lie in one flat array of symbols. In each round every sequence looks up the ranks of
its adjacent pairs, finds its own lowest one, and joins that pair wherever it stands in the sequence; all sequences take
their round at once. Sequences without a joinable pair leave with their count of surviving symbols.
"""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame

from .common import id_and_text, text_chunks
from .pieces import PLAIN, byte_ranks, cache, doc_pieces, load, special_strings

NO_RANK = np.int64(1 << 40)


class PairTable:
    """(left id, right id) -> (rank, joined id) by open addressing."""

    def __init__(self, pairs: dict[tuple[int, int], tuple[int, int]], bits: int = 19):
        while len(pairs) * 4 > 1 << bits:
            bits += 1
        self.shift = np.uint64(64 - bits)
        self.mask = (1 << bits) - 1
        self.key = np.full(1 << bits, -1, np.int64)
        self.rank, self.joined = np.full(1 << bits, NO_RANK), np.zeros(1 << bits, np.int32)
        keys = np.fromiter((a << 32 | b for a, b in pairs), np.int64, len(pairs))
        for key, slot, (rank, joined) in zip(keys.tolist(), self.home(keys).tolist(), pairs.values()):
            while self.key[slot] >= 0:
                slot = slot + 1 & self.mask
            self.key[slot], self.rank[slot], self.joined[slot] = key, rank, joined

    def home(self, keys: np.ndarray) -> np.ndarray:
        return (keys.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> self.shift).astype(np.int64)

    def slots(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Slot of each pair, or of an empty place, whose rank is NO_RANK."""
        keys = left.astype(np.int64) << 32 | right
        slot = self.home(keys)
        held = self.key[slot]
        todo = np.flatnonzero((held != keys) & (held >= 0))
        while len(todo):
            slot[todo] = slot[todo] + 1 & self.mask
            held = self.key[slot[todo]]
            todo = todo[(held != keys[todo]) & (held >= 0)]
        return slot


def merged_counts(symbols: np.ndarray, lens: np.ndarray, table: PairTable) -> np.ndarray:
    """Surviving symbols of each sequence. symbols: the ids of all sequences, one after another; lens: of each, 0 allowed."""
    out = lens.astype(np.int64).copy()
    live = np.flatnonzero(lens > 1)
    symbols, lens = symbols[np.repeat(lens > 1, lens)], lens[live].astype(np.int64)
    while len(live):
        starts = np.cumsum(lens) - lens
        slot = np.empty(len(symbols), np.int64)
        slot[:-1] = table.slots(symbols[:-1], symbols[1:])
        rank = table.rank[slot % len(table.rank)] if len(symbols) < 2 else np.append(table.rank[slot[:-1]], NO_RANK)
        rank[starts + lens - 1] = NO_RANK
        least = np.minimum.reduceat(rank, starts)
        hit = (rank == np.repeat(least, lens)) & (rank < NO_RANK)
        at = np.flatnonzero(hit)
        # of overlapping pairs, as in a run of equal symbols, the first, third and so on are joined
        fresh = np.append(True, np.diff(at) != 1) if len(at) else np.zeros(0, bool)
        at = at[(np.arange(len(at)) - np.maximum.accumulate(np.where(fresh, np.arange(len(at)), 0))) % 2 == 0]
        symbols[at] = table.joined[slot[at]]
        stay = np.ones(len(symbols), bool)
        stay[at + 1] = False
        seq = np.repeat(np.arange(len(live)), lens)
        lens = lens - np.bincount(seq[at], minlength=len(live))
        symbols = symbols[stay]
        out[live] = lens
        going = (least < NO_RANK) & (lens > 1)
        symbols, live, lens = symbols[np.repeat(going, lens)], live[going], lens[going]
    return out


def byte_pairs(path: str) -> tuple[np.ndarray, PairTable]:
    """Id of each byte and the pair table of a byte-level vocabulary file."""
    ranks, vocab = byte_ranks(path), load(path).get_vocab(with_added_tokens=False)
    merges = json.loads(load(path).to_str())["model"]["merges"]
    pairs = {}
    for rank, m in enumerate(merges):
        a, b = m.split(" ") if isinstance(m, str) else m
        pairs.setdefault((vocab[a], vocab[b]), (rank, vocab[a + b]))
    return np.array([ranks[bytes([b])] for b in range(256)], np.int32), PairTable(pairs)


def counting(path: str, pattern: str):
    """Counts of pieces, in the form that PieceCache takes: one value for each piece."""
    import regex

    find, pre = regex.compile(pattern).findall, load(path).pre_tokenizer
    first, table = byte_pairs(path)

    def encode_many(pieces: list) -> tuple[np.ndarray, np.ndarray]:
        of, words = np.zeros(len(pieces), np.int64), {}
        entry: list[int] = []
        for k, p in enumerate(pieces):
            text = p[0] if isinstance(p, tuple) else " " + p
            found = find(text) if text.isascii() or max(text) < PLAIN else [text[a:b] for _, (a, b) in pre.pre_tokenize_str(text)]
            of[k] = len(found)
            entry += [words.setdefault(w, len(words)) for w in found]
        raw = [w.encode() for w in words]
        lens = np.fromiter(map(len, raw), np.int64, len(raw))
        n = merged_counts(first[np.frombuffer(b"".join(raw), np.uint8)], lens, table)
        total = np.concatenate([[0], np.cumsum(n[np.asarray(entry, np.int64)] if entry else [])]).astype(np.int64)
        ends = np.cumsum(of)
        return np.ones(len(pieces), np.int64), (total[ends] - total[ends - of]).astype(np.int32)

    return encode_many


def token_counts(docs: DataFrame, path: str, pattern: str, limit: int = 1024) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit of every document.

    Null and empty texts have 0 tokens; repeated rows each get a row; a null doc_id stays null; an empty table gives none.
    No shuffle: a map over whole texts, whose state is one bounded cache of pieces per worker."""

    def run(batches):
        import pyarrow as pa

        held, special, tok = cache("counts", path, lambda: counting(path, pattern)), special_strings(path), load(path)
        for batch in batches:
            for part in text_chunks(batch):
                texts = part.column("text").to_pylist()
                pieces, n, whole = doc_pieces(texts, special)
                entries = held.index(pieces)
                at = held.start[entries]
                sums = np.concatenate([[0], np.cumsum(held.flat[at], dtype=np.int64)])
                ends = np.cumsum(n)
                total = sums[ends] - sums[ends - n]
                for i in whole:
                    total[i] = len(tok.encode(texts[i], add_special_tokens=False).ids)
                size = np.fromiter((len(t.encode()) for t in texts), np.int64, len(texts))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(size), pa.array(total), pa.array(total > limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return id_and_text(docs).mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
