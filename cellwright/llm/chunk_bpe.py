"""BPE encoding with reuse of content-defined chunks, and decoding.

A rolling hash over the last sixteen bytes cuts each text into chunks, so equal passages give equal chunks wherever they
stand. The inside of a chunk, from its first to its last space, is encoded once per worker, whatever documents it stands
in, and reused. Two chunks meet in the middle of a word: the fragments on both sides (over several chunks, where one
holds no space) are joined again and encoded. Each join is then repaired: it is encoded anew together with the word before
and the word after it, and where the ids do not agree with those of the chunks on both sides, the window grows to the
whole text. For vocabularies that drop white space, such as the word vocabulary, the first window agrees.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

from .common import id_and_text, ragged_index, text_chunks
from .pieces import PieceCache, by_marks, cache, load, special_strings

#: bytes that the rolling hash looks back on, leading bits that are zero at a cut (chunks of 1 KB on average), longest chunk
WINDOW, CUT_BITS, LONGEST = 16, 10, 16_384
BASE = 0x9E3779B97F4A7C15


def rolling_hash(data: np.ndarray) -> np.ndarray:
    """Polynomial hash of the WINDOW bytes that end at each place from WINDOW - 1 on, modulo 2^64; by doubling the window."""
    h, m, power = data.astype(np.uint64) + np.uint64(1), 1, BASE
    while m < WINDOW:
        h = h[m:] + np.uint64(power) * h[:-m]
        m, power = 2 * m, power * power % (1 << 64)
    return h


def chunk_cuts(data: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Ends of the chunks of concatenated texts; ends: of the texts. A cut depends on the bytes before it only, except where
    no cut comes for LONGEST bytes."""
    if len(data) <= WINDOW:
        return ends
    at = np.flatnonzero((rolling_hash(data)[:-1] * np.uint64(BASE)) >> np.uint64(64 - CUT_BITS) == 0) + WINDOW
    text = np.searchsorted(ends, at, side="right")
    at = np.union1d(at[at - WINDOW >= np.concatenate([[0], ends])[text]], ends)
    start = np.concatenate([[0], at[:-1]])
    long = np.flatnonzero(at - start > LONGEST)
    if len(long):
        more = (at[long] - start[long] - 1) // LONGEST
        at = np.union1d(at, ragged_index(np.zeros(len(long), np.int64), more) * LONGEST + np.repeat(start[long] + LONGEST, more))
    inner = at[at < len(data)]
    for _ in range(3):  # not within a character: the cut moves to its end
        inner = inner + ((data[np.minimum(inner, len(data) - 1)] & 0xC0) == 0x80)
    return np.union1d(inner, ends)


def _store(path: str) -> tuple[PieceCache, PieceCache]:
    words = cache("words", path, lambda: by_marks(path))

    def insides(chunks: list) -> tuple[np.ndarray, np.ndarray]:
        split = [c.decode().split(" ")[1:-1] for c in chunks]
        counts = np.fromiter(map(len, split), np.int64, len(split))
        pieces = [p for s in split for p in s]
        lens, ids = words.ids(words.index(pieces)) if pieces else (np.zeros(0, np.int64), np.zeros(0, np.int32))
        total = np.concatenate([[0], np.cumsum(lens)])
        ends = np.cumsum(counts)
        return total[ends] - total[ends - counts], ids

    held = cache("chunks", path, lambda: insides)
    held.max_entries, words.max_entries = 50_000, 500_000
    return words, held


def encode(texts: list[str], path: str) -> tuple[np.ndarray, np.ndarray]:
    """Number of ids of each text, and all ids."""
    words, held = _store(path)
    special = special_strings(path)
    whole = {i for i, t in enumerate(texts) if any(s in t for s in special)}
    raw = [b"" if i in whole else t.encode() for i, t in enumerate(texts)]
    sizes = np.fromiter(map(len, raw), np.int64, len(raw))
    blob = b"".join(raw)
    ends = np.cumsum(sizes)
    cuts = np.unique(chunk_cuts(np.frombuffer(blob, np.uint8), ends)) if blob else np.zeros(0, np.int64)
    joins: list[str] = []
    beside: list[tuple[str, str]] = []  # the words before and after each join
    chunks: list[bytes] = []
    order: list[bool] = []  # true: the inside of a chunk; false: a join
    items = np.zeros(len(texts), np.int64)
    at = k = 0
    for i in range(len(texts)):
        carry, end, before, word = b"", int(ends[i]), len(order), ""
        while at < end:
            c = blob[at : int(cuts[k])]
            at, k = int(cuts[k]), k + 1
            first = c.find(b" ")
            if first < 0:
                carry += c
                continue
            last = c.rfind(b" ")
            joins.append((carry + c[:first]).decode())
            order.append(False)
            after = c[first + 1 : max(c.find(b" ", first + 1), first + 1)].decode()
            beside.append((word, after))
            if last > first:
                chunks.append(c)
                order.append(True)
            word = c[max(c.rfind(b" ", 0, last), first) + 1 : last].decode() if last > first else ""
            carry = c[last + 1 :]
        if carry:
            joins.append(carry.decode())
            order.append(False)
            beside.append((word, ""))
        items[i] = len(order) - before
    inside = np.array(order, bool)
    lens = np.zeros(len(order), np.int64)
    a, ids_a = held.ids(held.index(chunks)) if chunks else (np.zeros(0, np.int64), np.zeros(0, np.int32))
    b, ids_b = words.ids(words.index(joins)) if joins else (np.zeros(0, np.int64), np.zeros(0, np.int32))
    lens[inside], lens[~inside] = a, b
    if joins:
        text_of = np.repeat(np.arange(len(texts)), items)[~inside]
        bad = set(text_of[~_agrees(words, by_marks(path), joins, beside)].tolist())
        whole |= bad  # no join of these texts agrees short of the whole text
    start = np.cumsum(lens) - lens
    out = np.empty(int(lens.sum()), np.int32)
    out[ragged_index(start[inside], a)], out[ragged_index(start[~inside], b)] = ids_a, ids_b
    total = np.concatenate([[0], np.cumsum(lens)])
    last = np.cumsum(items)
    n, first = total[last] - total[last - items], total[last - items]
    if not whole:
        return n, out
    parts = []
    for i in range(len(texts)):
        own = np.asarray(load(path).encode(texts[i], add_special_tokens=False).ids, np.int32) if i in whole else out[first[i] : first[i] + n[i]]
        n[i] = len(own)
        parts.append(own)
    return n, np.concatenate(parts)


def _agrees(words: PieceCache, encode_many, joins: list[str], beside: list[tuple[str, str]]) -> np.ndarray:
    """Whether each join, encoded together with its neighbours, gives the ids that the three have alone."""
    texts = [f"{a} {j} {z}" for j, (a, z) in zip(joins, beside)]
    n, ids = encode_many(texts)
    parts = [w for j, (a, z) in zip(joins, beside) for w in (a, j, z)]
    lens, want = words.ids(words.index(parts))
    total = lens.reshape(-1, 3).sum(1)
    ok = total == n
    of, wanted = np.repeat(np.arange(len(n)), n), np.repeat(np.arange(len(n)), total)
    same = np.ones(len(n), bool)
    same[of[ok[of]][ids[ok[of]] != want[ok[wanted]]]] = False
    return ok & same


def _token_bytes(path: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    tok = load(path)
    raw = [((tok.id_to_token(i) or "") + " ").encode() for i in range(tok.get_vocab_size())]
    lens = np.fromiter(map(len, raw), np.int64, len(raw))
    return np.frombuffer(b"".join(raw), np.uint8), np.cumsum(lens) - lens, lens


def decode(n: np.ndarray, ids: np.ndarray, path: str) -> list[str]:
    """What the library's decode gives of each text's ids, special tokens kept."""
    tok = load(path)
    ends = np.cumsum(n)
    if tok.decoder is not None:
        return tok.decode_batch([ids[e - k : e].tolist() for e, k in zip(ends, n)], skip_special_tokens=False)
    if path not in _TABLES:
        _TABLES[path] = _token_bytes(path)
    flat, starts, lens = _TABLES[path]
    size = lens[ids]
    blob = flat[ragged_index(starts[ids], size)].tobytes()  # without a decoder tokens are joined by spaces
    total = np.concatenate([[0], np.cumsum(size)])
    return [blob[total[e - k] : max(total[e] - 1, total[e - k])].decode() for e, k in zip(ends, n)]


_TABLES: dict[str, tuple] = {}


def encode_decode(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_tokens, ids (little-endian unsigned 32-bit integers), decoded (text) of every document.

    Null and empty texts have no ids and decode to an empty text; repeated rows each get a row; a null doc_id stays null.
    A map without shuffle; caches are bounded and live in the worker."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for part in text_chunks(batch, 2_000_000):
                n, ids = encode(part.column("text").to_pylist(), path)
                ends = np.cumsum(n)
                raw = ids.astype("<u4").tobytes()
                yield pa.RecordBatch.from_arrays(
                    [part.column("doc_id"), pa.array(n), pa.array([raw[4 * (e - k) : 4 * e] for e, k in zip(ends.tolist(), n.tolist())], pa.binary()), pa.array(decode(n, ids, path), pa.string())],
                    ["doc_id", "n_tokens", "ids", "decoded"],
                )

    return id_and_text(docs).mapInArrow(run, "doc_id long, n_tokens long, ids binary, decoded string")
