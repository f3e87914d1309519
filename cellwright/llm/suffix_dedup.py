"""Suffix-array dedup: blockwise suffix sorting over a difference cover.

A byte goes if a 100-byte string that covers it also starts earlier (smaller doc_id, or the same document further left).

Where suffixes go: every 100-byte window has a smallest 24-byte hash (its minimiser), so equal windows share it, and a
suffix bucket holds the suffixes whose first 100 bytes have minimisers of one hash class. (Classes stand in for ranges of
the order of suffixes: equal strings meet as well, without a sample of splitters.) Runs of consecutive windows with one
minimiser form a segment. First only hashes travel: the owner of a minimiser sees each block's distinct segments. Where
the minimiser has one segment in one place, nothing repeats; of equal segments all but the earliest repeat throughout;
the earliest of each travels as text to its suffix bucket only if the minimiser has other segments, too. So a passage of
any number of copies reaches a bucket once. Where a minimiser has very many different segments, as at the edge of a
passage that stands in many documents, its windows are dealt out further by the bytes beside the minimiser.

One suffix bucket at a time, an owner task concatenates its segments, ranks the suffixes at the positions of a difference
cover modulo 31 (to a depth of 124 bytes, by doubling; each bucket has a cover sample of its own, so memory is that of a
bucket), sorts all windows by their first 31 bytes, and resolves longer ties by the ranks of the two cover positions at
equal distance from both suffixes. Neighbours in that order that share 100 bytes form runs; all but the earliest repeat.

Texts are kept as compressed blocks of a few MB, so tasks exchange packed arrays, not rows per suffix.
"""

from __future__ import annotations

import struct

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import mix64, partitions, ragged_index, written

LENGTH, KMER, PERIOD = 100, 24, 31
#: a perfect difference set modulo 31: every distance is a difference of two members
COVER = np.array([1, 5, 11, 24, 25, 27])
BLOCK_BYTES = 2_000_000
TASK_BYTES = 64_000_000
#: windows hashed at a time, and bytes of segments sorted at a time: what a worker holds beside a block
SLICE, UNIT_BYTES = 250_000, 1_000_000
#: a minimiser with more different segments is dealt out by the bytes beside it
MANY, BESIDE = 1000, 16
LAST = (1 << 63) - 1  # where a null doc_id stands


def _zip(raw: bytes) -> bytes:
    import zstandard

    return zstandard.ZstdCompressor(level=1).compress(raw)


def _unzip(raw: bytes) -> bytes:
    import zstandard

    return zstandard.ZstdDecompressor().decompress(raw)


def packed(*arrays: np.ndarray) -> bytes:
    """Arrays, each with its length and type code before it."""
    return b"".join(struct.pack("<cBq", a.dtype.kind.encode(), a.dtype.itemsize, a.size) + a.tobytes() for a in arrays)


def unpacked(raw: bytes) -> list[np.ndarray]:
    out, at = [], 0
    while at < len(raw):
        kind, width, size = struct.unpack_from("<cBq", raw, at)
        at += 10
        out.append(np.frombuffer(raw, np.dtype(f"{kind.decode()}{width}"), size, at))
        at += width * size
    return out


def words_at(text: np.ndarray) -> np.ndarray:
    """The eight bytes from each position, little-endian; text must be padded by eight."""
    return np.ndarray((len(text) - 7,), "<u8", text, strides=(1,))


def minimiser_runs(text: np.ndarray, lens: np.ndarray, length: int = LENGTH) -> tuple[np.ndarray, ...]:
    """Runs of windows with one minimiser in one place over concatenated documents: hash, document, first window, number
    of windows, place. A slice of windows is read at a time; a run ends at its end."""
    ends = np.cumsum(lens)
    begin = ends - lens
    out = []
    for low in range(0, len(text) - length + 1, SLICE):
        part = text[low : low + SLICE + length - 1]
        d = np.arange(np.searchsorted(ends, low, side="right"), np.searchsorted(begin, low + SLICE))
        first = np.maximum(begin[d], low)
        count = np.minimum(ends[d] - length + 1, low + SLICE) - first
        d, first, count = d[count > 0], first[count > 0], count[count > 0]
        if not len(d):
            continue
        w = words_at(np.concatenate([part, np.zeros(8, np.uint8)]))
        n = len(part) - KMER + 1
        h = w[:n] * np.uint64(0x9E3779B97F4A7C15)
        h ^= (w[8 : n + 8] ^ (h >> np.uint64(31))) * np.uint64(0xC2B2AE3D27D4EB4F)
        h ^= (w[16 : n + 16] ^ (h >> np.uint64(29))) * np.uint64(0x165667B19E3779F9)
        h ^= h >> np.uint64(32)
        h *= np.uint64(0xD6E8FEB86659FD93)
        # leading bits of the hash over the place: of equal hashes in a window the leftmost counts
        mask = np.uint64((1 << 31) - 1)
        full, span, m = h, length - KMER + 1, 1
        h = (h & ~mask) | np.arange(n, dtype=np.uint64)
        while m * 2 <= span:
            h = np.minimum(h[:-m], h[m:])
            m *= 2
        h = np.minimum(h[: len(h) - (span - m)], h[span - m :]) if span > m else h
        v = h[ragged_index(first - low, count)]
        at = np.cumsum(count) - count  # windows of a document lie together
        new = np.append(True, v[1:] != v[:-1])
        new[at] = True
        head = np.flatnonzero(new)
        of = np.searchsorted(at, head, side="right") - 1
        place = (v[head] & mask).astype(np.int64)
        out.append((full[place], d[of], first[of] + head - at[of], np.diff(np.append(head, len(v))), low + place))
    empty = (np.zeros(0, np.uint64), *(np.zeros(0, np.int64) for _ in range(4)))
    return tuple(map(np.concatenate, zip(*out))) if out else empty


def segments_of(text: np.ndarray, lens: np.ndarray) -> tuple[tuple[np.ndarray, ...], np.ndarray]:
    """Runs, and the first run of each segment: consecutive runs of one document whose minimisers have one hash."""
    runs = minimiser_runs(text, lens)
    h, doc, first, count, _ = runs
    after = first[:-1] + count[:-1] == first[1:]
    return runs, np.flatnonzero(np.append(True, (h[1:] != h[:-1]) | (doc[1:] != doc[:-1]) | ~after))[: len(h)]


def segment_table(text: np.ndarray, lens: np.ndarray):
    """Of each segment: hash of its minimiser, hash of its bytes, document, first window, number of windows, first run."""
    from xxhash import xxh3_64_intdigest

    runs, head = segments_of(text, lens)
    h, doc, first, count, _ = runs
    total = np.concatenate([[0], np.cumsum(count)])
    n = total[np.append(head[1:], len(h))] - total[head]
    view, begin = memoryview(text), first[head]
    own = np.fromiter((xxh3_64_intdigest(view[a:b]) for a, b in zip(begin.tolist(), (begin + n + LENGTH - 1).tolist())), np.uint64, len(head))
    return runs, (h[head], own, doc[head], begin, n, head)


def first_equal(*keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order that brings equal entries together, each group in the order given, and where groups begin in it."""
    order = np.lexsort(keys[::-1])
    new = np.zeros(len(order), bool)
    new[:1] = True
    for k in keys:
        new[1:] |= k[order[1:]] != k[order[:-1]]
    return order, np.flatnonzero(new)


def bucket_of(h: np.ndarray, buckets: int) -> np.ndarray:
    return (mix64(h ^ np.uint64(0x5851F42D4C957F2D)) % np.uint64(buckets)).astype(np.int64)


# --- suffix order of one block


def refine(order: np.ndarray, group: np.ndarray, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorts members of equal group by key (indexed by member) and splits the groups; group numbers stay ascending."""
    tied = np.zeros(len(order), bool)
    same = group[1:] == group[:-1]
    tied[1:] |= same
    tied[:-1] |= same
    at = np.flatnonzero(tied)
    if len(at):
        sub, g = order[at], group[at]
        k = key[sub]
        inner = np.argsort(k, kind="stable") if g[0] == g[-1] else np.lexsort((k, g))
        order = order.copy()
        order[at] = sub[inner]
    k = key[order]
    new = np.append(True, (group[1:] != group[:-1]) | (k[1:] != k[:-1])) if len(order) else np.zeros(0, bool)
    return order, np.cumsum(new) - 1


def sort_by_head(text: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order of the suffixes by their first 31 bytes and the group of each in that order. text: padded by 40 bytes."""
    w = words_at(text)
    key = w[at].byteswap()
    order = np.argsort(key)
    k = key[order]
    group = np.cumsum(np.append(False, k[1:] != k[:-1])) if len(at) else np.zeros(0, np.int64)
    for d in (8, 16, 24):
        if not len(group) or group[-1] == len(group) - 1:
            break
        key = w[at + d].byteswap()
        order, group = refine(order, group, key & ~np.uint64(0xFF) if d == 24 else key)
    return order, group


def cover_ranks(text: np.ndarray, n: int) -> np.ndarray:
    """Ranks of the suffixes at cover positions below n, to a depth of 124 bytes; equal ranks: 124 equal bytes."""
    base = np.arange(0, n + PERIOD, PERIOD)[:, None] + COVER
    at = base.ravel()
    at = at[at < n]
    order, group = sort_by_head(text, at)
    rank = np.full(n + 4 * PERIOD + 1, -1, np.int64)
    rank[at[order]] = group
    for step in (PERIOD, 2 * PERIOD):
        order, group = refine(order, group, rank[at + step])
        fresh = np.full_like(rank, -1)
        fresh[at[order]] = group
        rank = fresh
    return rank


def _meet() -> np.ndarray:
    """For residues a, b: the least d for which a + d and b + d both lie in the cover."""
    inside = np.zeros(PERIOD, bool)
    inside[COVER] = True
    r = np.arange(PERIOD)
    both = inside[(r[:, None, None] + r) % PERIOD] & inside[(r[None, :, None] + r) % PERIOD]
    return both.argmax(axis=2)


MEET = _meet()


def suffix_order(text: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Indices of starts in the order of their suffixes (to 124 bytes at least), and the group of equal 31-byte heads."""
    n = len(text)
    padded = np.concatenate([text, np.zeros(160, np.uint8)])
    order, heads = sort_by_head(padded, starts)
    if not len(order) or heads[-1] == len(heads) - 1:
        return order, heads
    rank = cover_ranks(padded, n + 100)
    group, live = heads.copy(), np.ones(len(order), bool)
    while True:
        # groups still open: more than one member, not yet known to be equal
        size = np.bincount(group)
        open_ = np.flatnonzero(live & (size[group] > 1))
        if not len(open_):
            return order, heads
        g = group[open_]
        first = np.append(True, g[1:] != g[:-1])
        begin = np.flatnonzero(first)
        count = np.diff(np.append(begin, len(g)))
        pivot = np.repeat(starts[order[open_[begin + count // 2]]], count)
        x = starts[order[open_]]
        d = MEET[x % PERIOD, pivot % PERIOD]
        side = np.sign(rank[x + d] - rank[pivot + d])
        inner = np.lexsort((side, g))
        order[open_] = order[open_][inner]
        side = side[inner]
        live[open_] = side != 0
        cut = np.zeros(len(order), bool)
        cut[open_[1:]] = (g[1:] == g[:-1]) & (side[1:] != side[:-1])
        cut[1:] |= group[1:] != group[:-1]
        group = np.cumsum(cut)


def repeated_windows(text: np.ndarray, starts: np.ndarray, length: int = LENGTH) -> np.ndarray:
    """Whether an equal window starts further left in text, for each of the ascending window starts."""
    order, heads = suffix_order(text, starts)
    out = np.zeros(len(starts), bool)
    near = np.flatnonzero(heads[1:] == heads[:-1])
    w = words_at(np.concatenate([text, np.zeros(8, np.uint8)]))
    a, b = starts[order[near]], starts[order[near + 1]]
    for d in [*range(0, length - 7, 8), length - 8]:
        same = w[a + d] == w[b + d]
        near, a, b = near[same], a[same], b[same]
    joined = np.zeros(len(order), bool)
    joined[near + 1] = True
    run = np.cumsum(~joined) - 1
    if len(order):
        least = np.minimum.reduceat(order, np.flatnonzero(~joined))
        out[order] = order != least[run]
    return out


# --- the distributed steps


def _grouped(batches, key: str):
    """(value, rows) for each run of equal key values, rows as dicts, over batches sorted by key; blobs are not copied."""
    held, rows = None, []
    for batch in batches:
        names = batch.schema.names
        columns = [batch.column(c) if c == "blob" else batch.column(c).to_pylist() for c in names]
        for r in zip(*columns):
            r = dict(zip(names, r))
            r["blob"] = r["blob"].as_buffer()
            if rows and r[key] != held:
                yield held, rows
                rows = []
            held = r[key]
            rows.append(r)
    if rows:
        yield held, rows


def blocks_of(docs: DataFrame) -> DataFrame:
    """block, size, blob: documents of a task in blocks of about 2 MB, by doc_id within a block (null last).

    A blob holds the other columns as Arrow, the texts' lengths in bytes, and the texts; rows stay whole."""
    text = "__cw_bytes"
    order = F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST))
    frame = docs.select(F.coalesce(F.col("text"), F.lit("")).alias(text), order.alias("__cw_order"), F.struct(*(docs[c] for c in docs.columns)).dropFields("text").alias("__cw_rest"))

    def run(batches):
        from pyspark import TaskContext

        task, k = TaskContext.get().partitionId(), 0
        for batch in batches:
            sizes = np.fromiter((len(x.as_buffer()) if x.is_valid else 0 for x in batch.column(0)), np.int64, batch.num_rows)
            ends = np.cumsum(sizes)
            at = 0
            while at < batch.num_rows:
                end = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + BLOCK_BYTES, side="right")))
                part = batch.slice(at, end - at)
                key = np.asarray(part.column("__cw_order"), np.int64)
                part = part.take(pa.array(np.argsort(key, kind="stable")))
                raw = [x.encode() for x in part.column(0).to_pylist()]
                rest = part.select(["__cw_order", "__cw_rest"])
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, rest.schema) as w:
                    w.write_batch(rest)
                blob = _zip(packed(np.frombuffer(sink.getvalue(), np.uint8), np.sort(key), np.fromiter(map(len, raw), np.int64, len(raw)), np.frombuffer(b"".join(raw), np.uint8)))
                yield pa.RecordBatch.from_arrays([pa.array([task << 32 | k], pa.int64()), pa.array([int(sizes[at:end].sum())], pa.int64()), pa.array([blob], pa.binary())], ["block", "size", "blob"])
                at, k = end, k + 1

    return written(frame.mapInArrow(run, "block long, size long, blob binary"), "text-blocks")


def _batch(names: list[str], *columns):
    return pa.RecordBatch.from_arrays([pa.array(c, pa.binary() if n == "blob" else pa.int64()) for n, c in zip(names, columns)], names)


def _minimisers(buckets: int):
    """(bucket, block, each distinct segment: hash of its minimiser, of its bytes, doc_id, number, whether of several runs)."""

    def run(batches):
        for batch in batches:
            for block, blob in zip(batch.column("block").to_pylist(), batch.column("blob")):
                _, key, lens, text = unpacked(_unzip(blob.as_buffer()))
                runs, (h, own, doc, _, _, head) = segment_table(text, lens)
                order, group = first_equal(h, own)
                several = np.diff(np.append(head, len(runs[0]))) > 1
                lead = order[group]
                again = np.maximum.reduceat(several[order], group) if len(group) else several
                b = bucket_of(h[lead], buckets)
                by = np.lexsort((lead, b))
                own_b, first = np.unique(b[by], return_index=True)
                parts = np.split(by, first[1:]) if len(own_b) else []
                blobs = [_zip(packed(h[lead[i]], own[lead[i]], key[doc[lead[i]]], lead[i].astype(np.int32), again[i].astype(np.uint8))) for i in parts]
                yield _batch(["bucket", "block", "blob"], own_b.tolist(), [block] * len(own_b), blobs)

    return run


#: what becomes of a segment: its text is wanted; it repeats; its text is wanted, dealt out further
WANTED, REPEATS, DEALT = 1, 2, 3


def _verdicts(many: int):
    """(block, blob): numbers of a block's segments and what becomes of them; nothing for those that occur once."""

    def run(batches):
        for _, rows in _grouped(batches, "bucket"):
            parts = [unpacked(_unzip(r["blob"])) for r in rows]
            h, own, key, number, several = (np.concatenate([p[i] for p in parts]) for i in range(5))
            of = np.repeat(np.arange(len(rows)), [len(p[0]) for p in parts])
            block = np.array([r["block"] for r in rows])[of]
            order, _ = first_equal(h, own, key, block)
            h, own = h[order], own[order]
            new_h = np.append(True, h[1:] != h[:-1])
            lead = new_h | np.append(True, own[1:] != own[:-1])
            begin = np.flatnonzero(new_h)
            kinds = np.add.reduceat(lead, begin, dtype=np.int64)  # different segments of a minimiser
            kinds = np.repeat(kinds, np.diff(np.append(begin, len(h))))
            status = np.where(~lead, REPEATS, np.where(kinds > many, DEALT, np.where((kinds > 1), WANTED, 0))).astype(np.uint8)
            # a lone segment can repeat within itself, if the minimiser has several places in it
            begin = np.flatnonzero(lead)
            inner = np.maximum.reduceat(several[order], begin)
            status[begin[(status[begin] == 0) & (inner > 0)]] = WANTED
            back = np.empty(len(order), np.uint8)
            back[order] = status
            ends = np.cumsum([len(p[0]) for p in parts])
            kept = [(r["block"], n[x > 0], x[x > 0]) for r, n, x in zip(rows, np.split(number, ends[:-1]), np.split(back, ends[:-1])) if x.any()]
            yield _batch(["block", "kind", "blob"], [k for k, *_ in kept], [1] * len(kept), [packed(n, x) for _, n, x in kept])

    return run


def _dealt(text: np.ndarray, runs, of: np.ndarray):
    """Class, document, first window and number of windows of the parts of runs `of`. Equal windows have their minimiser at
    one distance from their start: windows with at least BESIDE bytes before it share these, the others what follows it."""
    from xxhash import xxh3_64_intdigest

    view, out = memoryview(text), []
    for h, d, a, n, p in zip(*(x[of].tolist() for x in runs)):
        split = min(max(p - BESIDE + 1 - a, 0), n)  # so many windows have the bytes before
        if split:
            out.append((xxh3_64_intdigest(view[p - BESIDE : p], h), d, a, split))
        if split < n:
            out.append((xxh3_64_intdigest(view[p + KMER : p + LENGTH - BESIDE], h ^ 1), d, a + split, n - split))
    c = list(zip(*out)) or [()] * 4
    return np.array(c[0], np.uint64), *(np.array(x, np.int64) for x in c[1:])


def _segments(buckets: int):
    """(bucket, kind, block, blob): kind 0, segments for a bucket; kind 1, repeats known already."""

    def run(batches):
        for block, rows in _grouped(batches, "block"):
            held = [unpacked(r["blob"]) for r in rows if r["kind"] == 1]
            if not held:  # nothing returned: only copies within the block, if any, which come back, too
                held = [(np.zeros(0, np.int32), np.zeros(0, np.uint8))]
            _, key, lens, text = unpacked(_unzip(next(r["blob"] for r in rows if r["kind"] == 0)))
            runs, (h, own, doc, first, count, head) = segment_table(text, lens)
            status = np.zeros(len(h), np.uint8)
            status[np.concatenate([n for n, _ in held])] = np.concatenate([x for _, x in held])
            order, group = first_equal(h, own)
            copy = np.ones(len(h), bool)
            copy[order[group]] = False  # of equal segments of the block only the first has a verdict
            gone = copy | (status == REPEATS)
            begin = np.cumsum(lens) - lens
            out = []
            if gone.any():
                at = first[gone] - begin[doc[gone]]
                out.append((block % buckets, 1, block, packed(doc[gone].astype(np.int32), at.astype(np.int32), (at + count[gone]).astype(np.int32))))
            plain = status == WANTED
            dealt = np.flatnonzero(status == DEALT)
            last = np.append(head[1:], len(runs[0]))
            c, d, a, n = _dealt(text, runs, ragged_index(head[dealt], last[dealt] - head[dealt]))
            c, d, a, n = (np.concatenate(x) for x in ((h[plain], c), (doc[plain], d), (first[plain], a), (count[plain], n)))
            b = bucket_of(c, buckets)
            order = np.argsort(b, kind="stable")
            for i in np.split(order, np.flatnonzero(np.diff(b[order])) + 1):
                if len(i):
                    size = n[i] + LENGTH - 1
                    out.append((int(b[i[0]]), 0, block, _zip(packed(c[i], key[d[i]], d[i].astype(np.int32), (a[i] - begin[d[i]]).astype(np.int32), n[i].astype(np.int32), text[ragged_index(a[i], size)]))))
            if out:
                yield _batch(["bucket", "kind", "block", "blob"], *zip(*out))

    return run


def _unit_repeats(raw: memoryview, at: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, ...]:
    """Repeated windows of segments given in their order in the corpus: segment, first window, end."""
    size = count + LENGTH - 1
    seen: dict[bytes, int] = {}
    pieces = [bytes(raw[a : a + n]) for a, n in zip(at.tolist(), size.tolist())]
    lead = np.fromiter((seen.setdefault(x, i) for i, x in enumerate(pieces)), np.int64, len(pieces)) == np.arange(len(pieces))
    own = np.flatnonzero(lead)
    text, n, s = np.frombuffer(b"".join(seen), np.uint8), count[own], size[own]
    again = repeated_windows(text, ragged_index(np.cumsum(s) - s, n))
    edge = np.cumsum(n) - n
    prev, after = np.append(False, again[:-1]), np.append(again[1:], False)
    prev[edge] = False
    after[edge[1:] - 1] = False
    start, end = np.flatnonzero(again & ~prev), np.flatnonzero(again & ~after) + 1
    seg = np.searchsorted(edge, start, side="right") - 1
    copy = np.flatnonzero(~lead)
    return np.concatenate([own[seg], copy]), np.concatenate([start - edge[seg], np.zeros(len(copy), np.int64)]), np.concatenate([end - edge[seg], count[copy]])


def _bucket_repeats(batches):
    """(block, kind, blob): repeated windows of each block, as document, first and end; one suffix bucket at a time, its
    classes in units of about UNIT_BYTES."""
    for _, rows in _grouped(batches, "bucket"):
        out = [(r["block"], r["blob"].to_pybytes()) for r in rows if r["kind"] == 1]
        parts = [(r["block"], unpacked(_unzip(r["blob"]))) for r in rows if r["kind"] == 0]
        if parts:
            cls, key, doc, offset, count = (np.concatenate([p[i] for _, p in parts]) for i in range(5))
            block = np.repeat(np.array([b for b, _ in parts]), [len(p[0]) for _, p in parts])
            raw = memoryview(np.concatenate([p[5] for _, p in parts]))
            del parts
            size = count.astype(np.int64) + LENGTH - 1
            at = np.cumsum(size) - size
            order = np.lexsort((offset, doc, block, key, cls))  # within a class by place in the corpus
            head = np.flatnonzero(np.append(True, cls[order[1:]] != cls[order[:-1]]))
            ends = np.append(np.add.accumulate(size[order])[head[1:] - 1], size.sum())
            found, i = [], 0
            while i < len(head):
                j = max(i + 1, int(np.searchsorted(ends, (ends[i - 1] if i else 0) + UNIT_BYTES, side="right")))
                own = order[head[i] : head[j] if j < len(head) else len(order)]
                own = own[np.lexsort((offset[own], doc[own], block[own], key[own]))]
                s, a, b = _unit_repeats(raw, at[own], count[own].astype(np.int64))
                found.append((own[s], a, b))
                i = j
            s, a, b = (np.concatenate(x) for x in zip(*found))
            order = np.argsort(block[s], kind="stable")
            s, a, b = s[order], a[order], b[order]
            spans = [x.astype(np.int32) for x in (doc[s], offset[s] + a, offset[s] + b)]
            cut = np.flatnonzero(np.diff(block[s])) + 1
            for i in np.split(np.arange(len(s)), cut):
                if len(i):
                    out.append((int(block[s[i[0]]]), packed(*(x[i] for x in spans))))
        yield _batch(["block", "kind", "blob"], [b for b, _ in out], [1] * len(out), [x for _, x in out])


def merged_spans(begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Disjoint spans that cover the same bytes, ascending."""
    order = np.argsort(begin, kind="stable")
    begin, end = begin[order], np.maximum.accumulate(end[order]) if len(end) else end
    new = np.flatnonzero(np.append(True, begin[1:] > end[:-1])) if len(begin) else np.zeros(0, np.int64)
    return begin[new], end[np.append(new[1:], len(begin)) - 1] if len(new) else end


def _cut(keep: bool):
    """Each document of a block without its repeated bytes."""

    def run(batches):
        for _, rows in _grouped(batches, "block"):
            rest, _, lens, text = unpacked(_unzip(next(r["blob"] for r in rows if r["kind"] == 0)))
            ends = np.cumsum(lens)
            begin = ends - lens
            spans = [unpacked(r["blob"]) for r in rows if r["kind"] == 1]
            d, a, b = (np.concatenate([np.zeros(0, np.int64), *(x[i] for x in spans)]).astype(np.int64) for i in range(3))
            # one more between documents, so that spans that meet at a border stay apart
            a, b = merged_spans(begin[d] + a + d, begin[d] + b + LENGTH - 1 + d)
            doc = np.searchsorted(begin + np.arange(len(lens)), a, side="right") - 1
            removed = np.bincount(doc, b - a, minlength=len(lens)).astype(np.int64)
            runs = np.bincount(doc, minlength=len(lens))
            a, b = a - doc, b - doc
            left, raw, k = memoryview(text), [], 0
            for i, (x, y, n) in enumerate(zip(begin.tolist(), ends.tolist(), runs.tolist())):
                at, own = x, []
                for u, v in zip(a[k : k + n].tolist(), b[k : k + n].tolist()):
                    own.append(left[at:u])
                    at = v
                own.append(left[at:y])
                raw.append(b"".join(own))
                k += n
            table = pa.ipc.open_stream(pa.py_buffer(rest.tobytes())).read_next_batch()
            for at in range(0, len(raw), 1000):
                part = slice(at, at + 1000)
                own = [pa.array(lens[part]), pa.array(removed[part]), pa.array(runs[part])]
                if keep:
                    yield pa.RecordBatch.from_arrays([table.column("__cw_rest").slice(at, 1000), *own, pa.array([x.decode(errors="ignore") for x in raw[part]], pa.string())], ["__cw_rest", "n_bytes", "n_removed", "n_spans", "kept"])
                else:
                    key = np.asarray(table.column("__cw_order").slice(at, 1000), np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array(key, mask=key == LAST), *own, pa.array(raw[part], pa.binary())], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept"])

    return run


def remove_repeats(docs: DataFrame, keep: bool = False, bucket_bytes: int = 4_000_000, many: int = MANY) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept (the remaining bytes) of every row.

    keep: all columns but text instead, with __cw_text (a character that is cut in two goes), __cw_removed.
    many: a minimiser with more different segments is dealt out by the bytes beside it. Null and empty texts have no bytes; texts below 100 bytes stay whole; a text of any length is hashed in slices and its
    windows sorted in units, so that a worker holds the text itself and little else; of rows that repeat a doc_id the one
    in the earlier block and place counts as earlier; a null doc_id comes after all others; an empty table gives no row."""
    spark = docs.sparkSession
    blocks = blocks_of(docs)
    total = blocks.agg(F.sum("size")).first()[0] or 0
    buckets = max(partitions(spark), total // bucket_bytes)  # a bucket's memory stays as the corpus grows
    texts = blocks.select("block", F.lit(0).cast("long").alias("kind"), "blob")
    dealt = max(partitions(spark), total // TASK_BYTES)  # a task's share of the blocks stays, too

    found = blocks.mapInArrow(_minimisers(buckets), "bucket long, block long, blob binary").repartition(dealt, "bucket").sortWithinPartitions("bucket")
    again = found.mapInArrow(_verdicts(many), "block long, kind long, blob binary")
    pairs = texts.unionByName(again).repartition(dealt, "block").sortWithinPartitions("block", "kind")
    segments = pairs.mapInArrow(_segments(buckets), "bucket long, kind long, block long, blob binary").repartition(dealt, "bucket").sortWithinPartitions("bucket")
    spans = written(segments.mapInArrow(_bucket_repeats, "block long, kind long, blob binary"), "repeat-spans")
    last = texts.unionByName(spans).repartition(dealt, "block").sortWithinPartitions("block", "kind")
    if not keep:
        return last.mapInArrow(_cut(False), "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary")
    rest = docs.select(F.struct(*(docs[c] for c in docs.columns)).dropFields("text").alias("__cw_rest")).schema
    out = last.mapInArrow(_cut(True), rest.add("n_bytes", "long").add("n_removed", "long").add("n_spans", "long").add("kept", "string"))
    return out.select("__cw_rest.*", F.col("kept").alias("__cw_text"), F.col("n_removed").alias("__cw_removed")).withColumn("text", F.col("__cw_text"))
