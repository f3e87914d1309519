"""Exact dedup through an extendible-hash index on shared files.

Texts are keyed by a 64-bit hash of their normalised bytes. A directory of 2^depth entries leads from the key's leading
bits to a bucket; a bucket above its capacity is split by one more bit, and the directory doubles where the bucket
already uses all of its bits. Owner tasks take buckets (key ranges): entries of one key are chained, bytes are compared
along the chain, and the pages (key, place in chain, digest, survivor, copies) are written to the shared folder. A key
that one row has needs no comparison: its page is written without its bytes.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import id_and_text, written

#: bytes of a bucket; what a page takes beside a text; prefixes whose loads the driver gathers at a time
CAPACITY, PAGE_BYTES, GATHERED = 8_000_000, 64, 1 << 16
#: tasks beyond which an owner takes several buckets, one after another
OWNERS = 50_000
#: bytes of texts that a task holds while it collapses copies
HELD_BYTES = 16_000_000


def normalised(text: Column) -> Column:
    return F.regexp_replace(text, "[\\x20\\x09-\\x0D]+", " ")


class Directory:
    """Extendible-hash directory. It grows by loads known for prefixes of ever more bits, where buckets are overfull."""

    def __init__(self, capacity: int):
        self.capacity, self.depth, self.entries = capacity, 0, np.zeros(1, np.int64)
        self.local, self.prefix = [0], [0]  # depth and leading bits of each bucket

    def grow(self, bits: int, prefixes: np.ndarray, loads: np.ndarray, buckets: list[int]) -> list[int]:
        """Splits overfull ones among the buckets; prefixes: ascending, of `bits` bits. Returns those that need more bits."""
        sums, more, todo = np.concatenate([[0], np.cumsum(loads)]), [], list(buckets)
        while todo:
            b = todo.pop()
            width = bits - self.local[b]
            low, high = np.searchsorted(prefixes, [self.prefix[b] << width, (self.prefix[b] + 1) << width])
            if sums[high] - sums[low] > self.capacity:
                if width:
                    todo += [b, self.split(b)]
                else:
                    more.append(b)
        return more

    def split(self, b: int) -> int:
        """Splits bucket b by one more bit; the new bucket takes the upper half."""
        if self.local[b] == self.depth:  # the directory doubles
            self.entries = np.repeat(self.entries, 2)
            self.depth += 1
        self.local[b] += 1
        self.prefix[b] *= 2
        new = len(self.local)
        self.local.append(self.local[b])
        self.prefix.append(self.prefix[b] + 1)
        width = self.depth - self.local[b]
        self.entries[self.prefix[new] << width : (self.prefix[new] + 1) << width] = new
        return new

    def buckets(self, keys: np.ndarray) -> np.ndarray:
        """Bucket of each key (signed 64-bit)."""
        return self.entries[(keys.view(np.uint64) >> np.uint64(64 - self.depth)).astype(np.int64)] if self.depth else np.zeros(len(keys), np.int64)


def build_directory(keys: DataFrame, capacity: int = CAPACITY) -> Directory:
    """keys: h, load. Loads are summed by leading bits, first few, then more where a bucket is still overfull; the driver
    gathers at most GATHERED prefixes at a time. No load counts for more than a quarter of a bucket, so that a single
    text of any length, which no bit can divide, does not drive the depth."""
    loads = keys.select("h", F.least("load", F.lit(max(1, capacity // 4))).alias("load"))
    directory, bits, over = Directory(capacity), 0, [0]
    while over and bits < 60:
        more = min(60 - bits, max(1, (GATHERED // len(over)).bit_length() - 1))
        rows = loads
        if bits:  # as many prefixes as overfull buckets
            part = keys.sparkSession.createDataFrame([(directory.prefix[b],) for b in over], "lead long")
            rows = loads.join(F.broadcast(part), F.shiftrightunsigned("h", 64 - bits) == F.col("lead"), "left_semi")
        bits += more
        sums = rows.groupBy(F.shiftrightunsigned("h", 64 - bits).alias("p")).agg(F.sum("load").alias("load")).collect()
        sums.sort()
        over = directory.grow(bits, np.array([r["p"] for r in sums], np.int64), np.array([r["load"] for r in sums], np.int64), over)
    return directory


def _combine(batches):
    """Equal texts of a task become one entry with the smallest doc_id and the number of copies; what is held is bounded."""
    import pyarrow as pa

    seen: dict[str, list] = {}
    held = 0

    def entries():
        columns = zip(*((*e, t) for t, e in seen.items()))
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, (pa.int64(), pa.int64(), pa.int64(), pa.string()))], ["h", "doc_id", "n", "norm"])

    for batch in batches:
        for h, d, t in zip(batch.column("h").to_pylist(), batch.column("doc_id").to_pylist(), batch.column("norm")):
            t = t.as_py()
            e = seen.get(t)
            if e is None:
                seen[t], held = [h, d, 1], held + len(t) + 200
                if held > HELD_BYTES:
                    yield entries()
                    seen, held = {}, 0
            else:
                e[1] = d if e[1] is None or d is not None and d < e[1] else e[1]
                e[2] += 1
    if seen:
        yield entries()


def _own(batches):
    """Entries in the order of their keys: a chain of different texts for each key, bytes compared along it."""
    import pyarrow as pa

    def page(key, chain):
        for place, (raw, keep, n) in enumerate(chain):
            yield key, place, hashlib.sha256(raw).hexdigest(), keep, n

    key, chain = None, []
    for batch in batches:
        out = []
        for h, d, n, t in zip(*(batch.column(c).to_pylist() for c in ("h", "doc_id", "n", "norm"))):
            if h != key:
                out += page(key, chain)
                key, chain = h, []
            raw = t.encode()
            for e in chain:
                if e[0] == raw:
                    e[1] = d if e[1] is None or d is not None and d < e[1] else e[1]
                    e[2] += n
                    break
            else:
                chain.append([raw, d, n])
        yield pa.RecordBatch.from_pylist([dict(zip(PAGE.names, r)) for r in out], schema=PAGE)
    yield pa.RecordBatch.from_pylist([dict(zip(PAGE.names, r)) for r in page(key, chain)], schema=PAGE)


def _page_schema():
    import pyarrow as pa

    return pa.schema([("h", pa.int64()), ("place", pa.int32()), ("text_sha256", pa.string()), ("keep_id", pa.int64()), ("group_size", pa.int64())])


PAGE = _page_schema()


def build_index(docs: DataFrame, capacity: int = CAPACITY) -> tuple[DataFrame, DataFrame, Directory]:
    """The rows (doc_id, h, text_sha256, size), the index pages (h, place, text_sha256, keep_id, group_size) of all keys,
    both written to the shared folder, and the directory.

    Only keys that more than one row has travel with their bytes, one entry for each task and text, so a group of copies
    of any size reaches its owner as a few entries. There is an owner task for each bucket, up to OWNERS."""
    keyed = id_and_text(docs).select("doc_id", normalised(F.col("text")).alias("norm")).withColumn("h", F.xxhash64("norm"))
    rows = written(keyed.select("doc_id", "h", F.sha2("norm", 256).alias("text_sha256"), F.octet_length("norm").alias("size")), "text-keys")
    keys = written(rows.groupBy("h").agg(F.count(F.lit(1)).alias("c"), F.max("size").alias("size"), F.min("doc_id").alias("doc_id")), "keys")
    repeated = written(keys.where("c > 1"), "repeated-keys")  # a table of its own, so that Spark sees its size
    directory = build_directory(repeated.select("h", (F.col("size") + PAGE_BYTES).alias("load")), capacity)
    shared = docs.sparkSession.sparkContext.broadcast(directory)  # a few bytes for each bucket of many megabytes

    def owned(batches):
        import pyarrow as pa

        for batch in batches:
            found = shared.value.buckets(np.ascontiguousarray(np.asarray(batch.column("h"), np.int64)))
            yield pa.RecordBatch.from_arrays([pa.array(found), *batch.columns], ["bucket", *batch.schema.names])

    entries = keyed.join(repeated.select("h"), "h", "left_semi").select("h", "doc_id", "norm").mapInArrow(lambda x: owned(_combine(x)), "bucket long, h long, doc_id long, n long, norm string")
    chains = entries.repartition(min(len(directory.local), OWNERS), "bucket").sortWithinPartitions("bucket", "h").drop("bucket")
    compared = chains.mapInArrow(_own, "h long, place int, text_sha256 string, keep_id long, group_size long")
    single = keys.where("c = 1").select("h", F.lit(0).alias("place"), F.lit(None).cast("string").alias("text_sha256"), F.col("doc_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"))
    return rows, written(compared.unionByName(single), "hash-index"), directory


def exact_groups(docs: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 of every row.

    Null and empty texts are equal; texts of any length are hashed and compared whole; rows that repeat the doc_id that
    stays are all marked kept; a null doc_id is kept only where its group has no other id; an empty table gives no row. A
    key with two different texts has a chain of two pages, told apart by the digest of their bytes."""
    rows, index, _ = build_index(docs, capacity)
    rows, index = rows.select("doc_id", "h", "text_sha256").alias("r"), index.alias("i")
    same = (F.col("r.h") == F.col("i.h")) & (F.col("i.text_sha256").isNull() | (F.col("i.text_sha256") == F.col("r.text_sha256")))
    return rows.join(index, same).select("r.doc_id", "keep_id", "group_size", F.col("r.doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "r.text_sha256")
