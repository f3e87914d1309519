"""SimHash near-duplicates: byte-position inverted index, count filtering, verification, components.

Two 64-bit fingerprints that differ in at most four bits share at least four of their eight positional bytes. Lists keyed
by one positional byte would hold 1/256 of all fingerprints each, so the index joins bytes: its lists are keyed by three
positional bytes, for a family of twenty position triples of which every four positions contain one. Within a list the
shared positional bytes of each pair are tallied, pairs below the guaranteed four are dropped, the rest verified bit by
bit. A list hands on a spanning forest of its links, never all pairs of a group.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_and_text, text_chunks, written

WORDS, BITS, SEED, SMALL_LIST = 4, 4, 42, 12
#: fingerprints of more than one such share of all rows are joined apart from the others
HOT_SHARES = 2000


def position_triples() -> list[tuple[int, ...]]:
    """Triples of the eight byte positions such that any four positions contain one of them.

    Three classes of positions; a triple lies in one class, or two in a class and one in the class that follows it."""
    classes = [(0, 1, 2), (3, 4, 5), (6, 7)]
    of = {p: k for k, c in enumerate(classes) for p in c}
    out = []
    for t in combinations(range(8), 3):
        held = sorted(of[p] for p in t)
        a, b = min(held, key=held.count), max(held, key=held.count)
        if held[0] == held[2] or len(set(held)) == 2 and (b + 1) % 3 == a:
            out.append(t)
    return out


def fingerprints_of(texts: list[str], words: int = WORDS, seed: int = SEED) -> np.ndarray:
    """SimHash of each text: majority bits of the XXH64 of its word shingles, repeats counted; no words: zero."""
    from xxhash import xxh64_intdigest

    fold = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")
    hashes: list[int] = []
    counts = np.zeros(len(texts), np.int64)
    for i, t in enumerate(texts):
        own = t.encode().translate(fold).split()
        if not own:
            continue
        line = b" ".join(own)
        n = max(1, len(own) - words + 1)
        if n == 1:
            hashes.append(xxh64_intdigest(line, seed))
        else:
            ends = np.cumsum(np.fromiter(map(len, own), np.int64, len(own)) + 1)
            starts = np.concatenate([[0], ends[: n - 1]]).tolist()
            hashes += [xxh64_intdigest(line[a:b], seed) for a, b in zip(starts, (ends[words - 1 :] - 1).tolist())]
        counts[i] = n
    out = np.zeros(len(texts), np.uint64)
    some = np.flatnonzero(counts)
    if len(some):
        n = counts[some]
        bits = np.unpackbits(np.array(hashes, "<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        ones = np.add.reduceat(bits, np.cumsum(n) - n, axis=0, dtype=np.int32)
        out[some] = np.packbits(2 * ones > n[:, None], axis=1, bitorder="little").view("<u8").ravel()
    return out


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, text_hash (of the text as it is), fp (the 64 bits as a signed long) of every row."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for part in text_chunks(batch, 1_500_000):
                fp = fingerprints_of(part.column("text").to_pylist())
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("text_hash"), pa.array(fp.view(np.int64))], ["doc_id", "text_hash", "fp"])

    rows = id_and_text(docs).withColumn("text_hash", F.xxhash64("text"))
    return rows.mapInArrow(run, "doc_id long, text_hash long, fp long")


def near(a: np.ndarray, b, bits: int = BITS) -> np.ndarray:
    """Whether fingerprints link: the tally of shared positional bytes reaches 8 - bits, then at most `bits` bits differ."""
    x = a ^ b
    y = x | x >> np.uint64(4)
    y |= y >> np.uint64(2)
    y |= y >> np.uint64(1)
    ok = np.bitwise_count(y & np.uint64(0x0101010101010101)) <= bits  # differing positional bytes
    at = np.flatnonzero(ok)
    ok[at] = np.bitwise_count(x[at]) <= bits
    return ok


def forest(fps: np.ndarray, bits: int = BITS) -> list[tuple[int, int]]:
    """(root, member) pairs that connect each component of one list's links."""
    out, rest = [], fps
    while len(rest):
        root, rest, front = rest[0], rest[1:], [rest[0]]
        while front and len(rest):
            hit = near(rest, front.pop(), bits)
            if hit.any():
                found = rest[hit]
                out += [(int(root), int(f)) for f in found]
                front += list(found)
                rest = rest[~hit]
    return out


def list_links(keys: np.ndarray, fps: np.ndarray, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """Links found in posting lists; keys sorted, one for each entry."""
    heads = np.flatnonzero(np.append(True, keys[1:] != keys[:-1]))
    size = np.diff(np.append(heads, len(keys)))
    a, b = [], []
    small = np.repeat((size > 1) & (size <= SMALL_LIST), size)
    k, f = keys[small], fps[small]
    for step in range(1, SMALL_LIST):
        at = np.flatnonzero(k[step:] == k[:-step])
        if not len(at):
            break
        at = at[near(f[at], f[at + step], bits)]
        a.append(f[at])
        b.append(f[at + step])
    for h, n in zip(heads[size > SMALL_LIST].tolist(), size[size > SMALL_LIST].tolist()):
        links = np.array(forest(fps[h : h + n], bits), np.uint64).reshape(-1, 2)
        a.append(links[:, 0])
        b.append(links[:, 1])
    return (np.concatenate(x) if x else np.zeros(0, np.uint64) for x in (a, b))


def links(nodes: DataFrame, bits: int = BITS) -> DataFrame:
    """Distinct links (a < b) of distinct fingerprints, enough to connect whatever is connected."""

    def byte(p: int):
        return F.shiftrightunsigned("fp", 8 * p).bitwiseAND(F.lit(255))

    postings = F.array(
        *(
            F.lit(k << 24).cast("long").bitwiseOR(F.shiftleft(byte(x), 16)).bitwiseOR(F.shiftleft(byte(y), 8)).bitwiseOR(byte(z))
            for k, (x, y, z) in enumerate(position_triples())
        )
    )

    def run(batches):
        import pyarrow as pa

        kept_k, kept_f = np.zeros(0, np.int64), np.zeros(0, np.uint64)

        def found(k, f):
            a, b = list_links(k, f, bits)
            a, b = a.view(np.int64), b.view(np.int64)
            pair = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)], axis=1), axis=0)
            return pa.RecordBatch.from_arrays([pa.array(pair[:, 0]), pa.array(pair[:, 1])], ["a", "b"])

        for batch in batches:
            k = np.concatenate([kept_k, np.asarray(batch.column("key"), np.int64)])
            f = np.concatenate([kept_f, np.asarray(batch.column("fp"), np.int64).view(np.uint64)])
            if not len(k):
                continue
            cut = int(np.searchsorted(k, k[-1]))  # the last list may go on in the next batch
            kept_k, kept_f = k[cut:], f[cut:]
            if cut:
                yield found(k[:cut], f[:cut])
        if len(kept_k):
            yield found(kept_k, kept_f)

    index = nodes.select(F.explode(postings).alias("key"), "fp").repartition("key").sortWithinPartitions("key", "fp")
    return index.mapInArrow(run, "a long, b long").groupBy("a", "b").agg(F.count(F.lit(1)).alias("lists")).select("a", "b")


def components(edges: DataFrame) -> DataFrame:
    """(node, root) of each linked node: root is the smallest node that it reaches. Alternating large and small stars.

    The least neighbour is an aggregate with partial sums, and its join back can be split, so a hub of any degree is no
    hot task; each round is written to the shared folder. Rounds go on until the stars stay as they are."""
    edges = written(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "links")
    state = None
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        joined = large.join(least, "u")
        small = joined.select("u", F.col("m").alias("v")).unionByName(joined.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")))
        edges = written(small.distinct(), "stars")
        now = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first()
        if now == state:
            return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
        state = now


def near_groups(docs: DataFrame) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable), text_hash of every row.

    Null and texts without words have fingerprint zero and link like any other; a text of any length is hashed whole; a
    null doc_id stays null and names a component only where nothing else does; repeated rows get the same component; an
    empty table gives no row."""
    prints = written(fingerprints(docs), "fingerprints")
    nodes = written(prints.groupBy("fp").agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("rows")), "nodes")
    found = components(links(nodes.select("fp")))
    member = found.select("node", "root").unionByName(found.select(F.col("root").alias("node"), "root").distinct())
    named = member.join(nodes.withColumnRenamed("fp", "node"), "node").groupBy("root").agg(F.min("first").alias("component"))
    label = member.join(named, "root").select(F.col("node").alias("fp"), "component")
    final = written(nodes.join(label, "fp", "left").select("fp", "rows", F.coalesce("component", "first").alias("component_id")), "labels")
    # a fingerprint of more than a share of all rows is hot: there are at most HOT_SHARES of them, so they can be broadcast
    bound = nodes.agg(F.sum("rows")).first()[0] or 0
    hot = F.broadcast(final.where(F.col("rows") * HOT_SHARES > bound).drop("rows"))
    rest = final.where(F.col("rows") * HOT_SHARES <= bound).drop("rows")
    out = prints.join(hot, "fp").unionByName(prints.join(hot.select("fp"), "fp", "left_anti").join(rest, "fp"))
    return out.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id", "text_hash")
