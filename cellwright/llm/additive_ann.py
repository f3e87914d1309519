"""Approximate nearest neighbours by additive quantisation, largest inner product first.

Every vector is the sum of one codeword from each of several full-dimensional codebooks, learned on successive residuals
of a bounded sample. Encoding keeps a beam of the best partial sums. With the codes a norm is stored, the true length
over that of the sum. A query's inner products with all codewords make lookup tables, from which all rows are scored by
adding table entries. With each row a bound of its score's error is stored: the best of each block are scored again,
exactly and in double precision, on the original vectors, and so is every row whose bound leaves it a place among them.
Codes are made of directions, so vectors may have any length.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import written
from .suffix_dedup import packed, unpacked

FIT_ROWS, BOOKS, WORDS, BEAM = 12_000, 16, 256, 4
ROW_BLOCK, QUERY_BLOCK, RERANK = 8192, 8192, 256
#: queries of a block that are scored at a time
AT_ONCE = 128


def usable(vectors: DataFrame) -> DataFrame:
    """vec_id and vector of the rows that take part: no null, non-finite or all-zero vectors, none of another length than most."""
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v"))
    rows = rows.where(F.col("v").isNotNull() & F.col("vec_id").isNotNull() & F.exists("v", lambda x: x != 0))
    rows = rows.where(~F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf")))))
    sizes = rows.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").limit(1).collect()
    return rows.where(F.size("v") == (sizes[0]["d"] if sizes else 0))


def fit(sample: np.ndarray, books: int = BOOKS, words: int = WORDS, rounds: int = 4, seed: int = 3) -> np.ndarray:
    """Codebooks (books, words, dimension): k-means on what the books before leave over."""
    rng = np.random.default_rng(seed)
    rest, out = sample.astype(np.float32).copy(), []
    words = max(1, min(words, len(sample)))
    for _ in range(books):
        c = rest[rng.choice(len(rest), words, replace=False)]
        for _ in range(rounds):
            near = ((c * c).sum(1) - 2 * rest @ c.T).argmin(1)
            n = np.bincount(near, minlength=words)
            total = np.zeros_like(c)
            np.add.at(total, near, rest)
            c = np.where(n[:, None] > 0, total / np.maximum(n, 1)[:, None], c)
        near = ((c * c).sum(1) - 2 * rest @ c.T).argmin(1)
        rest -= c[near]
        out.append(c)
    return np.stack(out)


def directions(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Vectors of length 1 and the lengths. The largest coordinate is brought near 1 first, so that no square overflows."""
    e = np.frexp(np.abs(x).max(axis=1))[1]
    near = np.ldexp(x, -e[:, None])
    length = np.linalg.norm(near, axis=1)
    return near / length[:, None], np.ldexp(length, e)


def encode(x: np.ndarray, books: np.ndarray, beam: int = BEAM) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Codes (n, books) of directions by beam search, the stored norm of each (1 over the length of its sum of codewords),
    and the length of what its codewords, times the norm, leave over."""
    m, words, _ = books.shape
    full, x = x, x.astype(np.float32)
    rest, codes = x[:, None, :], np.zeros((len(x), 1, 0), np.uint16)
    error = (rest**2).sum(2)
    for c in books:
        cost = error[:, :, None] + (c * c).sum(1) - 2 * rest @ c.T
        width = min(beam, cost.shape[1] * words)
        flat = cost.reshape(len(x), -1)
        best = np.argpartition(flat, width - 1, axis=1)[:, :width]
        error = np.take_along_axis(flat, best, 1)
        parent, word = best // words, best % words
        rest = np.take_along_axis(rest, parent[:, :, None], 1) - c[word]
        codes = np.concatenate([np.take_along_axis(codes, parent[:, :, None], 1), word[:, :, None].astype(np.uint16)], 2)
    first = error.argmin(1)
    codes = codes[np.arange(len(x)), first]
    made = np.zeros_like(full)
    for k, c in enumerate(books):
        made += c[codes[:, k]]
    length = np.linalg.norm(made, axis=1)
    norms = np.where(length > 0, 1 / np.where(length > 0, length, 1), 1).astype(np.float32)
    return codes, norms, np.linalg.norm(full - norms[:, None].astype(np.float64) * made, axis=1)


def slack(books: np.ndarray) -> float:
    """How far a table score, before the stored norm, can be from its exact sum for a query of length 1."""
    longest = np.sqrt((books.astype(np.float64) ** 2).sum(2)).max(1).sum()
    return float((books.shape[2] + 2 * len(books) + 8) * 2.0**-23 * longest)


def table_scores(queries: np.ndarray, books: np.ndarray, codes: np.ndarray, norms: np.ndarray) -> np.ndarray:
    """(queries, rows): sums of lookup-table entries, times the stored norms."""
    total = np.zeros((len(queries), len(codes)), np.float32)
    for k, c in enumerate(books):
        total += (queries.astype(np.float32) @ c.T)[:, codes[:, k]]
    return total * norms  # doubles, as norms hold the lengths of rows


def best_of_block(q_ids, q, ids, x, scores, bound, rerank: int, k: int):
    """For each query its k best rows of a block: query, rows, scores. scores and bound are for directions of queries.

    The rerank best by table are scored exactly; the k-th of them is a floor. Any other row that can reach it, by its
    table score and bound, is scored too: first with one product in doubles, then, within its rounding, as the others."""
    d, lengths = directions(q)
    size = np.linalg.norm(x, axis=1)
    for i in range(len(q)):
        mine = ids == q_ids[i]
        s = np.where(mine, -np.inf, scores[i])
        at = np.flatnonzero(~mine)
        if len(s) > rerank:
            first = np.argpartition(s, len(s) - rerank)[len(s) - rerank :]
            first = first[~mine[first]]
            rough = (x[first] * d[i]).sum(axis=1)
            if len(rough) >= k:
                floor = np.partition(rough, len(rough) - k)[len(rough) - k] - 1e-12 * size[first].max()
                # a bound that is not a number keeps its row
                at = np.flatnonzero(~mine & ~(s + bound < floor))
                rough = x[at] @ d[i]
                floor = np.partition(rough, len(rough) - k)[len(rough) - k]
                at = at[~(rough + 1e-12 * size[at] < floor - 1e-12 * size[at].max())]
        # one term after another, as a plain loop adds them
        exact = np.add.accumulate(x[at] * q[i], axis=1)[:, -1]
        order = np.lexsort((ids[at], -exact))[:k]
        yield i, at[order], exact[order]


def search(vectors: DataFrame, k: int = 20, every: int = 20, fit_rows: int = FIT_ROWS, rerank: int = RERANK) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest rows of each row whose vec_id is divisible by `every`.

    Codebooks are fitted on at most fit_rows rows, taken by the hash of their id; every row is indexed. Rows that repeat a
    vec_id are candidates each (none of them for the query of that id) and answered once each; an empty table, or one
    without usable vectors, gives no row. Rows beyond `rerank` a block are left out only where their error bound
    proves them worse, so the answer is the exact one; scores beyond a double's range are infinite. Tables meet in blocks of rows and of queries; a block pair is one row, so
    the rows travel once for each QUERY_BLOCK queries. Vectors of another length than most rows have take no part."""
    spark = vectors.sparkSession
    rows = written(usable(vectors), "vectors")
    n, n_q = rows.agg(F.count(F.lit(1)), F.count(F.when(F.col("vec_id") % every == 0, 1))).first()
    out = "query_id long, query_no long, vec_id long, score double"
    if not n or not n_q:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    sample = rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(fit_rows).toPandas()
    books = spark.sparkContext.broadcast(fit(directions(np.stack(sample["v"].to_numpy()))[0]))  # a fixed size
    blocks, groups = -(-n // ROW_BLOCK), -(-n_q // QUERY_BLOCK)

    def gather(coded: bool):
        def run(batches):
            import pyarrow as pa
            from pyspark import TaskContext

            ids, vs = [], []
            for b in batches:
                ids.append(np.asarray(b.column("vec_id"), np.int64))
                vs.append(np.asarray(b.column("v").flatten(), np.float64).reshape(b.num_rows, -1))
            if ids:
                i, v = np.concatenate(ids), np.concatenate(vs)
                order = np.argsort(i, kind="stable")
                i, v = i[order], v[order]
                more = ()
                if coded:
                    d, length = directions(v)
                    parts = [encode(d[a : a + 1024], books.value) for a in range(0, len(d), 1024)]
                    norms, left = (np.concatenate([p[j] for p in parts]) for j in (1, 2))
                    # what is left over, the rounding of tables and that of doubles
                    bound = length * (left + norms * slack(books.value) + 1e-6)
                    more = (np.concatenate([p[0] for p in parts]).ravel(), norms * length, bound)
                yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId()], pa.int64()), pa.array([packed(i, v.ravel(), *more)], pa.binary())], ["no", "blob"])

        return run

    def dealt(frame: DataFrame, parts: int, coded: bool, name: str) -> DataFrame:
        return written(frame.repartition(parts).mapInArrow(gather(coded), "no long, blob binary"), name)

    index = dealt(rows, blocks, True, "codes").select(F.col("no").alias("r"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(groups - 1).cast("long"))).alias("g"), F.col("blob").alias("rows"))
    asked = dealt(rows.where(F.col("vec_id") % every == 0), groups, False, "queries").select(F.col("no").alias("g"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("r"), F.col("blob").alias("queries"))

    def meet(batches):
        import pyarrow as pa

        for b in batches:
            for g, left, right in zip(*(b.column(c).to_pylist() for c in ("g", "queries", "rows"))):
                q_ids, q = unpacked(left)
                ids, x, codes, norms, bound = unpacked(right)
                q, x, codes = q.reshape(len(q_ids), -1), x.reshape(len(ids), -1), codes.reshape(len(ids), -1)
                for low in range(0, len(q), AT_ONCE):
                    part = slice(low, low + AT_ONCE)
                    scores = table_scores(directions(q[part])[0], books.value, codes, norms)
                    found = list(best_of_block(q_ids[part], q[part], ids, x, scores, bound, rerank, k))
                    no = low + np.concatenate([np.full(len(a), i) for i, a, _ in found])
                    at = np.concatenate([a for _, a, _ in found])
                    yield pa.RecordBatch.from_arrays([pa.array(q_ids[no]), pa.array(no + (g << 32)), pa.array(ids[at]), pa.array(np.concatenate([s for *_, s in found]))], ["query_id", "query_no", "vec_id", "score"])

    pairs = asked.join(index, ["g", "r"]).select("g", "queries", "rows")
    best = Window.partitionBy("query_id", "query_no").orderBy(F.desc("score"), "vec_id")
    ranked = pairs.mapInArrow(meet, out).withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
    return ranked.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def exact_search(vectors: DataFrame, k: int = 20, every: int = 20) -> DataFrame:
    """The same answer without an index, for measuring recall on small tables."""
    rows = usable(vectors)
    q = rows.where(F.col("vec_id") % every == 0).select(F.col("vec_id").alias("query_id"), F.col("v").alias("q"))
    dot = F.aggregate(F.zip_with("q", "v", lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    pairs = rows.join(F.broadcast(q), F.col("query_id") != F.col("vec_id")).withColumn("score", dot)
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return pairs.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
