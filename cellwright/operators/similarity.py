"""Similar formulas: token edit similarity, pooled embeddings, cosine, retrieval, and the two-layer similarity head."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cellwright.functions import lexing
from cellwright.functions.dialect import SPARK, Spark

DIM = 16


def masked(df: DataFrame, key: str = "formula_id") -> DataFrame:
    """id, tokens (constants masked) of all formulas; those equal after masking count once, under the smallest id."""
    out = lexing.with_tokens(df.select(key, "formula")).withColumn("masked", F.expr(lexing.sketch(SPARK, "tokens", "kinds", ("number", "string"))))
    return out.groupBy("masked").agg(F.min(key).alias("id")).select("id", F.expr(lexing.lex(SPARK, "masked")).alias("tokens"))


def _lowest(df: DataFrame, n: int, seed: int, key: str) -> DataFrame:
    return df.withColumn("h", F.expr(SPARK.u32(str(seed), key, "'similarity'"))).orderBy("h", key).limit(n).drop("h")


def masked_sample(df: DataFrame, n: int = 1000, seed: int = 1, key: str = "formula_id") -> DataFrame:
    """As masked, of the n formulas of lowest keyed hash: the evaluation set, of the published size."""
    return masked(_lowest(df, n, seed, key), key)


def similarity_sets(df: DataFrame, n_train: int = 10_000, n_eval: int = 1000, seed: int = 1, key: str = "formula_id") -> tuple[DataFrame, DataFrame]:
    """Training and evaluation formulas (id, tokens), disjoint also after masking; sizes are the published ones."""
    held = masked_sample(df, n_eval, seed, key)
    low = _lowest(df, n_train + n_eval, seed, key)
    train = masked(low, key).withColumn("m", F.array_join("tokens", "")).join(held.select(F.array_join("tokens", "").alias("m")), "m", "left_anti")
    return train.drop("m"), held


def paired(rows: DataFrame, partners: int = 10) -> DataFrame:
    """id_a, id_b, ta, tb: each row with `partners` others at fixed distances in the order of a hash, a bounded sample of all pairs."""
    order = Window.orderBy(F.xxhash64("id"), "id")  # rows are a bounded sample
    ranked = rows.withColumn("r", F.row_number().over(order) - 1).cache()
    n = ranked.count()
    steps = sorted({max(1, (7919 * k * k + k) % max(n, 2)) for k in range(1, partners + 1)})
    a = ranked.select(F.col("id").alias("id_a"), F.col("tokens").alias("ta"), F.explode(F.array(*(F.pmod(F.col("r") + F.lit(k), F.lit(max(n, 1))) for k in steps))).alias("r"))
    return a.join(ranked.select("r", F.col("id").alias("id_b"), F.col("tokens").alias("tb")), "r").where("id_a <> id_b").drop("r")


def edit_similarity(d: Spark, a: str, b: str) -> str:
    """1 - Levenshtein distance over tokens / the longer length. Tokens of the pair are numbered and written as one character
    each, so the engine's string distance applies."""
    # the pair's distinct tokens are bound once, as a field of a struct: written into the inner lambda they would be made anew for each token
    if type(d) is Spark:
        bound = d.arr(d.names(a=a, b=b, u=f"array_distinct(concat({a}, {b}))"))
        code = "case when size(z.u) < 127 then chr(array_position(z.u, x)) else decode(unhex(hex(19968 + array_position(z.u, x))), 'UTF-16BE') end"
        left, right = (f"array_join(transform({x}, x -> {code}), '')" for x in ("z.a", "z.b"))
        n = "greatest(size(z.a), size(z.b))"
    else:
        bound = d.arr(d.names(a=a, b=b, u=f"list_distinct({a} || {b})"))
        left, right = (f"array_to_string(list_transform({x}, lambda x: chr(CAST(list_position(z.u, x) AS INT))), '')" for x in ("z.a", "z.b"))
        n = "greatest(len(z.a), len(z.b))"
    one = f"(case when {n} = 0 then cast(1 as double) else 1 - cast(levenshtein({left}, {right}) as double) / {n} end)"
    return d.at(d.each(bound, "z", one), "1")


def pairwise(sample: DataFrame, similarity: str | None = None) -> DataFrame:
    """id_a < id_b, sim for all pairs of a bounded sample (thousands): blocks of about a hundred rows meet blocks by equal keys."""
    blocks = max(4, sample.count() // 100)
    left = sample.select(F.col("id").alias("id_a"), F.col("tokens").alias("ta"), F.pmod("id", F.lit(blocks)).alias("x"))
    right = sample.select(F.col("id").alias("id_b"), F.col("tokens").alias("tb"), F.pmod("id", F.lit(blocks)).alias("y"))
    grid = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long")))
    pairs = left.withColumn("y", grid).join(right.withColumn("x", grid), ["x", "y"]).where("id_a < id_b")
    return pairs.select("id_a", "id_b", F.expr(similarity or edit_similarity(SPARK, "ta", "tb")).alias("sim"))


def edit_sim_join(rows: DataFrame, tau: float) -> DataFrame:
    """Pairs with edit similarity of at least tau, exactly.

    Edits change at most (1 - tau) of the longer length, so pairs share at least that many tokens fewer than the length:
    every pair meets on one of the rarest tokens of both sides (prefix filter); lengths are compared, then the distance."""
    idx = rows.select("id", "tokens", F.size("tokens").alias("n"), F.posexplode("tokens").alias("p", "tok"))
    seen = Window.partitionBy("id", "tok").orderBy("p")
    idx = idx.withColumn("tok", F.concat("tok", F.lit("\u0001"), F.row_number().over(seen)))  # repeats are tokens of their own
    freq = idx.groupBy("tok").agg(F.count(F.lit(1)).alias("f"))
    rare = Window.partitionBy("id").orderBy("f", "tok")
    pre = idx.join(freq, "tok").withColumn("r", F.row_number().over(rare)).where(F.col("r") <= F.floor(F.col("n") * (1 - tau) / tau) + 1)
    # a partner is at most n / tau long; its edits are at most (1 - tau) times that
    a = pre.select("tok", F.col("id").alias("id_a"), F.col("n").alias("na"))
    b = pre.select("tok", F.col("id").alias("id_b"), F.col("n").alias("nb"))
    cand = a.join(b, "tok").where((F.col("id_a") < F.col("id_b")) & (F.least("na", "nb") >= tau * F.greatest("na", "nb") - 1e-9)).select("id_a", "id_b").distinct()
    full = cand.join(rows.select(F.col("id").alias("id_a"), F.col("tokens").alias("ta")), "id_a").join(rows.select(F.col("id").alias("id_b"), F.col("tokens").alias("tb")), "id_b")
    return full.select("id_a", "id_b", F.expr(edit_similarity(SPARK, "ta", "tb")).alias("sim")).where(F.col("sim") >= tau - 1e-9)


def _distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Levenshtein distances of the rows of two matrices of token numbers, row by row."""
    row = np.tile(np.arange(b.shape[1] + 1, dtype=np.int32), (len(a), 1)).T
    for i in range(a.shape[1]):
        new = np.empty_like(row)
        new[0] = i + 1
        for j in range(b.shape[1]):
            new[j + 1] = np.minimum(np.minimum(row[j + 1], new[j]) + 1, row[j] + (a[:, i] != b[:, j]))
        row = new
    return row[-1]


def _near(a: np.ndarray, b: np.ndarray, tau: float, room: int = 200_000) -> np.ndarray:
    """Whether the rows of two matrices of token numbers have an edit similarity of at least tau, pair by pair.

    Places that differ are an upper bound of the distance of rows of one length, tokens that are not shared a lower one;
    only pairs between the bounds have their distance worked out."""
    most = max(a.shape[1], b.shape[1])
    allowed = int(np.floor((1 - tau + 1e-9) * most))
    hit = np.zeros((len(a), len(b)), bool)
    if a.shape[1] == b.shape[1]:
        same = np.zeros(hit.shape, np.int32)
        for p in range(most):
            same += a[:, p, None] == b[None, :, p]
        hit = most - same <= allowed
    shared = np.zeros(hit.shape, np.float32)
    for k in np.intersect1d(a, b):
        na, nb = ((x == k).sum(1) for x in (a, b))
        for c in range(1, min(na.max(), nb.max()) + 1):  # the c-th of a token meets the c-th on the other side
            i, j = np.flatnonzero(na >= c), np.flatnonzero(nb >= c)
            if len(i) == len(a) and len(j) == len(b):
                shared += 1
            else:
                shared[np.ix_(i, j)] += 1
    i, j = np.nonzero(~hit & (most - shared <= allowed))
    for at in range(0, len(i), room):
        x, y = i[at : at + room], j[at : at + room]
        hit[x, y] = _distances(a[x], b[y]) <= allowed
    return hit


def edit_sim_links(rows: DataFrame, tau: float, rows_at_once: int = 1024) -> DataFrame:
    """id, links: how many other rows (different ids) have an edit similarity of at least tau. Exact; no pair is listed.

    Rows of one length are dealt to blocks of bounded size, and blocks whose lengths allow a link meet once by equal keys."""
    sized = rows.select("id", "tokens", F.size("tokens").alias("n")).where("n >= 0")
    lengths = {r["n"]: r["count"] for r in sized.groupBy("n").count().collect()}
    blocks = [(n, k) for n, c in sorted(lengths.items()) for k in range(-(-c // rows_at_once))]
    met = [(i, j) for i, (n, _) in enumerate(blocks) for j, (m, _) in enumerate(blocks[i:], i) if n >= tau * m - 1e-9]
    spark, first = rows.sparkSession, {}
    for i, (n, _) in enumerate(blocks):
        first.setdefault(n, i)
    of = spark.createDataFrame([(n, i, -(-lengths[n] // rows_at_once)) for n, i in first.items()], "n int, first int, parts int")
    own = sized.join(F.broadcast(of), "n").withColumn("b", F.col("first") + F.pmod(F.xxhash64("id"), "parts").cast("int"))
    plan = F.broadcast(spark.createDataFrame(met, "x int, y int"))
    left, right = own.select("id", "tokens", F.col("b").alias("x")).join(plan, "x"), own.select(F.col("id").alias("id_b"), F.col("tokens").alias("tb"), F.col("b").alias("y")).join(plan, "y")

    def linked(key, a, b):
        import pandas as pd

        if not len(a) or not len(b):
            return pd.DataFrame({"id": pd.Series(dtype="int64"), "met": pd.Series(dtype="int64")})
        number = {}
        u, v = (np.array([[number.setdefault(t, len(number)) for t in x] for x in p], np.int32).reshape(len(p), -1) for p in (a["tokens"], b["tb"]))
        hit = _near(u, v, tau)
        ia, ib = a["id"].to_numpy(), b["id_b"].to_numpy()
        hit &= ia[:, None] != ib[None, :]
        ids, counts = ia, hit.sum(1)
        if key[0] != key[1]:
            ids, counts = np.concatenate([ia, ib]), np.concatenate([counts, hit.sum(0)])
        return pd.DataFrame({"id": ids, "met": counts.astype(np.int64)})

    pairs = left.groupBy("x", "y").cogroup(right.groupBy("x", "y")).applyInPandas(linked, "id long, met long")
    return rows.select("id").join(pairs.groupBy("id").agg(F.sum("met").alias("links")), "id", "left").select("id", F.coalesce("links", F.lit(0)).cast("long").alias("links"))


def hash_pooled(d: Spark, tokens: str, dim: int = DIM, pool: str = "mean") -> str:
    """Pooled token vectors drawn by hash (a stand-in for an encoder): components are whole numbers from -3 to 3 but for mean
    and sum, whose tokens have signs. pool: mean, sum, max, first (that of the first token after the sign that begins a
    formula)."""
    sign = d.each(tokens, "x", f"2 * ({d.u32('x', 'j', "'vector'")} % 2) - 1")
    level = d.each(tokens, "x", f"cast({d.u32('x', 'j', "'vector'")} % 7 as bigint) - 3")
    n = d.size(tokens)
    if pool in ("max", "first"):
        one = d.most(level) if pool == "max" else f"coalesce({d.at(level, '2')}, {d.at(level, '1')})"
        return d.each(d.seq("1", str(dim)), "j", f"cast({one} as double)")
    total = f"cast({d.sum(sign)} as double)"
    return d.each(d.seq("1", str(dim)), "j", f"{total} / {n}" if pool == "mean" else total)


def cosine(d: Spark, a: str, b: str) -> str:
    """Cosine of two double arrays; null where one has no length."""
    if type(d) is Spark:
        def dot(x: str, y: str) -> str:
            return f"aggregate(zip_with({x}, {y}, (p, q) -> cast(p as double) * q), cast(0 as double), (s, z) -> s + z)"
    else:
        def dot(x: str, y: str) -> str:
            return f"list_sum(list_transform(range(1, len({x}) + 1), lambda q: CAST({x}[q] AS DOUBLE) * {y}[q]))"
    return f"({dot(a, b)} / nullif(sqrt({dot(a, a)}) * sqrt({dot(b, b)}), 0))"


def scored_pairs(sample: DataFrame) -> DataFrame:
    """id_a, id_b, sim (edit), cos (pooled hash vectors)."""
    vec = sample.select("id", "tokens", F.expr(hash_pooled(SPARK, "tokens")).alias("v"))
    pairs = pairwise(sample)
    a, b = vec.select(F.col("id").alias("id_a"), F.col("v").alias("va")), vec.select(F.col("id").alias("id_b"), F.col("v").alias("vb"))
    return pairs.join(a, "id_a").join(b, "id_b").select("id_a", "id_b", "sim", F.expr(cosine(SPARK, "va", "vb")).alias("cos"))


def retrieve(vectors: DataFrame, every: int = 20, k: int = 10, rows_at_once: int = 8192, queries_at_once: int = 1024) -> DataFrame:
    """query, id, rank, cos: exact nearest rows of each query (ids divisible by every) by cosine; ties to the smaller id.

    Rows and queries are dealt to blocks of bounded size, and each pair of blocks meets by equal keys. A product of matrices
    tells which rows of a block can be among the k nearest; only those have their cosine worked out term by term."""
    n, n_q = vectors.agg(F.count(F.lit(1)), F.count(F.when(F.col("vec_id") % every == 0, 1))).first()
    blocks, groups = max(1, -(-n // rows_at_once)), max(1, -(-n_q // queries_at_once))

    def all_of(m: int):
        return F.explode(F.sequence(F.lit(0), F.lit(m - 1)))

    h = F.xxhash64("vec_id")
    dim = vectors.select(F.max(F.size("embedding"))).first()[0] or 0
    # of the same length, finite and not zero; any other vector is compared by the expression, whose null and NaN it keeps
    plain = F.coalesce((F.size("embedding") == dim) & F.expr("forall(embedding, x -> x is not null and abs(x) < 1e15) and exists(embedding, x -> abs(x) > 1e-15)"), F.lit(False))
    vectors = vectors.select("vec_id", "embedding", plain.alias("plain"))
    asked = vectors.where(F.col("vec_id") % every == 0).select(F.col("vec_id").alias("query"), F.col("embedding").alias("qv"), F.col("plain").alias("q_plain"))
    q = asked.where("q_plain").select("query", "qv", F.pmod(F.xxhash64("query"), F.lit(groups)).cast("int").alias("g")).withColumn("b", all_of(blocks))
    rows = vectors.where("plain").select("vec_id", "embedding", F.pmod(h, F.lit(blocks)).cast("int").alias("b")).withColumn("g", all_of(groups))

    def nearest(left, right):
        """Of a block of rows the k nearest of each query, and those as near but for rounding; sums in the expression's order."""
        import pandas as pd

        out = []
        if len(left) and len(right):
            ids, x, y = left["vec_id"].to_numpy(), *(np.stack(c).astype(np.float64) for c in (left["embedding"], right["qv"]))
            nx, ny = (np.sqrt(np.cumsum(v * v, axis=1)[:, -1]) for v in (x, y))
            for at in range(0, len(y), 128):
                near = (y[at : at + 128] @ x.T) / ny[at : at + 128, None] / nx
                for j, (query, c) in enumerate(zip(right["query"].iloc[at : at + 128], near), at):
                    c[ids == query] = -np.inf
                    least = np.partition(c, len(c) - k)[len(c) - k] if len(c) > k else -2.0
                    i = np.flatnonzero((c >= least - 1e-8) & (ids != query))
                    out.append(pd.DataFrame({"query": query, "id": ids[i], "cos": np.cumsum(x[i] * y[j], axis=1)[:, -1] / (nx[i] * ny[j])}))
        return pd.concat(out) if out else pd.DataFrame({"query": pd.Series(dtype="int64"), "id": pd.Series(dtype="int64"), "cos": pd.Series(dtype="float64")})

    s = rows.groupBy("g", "b").cogroup(q.groupBy("g", "b")).applyInPandas(nearest, "query long, id long, cos double")
    odd = vectors.where("NOT plain").crossJoin(asked).unionByName(vectors.where("plain").crossJoin(asked.where("NOT q_plain"))).where("vec_id <> query")
    odd = odd.select("query", F.col("vec_id").alias("id"), F.expr(cosine(SPARK, "embedding", "qv")).alias("cos"))
    s = s.unionByName(odd).withColumn("cos", F.round("cos", 9))
    return s.withColumn("rank", F.row_number().over(Window.partitionBy("query").orderBy(F.desc("cos"), "id"))).where(F.col("rank") <= k).select("query", "id", "cos", "rank")


def cosine_links(vectors: DataFrame, tau: float = 0.8, rows_at_once: int = 8192) -> DataFrame:
    """vec_id, class_id (smallest id of an equal vector), links: how many other rows have a cosine (nine places) of at least
    tau. Exact over all pairs; null, zero and non-finite vectors and vectors of different lengths do not link.

    Equal vectors stand for each other with their number. Blocks of bounded size meet once by equal keys; products of
    matrices tell the links, and pairs near the bound are worked out term by term, as by the expression."""
    rows = vectors.select("vec_id", "embedding")
    classes = rows.withColumn("class_id", F.min("vec_id").over(Window.partitionBy("embedding")))
    plain = F.expr("size(embedding) > 0 and forall(embedding, x -> x is not null and abs(x) < double('Infinity')) and exists(embedding, x -> x <> 0)")
    sized = classes.where(plain).groupBy("class_id").agg(F.count(F.lit(1)).alias("n"), F.first("embedding").alias("v"))
    sized = sized.withColumn("dim", F.size("v")).persist()
    blocks = max(1, -(-sized.count() // rows_at_once))
    x = F.pmod(F.xxhash64("class_id"), F.lit(blocks)).cast("int")
    left = sized.withColumn("x", x).withColumn("y", F.explode(F.sequence(F.col("x"), F.lit(blocks - 1))))
    right = sized.withColumn("y", x).withColumn("x", F.explode(F.sequence(F.lit(0), F.col("y"))))

    def linked(key, a, b):
        import pandas as pd

        out = {}
        for dim in set(a["dim"]) & set(b["dim"]):
            own, other = (p[p["dim"] == dim] for p in (a, b))
            u, v = (np.stack(p["v"]).astype(np.float64) for p in (own, other))
            nu, nv = (np.sqrt(np.cumsum(z * z, axis=1)[:, -1]) for z in (u, v))
            ids, others, n, m = own["class_id"].to_numpy(), other["class_id"].to_numpy(), own["n"].to_numpy(np.float64), other["n"].to_numpy(np.float64)
            back = np.zeros(len(v))
            for at in range(0, len(u), 256):
                c = (u[at : at + 256] @ v.T) / nu[at : at + 256, None] / nv
                hit = c >= tau
                i, j = np.nonzero(np.abs(c - tau) < 1e-8)
                exact = np.cumsum(u[at + i] * v[j], axis=1)[:, -1] / (nu[at + i] * nv[j]) if len(i) else c[i, j]
                hit[i, j] = np.floor(exact * 1e9 + 0.5) / 1e9 >= tau
                hit = hit.astype(np.float64)
                for k, s in zip(ids[at : at + 256].tolist(), (hit @ m).tolist()):
                    out[k] = out.get(k, 0) + round(s)
                back += n[at : at + 256] @ hit
            if key[0] != key[1]:
                for k, s in zip(others.tolist(), back.tolist()):
                    out[k] = out.get(k, 0) + round(s)
        return pd.DataFrame({"class_id": pd.Series(list(out), dtype="int64"), "met": pd.Series(list(out.values()), dtype="int64")})

    met = left.groupBy("x", "y").cogroup(right.groupBy("x", "y")).applyInPandas(linked, "class_id long, met long")
    met = met.groupBy("class_id").agg((F.sum("met") - 1).alias("links"))
    return classes.select("vec_id", "class_id").join(met, "class_id", "left").select("vec_id", "class_id", F.coalesce("links", F.lit(0)).cast("long").alias("links"))


BANDS, WIDTH = 12, 6


def planes(bands: int = BANDS, width: int = WIDTH, dim: int = 64, seed: int = 1000) -> list[list[float]]:
    """Drawn projections, bands of width each."""
    return np.random.default_rng(seed).normal(size=(bands * width, dim)).round(4).tolist()


def sign_bands(v: str, bands: int = BANDS, width: int = WIDTH, dim: int = 64, seed: int = 1000) -> str:
    """Band keys of the signs of drawn projections, as SQL over an array column."""
    dot = f"aggregate(zip_with({v}, get(from_json('{planes(bands, width, dim, seed)}', 'array<array<double>>'), b * {width} + w), (x, y) -> x * y), cast(0 as double), (t, z) -> t + z)"
    return f"transform(sequence(0, {bands - 1}), b -> concat(b, ':', array_join(transform(sequence(0, {width - 1}), w -> if({dot} > 0, '1', '0')), '')))"


def retrieve_lsh(vectors: DataFrame, every: int = 20, k: int = 10) -> DataFrame:
    """As retrieve, among rows that share a band of signs."""
    keyed = vectors.select("vec_id", "embedding", F.explode(F.expr(sign_bands("embedding"))).alias("band"))
    q = keyed.where(F.col("vec_id") % every == 0).select(F.col("vec_id").alias("query"), F.col("embedding").alias("qv"), "band")
    cand = keyed.select("vec_id", "band").join(q.select("query", "band"), "band").where("vec_id <> query").select("query", "vec_id").distinct()
    full = cand.join(vectors.select("vec_id", "embedding"), "vec_id").join(q.select("query", "qv").dropDuplicates(["query"]), "query")
    s = full.select("query", F.col("vec_id").alias("id"), F.round(F.expr(cosine(SPARK, "embedding", "qv")), 9).alias("cos"))
    return s.withColumn("rank", F.row_number().over(Window.partitionBy("query").orderBy(F.desc("cos"), "id"))).where(F.col("rank") <= k)


def triplet_agreement(pairs: DataFrame) -> DataFrame:
    """Over anchors: does the partner with the highest edit similarity also have a higher cosine than the one with the lowest?"""
    both = pairs.unionByName(pairs.select(F.col("id_b").alias("id_a"), F.col("id_a").alias("id_b"), "sim", "cos"))
    best = both.groupBy("id_a").agg(F.max_by(F.round("cos", 9), F.struct("sim", -F.col("id_b"))).alias("near"), F.min_by(F.round("cos", 9), F.struct("sim", "id_b")).alias("far"))
    return best.agg(F.count(F.lit(1)).alias("anchors"), F.sum((F.col("near") > F.col("far")).cast("long")).alias("agree"))


# --- similarity head: two fully connected layers over frozen embeddings


@dataclass
class Head:
    """Weights of two layers with a rectifier between."""

    weights: dict[str, np.ndarray]

    def embed(self, x: np.ndarray) -> np.ndarray:
        return np.maximum(x @ self.weights["w1"] + self.weights["b1"], 0) @ self.weights["w2"] + self.weights["b2"]

    def gradient(self, xa: np.ndarray, xb: np.ndarray, y: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        """Sum of squared errors of the cosine and its gradient."""
        w, g = self.weights, {k: np.zeros_like(v) for k, v in self.weights.items()}
        ha, hb = xa @ w["w1"] + w["b1"], xb @ w["w1"] + w["b1"]
        za, zb = np.maximum(ha, 0) @ w["w2"] + w["b2"], np.maximum(hb, 0) @ w["w2"] + w["b2"]
        na, nb = (np.linalg.norm(z, axis=1, keepdims=True) + 1e-9 for z in (za, zb))
        c = (za * zb).sum(1, keepdims=True) / (na * nb)
        e = c - y[:, None]
        for x, h, z, o, n, m in ((xa, ha, za, zb, na, nb), (xb, hb, zb, za, nb, na)):
            dz = 2 * e * (o / (n * m) - c * z / n**2)
            g["w2"] += np.maximum(h, 0).T @ dz
            g["b2"] += dz.sum(0)
            dh = (dz @ w["w2"].T) * (h > 0)
            g["w1"] += x.T @ dh
            g["b1"] += dh.sum(0)
        return float((e**2).sum()), g


def linear_schedule(step: int, warmup: int = 100, total: int = 1000) -> float:
    """Share of the full rate: up over the warm-up, then down to zero."""
    return step / max(1, warmup) if step < warmup else max(0.0, (total - step) / max(1, total - warmup))


class Adafactor:
    """Row and column sums of squares in place of a full second moment; updates are clipped by their root mean square."""

    def __init__(self, rate: float = 1e-4, clip: float = 1.0, decay: float = 0.1):
        self.rate, self.clip, self.decay, self.step, self.state = rate, clip, decay, 0, {}

    def update(self, weights: dict, grads: dict, share: float = 1.0) -> None:
        self.step += 1
        beta = 1 - self.step**-0.8
        for k, g in grads.items():
            sq = g * g + 1e-30
            if g.ndim == 2:
                r, c = self.state.get(k, (np.zeros(g.shape[0]), np.zeros(g.shape[1])))
                r, c = beta * r + (1 - beta) * sq.mean(1), beta * c + (1 - beta) * sq.mean(0)
                self.state[k] = (r, c)
                v = r[:, None] * c / r.mean()
            else:
                v = self.state[k] = beta * self.state.get(k, np.zeros_like(g)) + (1 - beta) * sq
            u = g / np.sqrt(v)
            u /= max(1.0, float(np.sqrt((u * u).mean())) / self.clip)
            weights[k] = weights[k] - self.rate * share * (u + self.decay * weights[k] * (g.ndim == 2))


@dataclass
class EarlyStopping:
    """Stops after `patience` epochs without a better loss."""

    patience: int = 5
    best: float = float("inf")
    bad: int = 0

    def stop(self, loss: float) -> bool:
        self.best, self.bad = (loss, 0) if loss < self.best - 1e-9 else (self.best, self.bad + 1)
        return self.bad >= self.patience


def new_head(dim: int = DIM, seed: int = 1) -> Head:
    """Two layers that first give back what they get (a rectifier keeps the positive part, a second one the negative part), a
    little disturbed: training starts from the cosine of the raw embeddings."""
    rng, eye = np.random.default_rng(seed), np.eye(dim)
    w1, w2 = np.concatenate([eye, -eye], axis=1), np.concatenate([eye, -eye])
    return Head({"w1": w1 + rng.normal(0, 0.01, w1.shape), "b1": np.zeros(2 * dim), "w2": w2 + rng.normal(0, 0.01, w2.shape), "b2": np.zeros(dim)})


def fit_head(pairs: DataFrame, dim: int = DIM, epochs: int = 10, rate: float = 1e-4, warmup: int = 100, decay: float = 0.1, batch: int = 256, seed: int = 1, patience: int = 5) -> tuple[Head, list[float]]:
    """Fits the head to a bounded sample of pairs (va, vb, sim), which comes to the driver; rate, warm-up, decay and epochs
    as published. The order of pairs is that of their values' hash, so a rerun gives the same head."""
    rng, head = np.random.default_rng(seed), new_head(dim, seed)
    rows = pairs.select("va", "vb", "sim", F.xxhash64("va", "vb", "sim").alias("h")).orderBy("h").toPandas()
    if not len(rows):
        return head, []
    xa, xb, y = np.stack(rows["va"]), np.stack(rows["vb"]), rows["sim"].to_numpy()
    opt, early, losses, step = Adafactor(rate, decay=decay), EarlyStopping(patience), [], 0
    total = epochs * -(-len(y) // batch)
    for _ in range(epochs):
        loss, order = 0.0, rng.permutation(len(y))
        for a in range(0, len(y), batch):
            i = order[a : a + batch]
            part, g = head.gradient(xa[i], xb[i], y[i])
            loss, step = loss + part, step + 1
            opt.update(head.weights, {k: v / len(i) for k, v in g.items()}, linear_schedule(step, min(warmup, total // 2), total))
        losses.append(loss / len(y))
        if early.stop(losses[-1]):
            break
    return head, losses


def head_cosine(pairs: DataFrame, head: Head) -> DataFrame:
    """Adds cos of the transformed pair."""
    shared = pairs.sparkSession.sparkContext.broadcast(head)

    @F.pandas_udf("double")
    def cos(a, b):
        import pandas as pd

        if not len(a):
            return pd.Series([], dtype="float64")
        x, y = shared.value.embed(np.stack(a)), shared.value.embed(np.stack(b))
        return pd.Series((x * y).sum(1) / (np.linalg.norm(x, axis=1) * np.linalg.norm(y, axis=1) + 1e-12))

    return pairs.withColumn("cos", cos("va", "vb"))
