"""Accuracy and cost measures over candidate lists."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellwright.functions import lexing
from cellwright.functions.dialect import SPARK


def forms(df: DataFrame, text: str, exact: str, sketch: str) -> DataFrame:
    """Adds the normal forms for exact and sketch match of a text column."""
    out = df.withColumn("ft", F.expr(lexing.lex(SPARK, text))).withColumn("fk", F.expr(lexing.kinds(SPARK, "ft")))
    return out.withColumn(exact, F.expr(lexing.match_form(SPARK, "ft", "fk"))).withColumn(sketch, F.expr(lexing.sketch_match_form(SPARK, "ft", "fk"))).drop("ft", "fk")


def hits(gold: DataFrame, cands: DataFrame) -> DataFrame:
    """system, example_id, rank, em, sm. gold: example_id, gold; cands: system, example_id, rank, candidate."""
    g = forms(gold.select("example_id", "gold"), "gold", "ge", "gs")
    c = forms(cands, "candidate", "ce", "cs")
    return c.join(g, "example_id").select("system", "example_id", "rank", F.col("ce").eqNullSafe(F.col("ge")).alias("em"), F.col("cs").eqNullSafe(F.col("gs")).alias("sm"))


def match_at_k(gold: DataFrame, cands: DataFrame, ks: tuple[int, ...] = (1, 5)) -> DataFrame:
    """system, k, exact, sketch: shares over all examples, those without candidates included."""
    h = hits(gold, cands)
    per = h.groupBy("system", "example_id").agg(*(F.max((F.col(m) & (F.col("rank") <= k)).cast("int")).alias(f"{m}{k}") for m in ("em", "sm") for k in ks))
    n = gold.agg(F.count(F.lit(1)).alias("n"))
    total = per.groupBy("system").agg(*(F.sum(f"{m}{k}").alias(f"{m}{k}") for m in ("em", "sm") for k in ks)).crossJoin(F.broadcast(n))  # one row
    rows = F.explode(F.array(*(F.struct(F.lit(k).alias("k"), F.round(F.col(f"em{k}") / F.col("n"), 6).alias("exact"), F.round(F.col(f"sm{k}") / F.col("n"), 6).alias("sketch")) for k in ks)))
    return total.select("system", rows.alias("r")).select("system", "r.k", "r.exact", "r.sketch")


def divergence(gold: DataFrame, cands: DataFrame, k: int = 5) -> DataFrame:
    """Examples on which systems disagree about an exact hit within k: how many hit, how many do not."""
    per = hits(gold, cands).groupBy("system", "example_id").agg(F.max((F.col("em") & (F.col("rank") <= k)).cast("int")).alias("hit"))
    return per.groupBy("example_id").agg(F.sum("hit").cast("long").alias("hit"), F.count(F.lit(1)).alias("systems")).where("hit > 0 AND hit < systems")


def pearson(df: DataFrame, x: str, y: str) -> DataFrame:
    """Correlation in one pass; null where a side is constant."""
    return df.agg(F.round(F.try_divide(F.covar_pop(x, y), F.stddev_pop(x) * F.stddev_pop(y)), 6).alias("pearson"), F.count(F.lit(1)).alias("n"))


def timed(df: DataFrame, repeats: int = 1, counted: bool = True) -> tuple[float, int]:
    """Seconds of running a plan to a sink that keeps nothing, and its rows, if they are to be counted."""
    best, n = float("inf"), df.count() if counted else 0
    for _ in range(repeats):
        t = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        best = min(best, time.perf_counter() - t)
    return best, n
