"""Task data sets: repair pairs, completion prefixes, reserved splits, leakage."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellwright.functions import lexing, noise, shapes
from cellwright.functions.dialect import SPARK, Spark

FRACTIONS = (20, 30, 40, 50, 60, 70, 80)
EVAL_FRACTIONS = (50, 75, 90)
FORUM = 273  # the published size of the forum benchmark


def hash_rank(d: Spark, seed: int, key: str, purpose: str) -> str:
    return d.u32(str(seed), key, f"'{purpose}'")


def split_reserved(df: DataFrame, n: int, seed: int = 1, key: str = "formula_id") -> tuple[DataFrame, DataFrame]:
    """The n rows of lowest keyed hash (ties by key), and the rest. A top-n, not a sort of everything."""
    h = df.withColumn("h", F.expr(hash_rank(SPARK, seed, key, "split")))
    reserved = h.orderBy("h", key).limit(n).drop("h")
    rest = df.join(reserved.select(F.col(key).alias("k")), F.col(key) == F.col("k"), "left_anti")
    return reserved, rest


def stratified(df: DataFrame, by: str, percent: dict, seed: int = 1, key: str = "formula_id") -> DataFrame:
    """Rows of each stratum kept by keyed hash, in percent of the stratum; strata that are not named go."""
    share = " ".join(f"when {v!r} then {p}" for v, p in percent.items())
    return df.where(F.expr(f"{hash_rank(SPARK, seed, key, 'stratum')} % 100 < case {by} {share} end"))


def repair_set(df: DataFrame, seed: int = 1, key: str = "formula_id", ops: list[str] | None = None, known: DataFrame | None = None) -> DataFrame:
    """example_id, op_id, buggy, intended of well-formed formulas to which an operator applies. known: shapes.known of a
    table that has these texts, where it is at hand."""
    noisy = shapes.with_noise(df.select(key, "formula"), seed, key, ops, shapes=known, only_ok=True).withColumn("row_no", F.monotonically_increasing_id())
    return noisy.where("noisy IS NOT NULL AND row_no >= 0").select(F.col(key).alias("example_id"), "op_id", F.col("noisy").alias("buggy"), F.col("formula").alias("intended"))


def forum_stand_in(df: DataFrame, seed: int = 1, n: int = FORUM, key: str = "formula_id", known: DataFrame | None = None) -> DataFrame:
    """Stands in for the forum benchmark, which is not at hand: n pairs by the attested families of mistakes only."""
    attested = [k for k, v in noise.CATALOGUE.items() if v[2]]
    pairs = repair_set(df, seed, key, attested, known).withColumn("h", F.expr(hash_rank(SPARK, seed, "example_id", "forum")))
    return pairs.orderBy("h", "example_id").limit(n).drop("h")


def prefix(d: Spark, percent: str) -> str:
    """The first percent of the tokens, rounded down, at least one."""
    return d.join(d.cut("tokens", "1", f"greatest({d.div(f'{d.size("tokens")} * ({percent})', '100')}, 1)"))


def completion_set(df: DataFrame, seed: int = 1, key: str = "formula_id") -> DataFrame:
    """example_id, percent, prefix, formula: one fraction of 20 to 80 percent of the tokens, drawn by hash."""
    pick = SPARK.at(SPARK.arr(*map(str, FRACTIONS)), f"1 + {hash_rank(SPARK, seed, key, 'fraction')} % {len(FRACTIONS)}")
    out = lexing.with_tokens(df.select(key, "formula")).withColumn("percent", F.expr(pick))
    return out.select(F.col(key).alias("example_id"), "percent", F.expr(prefix(SPARK, "percent")).alias("prefix"), F.col("formula").alias("full"))


def completion_prefixes(df: DataFrame, key: str = "formula_id", fractions: tuple[int, ...] = EVAL_FRACTIONS) -> DataFrame:
    """example_id, percent, prefix, full for each fraction."""
    out = lexing.with_tokens(df.select(key, "formula"))
    rows = F.explode(F.array(*(F.struct(F.lit(p).alias("percent"), F.expr(prefix(SPARK, str(p))).alias("prefix")) for p in fractions)))
    return out.select(F.col(key).alias("example_id"), rows.alias("r"), F.col("formula").alias("full")).select("example_id", "r.percent", "r.prefix", "full")


def leakage(train: DataFrame, held: DataFrame, key: str = "formula_id") -> DataFrame:
    """Held-out rows whose text or sketch is in training: formula_id, by_text, by_sketch. Only keys are shuffled."""
    t = lexing.with_sketch(train).select("sketch_key", lexing.key128("formula").alias("text_key"))
    h = lexing.with_sketch(held).select(key, "sketch_key", lexing.key128("formula").alias("text_key"))
    texts = t.select("text_key").distinct().withColumn("by_text", F.lit(True))
    sketches = t.select("sketch_key").distinct().withColumn("by_sketch", F.lit(True))
    return h.join(texts, "text_key", "left").join(sketches, "sketch_key", "left").select(key, F.coalesce("by_text", F.lit(False)).alias("by_text"), F.coalesce("by_sketch", F.lit(False)).alias("by_sketch"))


def document_leakage(docs: DataFrame, items: DataFrame) -> DataFrame:
    """Benchmark items whose whole text is a document's text."""
    return items.join(docs.select(F.md5("text").alias("k")).distinct(), F.md5(items["text"]) == F.col("k"), "left_semi").select("item_id")


def passage_leakage(docs: DataFrame, items: DataFrame, most: int = 4) -> DataFrame:
    """item_id of benchmark items whose text stands anywhere in a document.

    Of an item's words between spaces all but the first and the last are whole words of such a document, too. Up to `most`
    of them, hashed, are looked up among the runs of words of every document; what meets is compared as text. Only hashes
    are shuffled before. Items of one or two words are compared with every document."""
    spaces = "[ \\t\\n\\x0B\\f\\r]+"
    texts = docs.select("text").where("text IS NOT NULL")
    asked = items.select(F.col("text").alias("item")).where("item IS NOT NULL").distinct().withColumn("w", F.split("item", spaces))
    asked = asked.withColumn("k", F.least(F.lit(most), F.size("w") - 2)).cache()
    inner = asked.where("k > 0").select("item", F.xxhash64(F.slice("w", F.lit(2), F.col("k"))).alias("h"))
    lengths = sorted(r["k"] for r in asked.where("k > 0").select("k").distinct().collect())
    found = texts.join(asked.where("k <= 0").select("item"), F.contains("text", "item")).select("item")
    if lengths:
        words = texts.select(F.xxhash64("text").alias("d"), F.split("text", spaces).alias("w"))
        runs = F.concat(*(F.expr(f"transform(sequence(1, greatest(size(w) - {k - 1}, 1)), i -> xxhash64(slice(w, i, {k})))") for k in lengths))
        met = words.select("d", F.explode(F.array_distinct(runs)).alias("h")).join(inner, "h").select("d", "item").distinct()
        found = found.unionByName(texts.withColumn("d", F.xxhash64("text")).join(met, "d").where(F.contains("text", "item")).select("item"))
    return items.join(found.distinct(), items["text"] == F.col("item"), "left_semi").select("item_id")
