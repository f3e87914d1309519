"""Curation: one formula per sketch and scope, reports of sizes and of how deduplication bends the distribution."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellwright.functions import lexing, shapes
from cellwright.functions.dialect import SPARK


@dataclass(frozen=True)
class SketchSpec:
    """What a sketch masks and whether it keeps spaces (a space can be the intersection of ranges)."""

    mask: tuple[str, ...] = lexing.MASKED
    keep_space: bool = False


def _keyed(df: DataFrame, scope: str, key: str, text: str, spec: SketchSpec, known: DataFrame | None = None) -> tuple[DataFrame, list[str]]:
    if key == "text":
        keyed = df.withColumn("sketch_key", lexing.key128(text))
    elif known is not None and spec == SketchSpec():
        keyed = shapes.with_sketch(df, text, known).drop("sketch")
    else:
        keyed = lexing.with_sketch(df, text, mask=spec.mask, keep_space=spec.keep_space).drop("tokens", "kinds", "sketch")
    return keyed, {"workbook": ["workbook_id", "sketch_key"], "global": ["sketch_key"]}[scope]


def dedup(df: DataFrame, scope: str = "workbook", key: str = "sketch", text: str = "formula", id_col: str = "formula_id", spec: SketchSpec = SketchSpec(), known: DataFrame | None = None) -> DataFrame:
    """The row with the smallest id of each key within the scope, with family_size. scope: workbook, global or none.

    The row travels as an aggregate: each task keeps one row of a key before the one shuffle, which so collapses hot keys,
    and no join brings rows back. Rows that share an id and a key are told apart by their other columns; equal ones count
    as one survivor and all in family_size. Input bucketed by workbook needs no shuffle. known: shapes.known of a table that
    has these texts; sketches are then made once a shape."""
    if scope == "none":
        return df.withColumn("family_size", F.lit(1).cast("long"))
    keyed, by = _keyed(df, scope, key, text, spec, known)
    best = keyed.groupBy(*by).agg(_first_row(df, id_col), F.count(F.lit(1)).alias("family_size"))
    return best.select(*(F.col("first_row")[c].alias(c) for c in df.columns), "family_size")


def _first_row(df: DataFrame, id_col: str):
    """The row with the smallest id, ties by the other columns."""
    return F.min(F.struct(id_col, *(c for c in df.columns if c != id_col))).alias("first_row")


def dedup_incremental(new: DataFrame, seen: DataFrame, scope: str = "workbook") -> DataFrame:
    """Survivors of a new batch whose key is not among the keys of the table `seen` (workbook_id, sketch_key)."""
    keyed, by = _keyed(new, scope, "sketch", "formula", SketchSpec())
    first = keyed.groupBy(*by).agg(_first_row(new, "formula_id"))
    # an outer join and a test, not an anti join: that would be pushed below the aggregate, with the sketch written out in its condition
    fresh = first.join(seen.withColumn("seen", F.lit(True)), by, "left").where("seen IS NULL")
    return fresh.select(*(F.col("first_row")[c].alias(c) for c in new.columns))


def seen_keys(df: DataFrame, scope: str = "workbook") -> DataFrame:
    keyed, by = _keyed(df, scope, "sketch", "formula", SketchSpec())
    return keyed.select(*by).distinct()


def dedup_report(df: DataFrame) -> DataFrame:
    """Formulas left at each level of curation, and the ratio to the raw count."""
    keyed = lexing.with_sketch(df).select("workbook_id", "sketch_key", lexing.key128("formula").alias("text_key"))
    n = keyed.agg(
        F.count(F.lit(1)).alias("raw"),
        F.countDistinct("workbook_id", "text_key").alias("exact_workbook"),
        F.countDistinct("workbook_id", "sketch_key").alias("sketch_workbook"),
        F.countDistinct("text_key").alias("exact_global"),
        F.countDistinct("sketch_key").alias("sketch_global"),
    )
    levels = ["raw", "exact_workbook", "sketch_workbook", "exact_global", "sketch_global"]
    rows = F.explode(F.array(*(F.struct(F.lit(k).alias("level"), F.col(k).alias("n"), F.col("raw")) for k in levels)))
    return n.select(rows.alias("r")).select("r.level", "r.n", F.round(F.col("r.raw") / F.col("r.n"), 6).alias("ratio"))


def size_report(df: DataFrame, parameters: list[tuple[str, int]] = ()) -> DataFrame:
    """what, n: workbooks, formulas at each level of curation, pretokens, and the published sizes of models in millions."""
    keyed = lexing.with_sketch(df).select("workbook_id", "sketch_key")
    c = keyed.agg(F.countDistinct("workbook_id").alias("a"), F.count(F.lit(1)).alias("b"), F.countDistinct("workbook_id", "sketch_key").alias("c"), F.countDistinct("sketch_key").alias("d"))
    p = df.select(F.explode(F.expr(lexing.pretokens(SPARK, "formula"))).alias("p")).agg(F.count(F.lit(1)).alias("e"), F.countDistinct("p").alias("f"))
    names = zip("abcdef", ("workbooks", "formulas", "kept per workbook", "kept globally", "pretokens", "distinct pretokens"))
    rows = [F.struct(F.lit(x).alias("what"), F.col(k).cast("double").alias("n")) for k, x in names]
    rows += [F.struct(F.lit(f"millions of parameters, {a}").alias("what"), F.lit(float(b)).alias("n")) for a, b in parameters]
    return c.crossJoin(p).select(F.explode(F.array(*rows)).alias("r")).select("r.what", "r.n")  # one row each


def function_counts(df: DataFrame) -> DataFrame:
    """fn, n: calls of each function."""
    names = F.expr(f"transform(filter(sequence(1, size(tokens)), i -> size(tokens) > 0 and get(kinds, i - 1) = 'function'), i -> translate(get(tokens, i - 1), '{'abcdefghijklmnopqrstuvwxyz'}', '{'ABCDEFGHIJKLMNOPQRSTUVWXYZ'}'))")
    return lexing.with_tokens(df).select(F.explode(names).alias("fn")).groupBy("fn").agg(F.count(F.lit(1)).alias("n"))


def curation_skew(before: DataFrame, after: DataFrame) -> DataFrame:
    """Distance of the function distributions before and after: total variation, divergence, entropies, top shares."""
    a, b = (function_counts(x) for x in (before, after))
    both = a.join(b.select("fn", F.col("n").alias("m")), "fn", "full").select("fn", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("m", F.lit(0)).alias("m"))
    total = both.agg(F.sum("n").alias("sn"), F.sum("m").alias("sm"))
    s = both.crossJoin(F.broadcast(total)).withColumn("p", F.col("n") / F.col("sn")).withColumn("q", F.col("m") / F.col("sm"))  # one row

    def info(x, y):
        return F.coalesce(F.sum(F.when((F.col(x) > 0) & (F.col(y) > 0), F.col(x) * F.log(F.col(x) / F.col(y)))), F.lit(0.0))

    def entropy(x):
        return -F.sum(F.when(F.col(x) > 0, F.col(x) * F.log(F.col(x))).otherwise(0.0))

    return s.agg(
        F.round(F.sum(F.abs(F.col("p") - F.col("q"))) / 2, 6).alias("total_variation"),
        F.round(info("p", "q"), 6).alias("divergence"),
        F.round(entropy("p"), 6).alias("entropy_before"),
        F.round(entropy("q"), 6).alias("entropy_after"),
        F.round(F.max("p"), 6).alias("top_before"),
        F.round(F.max("q"), 6).alias("top_after"),
    )


def sketch_families(df: DataFrame, min_size: int = 2) -> DataFrame:
    """Formulas that differ in their inputs only: size, spread over workbooks, the smallest text."""
    keyed = lexing.with_sketch(df).select("sketch", "workbook_id", "formula")
    g = keyed.groupBy("sketch").agg(F.count(F.lit(1)).alias("family_size"), F.countDistinct("workbook_id").alias("workbooks"), F.min("formula").alias("example"))
    return g.where(F.col("family_size") >= min_size)


def harvest(pages: DataFrame) -> DataFrame:
    """page_id, candidate: formulas found in the text of web pages."""
    text = F.regexp_replace(F.col("html"), "<[^<>]*>", "\n")
    for entity, mark in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        text = F.replace(text, F.lit(entity), F.lit(mark))
    found = F.regexp_extract_all(text, F.lit("(?m)^[ ]*(=[A-Za-z$(+-][^\\n]*)$"), F.lit(1))
    return pages.select("page_id", F.explode(found).alias("candidate"))


def well_formed(df: DataFrame, text: str = "formula") -> DataFrame:
    """Adds well_formed: balanced, closed, no dangling operator."""
    out = df if "kinds" in df.columns else lexing.with_tokens(df, text)
    return out.withColumn("well_formed", F.expr(lexing.well_formed(SPARK, "tokens", "kinds")))
