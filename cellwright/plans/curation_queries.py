"""Queries: carriers, lexing, sketches, curation."""

from __future__ import annotations

from pyspark.sql import functions as F

from cellwright.functions import lexing
from cellwright.functions.dialect import DUCK, SPARK
from cellwright.operators import curation
from cellwright.plans.twins import BASES, lexed, sketched
from cellwright.sources import carriers

QUERIES, SQL = {}, {}


def put(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def table(name: str):
    return lambda s, d: s.read.parquet(f"{d}/{name}.parquet")


put("formulas_carrier", carriers.formulas, carriers.FORMULAS)
put("formulas_wide_carrier", carriers.formulas_wide, carriers.FORMULAS_WIDE)
put("formula_edits_carrier", lambda s, d: carriers.formula_edits(s, d).drop("ts"), f"SELECT event_id, workbook_id, sheet, formula FROM ({carriers.edits_sql(True)})")


def _lexed(source, keys: list[str], text: str):
    def run(s, d):
        df = source(s, d).select(*keys, F.col(text).alias("x"))
        return df.withColumn("tokens", F.expr(lexing.lex(SPARK, "x"))).select(*keys, F.size("tokens").cast("long").alias("n_tokens"), F.md5(F.array_join("tokens", "\u0001")).alias("tokens_md5"), (F.array_join("tokens", "") == F.col("x")).alias("lossless"))

    return run


def _lexed_sql(table_sql: str, keys: list[str], text: str) -> str:
    t = lexing.lex(DUCK, text)
    k = ", ".join(keys)
    return f"SELECT {k}, len(t) AS n_tokens, md5(array_to_string(t, chr(1))) AS tokens_md5, array_to_string(t, '') = x AS lossless FROM (SELECT {k}, {text} AS x, {t} AS t FROM ({table_sql}))"


for _name, _source, _sql, _keys, _text in (
    ("lex_formulas", carriers.formulas, carriers.FORMULAS, ["formula_id"], "formula"),
    ("lex_documents", table("documents"), "SELECT * FROM documents", ["doc_id"], "text"),
    ("lex_pages", table("pages"), "SELECT * FROM pages", ["page_id"], "html"),
    ("lex_conversations", table("conversations"), "SELECT * FROM conversations", ["conv_id", "turn"], "text"),
):
    put(_name, _lexed(_source, _keys, _text), _lexed_sql(_sql, _keys, _text))

put(
    "token_kinds",
    lambda s, d: lexing.with_tokens(carriers.formulas(s, d)).select("formula_id", F.array_join("kinds", " ").alias("kinds")),
    lexed() + "SELECT formula_id, array_to_string(kinds, ' ') AS kinds FROM f",
)
put("sketch_formulas", lambda s, d: lexing.with_sketch(carriers.formulas(s, d)).select("formula_id", "sketch"), sketched() + "SELECT formula_id, sketch FROM s")
put(
    "sketch_keep_space",
    lambda s, d: lexing.with_sketch(carriers.formulas(s, d), keep_space=True, mask=("string", "number")).select("formula_id", "sketch"),
    lexed() + f"SELECT formula_id, {lexing.sketch(DUCK, 'tokens', 'kinds', ('string', 'number'), True)} AS sketch FROM f",
)


def _forms(d):
    return {
        "match_form": lexing.match_form(d, "tokens", "kinds"),
        "sketch_form": lexing.sketch_match_form(d, "tokens", "kinds"),
        "sketch_sheets": lexing.sketch_match_form(d, "tokens", "kinds", mask_sheets=True),
    }


put(
    "sketch_match_form",
    lambda s, d: lexing.with_tokens(carriers.formulas(s, d)).select("formula_id", *(F.expr(x).alias(k) for k, x in _forms(SPARK).items())),
    lexed() + "SELECT formula_id, " + ", ".join(f"{x} AS {k}" for k, x in _forms(DUCK).items()) + " FROM f",
)


def _dedup_sql(by: str, key: str = "sketch", base: str = "formulas") -> str:
    head = sketched(base) if key == "sketch" else f"WITH s AS (SELECT *, formula AS sketch FROM ({BASES[base]})) "
    return head + f"SELECT formula_id, workbook_id, formula, family_size FROM (SELECT *, count(*) OVER g AS family_size, row_number() OVER (g ORDER BY formula_id) AS r FROM s WINDOW g AS (PARTITION BY {by})) WHERE r = 1"


def _prose(s, d):
    return table("documents")(s, d).select(F.col("doc_id").alias("formula_id"), F.col("source").alias("workbook_id"), F.col("text").alias("formula"))


def _dedup(scope: str, key: str = "sketch", source=carriers.formulas):
    return lambda s, d: curation.dedup(source(s, d), scope, key).select("formula_id", "workbook_id", "formula", "family_size")


put("dedup_workbook", _dedup("workbook"), _dedup_sql("workbook_id, sketch"))
put("dedup_global", _dedup("global"), _dedup_sql("sketch"))
put("dedup_exact", _dedup("global", "text"), _dedup_sql("sketch", "text"))
put("dedup_none", _dedup("none"), f"SELECT formula_id, workbook_id, formula, 1 AS family_size FROM ({carriers.FORMULAS})")
put("dedup_workbook_wide", _dedup("workbook", source=carriers.formulas_wide), _dedup_sql("workbook_id, sketch", base="formulas_wide"))
put("dedup_documents_by_source", _dedup("workbook", source=_prose), _dedup_sql("workbook_id, sketch", base="prose"))
put("dedup_documents_exact", _dedup("global", "text", _prose), _dedup_sql("sketch", "text", "prose"))


def _incremental(s, d):
    f = carriers.formulas(s, d)
    return curation.dedup_incremental(f.where("formula_id % 4 = 0"), curation.seen_keys(f.where("formula_id % 4 <> 0"))).select("formula_id", "workbook_id", "formula")


put(
    "dedup_incremental",
    _incremental,
    sketched() + """SELECT min(formula_id) AS formula_id, workbook_id, min_by(formula, formula_id) AS formula FROM s n WHERE formula_id % 4 = 0
        AND NOT EXISTS (SELECT 1 FROM s o WHERE o.formula_id % 4 <> 0 AND o.workbook_id = n.workbook_id AND o.sketch = n.sketch) GROUP BY workbook_id, sketch""",
)


def _report_sql(base: str) -> str:
    counts = {"raw": "count(*)", "exact_workbook": "count(DISTINCT (workbook_id, formula))", "sketch_workbook": "count(DISTINCT (workbook_id, sketch))", "exact_global": "count(DISTINCT formula)", "sketch_global": "count(DISTINCT sketch)"}
    rows = " UNION ALL ".join(f"SELECT '{k}' AS level, {k} AS n, round(raw / {k}, 6) AS ratio FROM c" for k in counts)
    return sketched(base, f", c AS (SELECT {', '.join(f'{v} AS {k}' for k, v in counts.items())} FROM s)") + rows


put("dedup_report", lambda s, d: curation.dedup_report(carriers.formulas(s, d)), _report_sql("formulas"))
put("dedup_report_wide", lambda s, d: curation.dedup_report(carriers.formulas_wide(s, d)), _report_sql("formulas_wide"))


def _skew(scope: str):
    def run(s, d):
        f = carriers.formulas(s, d)
        return curation.curation_skew(f, curation.dedup(f, scope))

    return run


def _skew_sql(by: str) -> str:
    fn = "list_transform(list_filter(range(1, len(tokens) + 1), lambda i: kinds[i] = 'function'), lambda i: upper(tokens[i]))"
    return sketched(
        "formulas",
        f""", kept AS (SELECT * FROM s QUALIFY row_number() OVER (PARTITION BY {by} ORDER BY formula_id) = 1),
        a AS (SELECT fn, count(*) AS n FROM (SELECT unnest({fn}) AS fn FROM s) GROUP BY fn), z AS (SELECT fn, count(*) AS n FROM (SELECT unnest({fn}) AS fn FROM kept) GROUP BY fn),
        pq AS (SELECT coalesce(a.n, 0) / sum(a.n) OVER () AS p, coalesce(z.n, 0) / sum(z.n) OVER () AS q FROM a FULL JOIN z ON a.fn = z.fn)""",
    ) + """SELECT round(sum(abs(p - q)) / 2, 6) AS total_variation, round(coalesce(sum(CASE WHEN p > 0 AND q > 0 THEN p * ln(p / q) END), 0), 6) AS divergence,
        round(-sum(CASE WHEN p > 0 THEN p * ln(p) ELSE 0 END), 6) AS entropy_before, round(-sum(CASE WHEN q > 0 THEN q * ln(q) ELSE 0 END), 6) AS entropy_after,
        round(max(p), 6) AS top_before, round(max(q), 6) AS top_after FROM pq"""


put("curation_skew_workbook", _skew("workbook"), _skew_sql("workbook_id, sketch"))
put("curation_skew_global", _skew("global"), _skew_sql("sketch"))
put(
    "sketch_families",
    lambda s, d: curation.sketch_families(carriers.formulas(s, d)),
    sketched() + "SELECT sketch, count(*) AS family_size, count(DISTINCT workbook_id) AS workbooks, min(formula) AS example FROM s GROUP BY sketch HAVING count(*) >= 2",
)
put(
    "well_formed",
    lambda s, d: curation.well_formed(carriers.formulas(s, d)).select("formula_id", "well_formed"),
    lexed() + f"SELECT formula_id, {lexing.well_formed(DUCK, 'tokens', 'kinds')} AS well_formed FROM f",
)


def _harvest(s, d):
    f = carriers.formulas(s, d).select(F.col("formula_id").alias("page_id"), "formula")
    safe = F.col("formula")
    for mark, entity in (("&", "&amp;"), ("<", "&lt;"), (">", "&gt;"), ('"', "&quot;")):
        safe = F.replace(safe, F.lit(mark), F.lit(entity))
    return curation.harvest(table("pages")(s, d).join(f, "page_id").select("page_id", F.concat("html", F.lit("<p>"), safe, F.lit("</p>")).alias("html")))


put("harvest_pages", _harvest, f"SELECT page_id, formula AS candidate FROM pages JOIN ({carriers.FORMULAS}) ON formula_id = page_id")
