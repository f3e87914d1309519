"""Queries: task sets, measures, published tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from cellwright.functions import lexing
from cellwright.functions.dialect import DUCK
from cellwright.operators import measures, published, tasks
from cellwright.plans.corruption_queries import PLACES, SEED, noisy_cte
from cellwright.plans.twins import lexed, sketched
from cellwright.sources import carriers

QUERIES, SQL = {}, {}
RESERVED = 500


def put(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


_REPAIR = PLACES + noisy_cte() + f", rs AS (SELECT formula_id AS example_id, op_id, noisy AS buggy, formula AS intended FROM z WHERE {lexing.well_formed(DUCK, 'tokens', 'kinds')} AND noisy IS NOT NULL)"
put("repair_set", lambda s, d: tasks.repair_set(carriers.formulas(s, d), SEED), lexed("formulas", _REPAIR) + "SELECT * FROM rs")
_SPLIT = f", r AS (SELECT formula_id FROM b ORDER BY {tasks.hash_rank(DUCK, SEED, 'formula_id', 'split')}, formula_id LIMIT {RESERVED})"
put(
    "repair_split",
    lambda s, d: tasks.split_reserved(carriers.formulas(s, d), RESERVED, SEED)[0].select("formula_id", "formula"),
    lexed("formulas", _SPLIT) + "SELECT formula_id, formula FROM b JOIN r USING (formula_id)",
)
put(
    "repair_split_rest",
    lambda s, d: tasks.split_reserved(carriers.formulas(s, d), RESERVED, SEED)[1].groupBy("workbook_id").agg(F.count(F.lit(1)).alias("n")),
    lexed("formulas", _SPLIT) + "SELECT workbook_id, count(*) AS n FROM b WHERE formula_id NOT IN (SELECT formula_id FROM r) GROUP BY workbook_id",
)


def _leak(s, d):
    held, train = tasks.split_reserved(carriers.formulas(s, d), RESERVED, SEED)
    return tasks.leakage(train, held)


put(
    "leakage_check",
    _leak,
    sketched("formulas", _SPLIT + ", tr AS (SELECT * FROM s WHERE formula_id NOT IN (SELECT formula_id FROM r))")
    + "SELECT formula_id, formula IN (SELECT formula FROM tr) AS by_text, sketch IN (SELECT sketch FROM tr) AS by_sketch FROM s JOIN r USING (formula_id)",
)
put(
    "leakage_documents",
    lambda s, d: tasks.document_leakage(s.read.parquet(f"{d}/documents.parquet"), s.read.parquet(f"{d}/benchmark.parquet")),
    "SELECT item_id FROM benchmark WHERE text IN (SELECT text FROM documents)",
)
put("leakage_passages", lambda s, d: tasks.passage_leakage(s.read.parquet(f"{d}/documents.parquet"), s.read.parquet(f"{d}/benchmark.parquet")))
_PICK = DUCK.at(DUCK.arr(*map(str, tasks.FRACTIONS)), f"1 + {tasks.hash_rank(DUCK, SEED, 'formula_id', 'fraction')} % {len(tasks.FRACTIONS)}")
put(
    "completion_set",
    lambda s, d: tasks.completion_set(carriers.formulas(s, d), SEED),
    lexed("formulas", f", p AS (SELECT *, {_PICK} AS percent FROM f)") + f"SELECT formula_id AS example_id, percent, {tasks.prefix(DUCK, 'percent')} AS prefix, formula AS \"full\" FROM p",
)
put(
    "completion_prefixes",
    lambda s, d: tasks.completion_prefixes(carriers.formulas(s, d)),
    lexed("formulas", f", p AS (SELECT *, unnest([{', '.join(map(str, tasks.EVAL_FRACTIONS))}]) AS percent FROM f)") + f"SELECT formula_id AS example_id, percent, {tasks.prefix(DUCK, 'percent')} AS prefix, formula AS \"full\" FROM p",
)


def _rule_candidates(s, d):
    """Two rule systems on the repair set: leave as is; close what is open."""
    rs = tasks.repair_set(carriers.formulas(s, d), SEED).cache()  # read three times
    opened = F.length("buggy") - F.length(F.replace("buggy", F.lit("("), F.lit("")))
    shut = F.length("buggy") - F.length(F.replace("buggy", F.lit(")"), F.lit("")))
    same = rs.select(F.lit("identity").alias("system"), "example_id", F.lit(1).alias("rank"), F.col("buggy").alias("candidate"))
    fixed = rs.select(F.lit("balancer").alias("system"), "example_id", F.lit(1).alias("rank"), F.concat("buggy", F.repeat(F.lit(")"), F.greatest(opened - shut, F.lit(0)))).alias("candidate"))
    return rs.select("example_id", F.col("intended").alias("gold")), same.unionByName(fixed)


def _form(x: str, what: str) -> str:
    f = {"em": lexing.match_form, "sm": lexing.sketch_match_form}[what](DUCK, f"{x}_t", f"{x}_k")
    return f"{f} AS {x}_{what}"


_CANDS = (
    _REPAIR
    + """, cd AS (SELECT 'identity' AS system, example_id, 1 AS rank, buggy AS cand, intended AS gold FROM rs UNION ALL
      SELECT 'balancer', example_id, 1, buggy || repeat(')', greatest(length(buggy) - length(replace(buggy, '(', '')) - length(buggy) + length(replace(buggy, ')', '')), 0)), intended FROM rs)"""
    + f", c1 AS (SELECT *, {lexing.lex(DUCK, 'cand')} AS cand_t, {lexing.lex(DUCK, 'gold')} AS gold_t FROM cd), c2 AS (SELECT *, {lexing.kinds(DUCK, 'cand_t')} AS cand_k, {lexing.kinds(DUCK, 'gold_t')} AS gold_k FROM c1)"
    + f", h AS (SELECT system, example_id, {', '.join(_form(x, w) for x in ('cand', 'gold') for w in ('em', 'sm'))} FROM c2)"
)
put(
    "repair_eval_rules",
    lambda s, d: measures.match_at_k(*_rule_candidates(s, d)),
    lexed("formulas", _CANDS)
    + """SELECT system, unnest([1, 5]) AS k, round(sum(CAST(cand_em = gold_em AS INT)) / (SELECT count(*) FROM rs), 6) AS exact, round(sum(CAST(cand_sm = gold_sm AS INT)) / (SELECT count(*) FROM rs), 6) AS sketch FROM h GROUP BY system""",
)
put(
    "repair_divergence",
    lambda s, d: measures.divergence(*_rule_candidates(s, d)),
    lexed("formulas", _CANDS) + "SELECT example_id, CAST(sum(CAST(cand_em = gold_em AS INT)) AS BIGINT) AS hit, count(*) AS systems FROM h GROUP BY example_id HAVING sum(CAST(cand_em = gold_em AS INT)) BETWEEN 1 AND count(*) - 1",
)

# --- the published tables' measures over results measured on the given tables
_P = published.MEASURED


def _one(s, d, mode: str = "F"):
    """Results of one mode: a row a task, setting and system."""
    return published.measured(s, d).where(F.col("mode") == mode)


put("paper_results", lambda s, d: published.measured(s, d), _P + "SELECT * FROM p")
put(
    "paper_best_second",
    lambda s, d: published.best_and_second(published.measured(s, d)),
    _P + "SELECT * FROM (SELECT *, CAST(dense_rank() OVER (PARTITION BY task, setting ORDER BY CASE WHEN setting = 'ms' THEN -value ELSE value END DESC) AS INT) AS place FROM p) WHERE place <= 2",
)
put(
    "paper_wins",
    lambda s, d: published.wins(published.measured(s, d), "NATION_7", ("BUILDING", "FURNITURE", "MACHINERY"), ("BUILDING", "O")),
    _P
    + """SELECT task, count(*) AS settings, CAST(sum(CAST(value = top AS INT)) AS BIGINT) AS won FROM (SELECT *, max(value) OVER (PARTITION BY task, setting, task = 'BUILDING' AND mode = 'O') AS top FROM p
        WHERE task IN ('BUILDING', 'FURNITURE', 'MACHINERY') AND setting <> 'ms') WHERE system = 'NATION_7' GROUP BY task""",
)
for _name, _task, _ref in (("paper_deltas_ablation", "BUILDING", "NATION_1"), ("paper_deltas_size", "FURNITURE", "NATION_2")):
    put(
        _name,
        lambda s, d, t=_task, r=_ref: published.deltas(_one(s, d), t, r),
        _P + f"SELECT a.system, setting, round((a.value - r.value) * 100, 4) AS points FROM p a JOIN (SELECT setting, value FROM p WHERE task = '{_task}' AND mode = 'F' AND system = '{_ref}') r USING (setting) WHERE task = '{_task}' AND mode = 'F' AND system <> '{_ref}'",
    )
_TIMES = "(SELECT system, value FROM p WHERE task = 'BUILDING' AND mode = 'F' AND setting = 'ms')"
put(
    "paper_speedup",
    lambda s, d: published.speedup(_one(s, d).where("task = 'BUILDING'")),
    _P + f"SELECT system, round((value - (SELECT min(value) FROM {_TIMES})) / value * 100, 4) AS saved_percent FROM {_TIMES} WHERE value > (SELECT min(value) FROM {_TIMES})",
)
put(
    "paper_pareto",
    lambda s, d: published.pareto(_one(s, d), "BUILDING", "price"),
    _P + """, w AS (SELECT system, max(CASE WHEN setting = 'ms' THEN value END) AS cost, max(CASE WHEN setting = 'price' THEN value END) AS gain FROM p WHERE task = 'BUILDING' AND mode = 'F' GROUP BY system)
        SELECT * FROM w WHERE NOT EXISTS (SELECT 1 FROM w o WHERE o.cost <= w.cost AND o.gain >= w.gain AND (o.cost < w.cost OR o.gain > w.gain))""",
)


def _by_size(s, d):
    """A nation's size is its number of customers."""
    res = _one(s, d).unionByName(published.measured(s, d).where("mode <> 'F' AND task = 'BUILDING'"))
    size = s.sql("SELECT n_name AS system, count(*) AS millions FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
    return published.by_size(res, size, ("BUILDING", "price"), ("FURNITURE", "balance"))


put(
    "paper_summary_by_size",
    _by_size,
    _P + """, z AS (SELECT n_name AS system, count(*) AS millions FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name) SELECT z.system, millions, repair, completion FROM z
        JOIN (SELECT system, max(value) AS repair FROM p WHERE task = 'BUILDING' AND setting = 'price' GROUP BY system) r ON r.system = z.system LEFT JOIN (SELECT system, value AS completion FROM p WHERE task = 'FURNITURE' AND mode = 'F' AND setting = 'balance') c ON c.system = z.system""",
)
put(
    "paper_completion_table",
    lambda s, d: published.completion_table(_one(s, d), "BUILDING", tuple(published.MEASURES)),
    _P + "SELECT system, " + ", ".join(f"max(CASE WHEN setting = '{x}' THEN value END) AS {x}" for x in published.MEASURES) + " FROM p WHERE task = 'BUILDING' AND mode = 'F' GROUP BY system",
)
