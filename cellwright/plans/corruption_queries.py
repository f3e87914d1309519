"""Queries: pre-training objectives and the noise operators."""

from __future__ import annotations

from pyspark.sql import functions as F

from cellwright.functions import lexing, noise, shapes
from cellwright.functions.dialect import DUCK, SPARK
from cellwright.operators import corruption as c
from cellwright.operators import curation
from cellwright.plans.twins import lexed
from cellwright.sources import carriers

QUERIES, SQL = {}, {}
SEED, BATCHES, KEY = 1, 64, "formula_id"


def put(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def lexed_formulas(s, d):
    return lexing.with_tokens(carriers.formulas(s, d))


def chain(steps: list[dict[str, str]], start: str = "f", keep: str = "*") -> tuple[str, str]:
    """CTEs for steps of added columns, and the last one's name."""
    out, at = "", start
    for k, step in enumerate(steps):
        out += f", {start}_{k} AS (SELECT *, {', '.join(f'{v} AS {n}' for n, v in step.items())} FROM {at})"
        at = f"{start}_{k}"
    return out, at


put(
    "tail_mask_all_rates",
    lambda s, d: carriers.formulas(s, d).select(KEY, *(F.expr(c.tail_mask(SPARK, "formula", r)).alias(f"tail_{r}") for r in c.TAIL_RATES)),
    lexed() + "SELECT formula_id, " + ", ".join(f"{c.tail_mask(DUCK, 'formula', r)} AS tail_{r}" for r in c.TAIL_RATES) + " FROM f",
)
put(
    "tail_mask_documents",
    lambda s, d: s.read.parquet(f"{d}/documents.parquet").select("doc_id", *(F.md5(F.expr(c.tail_mask(SPARK, "text", r))).alias(f"tail_{r}") for r in c.TAIL_RATES)),
    "SELECT doc_id, " + ", ".join(f"md5({c.tail_mask(DUCK, 'text', r)}) AS tail_{r}" for r in c.TAIL_RATES) + " FROM documents",
)


def _span(rate: int, mean: int, law: str = "fixed", boundary: str = "lexer"):
    def run(s, d):
        out = c.span_mask(lexed_formulas(s, d), rate, mean, SEED, law, boundary)
        return out.select(KEY, "source", F.size(F.expr("filter(masked, x -> x)")).cast("long").alias("n_masked"))

    steps = (c.span_columns if boundary == "lexer" else c.generic_span_columns)(DUCK, SEED, KEY, rate, mean, law)
    more, last = chain(steps)
    return run, lexed("formulas", more) + f"SELECT formula_id, span_source AS source, len(list_filter(masked, lambda x: x)) AS n_masked FROM {last}"


for _rate, _mean in c.SPAN_GRID:
    put(f"span_mask_{_rate}_{_mean}", *_span(_rate, _mean))
put("span_mask_geometric", *_span(15, 2, "geometric"))
put("span_mask_generic", *_span(15, 3, "uniform", "none"))
put(
    "random_noise",
    lambda s, d: lexed_formulas(s, d).select(KEY, F.expr(c.random_noise(SPARK, SEED, KEY)).alias("source")),
    lexed() + f"SELECT formula_id, {c.random_noise(DUCK, SEED, KEY)} AS source FROM f",
)
PLACES, PLACED = chain(noise.places(DUCK))


def _operator(op: str):
    sql = lexed("formulas", PLACES) + f"SELECT formula_id, noisy FROM (SELECT formula_id, {noise.valid(DUCK, 'raw')} AS noisy FROM (SELECT *, {noise.rewrite(DUCK, op)} AS raw FROM {PLACED})) WHERE noisy IS NOT NULL"
    return lambda s, d: noise.apply_operator(lexed_formulas(s, d), op).select(KEY, "noisy"), sql


for _op in noise.CATALOGUE:
    put(f"user_noise_{_op}", *_operator(_op))
_OPS = list(noise.CATALOGUE)


def noisy_cte(at: str = PLACED, name: str = "z", ops: list[str] = _OPS, seed: int | str = SEED) -> str:
    """CTE with op_id and noisy for rows that have the helper columns."""
    return f""", {name}_r AS (SELECT *, {', '.join(f'{noise.rewrite(DUCK, o)} AS {o}' for o in ops)} FROM {at}),
        {name}_v AS (SELECT * REPLACE ({', '.join(f'{noise.valid(DUCK, o)} AS {o}' for o in ops)}) FROM {name}_r),
        {name}_p AS (SELECT *, {noise.pick(DUCK, seed, KEY, ops)} AS picked FROM {name}_v), {name} AS (SELECT *, picked.op_id AS op_id, picked.noisy AS noisy FROM {name}_p)"""


put(
    "user_noise_mix",
    lambda s, d: noise.user_noise(lexed_formulas(s, d), SEED).select(KEY, "op_id", "noisy"),
    lexed("formulas", PLACES + noisy_cte()) + "SELECT formula_id, op_id, noisy FROM z",
)
_KEPT_ONE = f", gs AS (SELECT *, {lexing.sketch(DUCK, 'tokens', 'kinds')} AS sketch FROM f), gk AS (SELECT * FROM gs QUALIFY row_number() OVER (PARTITION BY sketch ORDER BY formula_id) = 1)"
_more, _last = chain(noise.places(DUCK), "gk")
put(
    "noise_catalogue",
    lambda s, d: noise.catalogue(lexing.with_tokens(curation.dedup(carriers.formulas(s, d), "global").select(KEY, "formula").cache())),
    lexed("formulas", _KEPT_ONE + _more + noisy_cte(_last, "gz"))
    + "SELECT op_id, name, category, attested, CASE op_id " + " ".join(f"WHEN '{k}' THEN (SELECT count({k}) FROM gz)" for k in noise.CATALOGUE)
    + " END AS applies FROM (VALUES " + ", ".join(f"('{k}', '{a}', '{b}', {str(x).lower()})" for k, (a, b, x) in noise.CATALOGUE.items()) + ") v(op_id, name, category, attested)",
)


def dealt_sql(seed: int | str = SEED, base: str = "f") -> str:
    return f""", m0 AS (SELECT *, {c.batch_of(DUCK, seed, KEY, BATCHES)} AS batch_id FROM {base}), m1 AS (SELECT *, {c.objective_of(DUCK, seed)} AS objective FROM m0),
    m AS (SELECT *, {c.variant_of(DUCK, seed)} AS variant FROM m1)"""


_DEALT = dealt_sql()


def _pairs_sql(seed: int | str = SEED, base: str = "f", before: str = "", more: str = "") -> str:
    out, parts = before + dealt_sql(seed, base), []
    row = f"SELECT formula_id, {more}batch_id, objective, variant"
    for k, (r, n) in enumerate(c.SPAN_GRID):
        out += f", sp{k} AS (SELECT * FROM m WHERE objective = 'span' AND variant = '{r}/{n}')"
        added, last = chain(c.span_columns(DUCK, seed, KEY, r, n), f"sp{k}")
        out += added
        parts.append(f"{row}, span_source AS source, formula AS target FROM {last}")
    out += ", us AS (SELECT * FROM m WHERE objective = 'user')"
    added, last = chain(noise.places(DUCK), "us")
    out += added + noisy_cte(last, "uz", seed=seed)
    parts += [
        f"{row}, {c.tail_mask(DUCK, 'formula', 'cast(variant as int)')}, formula FROM m WHERE objective = 'tail'",
        f"{row}, coalesce(noisy, formula), formula FROM uz",
        f"{row}, {c.random_noise(DUCK, seed, KEY)}, formula FROM m WHERE objective = 'random'",
        f"{row}, formula, formula FROM m WHERE objective = 'intact'",
    ]
    return out + ", pairs AS (" + " UNION ALL ".join(parts) + ")"


def pairs(s, d):
    return c.pretraining_pairs(carriers.formulas(s, d), BATCHES, SEED)


put("objective_mix", lambda s, d: c.assign_objectives(carriers.formulas(s, d), BATCHES, SEED).select(KEY, "batch_id", "objective", "variant"), lexed("formulas", _DEALT) + "SELECT formula_id, batch_id, objective, variant FROM m")
put("pretraining_pairs", pairs, lexed("formulas", _pairs_sql()) + "SELECT * FROM pairs")
put(
    "corruption_report",
    lambda s, d: c.corruption_report(pairs(s, d)),
    lexed("formulas", _pairs_sql()) + """SELECT objective, variant, count(*) AS n, count(DISTINCT batch_id) AS batches, round(avg((length(source) - length(replace(source, '<mask>', ''))) / 6), 6) AS masks,
        round(avg(CAST(source = target AS INT)), 6) AS unchanged, round(avg(length(source) / length(target)), 6) AS length_ratio FROM pairs GROUP BY objective, variant""",
)


def _stream(s, d):
    f = carriers.formulas(s, d)
    known = shapes.known(f)
    return c.pretraining_stream(curation.dedup(f, known=known), BATCHES, EPOCHS, known=known)


EPOCHS = 10
_KEPT = f", sk AS (SELECT *, {lexing.sketch(DUCK, 'tokens', 'kinds')} AS sketch FROM f), ep AS (SELECT *, unnest(range(1, {EPOCHS + 1})) AS epoch FROM (SELECT * FROM sk QUALIFY row_number() OVER (PARTITION BY workbook_id, sketch ORDER BY formula_id) = 1))"
put(
    "pretraining_stream",
    lambda s, d: _stream(s, d).groupBy("epoch", "objective", "variant").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("batch_id").alias("batches"), F.sum(F.length("source")).alias("chars"), F.min("source").alias("least"), F.max("source").alias("most")),
    lexed("formulas", _pairs_sql("epoch", "ep", _KEPT, "epoch, ")) + "SELECT CAST(epoch AS INT) AS epoch, objective, variant, count(*) AS n, count(DISTINCT batch_id) AS batches, CAST(sum(length(source)) AS BIGINT) AS chars, min(source) AS least, max(source) AS most FROM pairs GROUP BY epoch, objective, variant",
)


def _lex_pieces() -> str:
    return f"flatten(list_transform(string_split(source, '{c.MASK}'), lambda p: {lexing.lex(DUCK, 'p')}))"


put(
    "corruption_audit",
    lambda s, d: c.corruption_audit(pairs(s, d).cache()),
    lexed("formulas", _pairs_sql()) + f"""SELECT objective, variant, count(*) AS n, CAST(sum(CAST(round((length(source) - length(replace(source, '<mask>', ''))) / 6) AS BIGINT)) AS BIGINT) AS runs,
        round(sum(length(target) - length(replace(source, '<mask>', ''))) / sum(length(target)), 6) AS hidden,
        CAST(sum(CASE WHEN objective = 'span' THEN CAST(len(list_filter({_lex_pieces()}, lambda x: x <> '' AND NOT list_contains({lexing.lex(DUCK, 'target')}, x))) > 0 AS BIGINT) ELSE 0 END) AS BIGINT) AS broken,
        CAST(sum(CAST(kinds > 1 AS BIGINT)) AS BIGINT) AS mixed FROM pairs JOIN (SELECT batch_id, count(DISTINCT (objective, variant)) AS kinds FROM pairs GROUP BY batch_id) USING (batch_id) GROUP BY objective, variant""",
)
