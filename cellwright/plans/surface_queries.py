"""Queries: size report, tokenizer diagnostics, set operations, strata, candidates by a table function, shards, similarity links."""

from __future__ import annotations

from pyspark.sql import functions as F

from cellwright.functions import lexing
from cellwright.functions.dialect import DUCK, SPARK
from cellwright.operators import corruption, curation, models, published, similarity, tasks, tokenizer
from cellwright.plans.corruption_queries import BATCHES, SEED
from cellwright.plans.twins import lexed, sketched
from cellwright.sources import carriers, shards, tables
from cellwright.streaming import edits

QUERIES, SQL = {}, {}
HELD = 500


def put(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


put(
    "size_report",
    lambda s, d: curation.size_report(carriers.formulas(s, d), published.PARAMETERS),
    sketched("formulas", f", pt AS (SELECT unnest({lexing.pretokens(DUCK, 'formula')}) AS p FROM b)")
    + """SELECT 'workbooks' AS what, CAST(count(DISTINCT workbook_id) AS DOUBLE) AS n FROM b UNION ALL SELECT 'formulas', count(*) FROM b UNION ALL SELECT 'kept per workbook', count(DISTINCT (workbook_id, sketch)) FROM s
        UNION ALL SELECT 'kept globally', count(DISTINCT sketch) FROM s UNION ALL SELECT 'pretokens', count(*) FROM pt UNION ALL SELECT 'distinct pretokens', count(DISTINCT p) FROM pt"""
    + "".join(f" UNION ALL SELECT 'millions of parameters, {a}', {b}" for a, b in published.PARAMETERS),
)

_HEX = "[\\p{L}0-9]"
put(
    "tokenizer_diagnostics",
    lambda s, d: tokenizer.diagnostics(carriers.formulas(s, d)),
    lexed("formulas", f""", q AS (SELECT formula_id, length(formula) AS chars, {lexing.pretokens(DUCK, 'formula')} AS p, {lexing.model_tokens(DUCK, 'tokens', 'kinds')} AS m FROM f)""")
    + f"""SELECT count(*) AS formulas, CAST(quantile_disc(len(p), 0.5) AS BIGINT) AS half, CAST(quantile_disc(len(p), 0.9) AS BIGINT) AS nine_tenths, max(len(p)) AS longest,
        CAST(sum(len(list_filter(p, lambda x: length(x) > 1 AND regexp_matches(x, '{_HEX}') AND regexp_matches(x, '[^\\p{{L}}0-9]')))) AS BIGINT) AS crossing,
        round(sum(len(list_filter(p, lambda x: regexp_matches(x, '^[^ -~]$')))) / sum(len(p)), 6) AS unknown,
        round(sum(chars) / sum(len(flatten(m))), 6) AS chars_each_model_token FROM q""",
)


def _sets(s, d):
    """Reserved and training rows share no id; what both have in texts and sketches, what only one has, as set operations."""
    held, train = tasks.split_reserved(carriers.formulas(s, d), HELD, SEED)
    a, b = (lexing.with_sketch(x).select("formula", "sketch").cache() for x in (held, train))
    parts = {
        "ids in both": held.select("formula_id").intersect(train.select("formula_id")),
        "texts in both": a.select("formula").intersect(b.select("formula")),
        "sketches in both": a.select("sketch").intersect(b.select("sketch")),
        "sketches of training only": b.select("sketch").subtract(a.select("sketch")),
        "texts of either": a.select("formula").union(b.select("formula")).distinct(),
        "reserved rows beyond a training row of the same text": a.select("formula").exceptAll(b.select("formula")),
    }
    out = None
    for name, rows in parts.items():
        own = rows.agg(F.count(F.lit(1)).alias("n")).withColumn("what", F.lit(name))
        out = own if out is None else out.unionByName(own)
    return out


_SPLIT = f", r AS (SELECT formula_id FROM b ORDER BY {tasks.hash_rank(DUCK, SEED, 'formula_id', 'split')}, formula_id LIMIT {HELD}), a AS (SELECT * FROM s JOIN r USING (formula_id)), z AS (SELECT * FROM s WHERE formula_id NOT IN (SELECT formula_id FROM r))"
put(
    "split_set_operations",
    _sets,
    sketched("formulas", _SPLIT)
    + """SELECT 'ids in both' AS what, count(*) AS n FROM (SELECT formula_id FROM a INTERSECT SELECT formula_id FROM z) UNION ALL SELECT 'texts in both', count(*) FROM (SELECT formula FROM a INTERSECT SELECT formula FROM z)
        UNION ALL SELECT 'sketches in both', count(*) FROM (SELECT sketch FROM a INTERSECT SELECT sketch FROM z) UNION ALL SELECT 'sketches of training only', count(*) FROM (SELECT sketch FROM z EXCEPT SELECT sketch FROM a)
        UNION ALL SELECT 'texts of either', count(*) FROM (SELECT formula FROM a UNION SELECT formula FROM z) UNION ALL SELECT 'reserved rows beyond a training row of the same text', count(*) FROM (SELECT formula FROM a EXCEPT ALL SELECT formula FROM z)""",
)
_STRATA = {1: 50, 0: 10}


def _strata(s, d):
    rows = s.read.parquet(f"{d}/labels.parquet").where("quality IS NOT NULL")
    return tasks.stratified(rows, "quality", _STRATA, SEED, "doc_id").select("doc_id", "quality")


put("stratified_labels", _strata, f"SELECT doc_id, quality FROM labels WHERE {tasks.hash_rank(DUCK, SEED, 'doc_id', 'stratum')} % 100 < CASE quality WHEN 1 THEN 50 WHEN 0 THEN 10 END")


def _candidates(s, d):
    """Inverse edits by a table function, for SQL users: one row a candidate."""
    models.register(s)
    held, _ = tasks.split_reserved(carriers.formulas(s, d), HELD, SEED)
    tasks.repair_set(held, SEED).createOrReplaceTempView("cellwright_broken")
    return s.sql("SELECT example_id, count(*) AS candidates, count(DISTINCT candidate) AS different, max(CASE WHEN candidate = intended THEN 1 ELSE 0 END) AS found FROM cellwright_broken, LATERAL inverse_edits(buggy) GROUP BY example_id")


put("inverse_edit_candidates", _candidates)


def _shards(s, d):
    """Pairs written as shards and read back through the data source: as many of each objective as were written."""
    path = edits.shared_path(s, "shards")
    tables.write_shards(corruption.pretraining_pairs(curation.dedup(carriers.formulas(s, d)), BATCHES, SEED), path)
    s.dataSource.register(shards.ShardSource)
    read = s.read.format("training_shards").option("path", path).load()
    spans = s.read.format("training_shards").option("path", path).option("objective", "span").load()
    return read.agg(F.count(F.lit(1)).alias("pairs"), F.countDistinct("batch_id").alias("batches")).crossJoin(spans.agg(F.count(F.lit(1)).alias("spans")))  # one row each


put(
    "training_shards",
    _shards,
    sketched("formulas", f", k AS (SELECT min(formula_id) AS formula_id FROM s GROUP BY workbook_id, sketch), m AS (SELECT {corruption.batch_of(DUCK, SEED, 'formula_id', BATCHES)} AS batch_id FROM k), o AS (SELECT batch_id, {corruption.objective_of(DUCK, SEED)} AS objective FROM m)")
    + "SELECT count(*) AS pairs, count(DISTINCT batch_id) AS batches, count(*) FILTER (objective = 'span') AS spans FROM o",
)


def _links(s, d):
    """Of every masked formula of the corpus: how many others are similar to it by 0.8 or more."""
    return similarity.edit_sim_links(similarity.masked(carriers.formulas(s, d)).cache(), 0.8)


put("edit_sim_links", _links)


def _workbooks(s, d):
    """A vector for each workbook: the mean of its formulas' vectors."""
    f = carriers.formulas(s, d)
    v = lexing.with_tokens(f).select("workbook_id", F.posexplode(F.expr(similarity.hash_pooled(SPARK, "tokens"))).alias("dim", "x"))
    return v.groupBy("workbook_id", (F.col("dim") + 1).alias("dim")).agg(F.round(F.avg("x"), 6).alias("x"))


put("workbook_embeddings", _workbooks, lexed("formulas", f", v AS (SELECT workbook_id, {similarity.hash_pooled(DUCK, 'tokens')} AS v FROM f), e AS (SELECT workbook_id, unnest(range(1, {similarity.DIM + 1}))::INT AS dim, unnest(v) AS x FROM v)") + "SELECT workbook_id, dim, round(avg(x), 6) AS x FROM e GROUP BY workbook_id, dim")


def _streams(d) -> dict[str, str]:
    """Separate token streams for constants and for the rest of a formula, so that each can have a vocabulary of its own."""
    idx, own = d.seq("1", d.size("tokens")), lexing.pretokens(d, d.at("tokens", "i"))
    constant = d.has(["string", "number"], d.at("kinds", "i"))
    return {
        "constants": f"array_to_string({d.flat(d.each(d.keep(idx, 'i', constant), 'i', own))}, '|')",
        "rest": f"array_to_string({d.flat(d.each(d.keep(idx, 'i', f'not {constant}'), 'i', own))}, '|')",
    }


put(
    "split_streams",
    lambda s, d: lexing.with_tokens(carriers.formulas(s, d)).select("formula_id", *(F.expr(x.replace("array_to_string", "array_join")).alias(k) for k, x in _streams(SPARK).items())),
    lexed() + "SELECT formula_id, " + ", ".join(f"{x} AS {k}" for k, x in _streams(DUCK).items()) + " FROM f",
)


def _texts(s, d):
    """The carrier written as lines, CSV and JSON and read back with the given schema."""
    f, out = carriers.formulas(s, d), None
    for kind in ("csv", "json", "text"):
        path = edits.shared_path(s, kind)
        (f.select("formula") if kind == "text" else f).write.format(kind).options(**({"escape": '"'} if kind == "csv" else {})).save(path)
        own = tables.read_formulas(s, path, kind).agg(F.count(F.lit(1)).alias("n"), F.countDistinct("formula").alias("different"), F.sum(F.length("formula")).alias("chars")).withColumn("kind", F.lit(kind))
        out = own if out is None else out.unionByName(own)
    return out


put("formula_sources", _texts, f"SELECT unnest(['csv', 'json', 'text']) AS kind, n, different, chars FROM (SELECT count(*) AS n, count(DISTINCT formula) AS different, CAST(sum(length(formula)) AS BIGINT) AS chars FROM ({carriers.FORMULAS}))")
