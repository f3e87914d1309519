"""Queries: stand-in models, ablations, streaming, and the ordinary operators around them."""

from __future__ import annotations

from pyspark.sql import functions as F

from cellwright.functions import lexing, noise, shapes
from cellwright.functions.dialect import DUCK, SPARK
from cellwright.operators import corruption, curation, measures, models, tasks, tokenizer
from cellwright.plans.corruption_queries import PLACES, SEED, noisy_cte
from cellwright.plans.twins import lexed, sketched
from cellwright.sources import carriers
from cellwright.streaming import edits

QUERIES, SQL = {}, {}
#: the published size of the reserved synthetic benchmark
EXAMPLES = 500


def put(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def split(s, d):
    return tasks.split_reserved(carriers.formulas(s, d), EXAMPLES, SEED)


def _prefixes(held):
    """Prefixes of the held-out formulas, an example for each fraction."""
    return tasks.completion_prefixes(held).withColumn("example_id", F.col("example_id") * 100 + F.col("percent"))


def completion_scores(train, held, systems: dict, k: int = 5, width: int = 20):
    """system, percent, k, exact, sketch. systems: name -> n-gram model, or None for the prefix baseline."""
    pre = _prefixes(held).cache()
    cands = None
    for name, model in systems.items():
        own = models.prefix_mode(train, pre, k) if model is None else models.complete(pre, model, name, k, width).drop("mean_logprob")
        cands = own if cands is None else cands.unionByName(own)
    cands = cands.cache()
    out = None
    for p in tasks.EVAL_FRACTIONS:
        own = pre.where(F.col("percent") == p).select("example_id", F.col("full").alias("gold"))
        part = measures.match_at_k(own, cands.join(own.select("example_id"), "example_id")).withColumn("percent", F.lit(p))
        out = part if out is None else out.unionByName(part)
    return out


def _completion(orders: dict[str, int], scope: str = "workbook", known=None):
    def run(s, d):
        held, train = split(s, d)
        own = curation.dedup(train, scope, known=shapes.known(carriers.formulas(s, d)) if known is None else known).cache()
        whole = models.shelve_ngrams(own, order=max(orders.values()))  # the smaller models read the same table
        return completion_scores(own, held, {"prefix-mode": None, **{name: whole.of_order(o) for name, o in orders.items()}})

    return run


def _dedup_ablation(s, d):
    """The same model over a corpus of one formula a sketch and workbook, and of one a sketch."""
    known = shapes.known(carriers.formulas(s, d))
    parts = [_completion({"ngram-5": 5}, scope, known)(s, d).withColumn("corpus", F.lit(scope)) for scope in ("workbook", "global")]
    return parts[0].unionByName(parts[1])


put("completion_eval_ngram", _completion({"ngram-5": 5}))
put("ablation_size", _completion({"ngram-2": 2, "ngram-3": 3, "ngram-5": 5}))
put("ablation_dedup", _dedup_ablation)


def _modes(s, d):
    """Zero-shot against counts tuned on the task's own training formulas, lexer tokens against generic ones."""
    held, train = split(s, d)
    own = curation.dedup(train, known=shapes.known(carriers.formulas(s, d))).select("formula").cache()
    task = tasks.completion_set(train, SEED).select(F.col("full").alias("formula"))
    systems = {}
    for name, order, units in (("", 4, "lexer"), ("generic ", 6, "generic")):
        counts = models.stored_counts(own, order=order, units=units)
        systems[f"{name}zero-shot"] = models.shelve_ngrams(own, order=order, units=units, counts=counts)
        systems[f"{name}tuned"] = models.shelve_ngrams(own, order=order, units=units, counts=counts, extra=task)
    return completion_scores(own, held, systems)


put("completion_modes", _modes)


def _completion_table(s, d):
    """Cut-off curves of our systems in the published table's form: a row a system, a column a prefix and measure."""
    scores = _completion({"ngram-5": 5})(s, d).where("k = 5")
    return scores.groupBy("system").pivot("percent", list(tasks.EVAL_FRACTIONS)).agg(F.first("exact").alias("exact"), F.first("sketch").alias("sketch"))


put("completion_table", _completion_table)


def _turns(s, d):
    """Completion over prose: the words that follow the first half of each turn, by the count model of the other turns."""
    turns = s.read.parquet(f"{d}/conversations.parquet").where("role = 'user' AND text IS NOT NULL").withColumn("example_id", F.col("conv_id") * 1000 + F.col("turn"))
    turns = turns.withColumn("formula", F.col("text"))
    held, train = tasks.split_reserved(turns.select("example_id", "formula"), 100, SEED, "example_id")
    pre = tasks.completion_prefixes(held.withColumnRenamed("example_id", "formula_id"), fractions=(75,))
    cands = models.complete(pre, models.shelve_ngrams(train, order=3), "ngram-3", 5, 10).drop("mean_logprob")
    return measures.match_at_k(pre.select("example_id", F.col("full").alias("gold")), cands)


put("completion_turns", _turns)


def _prefix_mode(s, d):
    held, train = split(s, d)
    pre = tasks.completion_prefixes(held, fractions=(75,))
    return models.prefix_mode(train, pre)


_LOW = f", r AS (SELECT formula_id FROM b ORDER BY {tasks.hash_rank(DUCK, SEED, 'formula_id', 'split')}, formula_id LIMIT {EXAMPLES})"


def _prefix_sql() -> str:
    return lexed("formulas", _LOW + f", p AS (SELECT formula_id AS example_id, {tasks.prefix(DUCK, '75')} AS prefix FROM f JOIN r USING (formula_id)), n AS (SELECT formula, count(*) AS n FROM b WHERE formula_id NOT IN (SELECT formula_id FROM r) GROUP BY formula)") + """
        SELECT 'prefix-mode' AS system, example_id, CAST(rank AS INT) AS rank, formula AS candidate FROM (SELECT example_id, formula, row_number() OVER (PARTITION BY example_id ORDER BY n DESC, formula) AS rank FROM p JOIN n ON starts_with(formula, prefix)) WHERE rank <= 5"""


put("completion_eval_prefix_mode", _prefix_mode, _prefix_sql())

# --- last-mile repair on the two benchmarks
_BENCH = PLACES + noisy_cte() + _LOW + f", rs AS (SELECT formula_id AS example_id, op_id, noisy AS buggy, formula AS intended FROM z JOIN r USING (formula_id) WHERE {lexing.well_formed(DUCK, 'tokens', 'kinds')} AND noisy IS NOT NULL)"
_ATTESTED = [k for k, v in noise.CATALOGUE.items() if v[2]]
_FORUM = PLACES + noisy_cte(ops=_ATTESTED) + f", fs AS (SELECT formula_id AS example_id, op_id, noisy AS buggy, formula AS intended FROM z WHERE {lexing.well_formed(DUCK, 'tokens', 'kinds')} AND noisy IS NOT NULL ORDER BY {tasks.hash_rank(DUCK, SEED, 'formula_id', 'forum')}, formula_id LIMIT {tasks.FORUM})"
put("repair_benchmark_synthetic", lambda s, d: tasks.repair_set(split(s, d)[0], SEED), lexed("formulas", _BENCH) + "SELECT * FROM rs")
put("repair_benchmark_forum", lambda s, d: tasks.forum_stand_in(carriers.formulas(s, d), SEED), lexed("formulas", _FORUM) + "SELECT * FROM fs")


def repair_scores(train, bench, channel=None, systems: dict | None = None):
    """system, k, exact, sketch of rule baselines and count models on a benchmark (example_id, buggy, intended)."""
    bench = bench.cache()
    rules = bench.select(F.lit("identity").alias("system"), "example_id", F.lit(1).alias("rank"), F.col("buggy").alias("candidate")).unionByName(models.arity_fixer(bench))
    out = rules
    for name, (model, prior) in (systems or {}).items():
        out = out.unionByName(models.repair(bench, model, name, prior=prior).drop("mean_logprob"))
    return measures.match_at_k(bench.select("example_id", F.col("intended").alias("gold")), out)


def _repair(s, d):
    """Both benchmarks, with and without fine-tuning on the repair set: tuned systems know how common each kind of edit is."""
    known = shapes.known(carriers.formulas(s, d))
    held, train = split(s, d)
    forum = tasks.forum_stand_in(carriers.formulas(s, d), SEED, known=known).cache()
    synthetic = tasks.repair_set(held, SEED, known=known).cache()
    train = train.join(forum.select(F.col("example_id").alias("formula_id")), "formula_id", "left_anti")
    own = curation.dedup(train, known=known).select("formula").cache()
    both = synthetic.unionByName(forum)
    model, generic = models.count_asked(own, both, order=4), models.count_asked(own, both, order=6, units="generic")
    prior = models.edit_prior(tasks.repair_set(train, SEED, known=known))
    systems = {"ngram not tuned": (model, None), "ngram tuned": (model, prior), "generic tokens tuned": (generic, prior)}
    scores = repair_scores(own, synthetic, systems=systems).withColumn("benchmark", F.lit("synthetic"))
    return scores.unionByName(repair_scores(own, forum, systems=systems).withColumn("benchmark", F.lit("forum")))


put("repair_eval_ngram", _repair)


def _latency(s, d):
    """Mean seconds to make repair candidates and the share repaired within five, system by system: the frontier's points."""
    known = shapes.known(carriers.formulas(s, d))
    held, train = split(s, d)
    bench = tasks.repair_set(held, SEED, known=known).cache()
    own = curation.dedup(train, known=known).select("formula").cache()
    prior = models.edit_prior(tasks.repair_set(train, SEED, known=known))
    gold, rows = bench.select("example_id", F.col("intended").alias("gold")), []
    for name, order, units in (("ngram-2", 2, "lexer"), ("ngram-4", 4, "lexer"), ("generic-6", 6, "generic")):
        cands = models.repair(bench, models.count_asked(own, bench, order=order, units=units), name, prior=prior).drop("mean_logprob").cache()
        seconds, _ = measures.timed(cands, counted=False)
        hit = measures.match_at_k(gold, cands).where("k = 5").first()
        rows.append((name, seconds / max(gold.count(), 1), hit["exact"] if hit else 0.0))
    return s.createDataFrame(rows, "system string, seconds_each double, repaired_at_5 double")


put("repair_latency", _latency)


#: objectives that can show a mistake: a lexer span hides tokens or nothing, a tail is no mistake, and intact rows have none
SHOWING = ("generic", "random", "user")


def _objectives(s, d):
    """Repair by systems that saw different mixes of objectives: what each mix shows of mistakes is all that differs."""
    known = shapes.known(carriers.formulas(s, d))
    held, train = split(s, d)
    own = curation.dedup(train, known=known).select("formula_id", "formula").cache()
    bench = tasks.repair_set(held, SEED, known=known).cache()
    model, systems = models.count_asked(own, bench, order=4), {}
    for name, weights in (("generic spans", corruption.ABLATION_BASE), ("with lexer spans and random noise", corruption.ABLATION_M), ("with user noise", corruption.ABLATION_MN)):
        # cached: a filter pushed below these columns would write their expressions out again and again
        pairs = corruption.pretraining_pairs(own, 64, SEED, weights, only=SHOWING, known=known).cache().where("source <> target AND NOT contains(source, '<mask>') AND objective <> 'tail'")
        systems[name] = (model, models.edit_prior(pairs.select(F.col("source").alias("buggy"), F.col("target").alias("intended"))) or None)
    return repair_scores(own, bench, systems=systems)


put("ablation_objectives_repair", _objectives)


def _nucleus(s, d):
    held, train = split(s, d)
    pre = tasks.completion_prefixes(held, fractions=(75,))
    return models.complete(pre, models.shelve_ngrams(train, order=4), "nucleus", 5, 20, "nucleus")


put("completion_nucleus", _nucleus)


def _constrained(s, d):
    """Decoding that drops what is not well formed against free decoding."""
    held, train = split(s, d)
    pre = tasks.completion_prefixes(held, fractions=(50,)).cache()
    model = models.count_ngrams(train, order=2)
    gold = pre.select("example_id", F.col("full").alias("gold"))
    both = models.complete(pre, model, "free", 5, 10).unionByName(models.complete(pre, model, "constrained", 5, 10, constraint=True))
    shape = lexing.with_tokens(both, "candidate").groupBy("system").agg(F.round(F.avg(F.expr(lexing.well_formed(SPARK, "tokens", "kinds")).cast("int")), 6).alias("well_formed"))
    return measures.match_at_k(gold, both.drop("mean_logprob")).join(shape, "system")


put("completion_constrained", _constrained)


def _prompts(s, d):
    held, train = split(s, d)
    return models.few_shot_prompt(tasks.repair_set(train, SEED), tasks.repair_set(held, SEED))


_ALL = PLACES + noisy_cte() + _LOW + f", rs AS (SELECT formula_id AS example_id, noisy AS buggy, formula AS intended, formula_id IN (SELECT formula_id FROM r) AS held FROM z WHERE {lexing.well_formed(DUCK, 'tokens', 'kinds')} AND noisy IS NOT NULL)"
put(
    "few_shot_prompts",
    _prompts,
    lexed("formulas", _ALL + f", low AS (SELECT *, {DUCK.u32('1', 'example_id', chr(39) + 'shot' + chr(39))} AS h FROM rs WHERE NOT held ORDER BY h, example_id LIMIT 3)")
    + """, shots AS (SELECT string_agg('broken: ' || buggy || chr(10) || 'fixed: ' || intended || chr(10), '' ORDER BY h, example_id) AS t FROM low)
        SELECT example_id, (SELECT t FROM shots) || 'broken: ' || buggy || chr(10) || 'fixed: ' AS prompt FROM rs WHERE held""",
)
put("few_shot_prompts_similar", lambda s, d: models.few_shot_prompt(tasks.repair_set(split(s, d)[1], SEED), tasks.repair_set(split(s, d)[0], SEED), pick="similar"))


def _tokenizer_ablation(s, d):
    """Pieces that cross a lexer boundary: none for the domain tokenizer, some where merges know no words."""
    f = carriers.formulas(s, d).select(F.lower("formula").alias("word"))
    counts = tokenizer.text_counts(f, 100).coalesce(s.sparkContext.defaultParallelism).persist()
    own = tokenizer.bpe_train(tokenizer.word_counts(counts.where("kind = 'stem'"), "text", False, "n").coalesce(s.sparkContext.defaultParallelism), 100)
    whole = tokenizer.bpe_train_counted(f, counts, 100)
    piece = F.concat("left", "right")
    crossing = (piece.rlike("[\\p{L}0-9]") & piece.rlike("[^\\p{L}0-9]")).cast("long")
    return own.select(F.lit("domain").alias("tokenizer"), crossing.alias("x")).unionByName(whole.select(F.lit("generic").alias("tokenizer"), crossing.alias("x"))).groupBy("tokenizer").agg(F.count(F.lit(1)).alias("merges"), F.sum("x").alias("crossing"))


put("ablation_tokenizer", _tokenizer_ablation)


def _stream_source(s, d) -> str:
    """The edits as a folder of several files, in no order of time, in the folder that the cluster shares."""
    path = edits.shared_path(s, "edits")
    carriers.formula_edits(s, d).withColumn("ts", F.col("ts").cast("timestamp")).repartition(4, "event_id").write.parquet(path)
    return path


def _stream_dedup(s, d):
    stream = edits.dedup_stream(edits.read_edits(s, _stream_source(s, d)), "60 days")
    return edits.run_to_table(stream.select("workbook_id", "sketch"))


put("stream_dedup", _stream_dedup, sketched("formula_edits") + "SELECT DISTINCT workbook_id, sketch FROM s")


def _stream_counts(s, d):
    out = edits.edit_counts(edits.read_edits(s, _stream_source(s, d)), delay="60 days")
    got = edits.run_to_table(out.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "sheet", "edits", "tokens"), "update", ["day", "sheet"])
    return got


put("stream_token_counts", _stream_counts, lexed("formula_edits") + "SELECT strftime(ts, '%Y-%m-%d') AS day, sheet, count(*) AS edits, CAST(sum(len(tokens)) AS BIGINT) AS tokens FROM f GROUP BY ALL")
put(
    "stream_late_edits",
    lambda s, d: edits.late_edits(carriers.formula_edits(s, d).withColumn("arrival", F.expr(SPARK.u32("1", "event_id", "'arrival'"))), "7 days", "arrival"),
    f"""SELECT event_id, workbook_id, late_hours FROM (SELECT event_id, workbook_id, CAST(floor((epoch_us(max(ts) OVER (PARTITION BY workbook_id ORDER BY {DUCK.u32('1', 'event_id', chr(39) + 'arrival' + chr(39))}, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)) - epoch_us(ts)) / 3600000000) AS BIGINT) AS late_hours
        FROM ({carriers.edits_sql(True)})) WHERE late_hours >= 168""",
)
put(
    "edit_sessions",
    lambda s, d: edits.sessions(carriers.formula_edits(s, d), "6 hours"),
    f"""SELECT workbook_id, epoch_us(min(ts)) AS first_us, epoch_us(max(ts)) AS last_us, count(*) AS edits FROM (SELECT *, sum(CASE WHEN ts - p < INTERVAL 6 HOUR THEN 0 ELSE 1 END) OVER (PARTITION BY workbook_id ORDER BY ts, event_id) AS g
        FROM (SELECT *, lag(ts) OVER (PARTITION BY workbook_id ORDER BY ts, event_id) AS p FROM ({carriers.edits_sql(True)}))) GROUP BY workbook_id, g""",
)
put(
    "edits_as_of",
    lambda s, d: edits.latest_edits(carriers.formula_edits(s, d), "2024-01-15 00:00:00"),
    f"SELECT workbook_id, sheet, first(formula ORDER BY ts DESC, event_id DESC) AS formula, count(*) AS edits FROM ({carriers.edits_sql(True)}) WHERE ts <= TIMESTAMP '2024-01-15' GROUP BY workbook_id, sheet",
)


def _star(s, d):
    f = curation.dedup(carriers.formulas(s, d)).select("formula_id", "workbook_id")
    cust, nat = (s.read.parquet(f"{d}/{t}.parquet") for t in ("customer", "nation"))
    j = f.join(cust.select(F.col("c_custkey").alias("workbook_id"), "c_nationkey", "c_mktsegment"), "workbook_id").join(F.broadcast(nat.select("n_nationkey", "n_name")), F.col("c_nationkey") == F.col("n_nationkey"))
    return j.cube("n_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("formulas"))


put(
    "corpus_cube",
    _star,
    sketched("formulas", ", k AS (SELECT min(formula_id) AS id, workbook_id FROM s GROUP BY workbook_id, sketch)")
    + "SELECT n_name, c_mktsegment, count(*) AS formulas FROM k JOIN customer ON c_custkey = workbook_id JOIN nation ON n_nationkey = c_nationkey GROUP BY CUBE (n_name, c_mktsegment)",
)
