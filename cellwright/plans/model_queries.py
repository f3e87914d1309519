"""Queries: tokenizer, similarity, retrieval."""

from __future__ import annotations

from pyspark.sql import functions as F

from cellwright.functions import lexing
from cellwright.functions.dialect import DUCK, SPARK
from cellwright.operators import measures, similarity, tokenizer
from cellwright.plans.twins import lexed
from cellwright.sources import carriers

QUERIES, SQL = {}, {}


def put(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def docs(s, d):
    return s.read.parquet(f"{d}/documents.parquet")


def vectors(s, d):
    return s.read.parquet(f"{d}/embeddings.parquet")


put(
    "pretokenize_formulas",
    lambda s, d: carriers.formulas(s, d).select("formula_id", F.expr(f"array_join({lexing.pretokens(SPARK, 'formula')}, '|')").alias("pieces")),
    f"SELECT formula_id, array_to_string({lexing.pretokens(DUCK, 'formula')}, '|') AS pieces FROM ({carriers.FORMULAS})",
)
put(
    "model_tokens",
    lambda s, d: lexing.with_tokens(carriers.formulas(s, d)).select("formula_id", F.expr(f"array_join(flatten({lexing.model_tokens(SPARK, 'tokens', 'kinds')}), '|')").alias("pieces")),
    lexed() + f"SELECT formula_id, array_to_string(flatten({lexing.model_tokens(DUCK, 'tokens', 'kinds')}), '|') AS pieces FROM f",
)
put(
    "tokenizer_report",
    lambda s, d: tokenizer.tokenizer_report(carriers.formulas(s, d)),
    f"""SELECT count(*) AS formulas, CAST(sum(len(t)) AS BIGINT) AS tokens, round(avg(len(t)), 6) AS tokens_each, round(sum(chars) / sum(len(t)), 6) AS chars_each, round(sum(len(list_filter(t, lambda y: {lexing.is_word(DUCK, 'y')}))) / sum(len(t)), 6) AS word_share
        FROM (SELECT length(formula) AS chars, {lexing.pretokens(DUCK, 'formula')} AS t FROM ({carriers.FORMULAS}))""",
)
put(
    "case_fragmentation",
    lambda s, d: tokenizer.case_fragmentation(carriers.formulas(s, d)),
    f"SELECT lower(t) AS word, count(DISTINCT t) AS spellings, count(*) AS n FROM (SELECT unnest({lexing.pretokens(DUCK, 'formula', False)}) AS t FROM ({carriers.FORMULAS})) WHERE regexp_matches(t, '^[A-Za-z]') GROUP BY lower(t)",
)
_WORDS = f"""WITH w AS (SELECT word, count(*) AS freq FROM (SELECT unnest({lexing.pretokens(DUCK, 'text')}) AS word FROM documents) WHERE {lexing.is_word(DUCK, 'word')} GROUP BY word),
    r0 AS (SELECT freq, regexp_replace(word, '(.)', '<\\1>', 'g') AS w FROM w)"""


def _words(s, d):
    return tokenizer.word_counts(docs(s, d), "text")


def _pairs(k: int) -> str:
    split = f"(SELECT freq, string_split(substring(w, 2, length(w) - 2), '><') AS s FROM r{k})"
    return f"p{k} AS (SELECT p.l AS l, p.r AS r, CAST(sum(freq) AS BIGINT) AS n FROM (SELECT freq, unnest(list_transform(range(1, len(s)), lambda i: {{'l': s[i], 'r': s[i + 1]}})) AS p FROM {split}) GROUP BY p.l, p.r), t{k} AS (SELECT * FROM p{k} ORDER BY n DESC, l, r LIMIT 1)"


put("bpe_pair_counts", lambda s, d: tokenizer.pair_counts(tokenizer.spelled(_words(s, d))), _WORDS + ", " + _pairs(0) + ' SELECT l AS "left", r AS "right", n FROM p0')
put("bpe_word_counts", _words, _WORDS + " SELECT word, freq FROM w")
ROUNDS = 4


def _first_merges(s, d):
    got = tokenizer.bpe_rounds(_words(s, d), ROUNDS)
    return s.createDataFrame([(i, *m) for i, m in enumerate(got)], "rank int, left string, right string, freq long")


_merges = _WORDS
for _k in range(ROUNDS):
    _merges += ", " + _pairs(_k) + f", r{_k + 1} AS (SELECT freq, replace(w, '<' || l || '><' || r || '>', '<' || l || r || '>') AS w FROM r{_k}, t{_k})"
put("bpe_first_merges", _first_merges, _merges + " ".join([""] + [" UNION ALL ".join(f'SELECT {k} AS rank, l AS "left", r AS "right", n AS freq FROM t{k}' for k in range(ROUNDS))]))


def _trained(s, d):
    return tokenizer.bpe_train(_words(s, d), 500)


put("bpe_train", _trained)


def _vocabulary(s, d):
    """The published size: fixed tokens and as many merges as fit, over formulas and prose."""
    words = tokenizer.word_counts(carriers.formulas(s, d), "formula").unionByName(_words(s, d)).groupBy("word").agg(F.sum("freq").alias("freq")).cache()
    letters = [r["c"] for r in words.select(F.explode(F.split("word", "")).alias("c")).where("c <> ''").distinct().orderBy("c").collect()]
    return tokenizer.build_vocab(tokenizer.bpe_train(words, tokenizer.VOCABULARY), letters)


put("vocabulary", _vocabulary)


def _roundtrip(s, d):
    words = tokenizer.word_counts(carriers.formulas(s, d), "formula")
    letters = [r["c"] for r in words.select(F.explode(F.split("word", "")).alias("c")).where("c <> ''").distinct().orderBy("c").collect()]
    merges = tokenizer.bpe_train(words, 200)
    vocab = tokenizer.build_vocab(merges, letters)
    ids = tokenizer.encode_ids(carriers.formulas(s, d), "formula", merges, vocab)
    return tokenizer.decode_ids(ids, vocab)


put("encode_decode_ids", _roundtrip, f"SELECT formula_id, lower(formula) AS text FROM ({carriers.FORMULAS})")


def _generic(s, d):
    whole = carriers.formulas(s, d).groupBy(F.lower("formula").alias("word")).agg(F.count(F.lit(1)).alias("freq"))
    return tokenizer.bpe_train(whole, 100)


put("bpe_generic_merges", _generic)


def sample(s, d, n: int = 1000):
    return similarity.masked_sample(carriers.formulas(s, d), n)


def masked_sql(limit: int | None) -> str:
    low = f"SELECT * FROM f ORDER BY {DUCK.u32('1', 'formula_id', chr(39) + 'similarity' + chr(39))}, formula_id LIMIT {limit}" if limit else "SELECT * FROM f"
    return f""", lo AS ({low}), mk AS (SELECT min(formula_id) AS id, masked FROM (SELECT *, {lexing.sketch(DUCK, 'tokens', 'kinds', ('number', 'string'))} AS masked FROM lo) GROUP BY masked),
    sm AS (SELECT id, {lexing.lex(DUCK, 'masked')} AS tokens FROM mk)"""


_SAMPLE, _WHOLE = masked_sql(1000), masked_sql(None)
_PAIRS = f", pr AS (SELECT a.id AS id_a, b.id AS id_b, {similarity.edit_similarity(DUCK, 'a.tokens', 'b.tokens')} AS sim FROM sm a JOIN sm b ON a.id < b.id)"


def _vectors(units: str = "tokens", pool: str = "mean", kinds: bool = False) -> str:
    """CTE vc: pooled vectors of the sample, over its tokens, their kinds or other units."""
    source = f"(SELECT id, {lexing.kinds(DUCK, 'tokens')} AS units FROM sm)" if kinds else f"(SELECT id, {units} AS units FROM sm)"
    return f", vc AS (SELECT id, {similarity.hash_pooled(DUCK, 'units', pool=pool)} AS v FROM {source})"


_SCORED = f", sp AS (SELECT id_a, id_b, sim, {similarity.cosine(DUCK, 'x.v', 'y.v')} AS cos FROM pr JOIN vc x ON x.id = id_a JOIN vc y ON y.id = id_b)"
put("pairwise_edit_similarity", lambda s, d: similarity.pairwise(sample(s, d)).withColumn("sim", F.round("sim", 9)), lexed("formulas", _SAMPLE + _PAIRS) + "SELECT id_a, id_b, round(sim, 9) AS sim FROM pr")
put("edit_sim_join", lambda s, d: similarity.edit_sim_join(sample(s, d), 0.8).withColumn("sim", F.round("sim", 9)), lexed("formulas", _SAMPLE + _PAIRS) + "SELECT id_a, id_b, round(sim, 9) AS sim FROM pr WHERE sim >= 0.8 - 1e-9")
put(
    "pooled_embeddings",
    lambda s, d: similarity.masked(carriers.formulas(s, d)).select("id", F.posexplode(F.expr(similarity.hash_pooled(SPARK, "tokens"))).alias("dim", "x")).withColumn("x", F.round("x", 9)).withColumn("dim", F.col("dim") + 1),
    lexed("formulas", _WHOLE + _vectors()) + f"SELECT id, unnest(range(1, {similarity.DIM + 1}))::INT AS dim, round(unnest(v), 9) AS x FROM vc",
)
put("retrieval_pearson", lambda s, d: measures.pearson(similarity.scored_pairs(sample(s, d)), "cos", "sim"), lexed("formulas", _SAMPLE + _PAIRS + _vectors() + _SCORED) + "SELECT round(corr(cos, sim), 6) AS pearson, count(*) AS n FROM sp")

#: encoders that stand in for the published ones: units that are pooled, and how
TRIGRAMS = "transform(sequence(1, greatest(length(array_join(tokens, '')) - 2, 1)), i -> substring(array_join(tokens, ''), i, 3))"
ENCODERS = {"tokens": ("tokens", "mean"), "trigrams": (TRIGRAMS, "mean"), "kinds": (lexing.kinds(SPARK, "tokens"), "mean"), "sum_pooling": ("tokens", "sum"), "max_pooling": ("tokens", "max"), "first_pooling": ("tokens", "first")}
_ENCODED = {
    "trigrams": _vectors("list_transform(range(1, greatest(length(array_to_string(tokens, '')) - 2, 1) + 1), lambda i: substring(array_to_string(tokens, ''), i, 3))"),
    "kinds": _vectors(kinds=True),
    "sum_pooling": _vectors(pool="sum"),
    "max_pooling": _vectors(pool="max"),
    "first_pooling": _vectors(pool="first"),
}


def encoded(rows, encoder: str):
    units, pool = ENCODERS[encoder]
    return rows.withColumn("u", F.expr(units)).select("id", F.expr(similarity.hash_pooled(SPARK, "u", pool=pool)).alias("v"))


def with_vectors(pairs, v):
    return pairs.join(v.toDF("id_a", "va"), "id_a").join(v.toDF("id_b", "vb"), "id_b")


def _baseline(encoder: str):
    def run(s, d):
        rows = sample(s, d)
        pairs = with_vectors(similarity.pairwise(rows), encoded(rows, encoder))
        return measures.pearson(pairs.select("sim", F.expr(similarity.cosine(SPARK, "va", "vb")).alias("cos")), "cos", "sim")

    return run


for _name, _sql in _ENCODED.items():
    put(f"retrieval_pearson_{_name}", _baseline(_name), lexed("formulas", _SAMPLE + _PAIRS + _sql + _SCORED) + "SELECT round(corr(cos, sim), 6) AS pearson, count(*) AS n FROM sp WHERE cos IS NOT NULL")
put(
    "triplet_agreement",
    lambda s, d: similarity.triplet_agreement(similarity.scored_pairs(sample(s, d)).withColumn("sim", F.round("sim", 9))),
    lexed("formulas", _SAMPLE + _PAIRS + _vectors() + _SCORED)
    + """, bo AS (SELECT id_a, id_b, round(sim, 9) AS sim, round(cos, 9) AS cos FROM sp UNION ALL SELECT id_b, id_a, round(sim, 9), round(cos, 9) FROM sp),
       bx AS (SELECT id_a, first(cos ORDER BY sim DESC, id_b) AS near, first(cos ORDER BY sim, id_b) AS far FROM bo GROUP BY id_a) SELECT count(*) AS anchors, CAST(sum(CAST(near > far AS INT)) AS BIGINT) AS agree FROM bx""",
)
_COS = f"""SELECT query, id, cos, rank FROM (SELECT *, row_number() OVER (PARTITION BY query ORDER BY cos DESC, id) AS rank FROM (SELECT q.vec_id AS query, e.vec_id AS id, round({similarity.cosine(DUCK, 'e.embedding', 'q.embedding')}, 9) AS cos
    FROM embeddings e JOIN embeddings q ON q.vec_id % 20 = 0 AND q.vec_id <> e.vec_id)) WHERE rank <= 10"""
put("embedding_topk", lambda s, d: similarity.retrieve(vectors(s, d)), _COS)


def _lsh(s, d):
    exact = similarity.retrieve(vectors(s, d)).select("query", "id")
    found = similarity.retrieve_lsh(vectors(s, d)).select("query", "id", F.lit(1).alias("hit"))
    return exact.join(found, ["query", "id"], "left").agg(F.count(F.lit(1)).alias("wanted"), F.count("hit").alias("found"))


_BANDS = f"""list_transform(range(0, {similarity.BANDS}), lambda b: b || ':' || array_to_string(list_transform(range(0, {similarity.WIDTH}), lambda w:
    CASE WHEN list_sum(list_transform(range(1, 65), lambda q: CAST(embedding[q] AS DOUBLE) * planes[b * {similarity.WIDTH} + w + 1][q])) > 0 THEN '1' ELSE '0' END), ''))"""
put(
    "embedding_lsh_recall",
    _lsh,
    f"""WITH ex AS ({_COS}), k AS (SELECT vec_id, embedding, unnest({_BANDS}) AS band FROM embeddings, (SELECT CAST('{similarity.planes()}' AS DOUBLE[][]) AS planes)),
        c AS (SELECT DISTINCT q.vec_id AS query, e.vec_id AS id FROM k q JOIN k e ON q.band = e.band AND q.vec_id % 20 = 0 AND q.vec_id <> e.vec_id),
        s AS (SELECT query, id, round({similarity.cosine(DUCK, 'e.embedding', 'q.embedding')}, 9) AS cos FROM c JOIN embeddings q ON q.vec_id = query JOIN embeddings e ON e.vec_id = id),
        f AS (SELECT query, id FROM (SELECT *, row_number() OVER (PARTITION BY query ORDER BY cos DESC, id) AS r FROM s) WHERE r <= 10)
        SELECT count(*) AS wanted, count(f.id) AS found FROM ex LEFT JOIN f ON f.query = ex.query AND f.id = ex.id""",
)


def _label(s, d):
    lab = vectors(s, d).select("vec_id", "label")
    top = similarity.retrieve(vectors(s, d)).select("query", "id", "rank")
    j = top.join(lab.toDF("id", "a"), "id").join(lab.toDF("query", "b"), "query")
    return j.groupBy("rank").agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("a") == F.col("b")).cast("long")).alias("same_label"))


put("retrieval_topk_labels", _label, f"SELECT rank, count(*) AS n, CAST(sum(CAST(a.label = b.label AS INT)) AS BIGINT) AS same_label FROM ({_COS}) t JOIN embeddings a ON a.vec_id = id JOIN embeddings b ON b.vec_id = query GROUP BY rank")


def _sets(s, d):
    train, held = similarity.similarity_sets(carriers.formulas(s, d))
    return train.select("id", F.lit("train").alias("part"), F.array_join("tokens", "").alias("masked")).unionByName(held.select("id", F.lit("eval").alias("part"), F.array_join("tokens", "").alias("masked")))


put(
    "similarity_sets",
    _sets,
    lexed("formulas", f""", al AS (SELECT *, {lexing.sketch(DUCK, 'tokens', 'kinds', ('number', 'string'))} AS masked, row_number() OVER (ORDER BY {DUCK.u32('1', 'formula_id', chr(39) + 'similarity' + chr(39))}, formula_id) AS r FROM f),
        ev AS (SELECT min(formula_id) AS id, masked FROM al WHERE r <= 1000 GROUP BY masked), tr AS (SELECT min(formula_id) AS id, masked FROM al WHERE r <= 11000 GROUP BY masked)""")
    + "SELECT id, 'eval' AS part, masked FROM ev UNION ALL SELECT id, 'train', masked FROM tr WHERE masked NOT IN (SELECT masked FROM ev)",
)


def _table(s, d, encoders=("tokens", "trigrams", "kinds")):
    """Correlation of cosine and edit similarity on the evaluation set, before and after fitting the head to the training set."""
    train, held = (x.cache() for x in similarity.similarity_sets(carriers.formulas(s, d)))
    some = similarity.paired(train).select("id_a", "id_b", F.expr(similarity.edit_similarity(SPARK, "ta", "tb")).alias("sim")).cache()
    every, out = similarity.pairwise(held).cache(), None
    for name in encoders:
        head, _ = similarity.fit_head(with_vectors(some, encoded(train, name)))
        pairs = with_vectors(every, encoded(held, name)).cache()
        raw = measures.pearson(pairs.select("sim", F.expr(similarity.cosine(SPARK, "va", "vb")).alias("cos")), "cos", "sim").withColumn("head", F.lit("untrained"))
        fit = measures.pearson(similarity.head_cosine(pairs, head).select("sim", "cos"), "cos", "sim").withColumn("head", F.lit("trained"))
        both = raw.unionByName(fit).withColumn("encoder", F.lit(name))
        out = both if out is None else out.unionByName(both)
    return out


put("retrieval_head", _table)


def _word2vec(s, d):
    """Mean-pooled vectors learned from the training set's token sequences."""
    from pyspark.ml.functions import vector_to_array
    from pyspark.ml.feature import Word2Vec

    train, held = similarity.similarity_sets(carriers.formulas(s, d))
    model = Word2Vec(vectorSize=similarity.DIM, minCount=1, maxIter=2, seed=1, inputCol="tokens", outputCol="w").fit(train)
    v = model.transform(held).select("id", vector_to_array("w").alias("v"))
    pairs = with_vectors(similarity.pairwise(held), v)
    return measures.pearson(pairs.select("sim", F.expr(similarity.cosine(SPARK, "va", "vb")).alias("cos")), "cos", "sim")


put("retrieval_pearson_word2vec", _word2vec)
