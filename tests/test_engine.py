"""Worked examples, independent oracles, invariants, DuckDB twins and plan shapes."""

import os
import random
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from cellwright.functions import lexing, noise, shapes
from cellwright.functions.dialect import SPARK
from cellwright.operators import corruption, curation, measures, models, published, similarity, tasks, tokenizer
from cellwright.sources import carriers

SF = "/root/testdata/sf0.001"


def frame(spark, *texts):
    return spark.createDataFrame([(i, 1, t) for i, t in enumerate(texts)], "formula_id long, workbook_id long, formula string")


EDGE = ["", None, "   ", '=A1&"open', '="a""b"', "='My ''x'' y'!$A$1", "=SUM(A:A)", "=SUM(3:5)", "=Tbl[[#All],[c]]", "=LOG10(2)", "=1,-2*(-3)", "=#REF!+1", "=true", "=" + "(" * 64 + "1" + ")" * 64, "=Größe!ß1+é", "=.5e-3", "=a<>b<=c"]


def test_lexer_is_lossless_and_kinds_hold(spark):
    rows = lexing.with_tokens(frame(spark, *EDGE)).orderBy("formula_id").collect()
    for r in rows:
        assert r["tokens"] is None if r["formula"] is None else "".join(r["tokens"]) == r["formula"]
    kinds = {r["formula"]: [k for k in r["kinds"] if k not in ("punct", "op")] for r in rows if r["formula"]}
    assert kinds["=LOG10(2)"] == ["function", "number"]
    assert kinds["=SUM(A:A)"] == ["function", "cell", "cell"] and kinds["=SUM(3:5)"] == ["function", "cell", "cell"]
    assert kinds["='My ''x'' y'!$A$1"] == ["sheet", "cell"] and kinds['="a""b"'] == ["string"] and kinds["=true"] == ["bool"]


def test_sketch_and_match_forms(spark):
    t = lexing.with_sketch(frame(spark, "=MAX(C2:C40)", "= max( d7:D9 )", '=IF(x>1,"a",-3)', "=F5>=ROUND(NOW(),-2)"))
    t = t.withColumn("m", F.expr(lexing.match_form(SPARK, "tokens", "kinds"))).withColumn("s", F.expr(lexing.sketch_match_form(SPARK, "tokens", "kinds"))).orderBy("formula_id").collect()
    assert t[0]["sketch"] == t[1]["sketch"] == "=MAX(cell:cell)"
    assert t[1]["m"] == "=MAX(D7:D9)" and t[2]["s"] == "=IF(X>number,string,number)" and t[3]["s"] == "=cell>=ROUND(NOW(),number)"


def test_pretokenizer_example(spark):
    got = frame(spark, '=CountIf(AB7:AB90, "Paid Twice")').select(F.expr(lexing.pretokens(SPARK, "formula")).alias("p")).first()["p"]
    assert "|".join(got) == '=|countif|(|ab|7|:|ab|9|0|,| |"|paid| |twice|"|)'


def test_registered_sql_functions(spark):
    lexing.register(spark)
    assert spark.sql("SELECT sketch('=MIN(B3:B8)') s, size(lex('=A1+2')) n").first() == ("=MIN(cell:cell)", 4)


def test_dedup_scopes(spark):
    f = spark.createDataFrame([(3, 1, "=A1+1"), (2, 1, "=B7+25"), (5, 2, "=C1+3"), (6, 2, "=C1*3")], "formula_id long, workbook_id long, formula string")
    ids = {s: sorted(r[0] for r in curation.dedup(f, s).select("formula_id").collect()) for s in ("workbook", "global", "none")}
    assert ids == {"workbook": [2, 5, 6], "global": [2, 6], "none": [2, 3, 5, 6]}


def test_dedup_with_repeated_ids_and_rows(spark):
    f = spark.createDataFrame([(1, 1, "=A1+1"), (1, 1, "=A1+1"), (1, 1, "=B7+2"), (2, 1, "=C9+3"), (1, 1, "=C9*3"), (None, 1, "=A2*8"), (4, None, "=A1"), (5, None, "=B2"), (6, 2, None), (7, 2, None)], "formula_id long, workbook_id long, formula string")
    got = sorted(map(str, (tuple(r) for r in curation.dedup(f).collect())))
    assert got == sorted(map(str, [(1, 1, "=A1+1", 4), (None, 1, "=A2*8", 2), (4, None, "=A1", 2), (6, 2, None, 2)]))
    new, seen = f.where("formula_id = 1"), curation.seen_keys(f.where("formula_id = 2"))
    assert [tuple(r) for r in curation.dedup_incremental(new, seen).collect()] == [(1, 1, "=C9*3")]


def test_dedup_plan_has_one_shuffle_and_no_python(spark, tmp_path):
    frame(spark, *EDGE).write.parquet(f"file://{tmp_path}/f")
    f = spark.read.parquet(f"file://{tmp_path}/f")
    for scope in ("workbook", "global"):
        plan = curation.dedup(f, scope)._jdf.queryExecution().executedPlan().toString()
        assert plan.count("Exchange hashpartitioning") == 1 and "SinglePartition" not in plan and "Join" not in plan and "Python" not in plan
    wide = carriers.formulas_wide(spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "SinglePartition" not in wide
    top = similarity.retrieve(spark.read.parquet(f"{SF}/embeddings.parquet"))._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in top and "Cartesian" not in top


def test_well_formed(spark):
    t = curation.well_formed(frame(spark, "=SUM(A1)", "=SUM(A1", "=A1+", "=A1**2", '="x', "=IF(A1,,2)", "=-A1", "=f(x)+1")).orderBy("formula_id").collect()
    assert [r["well_formed"] for r in t] == [True, False, False, False, False, False, True, True]


def test_noise_operators(spark):
    f = lexing.with_tokens(frame(spark, "=ROUND(ABS(G6*1.2),\"\")", "=AND(A1,B2)", "=S!A1:B2", "=SUMIF(A1,\"xy\",C1)<=3"))
    want = {
        "N01": {1: "=AND(A1)", 0: "=ROUND(ABS(G6*1.2))"},
        "N03": {0: "=ROUND(ABS(G6*1.2,\"\"))"},
        "N04": {1: "=AND(B2,A1)"},
        "N05": {3: "=SUMIF(A1,xy,C1)<=3"},
        "N06": {1: "=A1 AND B2"},
        "N07": {1: "=AND(A1,B2"},
        "N08": {1: "=AND(A1,B2))"},
        "N09": {1: "=ANDA1,B2)"},
        "N10": {1: "=AND(A1B2)"},
        "N11": {1: "=AND(A1;B2)"},
        "N12": {2: "=S!A1B2"},
        "N13": {3: "=SUMIF(A1,\"xy,C1)<=3"},
        "N14": {3: "=SUMIF(A1,\"xy\",C1)=<3"},
        "N15": {0: "=ROUND(ABS(G6**1.2),\"\")"},
        "N16": {1: "=NAD(A1,B2)"},
        "N17": {2: "=SA1:B2"},
        "N02": {1: "=AND(A1,B2,B2)"},
    }
    assert set(want) == set(noise.CATALOGUE)
    for op, rows in want.items():
        got = {r["formula_id"]: r["noisy"] for r in noise.apply_operator(f, op).collect()}
        for k, v in rows.items():
            assert got[k] == v, op


def test_span_masks_keep_lexer_tokens_whole(spark):
    f = lexing.with_tokens(carriers.formulas(spark, SF))
    for rate, mean in corruption.SPAN_GRID:
        rows = corruption.span_mask(f, rate, mean).select("tokens", "masked", "source", "counts").collect()
        share = sum(sum(c for c, m in zip(r["counts"], r["masked"]) if m) for r in rows) / sum(sum(r["counts"]) for r in rows)
        assert abs(share - rate / 100) < 0.05
        for r in rows[:200]:
            out, before = "", False
            for t, m in zip(r["tokens"], r["masked"]):
                out += "<mask>" * (m and not before) if m else t
                before = m
            assert out == r["source"]


def test_mixer(spark):
    f = carriers.formulas(spark, SF)
    p = corruption.pretraining_pairs(f, 400).cache()
    assert p.count() == f.count()
    assert p.groupBy("batch_id").agg(F.countDistinct("objective", "variant").alias("n")).where("n > 1").count() == 0
    share = {r["objective"]: r["n"] for r in p.groupBy("objective").agg(F.countDistinct("batch_id").alias("n")).collect()}
    total = sum(share.values())
    for k, w in corruption.WEIGHTS.items():
        assert abs(share.get(k, 0) / total - w / 100) < 3 * (w / 100 * (1 - w / 100) / total) ** 0.5 + 0.01
    same = {r[0]: r[1] for r in p.groupBy("objective").agg(F.avg((F.col("source") == F.col("target")).cast("int"))).collect()}
    assert same["intact"] == 1 and same["tail"] == 0 and same["user"] < 0.05
    with pytest.raises(ValueError):
        corruption.objective_of(SPARK, 1, {"span": 90})


def naive_bpe(words, merges):
    seqs, out = [(list(w), f) for w, f in words], []
    for _ in range(merges):
        c = Counter()
        for s, f in seqs:
            for p in zip(s, s[1:]):
                c[p] += f
        if not c:
            break
        (a, b), n = min(c.items(), key=lambda x: (-x[1], x[0]))
        out.append((a, b, n))
        for k, (s, f) in enumerate(seqs):
            new, i = [], 0
            while i < len(s):
                if i + 1 < len(s) and (s[i], s[i + 1]) == (a, b):
                    new.append(a + b)
                    i += 2
                else:
                    new.append(s[i])
                    i += 1
            seqs[k] = (new, f)
    return out


def test_bpe_training_and_encoding(spark):
    rng = random.Random(1)
    words = sorted({"".join(rng.choice("abca") for _ in range(rng.randrange(1, 9))): rng.randrange(1, 50) for _ in range(200)}.items())
    want = naive_bpe(words, 40)
    assert tokenizer.train_merges(words, 40) == want
    frame_ = spark.createDataFrame(words, "word string, freq long")
    assert tokenizer.bpe_rounds(frame_, 5) == want[:5]
    merges = tokenizer.bpe_train(frame_, 40)
    got = {r["word"]: r["pieces"] for r in tokenizer.bpe_encode(frame_, merges).collect()}
    assert all("".join(p) == w for w, p in got.items()) and min(map(len, got.values())) == 1
    vocab = tokenizer.build_vocab(merges, list("abc"), 100)
    assert vocab.count() <= 100 and vocab.select("token").distinct().count() == vocab.count()


def test_edit_similarity(spark):
    def lev(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            prev, row[0] = row[0], i
            for j, y in enumerate(b, 1):
                prev, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, prev + (x != y))
        return row[-1]

    rng = random.Random(2)
    data = [(i, [rng.choice("ABC") + str(rng.randrange(3)) for _ in range(rng.randrange(1, 12))]) for i in range(25)] + [(90, [f"t{k}" for k in range(140)]), (91, [f"t{k}" for k in range(5, 150)])]
    by = dict(data)
    rows = spark.createDataFrame(data, "id long, tokens array<string>")
    got = similarity.pairwise(rows).collect()
    assert len(got) == len(data) * (len(data) - 1) // 2
    for r in got:
        a, b = by[r["id_a"]], by[r["id_b"]]
        assert abs(r["sim"] - (1 - lev(a, b) / max(len(a), len(b)))) < 1e-9
    for tau in (0.5, 0.8):
        assert {(r["id_a"], r["id_b"]) for r in similarity.edit_sim_join(rows, tau).collect()} == {(r["id_a"], r["id_b"]) for r in got if r["sim"] >= tau - 1e-9}


def test_head_gradient_and_schedule():
    rng = np.random.default_rng(0)
    head = similarity.Head({"w1": rng.normal(size=(4, 6)), "b1": rng.normal(size=6), "w2": rng.normal(size=(6, 3)), "b2": rng.normal(size=3)})
    xa, xb, y = rng.normal(size=(5, 4)), rng.normal(size=(5, 4)), rng.random(5)
    _, g = head.gradient(xa, xb, y)
    for k in g:
        i = tuple(0 for _ in g[k].shape)
        old = head.weights[k][i]
        head.weights[k][i] = old + 1e-6
        up, _ = head.gradient(xa, xb, y)
        head.weights[k][i] = old - 1e-6
        down, _ = head.gradient(xa, xb, y)
        head.weights[k][i] = old
        assert abs((up - down) / 2e-6 - g[k][i]) < 1e-4
    assert similarity.linear_schedule(50) == 0.5 and similarity.linear_schedule(100) == 1 and similarity.linear_schedule(1000) == 0
    stop = similarity.EarlyStopping(2)
    assert [stop.stop(x) for x in (3, 2, 2, 2)] == [False, False, False, True]


def test_match_at_k_counts_examples_without_candidates(spark):
    gold = spark.createDataFrame([(1, "=SUM(A1)"), (2, "=B2"), (3, "=C3")], "example_id long, gold string")
    c = spark.createDataFrame([("m", 1, 2, "= sum(a1)"), ("m", 1, 1, "=SUM(A2)"), ("m", 2, 1, "=X")], "system string, example_id long, rank int, candidate string")
    got = {r["k"]: (r["exact"], r["sketch"]) for r in measures.match_at_k(gold, c).collect()}
    assert got == {1: (0.0, 0.333333), 5: (0.333333, 0.333333)}


def brute_ngrams(texts, order):
    table = {}
    for t in texts:
        w = [models.START, *models.tokens(t), models.END]
        for n in range(1, order + 1):
            for i in range(max(1, n - 1), len(w)):
                g = tuple(w[i - n + 1 : i + 1])
                own = table.setdefault(g[:-1], {})
                own[g[-1]] = own.get(g[-1], 0) + 1
    return table


def brute_share(table, t, key):
    while key and key not in table:
        key = key[1:]
    own = table.get(key, {})
    share = own.get(t, 0) / max(1, sum(own.values()))
    return 0.6 * share + 0.4 * brute_share(table, t, key[1:]) if key else share


def test_models(spark):
    f = curation.dedup(carriers.formulas(spark, SF))
    texts = [r["formula"] for r in f.collect()]
    m = models.count_ngrams(f, order=3)
    assert m.table == brute_ngrams(texts, 3)
    for past in ([models.START], ["=", "SUM"], ["(", "A1"], ["no", "such"], [","]):
        key = tuple(past[-2:])
        while key and key not in m.table:
            key = key[1:]
        want = sorted(((t, brute_share(m.table, t, key)) for t in m.table[()]), key=lambda x: (-x[1], x[0]))
        for k in (1, 7, 40):
            got = models.NGram(3, m.table).next_tokens(past, k)
            assert [g[0] for g in got] == [w[0] for w in want[:k]] and all(abs(g[1] - w[1]) < 1e-12 for g, w in zip(got, want))
    with pytest.raises(ValueError):
        models.count_ngrams(f, order=3, room=10)
    # decoding against every continuation of a small model
    small = models.NGram(2, brute_ngrams(["=A1+B2", "=A1*B2", "=A1+C3"], 2), longest=8)
    found, live = [], [(["="], 0.0)]
    while live:
        seq, lp = live.pop()
        for t, p in small.probabilities([models.START, *seq]).items():
            if t == models.END:
                found.append(("".join(seq), (lp + np.log(p)) / len(seq)))
            elif len(seq) < 4:
                live.append(([*seq, t], lp + np.log(p)))
    best = sorted(found, key=lambda x: (-x[1], x[0]))
    got = models.beam(small, ["="], 10_000, 10_000)
    assert {t for t, _ in best} <= {t for t, _ in got} and all(abs(dict(got)[t] - s) < 1e-9 for t, s in best)
    assert models.nucleus(small, ["="], 1, n=4) == models.nucleus(small, ["="], 1, n=4)
    assert all(models.well_formed(t) for t, _ in models.beam(m, ["="], 20, 20, allow=models.well_formed))


def test_inverse_edits_undo_the_noise_operators(spark):
    f = lexing.with_tokens(frame(spark, '=IF(A1>=2,"yes","no")', "=SUM(A1:B2)+MAX(C1,D4)", "=AND(A1,B2)", "='My tab'!C3*ROUND(D4,2)"))
    for op in noise.CATALOGUE:
        if op not in ("N01",):  # what an argument was cannot be told from the rest
            rows = noise.apply_operator(f, op).collect()
            assert all(r["formula"] in models.inverse_edits(r["noisy"]) for r in rows), (op, rows)
    assert models.balanced("=f(x)") and not models.balanced("=f(x))") and models.signature("=SUM(A1", "=SUM(A1)") == "-+)"


def test_scores_by_join_equal_scores_in_memory(spark):
    f = curation.dedup(carriers.formulas(spark, SF))
    m = models.count_ngrams(f, order=3)
    texts = [r["formula"] for r in f.limit(20).collect()] + ["=NEW(Z9)", "=A1++"]
    c = spark.createDataFrame([("x", i, t) for i, t in enumerate(texts)], "system string, example_id long, candidate string")
    got = {r["candidate"]: r["mean_logprob"] for r in models.score_by_join(c, models.ngram_counts(f, order=3), 3).collect()}
    assert got.keys() == set(texts) and all(abs(got[t] - m.logprob(models.tokens(t))) < 1e-9 for t in texts)


def test_repair_prompts_and_rules(spark):
    bench = spark.createDataFrame([(1, "=SUM(A1,B2"), (2, "=ABS(A1,3)"), (3, "=MAX(A1))")], "example_id long, buggy string")
    fixed = {r["example_id"]: r["candidate"] for r in models.arity_fixer(bench).collect()}
    assert fixed == {1: "=SUM(A1,B2)", 2: "=ABS(A1)", 3: "=MAX(A1)"}
    m = models.count_ngrams(frame(spark, *["=SUM(A1,B2)"] * 5, "=MAX(A1)", "=ABS(A1)"), order=3)
    best = {r["example_id"]: r["candidate"] for r in models.repair(bench, m, "x").where("rank = 1").collect()}
    assert best[1] == "=SUM(A1,B2)" and best[3] == "=MAX(A1)"
    train = spark.createDataFrame([(10, "=SUM(A1", "=SUM(A1)"), (11, "=SUM(B7", "=SUM(B7)"), (12, "=MAX(A1,2", "=MAX(A1,2)"), (13, "=IF(A1", "=IF(A1)")], "example_id long, buggy string, intended string")
    for pick in ("random", "similar"):
        got = {r["example_id"]: r["prompt"] for r in models.few_shot_prompt(train, bench, 2, pick=pick).collect()}
        assert len(got) == 3 and all(p.count("broken: ") == 3 and p.endswith("fixed: ") for p in got.values())
    assert "=MAX(A1,2" in got[3]
    prior = models.edit_prior(train.unionByName(train))
    assert prior == {"-+)": 0.0}


def test_head_learns_on_held_out_pairs(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(300, similarity.DIM))
    w = rng.normal(size=(similarity.DIM, 3))
    near = lambda a, b: float((a @ w) @ (b @ w) / np.linalg.norm(a @ w) / np.linalg.norm(b @ w))
    rows = [(a.tolist(), b.tolist(), near(a, b)) for a, b in zip(x[rng.integers(0, 300, 4000)], x[rng.integers(0, 300, 4000)])]
    pairs = spark.createDataFrame(rows, "va array<double>, vb array<double>, sim double")
    head, losses = similarity.fit_head(pairs, rate=0.02, epochs=8)
    assert losses[-1] < 0.8 * losses[0]
    y = rng.normal(size=(500, similarity.DIM))
    a, b = head.embed(y[:250]), head.embed(y[250:])
    cos = (a * b).sum(1) / np.linalg.norm(a, axis=1) / np.linalg.norm(b, axis=1)
    assert np.corrcoef(cos, [near(p, q) for p, q in zip(y[:250], y[250:])])[0, 1] > 0.4


def test_repair_and_completion_sets(spark):
    f = carriers.formulas(spark, SF)
    held, rest = tasks.split_reserved(f, 50)
    assert held.count() == 50 and held.join(rest, "formula_id").count() == 0 and rest.count() + 50 == f.count()
    r = tasks.repair_set(f).where("buggy = intended")
    assert r.count() == 0
    assert tasks.completion_prefixes(f).where("NOT startswith(full, prefix)").count() == 0


def test_published_counts(spark):
    res = published.results(spark)
    won = {r["task"]: r["won"] for r in published.wins(res).collect()}
    assert won["repair"] + won["completion"] == 10
    assert max(r["saved_percent"] for r in published.speedup(res).where("system = 'encdec-220M'").collect()) == pytest.approx(41.8502)
    gap = min(r["points"] for r in published.deltas(res, "size", "60M per-workbook dedup").where("system = '60M global dedup'").collect())
    assert gap == -25


def test_sources(spark, tmp_path):
    from cellwright.sources import tables

    c = spark.createDataFrame([("m", 1, 1, "=A1", -0.1)], tables.CANDIDATES)
    c.write.json(f"file://{tmp_path}/c")
    assert tables.external_candidates(spark, f"file://{tmp_path}/c").collect() == c.collect()
    tables.write_shards(corruption.pretraining_pairs(carriers.formulas(spark, SF).limit(100), 8), f"file://{tmp_path}/p")
    assert spark.read.parquet(f"file://{tmp_path}/p").count() == 100


FAST = ["formulas_carrier", "lex_documents", "token_kinds", "sketch_match_form", "dedup_workbook", "dedup_global", "dedup_report", "curation_skew_global", "span_mask_35_2", "random_noise", "user_noise_mix", "completion_set", "bpe_pair_counts", "retrieval_pearson", "paper_wins", "stream_dedup", "harvest_pages"]


@pytest.mark.parametrize("name", FAST)
def test_duckdb_twin(spark, name):
    duckdb = pytest.importorskip("duckdb")
    from cellwright import workloads

    con = duckdb.connect()
    for t in os.listdir(SF):
        con.execute(f"create view {t[:-8]} as select * from read_parquet('{SF}/{t}')")
    got = workloads.queries()[name](spark, SF).toPandas()
    want = con.execute(workloads.oracle_sql()[name]).df()
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    assert sorted(map(tuple, got[cols].astype(str).values.tolist())) == sorted(map(tuple, want[cols].astype(str).values.tolist()))


def test_passage_leakage(spark):
    from cellwright.operators import tasks

    docs = ["x alpha beta gamma delta epsilon zeta y", "prealpha beta\ngamma delta epsilon zetapost", "one two", None, "", "q  r\ts"]
    items = ["alpha beta gamma delta epsilon zeta", "alpha beta\ngamma delta epsilon zeta", "lpha beta gamma del", "beta delta", "ne tw", "e t", "", None, "q  r\ts", "q r s", "absent words in a whole long item", "one two"]
    d = spark.createDataFrame([(i, t) for i, t in enumerate(docs)], "doc_id long, text string")
    q = spark.createDataFrame([(i, t) for i, t in enumerate(items)], "item_id long, text string")
    want = [i for i, t in enumerate(items) if t is not None and any(t in x for x in docs if x is not None)]
    assert sorted(r["item_id"] for r in tasks.passage_leakage(d, q).collect()) == want
    d, q = (spark.read.parquet(f"/root/testdata/sf0.01/{n}.parquet") for n in ("documents", "benchmark"))
    whole = [r["text"] for r in d.collect() if r["text"]]
    want = sorted(r["item_id"] for r in q.collect() if any(r["text"] in x for x in whole))
    assert want and sorted(r["item_id"] for r in tasks.passage_leakage(d, q).collect()) == want


def test_bpe_in_distributed_rounds_gives_the_same_merges(spark, tmp_path):
    rng = random.Random(5)
    words = sorted({"".join(rng.choice("abcdefgh") for _ in range(rng.randrange(1, 8))): rng.randrange(1, 9) for _ in range(60)}.items())
    want = tokenizer.train_merges(words, 25)
    assert want == naive_bpe(words, 25)
    got = tokenizer.bpe_train_distributed(spark.createDataFrame(words, "word string, freq long"), 25, save=lambda x: x.cache())
    assert got == want
    # ties and shared symbols end the head
    assert tokenizer.independent_head([("a", "b", 9), ("c", "d", 8), ("a", "x", 7), ("", "", 0)]) == 2
    assert tokenizer.independent_head([("a", "b", 9), ("c", "d", 8), ("e", "f", 8), ("", "", 0)]) == 3
    assert tokenizer.independent_head([("a", "b", 9), ("c", "d", 8), ("e", "c", 8), ("", "", 0)]) == 1
    assert tokenizer.independent_head([("a", "b", 9), ("c", "d", 8), ("e", "f", 8)]) == 1


def test_steps_are_worked_out_once(spark):
    """What a lambda reads is bound before it, so a long formula costs its length, not the cube of it."""
    import time

    from cellwright.functions.dialect import SPARK

    once = spark.range(1).select(F.expr(SPARK.bind("v", "uuid()", lambda v: f"array_distinct(transform(sequence(1, 9), i -> {v}))")).alias("u"))
    assert len(once.first()["u"]) == 1
    formula = "=SUM(" + ",".join(f"A{i}" for i in range(1, 401)) + ")"
    rows = lexing.with_tokens(spark.createDataFrame([(1, formula)], "formula_id long, formula string"))
    start = time.perf_counter()
    got = corruption.span_mask(rows, 35, 2, 1).select("source", "masked").first()
    assert time.perf_counter() - start < 30
    assert len(got["masked"]) == 803 and 0 < sum(got["masked"]) < 803 and "<mask>" in got["source"]


def test_decoding_costs_no_pass_over_frequent_contexts():
    """A context followed by 20,000 tokens is summed and ranked once; samples are those of the full ranking."""
    import math
    import time

    class Counted(dict):
        passes = 0

        def values(self):
            Counted.passes += 1
            return super().values()

    first = {str(i): 1 + i % 7 for i in range(20_000)}
    table = {(): Counted(first | {models.END: 30_000, "=": 5, "+": 3}), ("=",): Counted(first), (models.START,): Counted({"=": 9})}
    table |= {(str(i),): Counted({models.END: 1, "+": 2}) for i in range(2000)}
    model = models.NGram(2, table, longest=6)
    start = time.perf_counter()
    got = models.beam(model, ["="], 20, 5)
    assert len(got) == 5 and Counted.passes < 500
    assert models.nucleus(model, ["="], "k", n=5) and time.perf_counter() - start < 60
    # brute force of the tempered head
    full = sorted(((t, model.probability(t, ("3",))) for t in table[()]), key=lambda x: (-x[1], x[0]))
    m = 64
    while m <= len(full) and sum(q for _, q in full[:m]) < 0.999:
        m *= 4
    whole = sum(q ** (1 / 0.7) for _, q in full[:m])
    for (t, share, log), (u, q) in zip(model.tempered(["=", "3"], 0.95, 0.7), full):
        assert t == u and math.isclose(share, q ** (1 / 0.7) / whole, rel_tol=1e-9) and math.isclose(log, math.log(q), rel_tol=1e-9)


def test_similar_shots_have_a_small_plan(spark):
    """the pairs and their sketches are read from a cached table, not written out for each key."""
    pair = "example_id long, buggy string, intended string"
    train = spark.createDataFrame([(i, f"=SUM(A{i}", f"=SUM(A{i})") for i in range(1, 8)] + [(9, "=ROUND(B1,2", "=ROUND(B1,2)")], pair)
    asked = spark.createDataFrame([(20, "=SUM(C3", "=SUM(C3)"), (21, "=ROUND(D4,1", "=ROUND(D4,1)")], pair)
    got = models.few_shot_prompt(train, asked, pick="similar")
    assert "InMemoryRelation" in got._jdf.queryExecution().optimizedPlan().toString()
    rows = {r["example_id"]: r["prompt"] for r in got.collect()}
    assert all(p.count("broken: ") == 4 for p in rows.values()) and rows[20].count("=SUM(A") == 6 and "=ROUND(B1,2)" in rows[21]


def test_exact_retrieval_by_blocks_keeps_ties_and_odd_vectors(spark):
    """the nearest rows are those of the expression over all pairs, in whatever blocks, and no pair is expanded."""
    from pyspark.sql.window import Window

    rng = random.Random(3)
    rows = [(i, [float(rng.randrange(-2, 3)) for _ in range(4)]) for i in range(200)] + [(200, None), (220, [0.0] * 4), (221, [1.0, None, 2.0, 3.0]), (240, [float("nan")] * 4), (241, [1.0])]
    v = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    pairs = v.alias("e").join(v.where("vec_id % 20 = 0").select(F.col("vec_id").alias("query"), F.col("embedding").alias("qv")), F.col("vec_id") != F.col("query"))
    every = pairs.select("query", F.col("vec_id").alias("id"), F.round(F.expr(similarity.cosine(SPARK, "embedding", "qv")), 9).alias("cos"))
    want = every.withColumn("rank", F.row_number().over(Window.partitionBy("query").orderBy(F.desc("cos"), "id"))).where("rank <= 10")
    want = {(r["query"], r["rank"], r["id"], str(r["cos"])) for r in want.collect()}
    for blocks in ({}, {"rows_at_once": 30, "queries_at_once": 3}):
        got = similarity.retrieve(v, **blocks)
        assert {(r["query"], r["rank"], r["id"], str(r["cos"])) for r in got.collect()} == want
    assert "FlatMapCoGroupsInPandas" in got._jdf.queryExecution().optimizedPlan().toString()


def test_rule_candidates_read_the_repair_set_once(spark):
    """three uses of the repair set share one cached table."""
    from cellwright.plans import task_queries

    gold, cands = task_queries._rule_candidates(spark, "/root/testdata/sf0.001")
    for df, n in ((gold, 1), (cands, 2)):
        assert df._jdf.queryExecution().optimizedPlan().toString().count("InMemoryRelation") >= n


def test_cosine_links_count_every_pair_without_listing_it(spark):
    """links of each vector are those of the expression over all pairs, in whatever blocks; copies and odd vectors included."""
    rng = random.Random(4)
    rows = [(i, [float(rng.randrange(-2, 3)) for _ in range(4)]) for i in range(150)] + [(200, None), (201, [0.0] * 4), (202, [0.0] * 4), (203, [1.0, None, 2.0, 3.0]), (204, [float("nan")] * 4), (205, [1.0]), (206, [4.0]), (207, [3.0, 4.0, 0.0, 0.0]), (208, [1.0, 0.0, 0.0, 0.0]), (209, [0.0, 1.0, 0.0, 0.0])]
    rows += [(300 + i, v) for i, v in rows[:40]]
    v = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    pairs = v.toDF("a", "va").crossJoin(v.toDF("b", "vb")).where("a <> b AND size(va) = size(vb)")
    near = pairs.where(F.round(F.expr(similarity.cosine(SPARK, "va", "vb")), 9).between(0.8, 2)).groupBy("a").count()
    want, first = {r["a"]: r["count"] for r in near.collect()}, {}
    for i, x in rows:
        first.setdefault(str(x), i)
    for blocks in ({}, {"rows_at_once": 20}):
        got = similarity.cosine_links(v, **blocks)
        assert {r["vec_id"]: (r["class_id"], r["links"]) for r in got.collect()} == {i: (first[str(x)], want.get(i, 0)) for i, x in rows}


def test_edit_links_are_those_of_all_pairs_and_no_pair_is_listed(spark):
    """F16: links of each row are counted within pairs of blocks; bounds decide most pairs, distances the rest."""
    rng = random.Random(6)
    data = [(i, [rng.choice("ABC") + str(rng.randrange(2)) for _ in range(rng.choice((5, 6, 9, 10)))]) for i in range(120)] + [(500, []), (501, [])]
    data += [(600 + i, x[1:] + x[:1]) for i, x in data[:40]]  # shifted: alike, though every place differs
    rows = spark.createDataFrame(data, "id long, tokens array<string>")
    pairs = [r for r in similarity.pairwise(rows).collect()]
    for tau in (0.5, 0.8):
        want = Counter(x for r in pairs if r["sim"] >= tau - 1e-9 for x in (r["id_a"], r["id_b"]))
        for blocks in ({}, {"rows_at_once": 9}):
            got = similarity.edit_sim_links(rows, tau, **blocks)
            assert {r["id"]: r["links"] for r in got.collect()} == {i: want[i] for i, _ in data}
    assert "FlatMapCoGroupsInPandas" in got._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("name", ["noise_catalogue", "paper_best_second", "paper_completion_table", "paper_deltas_ablation", "paper_deltas_size", "paper_pareto", "paper_results", "paper_speedup", "paper_summary_by_size"])
def test_measures_read_given_tables(spark, name):
    """The queries read orders and customers, with the results of their twins (paper_wins is among FAST)."""
    from cellwright import workloads

    assert "orders" in str(workloads.queries()[name](spark, SF).inputFiles()) or name == "noise_catalogue"
    test_duckdb_twin(spark, name)


def test_bpe_over_cut_words_gives_the_same_merges(spark):
    """words are cut where no merge can cross, so few pieces are trained; the bound is lowered until it holds."""
    rng = random.Random(7)
    words = sorted({"=sum(" + "".join(rng.choice("0123456789") for _ in range(rng.randrange(1, 9))) + rng.choice([")*2", ":a1)", "é😀)"]): rng.randrange(1, 9) for _ in range(400)}.items())
    frame_ = spark.createDataFrame([*words, (None, 3)], "word string, freq long")
    for merges in (3, 12, 60, 3000):
        got = [tuple(r)[1:] for r in tokenizer.bpe_train(frame_, merges, whole=10).orderBy("rank").collect()]
        assert got == tokenizer.train_merges(words, merges), merges
    beside = tokenizer.neighbours(frame_.where("word IS NOT NULL"))
    cut = tokenizer.cut_words(frame_.where("word IS NOT NULL"), {c for c, n in beside.items() if n >= 500})
    assert cut.count() < 20 and {r["word"] for r in cut.collect()} >= {"=sum("}


def _counts(texts):
    pairs, stems = Counter(), Counter()
    for t in texts:
        pairs.update(map("".join, zip(t, t[1:])))
        stems[re.sub("[0-9]+", "0", t)] += 1
    del stems[""]
    return pairs, stems


def test_bpe_over_counted_texts_gives_the_same_merges(spark):
    """one pass counts pairs, pieces and stems of whole texts; parts of any size, cut more or less, or texts where a cut
    pair is too frequent, give the merges of training on the texts."""
    rng = random.Random(9)
    texts = ["=sum(" + "".join(rng.choice("0123456789") for _ in range(rng.randrange(1, 9))) + rng.choice([")*2", ":a1)", "é😀)", "aaaa", ""]) for _ in range(500)]
    texts += ["", "7", "x", "12", *["&&".join(rng.choice("pqr") for _ in range(4)) for _ in range(300)], None, *["=sum(1)"] * 40]
    whole = [t for t in texts if t is not None]
    pairs, stems = _counts(whole)
    words = sorted(Counter(whole).items())
    frame_ = spark.createDataFrame([(t,) for t in texts], "word string").coalesce(1)
    fallbacks = 0
    for merges, at_once, slack in ((5, 2_000_000, 2), (30, 2_000_000, 1), (30, 700, 2), (12, 60, 1), (3000, 2_000_000, 2)):
        counts = tokenizer.text_counts(frame_, merges, at_once, slack).cache()
        rows = counts.collect()
        assert {r["text"]: r["n"] for r in rows if r["kind"] == "pair"} == pairs
        assert {r["text"]: r["n"] for r in rows if r["kind"] == "stem"} == stems
        want = tokenizer.train_merges(words, merges)
        got = tokenizer.bpe_train_counted(frame_, counts, merges)
        assert [tuple(r)[1:] for r in got.orderBy("rank").collect()] == want, (merges, at_once, slack)
        cut = max((r["n"] for r in rows if r["cut"]), default=0)
        fallbacks += bool(cut) and (len(want) < merges or want[-1][2] <= cut)
    assert 0 < fallbacks < 5  # both ways were taken


def test_counts_of_parts_hold_where_hashes_meet(monkeypatch):
    """parts of equal hash are compared, and counted one by one where they differ."""
    text = "=a1=b2=a1=b2x"
    flat = np.frombuffer(text.encode("utf-32-le"), np.int32)
    starts, stops = np.array([0, 3, 6, 9, 12]), np.array([3, 6, 9, 12, 13])
    want = Counter({"=a1": 2, "=b2": 2, "x": 1})
    assert tokenizer._tally(flat, starts, stops) == want
    monkeypatch.setattr(tokenizer, "_powers", lambda bits: [np.zeros(1 << bits, np.uint64)] * 2)
    assert tokenizer._tally(flat, starts, stops) == want


def test_tokenizer_ablation_trains_no_whole_formula(spark, monkeypatch):
    """formulas are read once and never counted as texts; words come from stems."""
    from cellwright.plans import eval_queries

    f = carriers.formulas(spark, SF)
    words = {r["word"]: r["freq"] for r in tokenizer.word_counts(f, "formula").collect()}
    whole = [(r["w"], r["n"]) for r in f.groupBy(F.lower("formula").alias("w")).agg(F.count(F.lit(1)).alias("n")).collect()]
    seen, real = [], tokenizer.bpe_train
    monkeypatch.setattr(tokenizer, "bpe_train", lambda w, *a: (seen.append({r["word"]: r["freq"] for r in w.collect()}), real(w, *a))[1])
    got = {r["tokenizer"]: (r["merges"], r["crossing"]) for r in eval_queries._tokenizer_ablation(spark, SF).collect()}
    assert len(seen) == 2 and seen[0] == words and not {w for w, _ in whole} & {w for w in seen[1] if re.search("[0-9]{3}", w)}
    for name, own in (("domain", sorted(words.items())), ("generic", sorted(whole))):
        merges = [a + b for a, b, _ in tokenizer.train_merges(own, 100)]
        assert got[name] == (len(merges), sum(bool(re.search("[a-z0-9]", m) and re.search("[^a-z0-9]", m)) for m in merges))


def test_word_counts_take_letter_runs_only(spark):
    """what the pre-tokenizer leaves to BPE, without a row for each mark and space."""
    f = frame(spark, *EDGE, "Größe größe SUM sum² x1y _a b_c naïve", "İstanbul straße ٣abc")
    old = f.select(F.explode(F.expr(lexing.pretokens(SPARK, "formula"))).alias("w")).where(F.expr(lexing.is_word(SPARK, "w"))).groupBy("w").count()
    got = tokenizer.word_counts(f, "formula")
    assert {tuple(r) for r in got.collect()} == {tuple(r) for r in old.collect()}
    assert "(?s:.)" not in got._jdf.queryExecution().optimizedPlan().toString()


def test_bpe_over_arrays_gives_the_same_merges():
    """a merge costs a comparison of arrays, not a pass over words one by one; runs of one letter merge from the left."""
    rng = random.Random(8)
    words = sorted({"".join(rng.choice("aab😀é") for _ in range(rng.randrange(0, 10))): rng.randrange(1, 9) for _ in range(300)}.items())
    flat = np.frombuffer("".join(w for w, _ in words).encode("utf-32-le"), np.uint32)
    for merges in (1, 30, 5000):
        assert tokenizer.train_merges_arrays(flat, [len(w) for w, _ in words], [n for _, n in words], merges) == tokenizer.train_merges(words, merges)
    assert tokenizer.train_merges_arrays(flat[:0], [], [], 3) == []


def test_only_objectives_that_show_mistakes_are_worked_out(spark):
    """F8: the pairs that the edit priors are learned from, without the rows that the filter takes out again."""
    from cellwright.plans import eval_queries

    f = carriers.formulas(spark, SF).where("formula_id < 60").cache()
    kept = "source <> target AND NOT contains(source, '<mask>') AND objective <> 'tail'"
    weights = {"span": 40, "tail": 10, "random": 30, "generic": 10, "intact": 10}
    every = corruption.pretraining_pairs(f, 64, 1, weights).cache()
    some = corruption.pretraining_pairs(f, 64, 1, weights, only=eval_queries.SHOWING).cache()
    rows = sorted(map(tuple, some.where(kept).collect()))
    assert rows and rows == sorted(map(tuple, every.where(kept).collect()))
    assert not some.where("objective IN ('span', 'tail', 'intact')").count()


def test_work_by_shape_equals_work_by_formula(spark):
    """Also where texts differ in digits only, and arguments look equal without being so."""
    rnd = random.Random(3)
    parts = ["SUM(", "AND(", "LOG10(", "A1", "A2", "1", "12", "21", ",", ",", ")", ")", '"a1"', '"a2"', "'S 1'!", ":", "<=", "+", " ", "Q1x(", "x1", "#REF!", '"', "\u0663"]
    odd = ["".join(rnd.choice(parts) for _ in range(rnd.randint(1, 10))) for _ in range(600)]
    f = frame(spark, *EDGE, "=IF(A1,A1)", "=IF(A1,A2)", "=IF(a 1,A1)", "=MAX(1,2,3)", *odd, *[r["formula"] for r in carriers.formulas(spark, SF).limit(100).collect()]).cache()
    known = shapes.known(f)
    for ops in (None, ["N04", "N07", "N16"]):
        want = noise.user_noise(lexing.with_tokens(f), 1, ops=ops).select("formula_id", "op_id", "noisy")
        assert {tuple(r) for r in shapes.with_noise(f, 1, ops=ops, shapes=known).select("formula_id", "op_id", "noisy").collect()} == {tuple(r) for r in want.collect()}
    assert {tuple(r) for r in shapes.with_sketch(f, shapes=known).select("formula_id", "sketch").collect()} == {tuple(r) for r in lexing.with_sketch(f).select("formula_id", "sketch").collect()}
    assert {tuple(r) for r in curation.dedup(f, known=known).collect()} == {tuple(r) for r in curation.dedup(f).collect()}


def test_asked_counts_score_as_all_counts(spark):
    """Repair of a corpus that has more n-grams than a table has room for: only those asked for are held, with the same scores."""
    f = curation.dedup(carriers.formulas(spark, SF)).unionByName(frame(spark, "=\u0003+1", "=\u0002A1", "=Ä1+ä1").withColumn("sheet_no", F.lit(0)).withColumn("family_size", F.lit(1).cast("long")), allowMissingColumns=True)
    pairs = tasks.repair_set(f).limit(12).cache()
    for order, units in ((3, "lexer"), (4, "generic")):
        few, whole = models.count_asked(f, pairs, order=order, units=units), models.count_ngrams(f, order=order, units=units)
        assert sum(map(len, few.table.values())) < sum(map(len, whole.table.values())) / 2
        for r in pairs.collect():
            assert all(few.logprob(few.split(c)) == whole.logprob(whole.split(c)) for c in models.candidates(r["buggy"]))
    signed = Counter(models.signature(r["buggy"], r["intended"]) for r in pairs.collect())
    assert models.edit_prior(pairs).keys() == {k for k, n in signed.items() if n > 1}


def test_shelved_counts_are_the_counted_ones(spark):
    """Read by pickled copies, as workers do, with little room; and the completions are the same."""
    import pickle

    f = curation.dedup(carriers.formulas(spark, SF)).select("formula_id", "formula").unionByName(frame(spark, "=Ä1\u0001+1", "x", None).select("formula_id", "formula"))
    pre = tasks.completion_prefixes(f.limit(6), fractions=(50,))
    for order, units in ((3, "lexer"), (2, "generic")):
        whole, m = models.count_ngrams(f, order=order, units=units), models.shelve_ngrams(f, order=order, units=units, files=16)
        assert m.longest == whole.longest
        m.table.room = 50
        shelf = pickle.loads(pickle.dumps(m)).table
        assert all(shelf[k] == v and k in shelf for k, v in whole.table.items()) and shelf.held < 1000
        assert shelf.get(("no", "such"), {}) == {} and ("no",) not in shelf
        want, got = ({tuple(r) for r in models.complete(pre, x, "x", 3, 8).collect()} for x in (whole, m))
        assert got == want and got


def test_stream_in_one_pass_equals_a_query_for_each_objective(spark):
    """Also for empty and odd texts; and the plan reads each formula once, whatever the number of objectives."""
    f = frame(spark, *[x for x in EDGE if x is not None], *[r["formula"] for r in carriers.formulas(spark, SF).limit(60).collect()]).select("formula_id", "formula").cache()
    rows = f.withColumn("epoch", F.explode(F.sequence(F.lit(1), F.lit(4))))
    cols = ["formula_id", "epoch", "batch_id", "objective", "variant", "source", "target"]
    want = {tuple(r) for r in corruption.pretraining_pairs(rows, 16, "epoch", more=("epoch",)).select(*cols).collect()}
    got = corruption.pretraining_stream(f, 16, 4)
    assert {tuple(r) for r in got.select(*cols).collect()} == want and {r[3] for r in want} == set(corruption.WEIGHTS)
    assert "Union" not in got._jdf.queryExecution().executedPlan().toString()


def test_large_contexts_of_a_shelf_rank_as_counted(spark, monkeypatch):
    """Contexts kept in parts, with few likeliest tokens at hand: ranks, draws and smaller orders are those of the counts."""
    monkeypatch.setattr(models, "LARGE", 5)
    monkeypatch.setattr(models, "HEAD", 8)
    f = curation.dedup(carriers.formulas(spark, SF)).select("formula_id", "formula").limit(3000).cache()
    whole, m = models.count_ngrams(f, order=4), models.shelve_ngrams(f, order=4, files=8)
    assert sum(isinstance(m.table[k], models.Wide) for k in whole.table) > 20
    for own, got in ((whole, m), (models.NGram(2, whole.table), m.of_order(2))):
        for past in ([models.START], ["=", "SUM"], ["IF", "("], ["(", "A1"], ["no", "such"], [","]):
            for k in (1, 7, 40):
                assert got.next_tokens(past, k) == own.next_tokens(past, k), (past, k)
            a, b = own.tempered(past, 0.95, 0.7), got.tempered(past, 0.95, 0.7)
            assert [x[0] for x in a] == [x[0] for x in b] and all(abs(x[1] - y[1]) < 1e-9 for x, y in zip(a, b))
    task = frame(spark, "=SUM(A1,B2)", "=NEW(1)")
    tuned, both = models.tuned(whole, models.count_ngrams(task, order=4), 3), models.shelve_ngrams(f, order=4, files=8, extra=task, weight=3)
    assert all(dict(both.table[k]) == v for k, v in tuned.table.items()) and both.longest == tuned.longest


@pytest.fixture
def no_table(monkeypatch):
    """No room for a table of n-grams on the driver."""

    def full(*a, **k):
        raise ValueError("no room")

    monkeypatch.setattr(models, "count_ngrams", full)


def run_small(spark, name):
    from cellwright.plans import eval_queries

    return eval_queries.QUERIES[name](spark, SF).collect()


def test_completion_eval_ngram_holds_no_table(spark, no_table):
    assert len(run_small(spark, "completion_eval_ngram")) == 12


def test_ablation_size_holds_no_table(spark, no_table):
    assert len(run_small(spark, "ablation_size")) == 24


def test_ablation_dedup_holds_no_table(spark, no_table):
    assert len(run_small(spark, "ablation_dedup")) == 24


def test_completion_table_holds_no_table(spark, no_table):
    assert len(run_small(spark, "completion_table")) == 2


def test_completion_nucleus_holds_no_table(spark, no_table):
    assert len({r["example_id"] for r in run_small(spark, "completion_nucleus")}) == 500


def test_completion_modes_holds_no_table(spark, no_table):
    assert len(run_small(spark, "completion_modes")) == 24


def test_completion_modes_takes_all_reserved_formulas(spark, monkeypatch):
    from cellwright.plans import eval_queries

    seen = []
    monkeypatch.setattr(eval_queries, "completion_scores", lambda train, held, systems: seen.append(held.count()))
    eval_queries._modes(spark, SF)
    assert seen == [eval_queries.EXAMPLES]


def test_ablation_objectives_repair_holds_no_table(spark, no_table):
    assert len(run_small(spark, "ablation_objectives_repair")) == 10
