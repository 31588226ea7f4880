"""Worked examples and invariants."""

import pytest
from pyspark.sql import functions as F

from chapterforge.functions import parsers, text
from chapterforge.operators import alignment, execacc, filtering, lm, measures, pages, qa, retrieval, selection
from chapterforge.plans import curriculum


def one(spark, expr, value=None):
    return spark.createDataFrame([(value,)], "o string").select(expr).first()[0]


@pytest.mark.parametrize("said,letter,route", [("Answer: (B)", "B", "tag"), ("answer: c.", "C", "tag"), ("I take D because", "D", "fallback"), ("maybe", None, "none"), (None, None, "none"), ("ABBA", None, "none")])
def test_choice(spark, said, letter, route):
    got = spark.createDataFrame([(said,)], "o string").select(*parsers.parse_choice(F.col("o"))).first()
    assert tuple(got) == (letter, route)


@pytest.mark.parametrize("said,names,route", [("<tables>b\na\nb</tables>", ["a", "b"], "tag"), ("<TABLES>a , b</TABLES>", ["a", "b"], "tag"), ("a\n b \n", ["a", "b"], "fallback"), ("", [], "none"), (None, [], "none"), ("<tables></tables>", [], "tag")])
def test_tables(spark, said, names, route):
    got = spark.createDataFrame([(said,)], "o string").select(*parsers.parse_tables(F.col("o"))).first()
    assert (list(got[0]), got[1]) == (names, route)


@pytest.mark.parametrize("said,sql,route", [("<sql>select 1</sql>", "select 1", "tag"), ("x ```sql\nselect 2\n``` y", "select 2", "fallback"), ("none", None, "none"), (None, None, "none")])
def test_sql(spark, said, sql, route):
    assert tuple(spark.createDataFrame([(said,)], "o string").select(*parsers.parse_sql(F.col("o"))).first()) == (sql, route)


def test_macros(spark):
    text.register_macros(spark)
    assert spark.sql("select parse_choice('Answer: (b)'), count_tokens('Two words'), round(cosine(array(1f,0f), array(1f,1f)), 3), jaccard(array('a'), array('a','b'))").first()[1] == 2


def test_set_accuracy_needs_equal_sets(spark):
    rows = [("q", ["a", "b"], ["b", "a", "a"]), ("r", ["a"], ["a", "b"]), ("s", ["a"], [])]
    got = measures.set_accuracy(spark.createDataFrame(rows, "q_id string, gold array<string>, predicted array<string>"), ["q_id"]).collect()
    assert {r["q_id"]: r["accuracy"] for r in got} == {"q": 1.0, "r": 0.0, "s": 0.0}


def test_missing_prediction_counts(spark):
    gold = spark.createDataFrame([("q", ["a"]), ("r", ["b"])], "q_id string, gold array<string>")
    pred = spark.createDataFrame([("q", "p", ["a"])], "q_id string, predictor string, predicted array<string>")
    assert measures.set_accuracy(measures.with_gold(pred, gold), ["predictor"]).first()["accuracy"] == 0.5


def test_record_example(spark):
    rows = spark.createDataFrame([("x", i, v) for i, v in enumerate([11.5, 11.4, 11.5], 1)], "g string, t int, v double")
    assert pages.record_moves(rows, "g", ["t"], "v", lower_is_better=True, start=F.lit(11.5)).first()["matches_or_beats"] == 2


def test_nucleus_and_temperature(spark):
    p = spark.createDataFrame([("c", "x", 0.6), ("c", "y", 0.3), ("c", "z", 0.1)], "ctx string, token string, p double")
    cut = {r["token"]: r["p"] for r in lm.nucleus(p, 0.85).collect()}
    assert cut == pytest.approx({"x": 2 / 3, "y": 1 / 3})
    assert sum(r["p"] for r in lm.temper(p, 0.7).collect()) == pytest.approx(1)
    assert sorted(r["p"] for r in lm.temper(p, 0.0).collect()) == [0, 0, 1]
    assert lm.nucleus(p, 1.0).count() == 3


def test_masks(spark):
    row = spark.createDataFrame([(2, 3), (0, 0)], "a int, b int").select(lm.loss_mask(F.col("a"), F.col("b")).alias("m"), lm.loss_mask(F.col("a"), F.col("b"), "all").alias("n")).collect()
    assert [list(r["m"]) for r in row] == [[0, 0, 1, 1, 1], []] and list(row[0]["n"]) == [1] * 5


def test_learning_rate(spark):
    lr = [r["lr"] for r in curriculum.cosine_lr(curriculum.steps_frame(spark, 10), 10).orderBy("step").collect()]
    assert lr[0] == pytest.approx(1e-6) and lr[-1] == pytest.approx(0, abs=1e-18) and lr == sorted(lr, reverse=True)


def test_softmax_trainer_learns(spark):
    rows = [(1, ["bad", "junk"])] * 20 + [(5, ["good", "prose"])] * 20
    w = curriculum.train_softmax(spark.createDataFrame(rows, "score int, tokens array<string>"), features=16, steps=10)
    assert w.shape == (16, 5) and abs(w).max() > 0


def test_curriculum_exposure(spark):
    ex = lambda c, n: spark.createDataFrame([(f"{c}-{i}", c) for i in range(n)], "example_id string, chapter int")
    seen = {(r["stage"], r["chapter"]): (r["least"], r["most"]) for r in curriculum.exposure(curriculum.curriculum(ex(1, 200), ex(3, 50))).collect()}
    assert seen[1, 1] == (1, 1) and seen[2, 3] == (2, 2) and seen[2, 1] == (2, 2)


def test_entailment_and_table_filter(spark):
    rows = [("t", 1, {"rank": "2", "name": "Ann"}, "Ann came second."), ("t", 2, {"name": "Bo"}, "No name."), ("u", 1, {"n": "7"}, "It was 8."), ("u", 2, {"n": "7"}, "It was seven.")]
    got = alignment.entail(spark.createDataFrame(rows, "table_id string, row_no int, cells map<string,string>, text string"))
    assert [r["verdict"] for r in got.orderBy("table_id", "row_no").collect()] == ["entailed", "neutral", "contradicted", "entailed"]
    assert {r["table_id"] for r in alignment.keep_consistent_tables(got).collect()} == {"t"}
    assert alignment.keep_consistent_tables(got, "row").count() == 3


def test_scenarios_are_kept_strictly_above(spark):
    d = alignment.judge_scenarios(alignment.draft_scenarios(spark.createDataFrame([("s", ["orders", "customer", "nation"])], "schema_id string, tables array<string>")))
    assert {r["draft_no"]: (r["score"], r["kept"]) for r in d.collect()}[1] == (5, True)
    assert not any(r["kept"] for r in d.collect() if r["score"] <= 4)


def test_sub_schemas_and_catalog(spark, data):
    assert len(alignment.sub_schemas(alignment.SALES_KEYS)) == 43
    from chapterforge.workloads import selection as ws

    tables = {t: spark.read.parquet(f"{data}/{t}.parquet") for t in ws.ALL}
    got = alignment.catalog_of(spark, "sales", tables, alignment.SALES_KEYS)
    assert {(r["table"], r["ordinal"], r["column"], r["type"]) for r in got.collect()} == set(ws.CATALOG)
    assert alignment.filter_schemas(got).count() == 1
    found = {(r["table"], r["column"], r["to_table"]) for r in alignment.discover_keys(spark, {k: tables[k] for k in ("region", "nation", "customer")}).collect()}
    assert ("nation", "n_regionkey", "region") in found and ("customer", "c_nationkey", "nation") in found


def test_gold_tables_agree(spark):
    from chapterforge.workloads import selection as ws

    by_regex = {r["q_id"]: list(r["gold"]) for r in ws.questions(spark).collect()}
    for q, _, sql in ws.ITEMS:
        assert by_regex[q] == selection.gold_tables_parsed(spark, sql)


def test_results_compare(spark):
    a, b = spark.sql("select * from values (1, 'x'), (2, 'y') t(a, b)"), spark.sql("select * from values (2, 'y'), (1, 'x'), (1, 'x') t(a, b)")
    assert execacc.same_result(execacc._plain(a), execacc._plain(b), "set") and not execacc.same_result(execacc._plain(a), execacc._plain(b), "bag")
    assert not execacc.same_result(execacc._plain(a), execacc._plain(a.orderBy(F.desc("a"))), "ordered")
    assert execacc.run_one(spark, "drop view nothing", "select 1")[1] == "not read-only"
    gaps = execacc.structure_gaps("select 1 from a", "select 1 from a join b on x = y where z > 3", ["z > 3"])
    assert gaps["missing"] == ["b"] and gaps["hints_missing"] == ["z > 3"]


def test_page_tables(spark):
    html = "<h2>A b</h2><table><tr><th>x<th>y<tr><td><a href='#'>1</a><td><table><tr><td>in</td></tr></table></table><h2>A b</h2><table></table><p>&amp;"
    got = pages.name_tables(pages.page_tables(spark.createDataFrame([(1, html), (2, None)], "page_id long, html string"))).orderBy("ordinal").collect()
    assert [(r["table_name"], r["n_rows"], r["n_cols"]) for r in got] == [("A_b_1", 1, 2), ("A_b_2", 0, 0)] and "| 1 | in |" in got[0]["markdown"]


def test_pairs_round_trip(spark):
    docs = spark.createDataFrame([(1, "Question: a?\nAnswer: b\nquestion: c\nanswer: d"), (2, "no markers"), (3, "Question: only")], "doc_id long, text string")
    assert [(r["question"], r["answer"]) for r in qa.extract_pairs(docs).orderBy("pair_no").collect()] == [("a?", "b"), ("c", "d")]
    assert {r["doc_id"]: r["route"] for r in qa.route_documents(qa.flag_markers(docs)).collect()} == {1: "extract", 2: "synthesize", 3: "synthesize"}


def test_review_loop_ends(spark):
    spark.sparkContext.setCheckpointDir("/tmp/chapterforge-tests")
    draft = lambda ids, k: spark.createDataFrame([(i,) for i in range(6)], "q_id int") if ids is None else ids
    vote = lambda d, k: d.select("q_id", F.explode(F.array(*map(F.lit, (1, 2, 3)))).alias("reviewer")).withColumn("valid", F.col("q_id") <= k * 2 + F.col("reviewer"))
    got = qa.review_loop(draft, vote, max_rounds=4).collect()
    assert sorted(r["q_id"] for r in got) == list(range(6)) and max(r["round"] for r in got) <= 2


def test_rank_variants(spark):
    pool = spark.createDataFrame([("a", "red apple"), ("b", "green apple"), ("c", "blue sky")], "id string, text string")
    ask = spark.createDataFrame([("q", "red apple")], "q_id string, text string")
    for score in ("bm25", "cosine_sparse"):
        assert retrieval.bm25_rank(ask, pool, score=score).filter("rank = 1").first()["id"] == "a"


def test_index_appends(spark, tmp_path):
    pool = spark.createDataFrame([("a", "red apple"), ("b", "green apple")], "id string, text string")
    retrieval.build_text_index(pool, str(tmp_path / "i"))
    assert retrieval.build_text_index(spark.createDataFrame([("c", "blue")], "id string, text string"), str(tmp_path / "i"), append=True).size == 3


def test_plan_keeps_top_k_small(spark):
    scored = spark.createDataFrame([("q", "a", 1.0)], "q_id string, id string, score double")
    assert "WindowGroupLimit" in retrieval.ranked(scored, 3)._jdf.queryExecution().executedPlan().toString()


def test_filter_samples(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    for method in ("bernoulli", "stratified", "files"):
        assert filtering.rating_sample(docs, 0.5, method=method, strata="lang").count() <= docs.count()


def test_bayes_forms_agree(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    model = filtering.train_bayes(docs.join(filtering.ratings_from_labels(spark.read.parquet(f"{data}/labels.parquet")), "doc_id"))
    a, b = filtering.bayes_scores(docs, model), filtering.bayes_scores(docs, model, map_terms=0)
    key = lambda df: sorted((r["doc_id"], r["predicted"], round(r["margin"], 4)) for r in df.collect())
    assert key(a) == key(b)
    assert "Exchange" not in filtering.bayes_scores(docs, model)._jdf.queryExecution().executedPlan().toString()
