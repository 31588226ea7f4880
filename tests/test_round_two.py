"""Dense ranking by blocks, recall of approximate ranks, the guard, ordered results, the whole pass over documents."""

import numpy as np
import pytest

from chapterforge.operators import execacc, qa, retrieval


def vectors(spark, n, dim=8, seed=1, ids="id"):
    rng = np.random.default_rng(seed)
    rows = [(int(i), [float(x) for x in v / np.linalg.norm(v)]) for i, v in enumerate(rng.standard_normal((n, dim)).round(1) + 0.05)]
    return rows, spark.createDataFrame(rows, f"{ids} long, embedding array<double>")


@pytest.mark.parametrize("block_rows,pool_rows", [(2000, 20000), (7, 11), (1, 50)])
def test_dense_rank_equals_brute_force(spark, block_rows, pool_rows):
    (q, questions), (t, pool) = vectors(spark, 23, seed=1, ids="q_id"), vectors(spark, 60, seed=2)
    t += [(100 + i, v) for i, v in t[:20]]  # ties, told apart by id
    pool = spark.createDataFrame(t, "id long, embedding array<double>")
    got = sorted((r["q_id"], r["rank"], r["id"], r["score"]) for r in retrieval.dense_rank(questions, pool, 5, block_rows, pool_rows).collect())
    want = []
    for i, v in q:
        scored = sorted((-round(float(np.dot(v, w)), 6), j) for j, w in t)[:5]
        want += [(i, k + 1, j, pytest.approx(-s, abs=2e-6)) for k, (s, j) in enumerate(scored)]
    assert got == want
    assert retrieval.dense_rank(questions.limit(0), pool, 5).count() == 0 and retrieval.dense_rank(questions, pool.limit(0), 5).count() == 0


def test_dense_rank_has_no_single_partition(spark):
    (_, questions), (_, pool) = vectors(spark, 23, ids="q_id"), vectors(spark, 60)
    plan = retrieval.dense_rank(questions, pool, 5)._jdf.queryExecution().executedPlan().toString()
    assert "SinglePartition" not in plan and "CartesianProduct" not in plan and "NestedLoop" not in plan


def test_approximate_recall(spark):
    from chapterforge import workloads

    for name in ("w4c_ivf_recall", "w4c_lsh_recall"):
        assert workloads.queries()[name](spark, "/root/testdata/sf0.001").first()["recall"] >= 0.9


def test_lsh_pairs_come_once(spark):
    (_, questions), (_, pool) = vectors(spark, 40, ids="q_id"), vectors(spark, 40)
    ranks = retrieval.lsh_rank(questions, pool, 40, tables=6, bits=2)
    assert ranks.count() == ranks.select("q_id", "id").distinct().count() and ranks.filter("rank = 1 and q_id = id").count() == 40


def test_guard_walks_the_tree(spark):
    spark.range(3).createOrReplaceTempView("three")
    for sql in (
        "select * from three where id in (select max(id) from three)", "with a as (select id from three) select * from a order by 1 limit 2",
        "select (select max(id) from three) as m, count(*) from three group by all", "values (1), (2)",
    ):
        execacc.guard(spark, sql)
    for sql in (
        "with a as (select 1 as x) insert into three select * from a", "from three insert overwrite three select *", "drop table three", "create table z as select 1",
        "select transform(id) using 'cat' as (a) from three", "with a as (select transform(id) using 'cat' as (b) from three) select * from a",
        "select * from (select transform(id) using 'cat' as (b) from three) as x where b in (select 1)", "set spark.x = 1",
    ):
        with pytest.raises(execacc.Refused):
            execacc.guard(spark, sql)
    assert execacc.run_one(spark, "with a as (select 1 as x) insert into three select * from a", "select 1")[1] == "not read-only"


def test_ordered_results(spark):
    up, down = spark.range(1000).orderBy("id"), spark.range(1000).orderBy("id", ascending=False)
    assert execacc.same_result(up, up, "ordered") and not execacc.same_result(up, down, "ordered") and not execacc.same_result(up, up.limit(999), "ordered")


def test_whole_documents_make_pairs(spark):
    text = ". ".join(f"sentence number {i} has several plain words" for i in range(40))
    docs = spark.createDataFrame([(1, text), (2, "Question: what is it?\nAnswer: it is that"), (3, None), (4, "")], "doc_id long, text string")
    pairs = qa.synthesize_pairs(docs.filter("doc_id = 1")).collect()
    assert sorted(r["pair_no"] for r in pairs) == list(range(40 - (40 % 2 == 0))) and qa.synthesize_pairs(docs.filter("doc_id = 1"), 2).count() == 2
    kept, report = qa.build_knowledge(docs)
    rows = kept.collect()
    assert {(r["doc_id"], r["route"]) for r in rows} == {(1, "synthesize"), (2, "extract")} and report.count() == 3
    only, _ = qa.build_knowledge(docs, spark.createDataFrame([(2,)], "doc_id long"))
    assert [(r["doc_id"], r["question"], r["answer"]) for r in only.collect()] == [(2, "what is it?", "it is that")]


def test_review_loop_needs_no_checkpoint_folder(spark):
    draft = lambda ids, turn: spark.range(10).withColumnRenamed("id", "q_id") if ids is None else ids
    vote = lambda drafts, turn: drafts.selectExpr("q_id", "explode(array(1, 2, 3)) as reviewer", f"q_id % 3 <= {turn} as valid")
    got = {r["q_id"]: r["round"] for r in qa.review_loop(draft, vote).collect()}
    assert got == {i: i % 3 for i in range(10)}


def test_backoff_probabilities_sum_to_one(spark):
    from chapterforge.operators import lm

    model = lm.BackoffModel(spark.createDataFrame([(1, "a b a c"), (2, "b a"), (3, ""), (4, None)], "id long, text string"), 3)
    # the last token of each asks for its probability: after a seen pair, a seen token behind an unseen one, an unseen token
    asked = [(10 * i + j, f"{before} {t}") for i, before in enumerate(("b a", "c b", "a z")) for j, t in enumerate("abc")]
    rows = model.token_losses(spark.createDataFrame(asked, "id long, text string")).filter("pos = 3").collect()
    sums, used = {}, {}
    for r in rows:
        sums[r["id"] // 10] = sums.get(r["id"] // 10, 0) + np.exp(-r["nll"])
        used[r["id"] // 10] = r["context"]
    assert used == {0: 2, 1: 1, 2: 0} and all(v == pytest.approx(1) for v in sums.values()) and len(rows) == 9
