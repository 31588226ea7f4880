"""What the second round's findings were about: limits, pool blocks, tables that a query reads."""

import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from chapterforge.functions.text import in_sample
from chapterforge.operators import execacc, lm, retrieval
from chapterforge.plans import curriculum
from chapterforge.workloads import language


def _slow(seconds):
    @F.udf("long")
    def wait(x):
        time.sleep(seconds)
        return x

    return wait


@pytest.mark.parametrize("compare", ["set", "bag"])
def test_gold_has_no_time_limit(spark, compare):
    """A slow gold runs once and its time isn't the predictions'; a slow prediction fails, unless there is no limit."""
    spark.udf.register("wait", _slow(3))
    rows = [("q", "fast", "select 1L as x", "select wait(1) as x"), ("q", "other", "select 2L", "select wait(1) as x"), ("q", "slow", "select wait(1) as x", "select wait(1) as x")]
    items = spark.createDataFrame(rows, "q_id string, predictor string, predicted string, gold_sql string")
    limited = {r["predictor"]: r["correct"] for r in execacc.execution_accuracy(spark, items, compare, 2).collect()}
    assert limited == {"fast": 1, "other": 0, "slow": 0}
    free = {r["predictor"]: (r["correct"], r["class"]) for r in execacc.execution_accuracy(spark, items, compare, None).collect()}
    assert free == {"fast": (1, "right"), "other": (0, "wrong rows"), "slow": (1, "right")}


def test_gold_that_fails_or_fits_no_file(spark):
    gold = ["select * from not_there", "select null as x", "select 1 as x order by 1"]
    items = spark.createDataFrame([(str(i), "p", g if i else "select 1", g) for i, g in enumerate(gold)], "q_id string, predictor string, predicted string, gold_sql string")
    got = {r["q_id"]: (r["correct"], r["class"]) for r in execacc.execution_accuracy(spark, items).collect()}
    assert got == {"0": (0, "unknown table"), "1": (1, "right"), "2": (1, "right")}


def unit(n, dim, seed, copies=0):
    rng = np.random.default_rng(seed)
    found = [v / np.linalg.norm(v) for v in rng.standard_normal((n, dim))]
    return [(i, [float(x) for x in v]) for i, v in enumerate(found + found[:1] * copies)]


@pytest.mark.parametrize("block_rows,pool_rows", [(2000, 20000), (7, 11)])
def test_sign_hashes_compare_what_shares_a_key(spark, block_rows, pool_rows):
    q, t = unit(30, 8, 1), unit(80, 8, 2, copies=40)  # a bucket of 41 copies
    questions, pool = spark.createDataFrame(q, "q_id long, embedding array<double>"), spark.createDataFrame(t, "id long, embedding array<double>")
    ranks = retrieval.lsh_rank(questions, pool, 5, 3, 4, 5, block_rows, pool_rows)
    planes = np.random.default_rng(5).standard_normal((12, 8))
    keys = lambda v: [tuple(np.array(v) @ p >= 0 for p in planes[i * 4 : i * 4 + 4]) for i in range(3)]
    want = []
    for i, v in q:
        scored = [(-round(float(np.dot(v, w)), 6), j) for j, w in t if any(x == y for x, y in zip(keys(v), keys(w)))]
        want += [(i, r + 1, j) for r, (_, j) in enumerate(sorted(scored)[:5])]
    assert sorted((r["q_id"], r["rank"], r["id"]) for r in ranks.collect()) == want


def test_inverted_lists_in_parts(spark):
    """With every list probed, ranks are the exact ones, whatever parts a list is dealt into; nothing is broadcast, no pair is a row."""
    q, t = unit(30, 8, 1), unit(80, 8, 2, copies=40)
    questions, pool = spark.createDataFrame(q, "q_id long, embedding array<double>"), spark.createDataFrame(t, "id long, embedding array<double>")
    rows = lambda df: sorted((r["q_id"], r["rank"], r["id"]) for r in df.collect())
    exact = rows(retrieval.dense_rank(questions, pool, 3))
    for pool_rows in (20000, 9):
        found = retrieval.ivf_rank(questions, pool, 3, lists=4, probes=4, pool_rows=pool_rows)
        assert rows(found) == exact
        plan = found._jdf.queryExecution().executedPlan().toString()
        assert not any(x in plan for x in ("Broadcast", "NestedLoop", "CartesianProduct", "Join"))


def test_every_fiftieth_vector_asks(spark, data):
    from chapterforge import workloads

    for name in ("w4c_ivf_recall", "w4c_lsh_recall"):
        got = workloads.queries()[name](spark, data).first()
        assert got["exact"] == workloads.table(spark, data, "embeddings").filter("vec_id % 50 = 0").count() and got["recall"] >= 0.9


def test_losses_of_all_recipes_in_one_pass(spark):
    """Each recipe's plan, model and loss apart give the same; the counts that serve all are read from files, not from the examples."""
    rng = np.random.default_rng(7)
    kinds = [(1, "pairs"), (1, "plain text"), (2, "row to text"), (3, "table selection")]
    rows = [(f"x{i}", *kinds[i % 4], " ".join(rng.choice(list("abcdefg"), 9)), 4, 5) for i in range(120)] + [("none", 1, "pairs", "", 0, 0)]
    every = spark.createDataFrame(rows, "example_id string, chapter int, task string, text string, n_in int, n_out int")
    held = (F.col("task") == "pairs") & in_sample(F.col("example_id"), 0.3, 31)
    test = every.filter(held).select(F.col("example_id").alias("id"), "text", "n_in")
    times, want = {}, {}
    for recipe in language._USED:
        times[recipe] = curriculum.times_seen(*language._recipe_parts(recipe))
        plan = language.recipe_plan(every.filter(~held), recipe)
        shown = {r["example_id"]: r["count"] for r in plan.groupBy("example_id").count().collect()}
        assert shown == {r["example_id"]: r["n"] for r in every.filter(~held).select("example_id", times[recipe].alias("n")).collect() if r["n"]}
        model = lm.fit_bigrams(plan.select(F.col("example_id").alias("id"), "text"))
        for mask in ("all", "output"):
            want[recipe, mask] = tuple(lm.corpus_loss(test, model, mask).select("tokens", "mean_nll", "perplexity").first())
    found = lm.losses_by_weights(every, times, held)
    got = {(r["model"], r["mask"]): (r["tokens"], r["mean_nll"], r["perplexity"]) for r in found.collect()}
    assert got.keys() == want.keys() and all(got[x] == pytest.approx(want[x], abs=0.011) for x in want)
    assert "LocalTableScan" not in found._jdf.queryExecution().executedPlan().toString()


def reads(spark, data, name):
    from chapterforge import workloads

    plan = workloads.queries()[name](spark, data)._jdf.queryExecution().executedPlan().toString()
    return "FileScan parquet" in plan or "Scan parquet" in plan


@pytest.mark.parametrize("name", ["w12_examples", "w12_acceptance"])
def test_scenarios_read_customers(spark, data, name):
    assert reads(spark, data, name)


@pytest.mark.parametrize("name", ["w3_accuracy", "w3_context_failures", "w3_examples", "w3_format_errors", "w3_gold_tables", "w3_profile", "w6_examples", "w7_examples"])
def test_items_come_from_tables(spark, data, name):
    assert reads(spark, data, name)


def test_schedule_is_as_long_as_the_conversations(spark, data):
    from chapterforge import workloads
    from chapterforge.functions.text import count_tokens

    turns = workloads.table(spark, data, "conversations").select(count_tokens(F.col("text")).alias("n")).collect()
    got = [r["lr_millionths"] for r in workloads.queries()["w13_lr"](spark, data).orderBy("step").collect()]
    assert len(got) == -(-sum(r["n"] for r in turns) // language.STEP_TOKENS) + 1 and (got[0], got[-1]) == (1.0, 0.0)


def test_published_corpus_beside_the_one_made(spark, data):
    from chapterforge import workloads

    assert reads(spark, data, "w10_published_corpus")
    got = {(r["chapter"], r["task"], r["level"]): r for r in workloads.queries()["w10_published_corpus"](spark, data).collect()}
    made = {(r["chapter"], r["task"]): r for r in workloads.queries()["w10_overview"](spark, data).collect() if r["task"] != "all"}
    assert all(got[(*x, 0)]["made"] == r["examples"] and got[(*x, 0)]["made_tokens"] == r["tokens"] for x, r in made.items())
    assert got[0, "all", 3]["made"] == sum(r["examples"] for r in made.values()) and got[1, "pairs", 0]["examples"] == 8.8e6
