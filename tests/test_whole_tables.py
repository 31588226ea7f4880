"""Queries cover every row of their tables; recounted in plain Python, apart from the SQL beside them."""

import collections
import hashlib
import math
import re

import pytest
from pyspark.sql import functions as F

from chapterforge import workloads
from chapterforge.operators import filtering, lm, selection
from chapterforge.plans import curriculum

words = lambda s: re.findall(r"[^\W_]+", s.lower())
md5 = lambda s: hashlib.md5(s.encode()).hexdigest()


def rows(spark, data, name):
    return spark.read.parquet(f"{data}/{name}.parquet").collect()


def test_mcq_item_for_every_customer_and_event(spark, data):
    facts = [(f"Which segment has customer {r['c_custkey']}?", r["c_mktsegment"]) for r in rows(spark, data, "customer")]
    events = [(f"Which event type has event {r['event_id']}?", r["event_type"]) for r in rows(spark, data, "events")]
    got = {r["question"]: r for r in workloads.queries()["w1_mcq_items"](spark, data).collect()}
    assert len(facts) == 150 and len(events) == 1000
    for category, some in (("da", facts), ("ml", events)):
        values = {v for _, v in some}
        assert sum(r["category"] == category for r in got.values()) == len(some)
        for q, fact in some:
            wrong = sorted(values - {fact}, key=lambda v: (md5(f"{q}{v}|3"), v))[:3]
            placed = sorted([fact, *wrong], key=lambda v: (md5(f"{v}{q}|4"), v))
            assert [got[q][c] for c in "abcd"] == placed and got[q]["answer"] == "ABCD"[placed.index(fact)]
    counts = {(r["predictor"], r["category"]): r["n"] for r in workloads.queries()["w1_mcq_accuracy"](spark, data).collect()}
    assert counts["first_choice", "da"] == len(facts) and counts["hash_choice", "ml"] == len(events)


def test_cell_question_for_every_customer(spark, data):
    nations = {r["n_nationkey"]: r["n_name"] for r in rows(spark, data, "nation")}
    gold = {str(r["c_custkey"]): (f"customer|{nations[r['c_nationkey']]}|{r['c_mktsegment']}", r["c_name"]) for r in rows(spark, data, "customer")}
    cells = collections.defaultdict(list)
    for key, (slice_id, name) in sorted(gold.items(), key=lambda x: (md5(f"{x[0]}|0"), x[0])):
        cells[slice_id].append(name)
    pool = {r["id"]: words(" ".join([r["title"], *cells[r["id"]][:3]])) for r in workloads.queries()["w4_pool"](spark, data).collect()}
    df = collections.Counter(t for w in pool.values() for t in set(w))
    mean, top1, in_ten, mrr = sum(map(len, pool.values())) / len(pool), 0, 0, 0.0
    for slice_id, name in gold.values():
        scores = []
        for i, w in pool.items():
            both = set(words(f"in which table is {name}")) & set(w)
            if both:
                s = sum(math.log(1 + (len(pool) - df[t] + 0.5) / (df[t] + 0.5)) * w.count(t) * 2.2 / (w.count(t) + 1.2 * (0.25 + 0.75 * len(w) / mean)) for t in sorted(both))
                scores.append((-round(s, 6), i))
        best = [i for _, i in sorted(scores)[:10]]
        at = best.index(slice_id) + 1 if slice_id in best else 0
        top1, in_ten, mrr = top1 + (at == 1), in_ten + (at > 0), mrr + (1 / at if at else 0)
    got = next(r for r in workloads.queries()["w4_bm25_top1"](spark, data).collect() if r["style"] == "cell")
    n = len(gold)
    assert n == 150 and got["questions"] == n
    assert (got["top1"], got["in_ten"], got["mrr"]) == pytest.approx((top1 / n, in_ten / n, mrr / n), abs=1e-6)
    made = workloads.queries()["w4_examples"](spark, data).collect()
    assert {r["q_id"] for r in made if r["policy"] == "force"} == set(gold) and sum(r["policy"] == "filter" for r in made) == in_ten


def test_next_tokens_of_every_context_and_setting(spark, data):
    follow = collections.defaultdict(collections.Counter)
    for r in rows(spark, data, "conversations"):
        w = ["<s>", *words(r["text"] or "")]
        for a, b in zip(w, w[1:]):
            follow[a][b] += 1
    greedy = {r["ctx"]: r["token"] for r in workloads.queries()["w13_greedy"](spark, data).collect()}
    assert greedy == {c: min(n, key=lambda t: (-n[t], t)) for c, n in follow.items()}
    assert min(sum(n.values()) for n in follow.values()) < 20
    got = {(r["temperature"], r["top_p"], r["ctx"]): (r["kept"], r["top"]) for r in workloads.queries()["w13_nucleus"](spark, data).collect()}
    assert set(got) == {(t, p, c) for t in (0.0, 0.7, 1.0) for p in (0.95, 0.99, 1.0) for c in follow}
    for (t, top_p, c), (kept, top) in got.items():
        n = sorted(follow[c].values(), reverse=True)
        p = [x ** (1 / t) for x in n] if t else [1.0]
        before, want = 0.0, []
        for x in p:
            if top_p == 1 or round(before, 9) < top_p:
                want.append(x)
            before += x / sum(p)
        assert kept == len(want) and top == pytest.approx(want[0] / sum(want), abs=2e-6)


def test_grid_equals_single_settings(spark):
    p = spark.createDataFrame([("c", "x", 0.6), ("c", "y", 0.3), ("c", "z", 0.1), ("d", "x", 1.0)], "ctx string, token string, p double")
    for r in lm.nucleus_grid(p, (0.0, 0.7), (0.85, 1.0)).collect():
        cut = [x["p"] for x in lm.nucleus(lm.temper(p, r["temperature"]), r["top_p"]).filter(F.col("ctx") == r["ctx"]).collect()]
        assert (r["kept"], r["top"]) == (len(cut), pytest.approx(max(cut)))


def test_whole_nucleus_keeps_rare_tokens(spark):
    p = spark.createDataFrame([("c", "x", 1 - 1e-11), ("c", "y", 1e-11)], "ctx string, token string, p double")
    assert lm.nucleus(p, 1.0).count() == 2 and lm.nucleus_grid(p, (1.0,), (1.0,)).first()["kept"] == 2


def test_bayes_reads_whole_texts(spark):
    rated = spark.createDataFrame([("good " * 9, 5), ("bad " * 9, 1), ("good " * 4096 + "rare", 5)], "text string, score int")
    model = filtering.train_bayes(rated)
    assert model.sizes[5] == 9 + 4097 and model.terms.filter("term = 'rare' and n5 = 1").count() == 1
    even = filtering.train_bayes(rated.limit(2), classes=[1, 5])
    long = spark.createDataFrame([(1, "bad " * 4100 + "good " * 5000), (2, "good " * 4100 + "bad " * 5000), (3, "good")], "doc_id long, text string")
    for form in ({}, {"map_terms": 0}):
        assert {r["doc_id"]: r["predicted"] for r in filtering.bayes_scores(long, even, **form).collect()} == {1: 5, 2: 1, 3: 5}


def test_loss_of_every_recipe(spark, data):
    got = workloads.queries()["w9_recipe_loss"](spark, data).collect()
    assert {(r["recipe"], r["mask"]) for r in got} == {(x, m) for x in curriculum.RECIPES if x != "base" for m in ("all", "output")}
    assert len(got) == 12 and len({r["tokens"] for r in got if r["mask"] == "all"}) == 1 and all(r["mean_nll"] > 0 for r in got)


def test_sql_prompts_with_and_without_knowledge(spark):
    catalog = spark.createDataFrame([("d", "t", 1, "b", "int"), ("d", "t", 0, "a", "string")], "db string, table string, ordinal int, column string, type string")
    asked = spark.createDataFrame([("x", "d", "How many?", "many: 3 or more"), ("y", "d", "Which?", None)], "q_id string, db string, question string, hint string")
    for knowledge in (True, False):
        got = {r["q_id"]: r["prompt"].split("\n") for r in selection.sql_examples(asked, catalog, knowledge).collect()}
        assert got["x"] == ["t(a string, b int)", selection.SQL_INSTRUCTION, *["Knowledge: many: 3 or more"] * knowledge, "Question: How many?"]
        assert got["y"] == ["t(a string, b int)", selection.SQL_INSTRUCTION, "Question: Which?"]


def test_sql_prompts_and_profile_are_registered():
    assert {"w4_profile", "w6_examples", "w7_examples"} <= set(workloads.queries())
