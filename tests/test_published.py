"""Printed averages and improvements come out of the printed cells."""

import pytest
from pyspark.sql import functions as F

from chapterforge.operators import measures
from chapterforge.plans import curriculum, published


def test_family_and_overall_averages(spark):
    rows = {r["model"]: r for r in measures.leaderboard(published.scores(spark)).collect()}
    for model, want in {"post12b": (76.3, 75.3, 57.6, 69.7), "base12b": (71.0, 33.1, 46.1, 50.1), "closed_flagship": (81.0, 67.2, 53.1, 67.1)}.items():
        assert [rows[model][c] for c in ("mcq", "ts", "t2s", "overall")] == pytest.approx(want, abs=0.1)
    assert rows["closed_old"]["ts"] is None and rows["closed_old"]["overall"] is None  # a set beyond the context has no average
    assert rows["openmoe47b"]["ts"] == pytest.approx(12.7, abs=0.1)  # a failure on long inputs counts as 0


def test_mean_of_sets_differs(spark):
    rows = {r["model"]: r["overall"] for r in measures.leaderboard(published.scores(spark), "mean_of_sets").collect()}
    assert rows["post12b"] == pytest.approx(71.3, abs=0.1)


def test_improvements(spark):
    gains = {(r["item"], r["reference"]): r["gain"] for r in measures.improvement(published.scores(spark), "post12b", ["base12b", "closed_flagship"]).collect()}
    for item, want in {"mcq_da": 12.2, "mcq_db": 8.5, "mcq_ml": 2.2, "mcq avg": 7.6, "ts_schema": 89.8, "ts_retrieved": 213.7, "ts_page": 93.7, "ts avg": 127.5, "t2s_easy": 19.8, "t2s_hard": 37.4, "t2s avg": 24.9, "overall": 39.3}.items():
        assert gains[item, "base12b"] == pytest.approx(want, abs=0.1)
    for item, want in {"mcq_da": -3.7, "mcq_db": -6.4, "mcq_ml": -7.1, "mcq avg": -5.8, "ts_schema": 9.1, "ts_retrieved": 29.3, "ts_page": -4.9, "ts avg": 12.1, "t2s_easy": 8.9, "t2s_hard": 7.8, "t2s avg": 8.6, "overall": 4.0}.items():
        assert gains[item, "closed_flagship"] == pytest.approx(want, abs=0.1)
    points = {(r["item"], r["reference"]): r["gain"] for r in measures.improvement(published.scores(spark), "post12b", ["closed_mini", "closed_flagship"], "points").collect()}
    assert -points["mcq avg", "closed_mini"] == pytest.approx(1.5, abs=0.1) and -points["mcq avg", "closed_flagship"] == pytest.approx(4.7, abs=0.1)


def test_totals_leave_plain_text_out(spark):
    held = published.corpus(spark).filter("in_total").agg(F.sum("examples"), F.sum("tokens")).first()
    assert held[0] == pytest.approx(9.0e6, rel=0.01) and held[1] == pytest.approx(1.0e9, rel=0.01)


def test_ablation_is_not_monotone(spark):
    c = {(r["contrast"], r["dataset"]): r["points"] for r in measures.ablation_contrasts(published.ablation(spark)).collect()}
    assert c["with chapter 1", "ts_schema"] < 0 < c["with chapter 1", "mcq_db"]


def test_parameter_count():
    assert curriculum.param_count() == pytest.approx(12.28e9, rel=0.005)
