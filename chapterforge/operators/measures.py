"""Measures over predictions and over score sheets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def strict_mean(c: str) -> Column:
    """The mean, or null if any value is: a set that a model can't read has no average."""
    return F.when(F.count_if(F.col(c).isNull()) == 0, F.avg(c))


def leaderboard(scores: DataFrame, overall: str = "macro_of_tasks", by: str = "model") -> DataFrame:
    """Family means and an overall: the mean of family means, or with mean_of_sets that of all sets."""
    wide = scores.groupBy(by).pivot("family", ["mcq", "ts", "t2s"]).agg(strict_mean("score"))
    if overall == "macro_of_tasks":
        return wide.withColumn("overall", (F.col("mcq") + F.col("ts") + F.col("t2s")) / 3)
    return wide.join(scores.groupBy(by).agg(strict_mean("score").alias("overall")), by)


def columns_of(scores: DataFrame) -> DataFrame:
    """Sets, family averages and the overall in long form: model, item, score."""
    sheet = leaderboard(scores)
    averages = sheet.select("model", F.expr("stack(4, 'mcq avg', mcq, 'ts avg', ts, 't2s avg', t2s, 'overall', overall) as (item, score)"))
    return scores.select("model", F.col("dataset").alias("item"), "score").unionByName(averages)


def improvement(scores: DataFrame, subject: str, references: list[str], mode: str = "relative") -> DataFrame:
    """How far the subject is above each reference: per cent of unrounded scores, or points."""
    long = columns_of(scores)
    own = long.filter(F.col("model") == subject).select("item", F.col("score").alias("own"))
    others = long.filter(F.col("model").isin(references)).select("item", F.col("model").alias("reference"), "score")
    gain = (F.col("own") / F.col("score") - 1) * 100 if mode == "relative" else F.col("own") - F.col("score")
    return others.join(own, "item").select("item", "reference", gain.alias("gain"))


def winners(scores: DataFrame) -> DataFrame:
    """Each set's ranks, best first; models without a score have none."""
    place = F.rank().over(W.partitionBy("dataset").orderBy(F.desc("score")))
    return scores.filter("score is not null").withColumn("place", place).select("dataset", "model", "score", "place")


def by_exposure(scores: DataFrame) -> DataFrame:
    return scores.groupBy("model", "exposure").agg(strict_mean("score").alias("score"), F.count("*").alias("sets"))


CONTRASTS = (
    ("instructed over plain", "ch1_instructed", "ch1_plain"),
    ("instructed over plain, with 2 and 3", "ch1_instructed_2_3", "ch1_plain_2_3"),
    ("with chapter 1", "ch1_instructed_2_3", "ch2_3"),
    ("with chapter 2", "ch1_instructed_2_3", "ch1_instructed_3"),
    ("with chapter 3", "ch1_instructed_3", "ch1_instructed"),
    ("final over base", "ch1_instructed_2_3", "base"),
)


def ablation_contrasts(ablation: DataFrame, contrasts=CONTRASTS) -> DataFrame:
    """Points between pairs of recipes, for each set."""
    named = ablation.sparkSession.createDataFrame(list(contrasts), "contrast string, a string, b string")
    one = ablation.select(F.col("recipe").alias("a"), "dataset", F.col("score").alias("score_a"))
    two = ablation.select(F.col("recipe").alias("b"), "dataset", F.col("score").alias("score_b"))
    return F.broadcast(named).join(one, "a").join(two, ["b", "dataset"]).select("contrast", "dataset", (F.col("score_a") - F.col("score_b")).alias("points"))


# ---- answers ----------------------------------------------------------------------------------------------


def choice_accuracy(answers: DataFrame, by: list[str]) -> DataFrame:
    """answers: letter (null if none was found) and answer; unparsed ones are wrong."""
    return answers.groupBy(*by).agg(F.count("*").alias("n"), F.avg(F.coalesce((F.col("letter") == F.col("answer")).cast("double"), F.lit(0.0))).alias("accuracy"))


def with_gold(predictions: DataFrame, gold: DataFrame) -> DataFrame:
    """Every gold question of every predictor; one without a prediction has an empty set."""
    who = predictions.select("predictor").distinct()
    every = gold.crossJoin(F.broadcast(who))  # a few predictors
    return every.join(predictions, ["q_id", "predictor"], "left").withColumn("predicted", F.coalesce("predicted", F.array().cast("array<string>")))


def _set(c: str) -> Column:
    return F.array_sort(F.array_distinct(F.col(c)))


def set_accuracy(pairs: DataFrame, by: list[str]) -> DataFrame:
    """pairs: predicted and gold arrays. 1 only for equal sets; with precision, recall, F1, Jaccard, over and under choice."""
    both = F.size(F.array_intersect("predicted", "gold"))
    p, g = F.size(_set("predicted")), F.size(_set("gold"))
    return pairs.groupBy(*by).agg(
        F.count("*").alias("n"),
        F.avg((_set("predicted") == _set("gold")).cast("double")).alias("accuracy"),
        F.avg(F.when(p > 0, both / p).otherwise(0.0)).alias("set_precision"),
        F.avg(F.when(g > 0, both / g).otherwise(1.0)).alias("set_recall"),
        F.avg(F.when(p + g > 0, 2 * both / (p + g)).otherwise(1.0)).alias("f1"),
        F.avg(F.when(p + g > 0, both / (p + g - both)).otherwise(1.0)).alias("jaccard"),
        F.avg((p > both).cast("double")).alias("over"),
        F.avg((g > both).cast("double")).alias("under"),
    )


def format_errors(parsed: DataFrame, by: list[str]) -> DataFrame:
    """Shares of answers that only a fallback found, or nothing did."""
    return parsed.groupBy(*by).agg(
        F.count("*").alias("n"), F.avg((F.col("route") == "fallback").cast("double")).alias("fallback"), F.avg((F.col("route") == "none").cast("double")).alias("missing")
    )


def long_context_failures(parsed: DataFrame, by: list[str]) -> DataFrame:
    """Share of answers that name no candidate at all. parsed: predicted, candidates."""
    none = F.size(F.array_intersect("predicted", "candidates")) == 0
    return parsed.groupBy(*by).agg(F.count("*").alias("n"), F.avg(none.cast("double")).alias("failed"))


def context_exceeded(prompts: DataFrame, limit: int, by: list[str]) -> DataFrame:
    """prompts: n_in, correct. A set with an input over the limit has no score."""
    return prompts.groupBy(*by).agg(
        F.max("n_in").alias("longest"), F.when(F.max("n_in") <= limit, F.avg(F.col("correct").cast("double"))).alias("score")
    )


def input_profile(examples: DataFrame, by: list[str]) -> DataFrame:
    """examples: n_in, n_candidates, n_gold. Means, maxima and exact percentiles (between two values: in proportion)."""
    return examples.groupBy(*by).agg(
        F.count("*").alias("questions"), F.avg("n_in").alias("avg_tokens"), F.max("n_in").alias("max_tokens"), F.percentile("n_in", 0.5).alias("p50_tokens"),
        F.percentile("n_in", 0.95).alias("p95_tokens"), F.avg("n_candidates").alias("avg_candidates"),
        F.avg("n_gold").alias("avg_gold"), F.count_if(F.col("n_gold") > 1).alias("several_gold"),
    )
