"""Runnable predictors that exercise every path, and planted errors of known kinds."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import order_hash, tokens


def _out(examples: DataFrame, name: str, output: Column) -> DataFrame:
    return examples.select("q_id", F.lit(name).alias("predictor"), output.alias("output"))


def first_choice(items: DataFrame) -> DataFrame:
    return _out(items, "first_choice", F.lit("Answer: (A)"))


def hash_choice(items: DataFrame, seed: int = 13) -> DataFrame:
    """Chance level, the same each time."""
    place = F.conv(F.substring(order_hash(F.col("q_id"), seed), 1, 4), 16, 10).cast("int") % 4
    return _out(items, "hash_choice", F.concat(F.lit("Answer: ("), F.substring(F.lit("ABCD"), place + 1, F.lit(1)), F.lit(")")))


def lexical_choice(items: DataFrame) -> DataFrame:
    """The choice that shares most words with the question; the first of equals. items: question, a, b, c, d."""
    shared = lambda c: F.size(F.array_intersect(tokens(F.col("question")), tokens(F.col(c))))
    best = F.array_sort(F.array(*[F.struct((-shared(c)).alias("n"), F.lit(c.upper()).alias("c")) for c in "abcd"]))[0]["c"]
    return _out(items, "lexical_choice", F.concat(F.lit("Answer: ("), best, F.lit(")")))


def lm_choice(items: DataFrame, model) -> DataFrame:
    """The choice whose words cost least after the question, by a count model's loss for each token."""
    from .lm import token_losses

    parts = items.select("q_id", "question", F.explode(F.array(*[F.struct(F.lit(c.upper()).alias("c"), F.col(c).alias("t")) for c in "abcd"])).alias("x"))
    texts = parts.select(F.concat_ws("|", "q_id", "x.c").alias("id"), F.concat_ws(" ", "question", "x.t").alias("text"), F.size(tokens(F.col("question"))).alias("n_in"))
    cost = token_losses(texts, model).join(texts.select("id", "n_in"), "id").filter(F.col("pos") > F.col("n_in")).groupBy("id").agg(F.avg("nll").alias("cost"))
    best = cost.select(F.substring_index("id", "|", -1).alias("c"), F.expr("left(id, length(id) - 2)").alias("q_id"), "cost").groupBy("q_id").agg(F.min_by("c", F.struct("cost", "c")).alias("c"))
    return _out(items.select("q_id").join(best, "q_id", "left"), "lm_choice", F.concat(F.lit("Answer: ("), F.col("c"), F.lit(")")))


def gold_echo(examples: DataFrame) -> DataFrame:
    return _out(examples, "gold_echo", F.concat(F.lit("<tables>"), F.array_join("gold", "\n"), F.lit("</tables>")))


def all_candidates(examples: DataFrame) -> DataFrame:
    return _out(examples, "all_candidates", F.concat(F.lit("<Tables>"), F.array_join("candidates", ", "), F.lit("</Tables>")))


def corrupted(examples: DataFrame, kind: str) -> DataFrame:
    """A known error in a table list: lines (no tag), comma, extra, missing, nonsense, empty."""
    gold = F.col("gold")
    other = F.element_at(F.array_except("candidates", "gold"), 1)
    text = {
        "lines": F.array_join(gold, "\n"),
        "comma": F.concat(F.lit("<TABLES>"), F.array_join(gold, " , "), F.lit("</TABLES>")),
        "extra": F.concat(F.lit("<tables>"), F.concat_ws("\n", F.array_join(gold, "\n"), other), F.lit("</tables>")),
        "missing": F.concat(F.lit("<tables>"), F.array_join(F.slice(gold, 2, 99), "\n"), F.lit("</tables>")),
        "nonsense": F.lit("I would look at the data first."),
        "empty": F.lit(""),
    }[kind]
    return _out(examples, kind, text)


def context_capped(outputs: DataFrame, prompts: DataFrame, limit: int = 16385) -> DataFrame:
    """Blank outputs where the prompt (n_in) is over the limit."""
    held = outputs.join(prompts.select("q_id", "n_in"), "q_id", "left")
    return held.select("q_id", "predictor", F.when(F.col("n_in") <= limit, F.col("output")).alias("output"))


def nearest_question_sql(questions: DataFrame, train: DataFrame) -> DataFrame:
    """The SQL of the most similar training question by BM25. questions: q_id, text; train: id, text, sql."""
    from .retrieval import bm25_rank

    best = bm25_rank(questions, train.select("id", "text"), 1)
    found = questions.select("q_id").join(best, "q_id", "left").join(train.select("id", "sql"), "id", "left")
    return _out(found, "nearest_question", F.concat(F.lit("<sql>"), F.col("sql"), F.lit("</sql>")))
