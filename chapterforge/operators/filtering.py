"""Cascade filtering: rate a sample, train a cheap classifier on it, run that over everything."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import JUNK, chunks, head_tail, in_sample, tokens, truncate

CONTEXT = 4096


def rating_sample(docs: DataFrame, fraction: float = 0.001, key: str = "doc_id", seed: int = 7, method: str = "hash", strata: str | None = None) -> DataFrame:
    """hash: repeatable, by key; bernoulli: by chance; stratified: by chance, the same share of each stratum; files: whole
    input files, so that the rest is not read."""
    if method == "hash":
        return docs.filter(in_sample(F.col(key), fraction, seed))
    if method == "bernoulli":
        return docs.sample(fraction=fraction, seed=seed)
    if method == "stratified":
        shares = {r[0]: fraction for r in docs.select(strata).distinct().collect()}  # strata, not rows
        return docs.sampleBy(strata, shares, seed)
    if method == "files":
        files = sorted(docs.inputFiles())
        return docs.sparkSession.read.schema(docs.schema).parquet(*files[: max(1, round(len(files) * fraction))])
    raise ValueError(f"unknown method {method!r}")


def rubric(text: Column, lang: Column) -> Column:
    """1 and one more for each: 50 to 4,096 tokens; English; no junk marks; four fifths of lines distinct. 5 at most."""
    n, lines = F.size(tokens(text)), F.split(text, "\n")
    tests = [n.between(50, CONTEXT), lang == "en", ~text.rlike(JUNK), F.size(F.array_distinct(lines)) >= 0.8 * F.size(lines)]
    return sum((F.coalesce(t, F.lit(False)).cast("int") for t in tests), F.lit(1))


def rate_documents(docs: DataFrame, service=None) -> DataFrame:
    """doc_id, score, rater, rationale. Without a service the rubric rates; a service's replies hold "score n"."""
    if service is None:
        score = rubric(F.col("text"), F.col("lang"))
        return docs.select("doc_id", score.alias("score"), F.lit("rubric").alias("rater"), F.concat(F.lit("score "), score).alias("rationale"))
    asked = docs.select(F.col("doc_id").cast("string").alias("req_id"), F.lit("rate").alias("role"), F.col("text").alias("prompt"))
    found = service.complete(asked)
    score = F.regexp_extract("response", r"(?i)score\D{0,3}([1-5])", 1).cast("int")
    return found.select(F.col("req_id").cast("long").alias("doc_id"), score.alias("score"), F.lit("service").alias("rater"), F.col("response").alias("rationale")).filter("score is not null")


def ratings_from_labels(labels: DataFrame) -> DataFrame:
    """Quality and toxicity as a score: (1,0) 5, (1,1) 3, (0,0) 2, (0,1) 1."""
    q, t = F.col("quality"), F.col("toxic")
    return labels.select("doc_id", F.when((q == 1) & (t == 0), 5).when(q == 1, 3).when(t == 0, 2).otherwise(1).alias("score"))


def split_ratings(ratings: DataFrame, test: float = 0.2, seed: int = 11) -> DataFrame:
    return ratings.withColumn("split", F.when(in_sample(F.col("doc_id"), test, seed), "test").otherwise("train"))


def encode_context(docs: DataFrame, limit: int = CONTEXT, policy: str = "truncate") -> DataFrame:
    """doc_id, part, tokens: one part, or with ``chunks`` all stretches of the text."""
    words = docs.withColumn("tokens", tokens(F.col("text")))
    if policy == "truncate":
        return words.select("doc_id", F.lit(0).alias("part"), truncate(F.col("tokens"), limit).alias("tokens"))
    if policy == "head_tail":
        return words.select("doc_id", F.lit(0).alias("part"), head_tail(F.col("tokens"), limit).alias("tokens"))
    if policy == "chunks":
        return words.select("doc_id", F.posexplode(chunks(F.col("tokens"), limit)).alias("part", "tokens"))
    raise ValueError(f"unknown policy {policy!r}")


class BayesModel:
    """Multinomial naive Bayes as two tables: (class, rows, tokens) and (term, counts of each class)."""

    def __init__(self, classes: DataFrame, terms: DataFrame, names: list[int], vocabulary: int):
        self.classes, self.terms, self.names, self.vocabulary = classes, terms, names, vocabulary
        held = {r["score"]: r for r in classes.collect()}  # a row for each class
        self.rows = {c: held[c]["n"] if c in held else 0 for c in names}
        self.sizes = {c: held[c]["tokens"] if c in held else 0 for c in names}

    def prior(self, c: int) -> float:
        from math import log

        return log((self.rows[c] + 1) / (sum(self.rows.values()) + len(self.names)))


def train_bayes(rated: DataFrame, classes: list[int] | None = None, binarize_at: int | None = None) -> BayesModel:
    """rated: text and score; all words of a text count, however many. ``binarize_at``: two classes, 1 from that score on. One shuffle, by term, after partial sums."""
    names = [0, 1] if binarize_at else classes or [1, 2, 3, 4, 5]
    score = (F.col("score") >= binarize_at).cast("int") if binarize_at else F.col("score")
    words = rated.select(score.alias("score"), tokens(F.col("text")).alias("tokens"))
    sums = words.groupBy("score").agg(F.count("*").alias("n"), F.sum(F.size("tokens")).cast("long").alias("tokens"))
    terms = words.select("score", F.explode("tokens").alias("term")).groupBy("term").agg(*[F.count_if(F.col("score") == c).alias(f"n{c}") for c in names])
    return BayesModel(sums, terms, names, terms.count())


def bayes_scores(docs: DataFrame, model: BayesModel, map_terms: int = 500_000) -> DataFrame:
    """doc_id, predicted, margin (best log score less the next). Terms the model lacks are passed over; ties go to the lower class.

    While the model has ``map_terms`` terms at most it goes out to the tasks and scoring is one pass without a shuffle; beyond, term
    counts of each document are joined with the terms' table. Both give the same scores.
    """
    words = docs.select("doc_id", tokens(F.col("text")).alias("tokens"))
    scored = _scores_by_map(words, model) if model.vocabulary <= map_terms else _scores_by_join(docs, words, model)
    ranked = F.array_sort(F.array(*[F.struct((-F.col(f"s{c}")).alias("s"), F.lit(c).alias("c")) for c in model.names]))
    return scored.withColumn("r", ranked).select("doc_id", F.col("r")[0]["c"].alias("predicted"), F.round(F.col("r")[1]["s"] - F.col("r")[0]["s"], 6).alias("margin"))


def _scores_by_map(words: DataFrame, model: BayesModel) -> DataFrame:
    import numpy as np
    import pandas as pd

    held, names = model.terms.collect(), [f"s{c}" for c in model.names]  # ``map_terms`` rows at most
    counts = np.array([[r[f"n{c}"] for c in model.names] for r in held], dtype=float).reshape(len(held), len(model.names))
    weights = np.log((counts + 1) / (np.array([float(model.sizes[c]) for c in model.names]) + model.vocabulary)) if held else counts
    place = words.sparkSession.sparkContext.broadcast(({r["term"]: i for i, r in enumerate(held)}, weights, np.array([model.prior(c) for c in model.names])))

    def score(batches):
        at, w, prior = place.value
        for pdf in batches:
            out = np.tile(prior, (len(pdf), 1))
            for i, run in enumerate(pdf["tokens"]):
                known = [at[t] for t in run if t in at]
                if known:
                    out[i] += w[known].sum(axis=0)
            done = pd.DataFrame(np.round(out, 6), columns=names)
            done.insert(0, "doc_id", pdf["doc_id"].to_numpy())
            yield done

    return words.mapInPandas(score, ", ".join(["doc_id long", *[f"{n} double" for n in names]]))


def _scores_by_join(docs: DataFrame, words: DataFrame, model: BayesModel) -> DataFrame:
    counts = words.select("doc_id", F.explode("tokens").alias("term")).groupBy("doc_id", "term").agg(F.count("*").alias("tf"))
    part = [F.sum(F.col("tf") * F.log((F.col(f"n{c}") + 1) / F.lit(float(model.sizes[c] + model.vocabulary)))).alias(f"s{c}") for c in model.names]
    sums = counts.join(model.terms, "term").groupBy("doc_id").agg(*part)
    every = docs.select("doc_id").join(sums, "doc_id", "left")
    return every.select("doc_id", *[F.round(F.coalesce(f"s{c}", F.lit(0.0)) + model.prior(c), 6).alias(f"s{c}") for c in model.names])


def train_logistic(rated: DataFrame, features: int = 1 << 12, limit: int = CONTEXT, rounds: int = 20):
    """The hashed-feature variant: multinomial logistic regression, a pipeline model."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF

    words = rated.select("score", truncate(tokens(F.col("text")), limit).alias("tokens"))
    return Pipeline(stages=[HashingTF(inputCol="tokens", outputCol="features", numFeatures=features), LogisticRegression(labelCol="score", maxIter=rounds, family="multinomial")]).fit(words)


def classifier_report(predictions: DataFrame, high: int = 4) -> DataFrame:
    """metric, value: accuracy over all classes, recall of high ratings, and how many rows."""
    ok, top = (F.col("predicted") == F.col("score")).cast("double"), F.col("score") >= high
    sums = predictions.agg(
        F.count("*").cast("double").alias("n"), F.avg(ok).alias("accuracy"), F.avg(F.when(top, (F.col("predicted") >= high).cast("double"))).alias("recall_high")
    )
    return sums.select(F.expr("stack(3, 'n', n, 'accuracy', accuracy, 'recall_high', recall_high) as (metric, value)"))


def confusion(predictions: DataFrame) -> DataFrame:
    return predictions.groupBy("score", "predicted").agg(F.count("*").alias("n"))


def class_quality(predictions: DataFrame) -> DataFrame:
    """Precision, recall and F1 of each class, from the confusion matrix."""
    c = confusion(predictions)
    hit = F.sum(F.when(F.col("score") == F.col("predicted"), F.col("n")).otherwise(0))
    rows = c.groupBy(F.col("score").alias("class")).agg(F.sum("n").alias("actual"), hit.alias("hit"))
    said = c.groupBy(F.col("predicted").alias("class")).agg(F.sum("n").alias("said"))
    out = rows.join(said, "class", "full").fillna(0, ["actual", "hit", "said"])
    return out.select("class", F.try_divide("hit", "said").alias("class_precision"), F.try_divide("hit", "actual").alias("class_recall"), F.try_divide(2 * F.col("hit"), F.col("said") + F.col("actual")).alias("f1"))


def apply_filter(docs: DataFrame, model: BayesModel, keep_at: int = 4) -> DataFrame:
    kept = bayes_scores(docs, model).filter(F.col("predicted") >= keep_at).select("doc_id")
    return docs.join(kept, "doc_id", "left_semi")


def retention(flagged: DataFrame) -> DataFrame:
    """flagged: text and kept. One pass: documents and tokens before and after, and the share of each."""
    n = F.size(tokens(F.col("text"))).cast("long")
    sums = flagged.select("kept", n.alias("n")).agg(
        F.count("*").alias("docs_before"), F.count_if("kept").alias("docs_after"), F.sum("n").alias("tokens_before"), F.sum(F.when(F.col("kept"), F.col("n")).otherwise(0)).alias("tokens_after")
    )
    return sums.withColumn("docs_share", F.col("docs_after") / F.col("docs_before")).withColumn("tokens_share", F.col("tokens_after") / F.col("tokens_before"))


def topic_rubric(text: Column, topic_words: list[str], one: float, two: float) -> Column:
    """Quality and topic points: no junk marks; distinct lines; and the share of words from a topic list past two cuts."""
    words, lines = tokens(text), F.split(text, "\n")
    share = F.size(F.filter(words, lambda w: w.isin(topic_words))) / F.greatest(F.size(words), F.lit(1))
    tests = [~text.rlike(JUNK), F.size(F.array_distinct(lines)) >= 0.8 * F.size(lines), share >= one, share >= two]
    return sum((F.coalesce(t, F.lit(False)).cast("int") for t in tests), F.lit(1))


