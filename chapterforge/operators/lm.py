"""A count language model that stands for the network: losses, masks, tempered and cut distributions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.text import tokens
from ..session import settled

BEGIN = "<s>"


def pairs_of(texts: DataFrame) -> DataFrame:
    """id, pos (from 1), ctx, tok: each token with the one before it; a start symbol is before the first."""
    words = F.concat(F.array(F.lit(BEGIN)), tokens(F.col("text")))
    both = F.transform(F.sequence(F.lit(1), F.size("w") - 1), lambda i: F.struct(i.alias("pos"), F.get("w", i - 1).alias("ctx"), F.get("w", i).alias("tok")))
    return texts.select("id", words.alias("w")).filter(F.size("w") > 1).select("id", F.inline(both))


class BigramModel:
    """counts (ctx, tok, n), contexts (ctx, total) and the vocabulary's size; add-k smoothing."""

    def __init__(self, counts: DataFrame, k: float):
        self.k, self.counts = k, counts
        self.contexts = counts.groupBy("ctx").agg(F.sum("n").alias("total"))
        self.vocabulary = counts.select("tok").distinct().count()


def fit_bigrams(texts: DataFrame, k: float = 0.1, min_count: int = 1) -> BigramModel:
    return BigramModel(pairs_of(texts).groupBy("ctx", "tok").agg(F.count("*").alias("n")).filter(F.col("n") >= min_count), k)


def token_losses(texts: DataFrame, model: BigramModel) -> DataFrame:
    """id, pos, nll: joins on (ctx, tok); unseen pairs have the smoothed mass alone."""
    held = pairs_of(texts).join(model.counts, ["ctx", "tok"], "left").join(model.contexts, "ctx", "left")
    p = (F.coalesce("n", F.lit(0)) + model.k) / (F.coalesce("total", F.lit(0)) + model.k * model.vocabulary)
    return held.select("id", "pos", (-F.log(p)).alias("nll"))


def sequence_nll(texts: DataFrame, model: BigramModel) -> DataFrame:
    return token_losses(texts, model).groupBy("id").agg(F.count("*").alias("n"), F.round(F.sum("nll"), 4).alias("nll"))


def grams_of(texts: DataFrame, order: int) -> DataFrame:
    """id, pos, tok, ctx1 ... ctx{order - 1}: each token with what stands before it, by number of tokens; start symbols lead."""
    words = F.concat(F.array_repeat(F.lit(BEGIN), order - 1), tokens(F.col("text")))
    one = lambda i: F.struct(
        i.alias("pos"), F.get("w", i + (order - 2)).alias("tok"), *[F.array_join(F.slice("w", i + (order - 1) - m, m), " ").alias(f"ctx{m}") for m in range(1, order)]
    )
    return texts.select("id", words.alias("w")).filter(F.size("w") > order - 1).select("id", F.inline(F.transform(F.sequence(F.lit(1), F.size("w") - (order - 1)), one)))


class BackoffModel:
    """Counts of each order. A token's probability is add-k smoothed after the longest context that training saw, so each context's
    probabilities sum to 1 over the vocabulary; without any seen context it is the smoothed share of the token alone."""

    def __init__(self, texts: DataFrame, order: int, k: float = 0.1):
        grams = grams_of(texts, order)
        self.order, self.k = order, k
        self.counts = {m: grams.groupBy(f"ctx{m}", "tok").agg(F.count("*").alias(f"n{m}")) for m in range(1, order)}
        self.contexts = {m: self.counts[m].groupBy(f"ctx{m}").agg(F.sum(f"n{m}").alias(f"total{m}")) for m in range(1, order)}
        self.tokens = grams.groupBy("tok").agg(F.count("*").alias("n0"))
        held = self.tokens.agg(F.count("*").alias("v"), F.sum("n0").alias("n")).first()
        self.vocabulary, self.total = held["v"], held["n"] or 0

    def token_losses(self, texts: DataFrame) -> DataFrame:
        """id, pos, context (how many tokens of context were used), nll. Equal grams are joined once, by their number."""
        keys = [f"ctx{m}" for m in range(1, self.order)]
        grams = grams_of(texts, self.order)
        kinds = grams.select("tok", *keys).distinct().join(self.tokens, "tok", "left")
        for m in range(1, self.order):
            kinds = kinds.join(self.counts[m], [f"ctx{m}", "tok"], "left").join(self.contexts[m], f"ctx{m}", "left")
        smooth = lambda n, total: (F.coalesce(n, F.lit(0)) + self.k) / (total + self.k * self.vocabulary)
        p, used = smooth(F.col("n0"), F.lit(self.total)), F.lit(0)
        for m in range(1, self.order):
            seen = F.col(f"total{m}").isNotNull()
            p, used = F.when(seen, smooth(F.col(f"n{m}"), F.col(f"total{m}"))).otherwise(p), F.when(seen, F.lit(m)).otherwise(used)
        scored = kinds.select("tok", *keys, used.alias("context"), (-F.log(p)).alias("nll"))
        return grams.join(scored, ["tok", *keys]).select("id", "pos", "context", "nll")


def loss_mask(n_in, n_out, mode: str = "output"):
    """A weight for each token: all of them, or the output's alone."""
    weight = (lambda i: F.lit(1)) if mode == "all" else (lambda i: F.when(i > n_in, 1).otherwise(0))
    return F.when(n_in + n_out > 0, F.transform(F.sequence(F.lit(1), (n_in + n_out).cast("int")), weight)).otherwise(F.array().cast("array<int>"))


def corpus_loss(examples: DataFrame, model: BigramModel, mask: str = "output") -> DataFrame:
    """examples: id, text (input then output), n_in. tokens, mean_nll and perplexity over weighted tokens."""
    losses = token_losses(examples, model).join(examples.select("id", "n_in"), "id")
    w = F.lit(1) if mask == "all" else (F.col("pos") > F.col("n_in")).cast("int")
    sums = losses.agg(F.sum(w).alias("tokens"), (F.sum(w * F.col("nll")) / F.sum(w)).alias("mean_nll"))
    return sums.select(F.lit(mask).alias("mask"), "tokens", F.round("mean_nll", 4).alias("mean_nll"), F.round(F.exp("mean_nll"), 2).alias("perplexity"))


def losses_by_weights(examples: DataFrame, weights: dict[str, Column], held: Column, k: float = 0.1) -> DataFrame:
    """``corpus_loss`` of the examples that are ``held`` under several models at once, for both masks: mask, tokens, mean_nll,
    perplexity, model. weights: how often the model of that name sees an example that is not held. examples: text, n_in.

    A loss depends on its pair of tokens alone, so one pass counts each pair: how often it is asked, and how often each model sees it.
    """
    at = range(len(weights))
    known = F.struct(held.alias("held"), F.col("n_in"), *[F.when(~held, w).otherwise(0).alias(f"w{i}") for i, w in enumerate(weights.values())])
    asked, output = F.col("id.held"), F.col("pos") > F.col("id.n_in")
    counts = pairs_of(examples.select(known.alias("id"), "text")).groupBy("ctx", "tok").agg(F.count_if(asked).alias("all"), F.count_if(asked & output).alias("output"), *[F.sum(f"id.w{i}").alias(f"n{i}") for i in at])
    counts = settled(counts, "pair-counts")
    contexts = counts.groupBy("ctx").agg(*[F.sum(f"n{i}").alias(f"total{i}") for i in at])
    sizes = counts.groupBy("tok").agg(*[F.max(F.col(f"n{i}") > 0).alias(f"v{i}") for i in at]).agg(*[F.count_if(f"v{i}") for i in at]).first()
    nll = lambda i: -F.log((F.col(f"n{i}") + k) / (F.col(f"total{i}") + k * sizes[i]))
    masks = ("all", "output")
    sums = counts.filter(F.col("all") > 0).join(contexts, "ctx").agg(*[F.sum(m).alias(m) for m in masks], *[F.sum(F.col(m) * nll(i)).alias(f"{m}{i}") for m in masks for i in at])
    each = F.inline(F.array(*[F.struct(F.lit(m).alias("mask"), F.col(m).alias("tokens"), F.try_divide(f"{m}{i}", m).alias("mean"), F.lit(name).alias("model")) for i, name in enumerate(weights) for m in masks]))
    return sums.select(each).select("mask", "tokens", F.round("mean", 4).alias("mean_nll"), F.round(F.exp("mean"), 2).alias("perplexity"), "model")


def temper(next_tokens: DataFrame, t: float) -> DataFrame:
    """next_tokens: ctx, token, p. Probabilities at a temperature; at 0 the most likely (first of equals) has all."""
    ctx = W.partitionBy("ctx")
    if t == 0:
        first = F.row_number().over(ctx.orderBy(F.desc("p"), "token"))
        return next_tokens.withColumn("p", F.when(first == 1, 1.0).otherwise(0.0))
    hot = next_tokens.withColumn("p", F.pow("p", 1.0 / t))
    return hot.withColumn("p", F.col("p") / F.sum("p").over(ctx))


def nucleus(next_tokens: DataFrame, top_p: float) -> DataFrame:
    """The smallest set of most likely tokens that reaches ``top_p``, normalized anew."""
    before = F.coalesce(F.sum("p").over(W.partitionBy("ctx").orderBy(F.desc("p"), "token").rowsBetween(W.unboundedPreceding, -1)), F.lit(0.0))
    kept = next_tokens.withColumn("before", before).filter((F.lit(top_p >= 1) | (F.round("before", 9) < top_p)) & (F.col("p") > 0)).drop("before")
    return kept.withColumn("p", F.col("p") / F.sum("p").over(W.partitionBy("ctx")))


def nucleus_grid(next_tokens: DataFrame, temperatures: tuple[float, ...], top_ps: tuple[float, ...]) -> DataFrame:
    """temperature, top_p, ctx, kept (how many tokens stay), top (the first one's probability among them): ``temper`` then
    ``nucleus`` for every setting, over one sort of each context, as a temperature leaves the order as it is."""
    ctx = W.partitionBy("ctx")
    order = ctx.orderBy(F.desc("p"), "token")
    place = next_tokens.withColumn("place", F.row_number().over(order))
    hot = lambda t: F.pow("p", 1.0 / t) if t else F.when(F.col("place") == 1, 1.0).otherwise(0.0)
    at = [(i, t) for i, t in enumerate(temperatures)]
    one = place.select("*", *[hot(t).alias(f"h{i}") for i, t in at]).select("*", *[(F.col(f"h{i}") / F.sum(f"h{i}").over(ctx)).alias(f"p{i}") for i, _ in at])
    before = lambda i: F.coalesce(F.sum(f"p{i}").over(order.rowsBetween(W.unboundedPreceding, -1)), F.lit(0.0))
    cut = one.select("ctx", *[f"p{i}" for i, _ in at], *[before(i).alias(f"b{i}") for i, _ in at])
    sums, settings = [], []
    for i, t in at:
        for j, top_p in enumerate(top_ps):
            p = F.when((F.lit(top_p >= 1) | (F.round(f"b{i}", 9) < top_p)) & (F.col(f"p{i}") > 0), F.col(f"p{i}"))
            sums += [F.count(p).alias(f"n{i}_{j}"), (F.max(p) / F.sum(p)).alias(f"t{i}_{j}")]
            settings.append(F.struct(F.lit(float(t)).alias("temperature"), F.lit(float(top_p)).alias("top_p"), F.col(f"n{i}_{j}").alias("kept"), F.col(f"t{i}_{j}").alias("top")))
    return cut.groupBy("ctx").agg(*sums).select("ctx", F.inline(F.array(*settings)))


# fixed values: temperature and top_p by family
DECODE_DEFAULTS = {"mcq": (0.0, 0.99), "ts": (0.7, 0.95), "t2s": (1.0, 1.0)}


def decode_grid(scores: DataFrame) -> DataFrame:
    """scores: family, temperature, top_p, score. The best setting of each family; ties to the lower values."""
    order = F.struct("score", -F.col("temperature"), -F.col("top_p"))
    return scores.groupBy("family").agg(F.max_by(F.struct("temperature", "top_p", "score"), order).alias("b")).select("family", "b.*")
