"""Staged training plans: which example is seen when, learning rates, sizes."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import in_sample, order_hash

#: recipe -> (chapter 1 variant or none, other chapters)
RECIPES = {
    "base": (None, ()), "ch1_plain": ("plain", ()), "ch1_instructed": ("pairs", ()), "ch1_instructed_3": ("pairs", (3,)),
    "ch2_3": (None, (2, 3)), "ch1_plain_2_3": ("plain", (2, 3)), "ch1_instructed_2_3": ("pairs", (2, 3)),
}


def curriculum(ch1: DataFrame | None, later: DataFrame | None, epochs=(1, 2), mix: float = 0.10, mix_basis: str = "source_rows", seed: int = 17, resample: bool = False) -> DataFrame:
    """Uniform examples with stage, epoch and an order key. Stage 1: chapter 1 once. Stage 2: the others ``epochs[1]`` times with a
    uniform share of chapter 1 mixed in, of its own rows or (share_of_mix) of the mix; one draw for all epochs, or one for each.
    Written in order by ``ordered``."""
    parts = []
    if ch1 is not None:
        parts.append(ch1.select("*", F.lit(1).alias("stage"), F.explode(F.sequence(F.lit(1), F.lit(epochs[0]))).alias("epoch")))
    if later is not None:
        parts.append(later.select("*", F.lit(2).alias("stage"), F.explode(F.sequence(F.lit(1), F.lit(epochs[1]))).alias("epoch")))
        if ch1 is not None:
            share = mix if mix_basis == "source_rows" else min(1.0, later.count() * mix / (1 - mix) / max(ch1.count(), 1))
            for epoch in range(1, epochs[1] + 1):
                drawn = ch1.filter(in_sample(F.col("example_id"), share, seed + epoch * resample))
                parts.append(drawn.select("*", F.lit(2).alias("stage"), F.lit(epoch).alias("epoch")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.withColumn("order_key", F.concat_ws("-", "stage", F.lpad(F.col("epoch").cast("string"), 4, "0"), order_hash(F.col("example_id"), seed)))


def times_seen(ch1: Column | None, later: Column | None, epochs=(1, 2), mix: float = 0.10, seed: int = 17) -> Column:
    """How often ``curriculum`` shows an example, with one draw of its source rows; ch1 and later: what the example must be, as conditions."""
    once = lambda which: F.lit(0) if which is None else which.cast("int")
    out = epochs[0] * once(ch1) + epochs[1] * once(later)
    if ch1 is not None and later is not None:
        out = out + epochs[1] * once(ch1 & in_sample(F.col("example_id"), mix, seed))
    return out


def ordered(plan: DataFrame, partitions: int) -> DataFrame:
    """Range shards in training order, without a global sort in one task."""
    return plan.repartitionByRange(partitions, "order_key", "example_id").sortWithinPartitions("order_key", "example_id")


def plan_sizes(plan: DataFrame) -> DataFrame:
    return plan.groupBy("stage", "epoch", "chapter").agg(F.count("*").alias("n"), F.sum(F.col("n_in") + F.col("n_out")).alias("tokens"))


def exposure(plan: DataFrame) -> DataFrame:
    """How often an example of each chapter is seen, by stage: at most and at least."""
    each = plan.groupBy("stage", "chapter", "example_id").agg(F.count("*").alias("k"))
    return each.groupBy("stage", "chapter").agg(F.min("k").alias("least"), F.max("k").alias("most"))


def final_checkpoint(steps: DataFrame) -> DataFrame:
    """The last point of the schedule. steps: step, and what is known of it."""
    return steps.agg(F.max_by(F.struct(*steps.columns), "step").alias("s")).select("s.*")


def cosine_lr(steps: DataFrame, total: int, hi: float = 1e-6, lo: float = 0.0) -> DataFrame:
    """step from 0 to total: from hi to lo along half a cosine."""
    return steps.withColumn("lr", lo + (hi - lo) * (1 + F.cos(F.pi() * F.col("step") / total)) / 2)


@dataclass(frozen=True)
class Architecture:
    # fixed values of the subject model
    layers: int = 40
    width: int = 5120
    hidden: int = 14436
    head: int = 128
    heads: int = 32
    groups: int = 8
    vocabulary: int = 128_000
    tied: bool = False


def param_count(a: Architecture = Architecture()) -> int:
    """Projections of attention and of a gated block, two norms a layer, the last norm, both ends of the vocabulary."""
    attention = a.width * a.head * (2 * a.heads + 2 * a.groups)
    return a.layers * (attention + 3 * a.width * a.hidden + 2 * a.width) + a.width + a.vocabulary * a.width * (1 if a.tied else 2)


class AdamW:
    """Decoupled weight decay; the defaults are the training's own settings."""

    def __init__(self, lr: float, betas=(0.9, 0.98), eps: float = 1e-8, decay: float = 0.01):
        self.lr, self.betas, self.eps, self.decay, self.t, self.m, self.v = lr, betas, eps, decay, 0, 0.0, 0.0

    def step(self, weights, gradient, lr: float | None = None):
        self.t += 1
        b1, b2 = self.betas
        self.m, self.v = b1 * self.m + (1 - b1) * gradient, b2 * self.v + (1 - b2) * gradient**2
        rate = self.lr if lr is None else lr
        up = (self.m / (1 - b1**self.t)) / ((self.v / (1 - b2**self.t)) ** 0.5 + self.eps)
        return weights - rate * (up + self.decay * weights)


def train_softmax(rated: DataFrame, features: int = 512, classes: int = 5, steps: int = 30, optimizer: AdamW | None = None):
    """Softmax over hashed term shares. Each step sums partial gradients in the tasks; the driver holds features x classes weights.
    rated: score (1 to classes), tokens."""
    import numpy as np
    import pandas as pd

    optimizer = optimizer or AdamW(lr=0.05)
    cells = F.transform("tokens", lambda t: F.pmod(F.xxhash64(t), F.lit(features)).cast("int"))
    data = rated.select("score", cells.alias("cells")).persist()
    n, w = data.count(), np.zeros((features, classes))
    for _ in range(steps):

        def partial(batches, w=w):
            g, loss = np.zeros_like(w), 0.0
            for pdf in batches:
                x = np.zeros((len(pdf), features))
                for i, c in enumerate(pdf["cells"]):
                    np.add.at(x[i], np.asarray(c, dtype=int), 1 / max(len(c), 1) ** 0.5)
                z = x @ w
                p = np.exp(z - z.max(axis=1, keepdims=True))
                p /= p.sum(axis=1, keepdims=True)
                y = pdf["score"].to_numpy() - 1
                loss -= np.log(np.maximum(p[np.arange(len(y)), y], 1e-12)).sum()
                p[np.arange(len(y)), y] -= 1
                g += x.T @ p
            yield pd.DataFrame({"cell": np.arange(g.size), "g": g.ravel()})

        sums = data.mapInPandas(partial, "cell int, g double").groupBy("cell").agg(F.sum("g").alias("g")).collect()  # a row a weight
        g = np.zeros(w.size)
        for r in sums:
            g[r["cell"]] = r["g"]
        w = optimizer.step(w, g.reshape(w.shape) / max(n, 1))
    data.unpersist()
    return w


def mix_sources(sources: dict[str, DataFrame], quotas: dict[str, int], key: str = "example_id", seed: int = 23) -> DataFrame:
    """The first rows of each source by hash, up to its quota."""
    out = None
    for name in sorted(sources):
        one = sources[name].orderBy(order_hash(F.col(key), seed), key).limit(quotas[name]).withColumn("source", F.lit(name))
        out = one if out is None else out.unionByName(one, allowMissingColumns=True)
    return out


def leak_audit(corpus: DataFrame, items: DataFrame, mode: str = "contains", n: int = 13) -> DataFrame:
    """item_id, doc_id of items that occur in the corpus: as a whole string, or by any run of n words. Items go out to all tasks while
    they are few (an evaluation set); n-grams meet by an equi-join."""
    if mode == "contains":
        wanted = items.select("item_id", F.col("text").alias("needle")).filter("length(needle) > 0")
        return corpus.select("doc_id", "text").join(F.broadcast(wanted) if wanted.count() <= 100_000 else wanted, F.contains("text", "needle")).select("item_id", "doc_id")
    from ..functions.text import tokens

    def grams(df, key):
        w = df.select(key, tokens(F.col("text")).alias("w")).filter(F.size("w") >= n)
        return w.select(key, F.explode(F.transform(F.sequence(F.lit(1), F.size("w") - (n - 1)), lambda i: F.array_join(F.slice("w", i, n), " "))).alias("gram")).distinct()

    return grams(corpus, "doc_id").join(grams(items, "item_id"), "gram").select("item_id", "doc_id").distinct()


def uniform(df: DataFrame, chapter: int, task: str, example_id, instruction, data, query, output) -> DataFrame:
    """Any chapter's rows in the one example format, token counts included."""
    from ..functions.text import count_tokens

    cols = {"example_id": example_id, "instruction": instruction, "data": data, "query": query, "output": output}
    out = df.select(F.lit(chapter).alias("chapter"), F.lit(task).alias("task"), *[c.cast("string").alias(k) for k, c in cols.items()])
    return out.withColumn("n_in", count_tokens(F.concat_ws(" ", "instruction", "data", "query"))).withColumn("n_out", count_tokens(F.col("output")))


def corpus_overview(examples: DataFrame) -> DataFrame:
    """Examples and tokens by chapter and task with subtotals; plain text is out of the totals."""
    return examples.filter("task <> 'plain text'").rollup("chapter", "task").agg(F.count("*").alias("examples"), F.sum(F.col("n_in") + F.col("n_out")).alias("tokens"))


def steps_frame(spark: SparkSession, total: int) -> DataFrame:
    return spark.range(total + 1).withColumnRenamed("id", "step")
