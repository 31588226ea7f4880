"""Toxicity by weak supervision.

1. Lexicon: words and word beginnings that mark toxic texts, from a bounded sample of labelled training rows
   (``per_class`` rows of each class, the first by a hash of their id; ``entries`` features at most).
2. Voters: shards of the lexicon, and patterns. Their votes on *every* training-fold document are counted by pattern.
3. Label model: EM over these counts, started and anchored by the labelled sample, estimates each voter's accuracy and, by a forest of
   class-conditional dependencies, which voters are correlated; it gives P(toxic) of each pattern of votes.
4. A linear classifier over lexicon entries scores every document. Its targets are the label model's posteriors, of labelled rows
   too: no row's own label is a target.

Inputs of a score are the text's words alone. Defined results: a null or empty text gets the score of a text without
any lexicon entry; a score of exactly 0.5 is predicted toxic; rows that repeat an id are scored each, and one of them (that of the
first votes in order) stands for the id in training; labels that repeat an id count as toxic if one of them is; without labelled rows of
both classes every score is the share of toxic labels, or 0; an empty table gives no rows; columns other than id and text are
not read, whatever their names.
"""

from __future__ import annotations

import string
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_batches, fold, frugal, rows_of, written

MARKS = string.punctuation + "…«»“”„’‘¿¡"
SHARDS, PREFIXES, LEVELS, EARLY = 9, (4, 5, 6), 3, 20
#: after the lexicon shards: at least two words with an entry; one in 100 words; entries of two shards; one among the first words;
#: one exclamation mark in 20 words; two in a row; no entry at all (votes clean)
PATTERNS = ("several", "dense", "roots", "early", "shouting", "repeated", "none")
VOTERS = SHARDS + len(PATTERNS)
#: weight of labelled documents against that of all others in the label model
ANCHOR = 3.0


def features_of(word: str) -> tuple[str, ...]:
    """The word itself and its beginnings, told apart by their first sign."""
    w = word.strip(MARKS)
    return ("=" + w, *("^" + w[:n] for n in PREFIXES if len(w) > n)) if w else ()


def levels(f: str, times: int) -> list[str]:
    """An entry for each number of words, up to LEVELS, that carry the feature."""
    return [f"{f}#{k}" for k in range(1, min(times, LEVELS) + 1)]


def shard_of(entry: str) -> int:
    """Entries of one root share a voter, so that they can't outvote others."""
    return zlib.crc32(entry[1:5].encode()) % SHARDS


class Spotter:
    """Lexicon entries of a text and the number of words that carry one; remembers words, ``most`` at a time."""

    def __init__(self, lexicon: list[str], most: int = 150_000):
        self.at, self.most, self.memo = {f: i for i, f in enumerate(lexicon)}, most, {}
        self.roots = {f.rpartition("#")[0] for f in lexicon}
        self.shards = [shard_of(f) for f in lexicon]

    def __call__(self, text: str) -> tuple[list[int], int]:
        words, memo, roots, held, hits = text.lower().split(), self.memo, self.roots, Counter(), 0
        for w, n in Counter(words).items():
            found = memo.get(w)
            if found is None:
                if len(memo) >= self.most:
                    memo.clear()
                found = memo[w] = tuple(f for f in features_of(w) if f in roots)
            if found:
                hits += n
                for f in found:
                    held[f] += n
        entries = sorted(self.at[e] for f, n in held.items() for e in levels(f, n) if e in self.at)
        bits, n = 0, max(len(words), 1)
        for e in entries:
            bits |= 1 << self.shards[e]
        votes = (hits >= 2, hits * 100 >= n, bits.bit_count() >= 2, hits > 0 and any(memo.get(w) for w in words[:EARLY]), text.count("!") * 20 > n, "!!" in text, not entries)
        for k, vote in enumerate(votes):
            bits |= vote << (SHARDS + k)
        return entries, bits


# ---- label model ------------------------------------------------------------------------------------------


class LabelModel:
    """Two classes; each voter votes or abstains; given the class, voters depend on at most one other (a forest)."""

    def __init__(self, prior: float):
        self.prior, self.parent, self.cpt = prior, np.full(VOTERS, -1), None

    def fit(self, patterns: np.ndarray, counts: np.ndarray, known: np.ndarray, rounds: int = 40, least: float = 0.01, anchor: float = ANCHOR) -> LabelModel:
        """patterns: votes as 0/1 rows; counts: how many unlabelled documents voted so; known: labelled ones, a row
        for each class, weighted to the prior. Labelled documents keep their class and together weigh ``anchor`` times as much as
        all others, so that the classes keep their meaning. Independent voters first, then the forest."""
        self.known = known * (anchor * counts.sum() / max(known.sum(), 1e-12)) if counts.sum() else known
        self.cpt = np.full((2, VOTERS, 2), 0.5)  # [class, voter, the parent's vote]
        self._update(patterns, np.zeros(len(counts)), counts * 0)
        self._em(patterns, counts, rounds)
        self._forest(patterns, counts, least)
        self._em(patterns, counts, rounds)
        return self

    def _update(self, v: np.ndarray, post: np.ndarray, counts: np.ndarray) -> None:
        above = np.where(self.parent >= 0, v[:, np.maximum(self.parent, 0)], 0)
        mass = np.stack([counts * (1 - post), counts * post]) + self.known
        for y in (0, 1):
            for u in (0, 1):
                held = mass[y][:, None] * (above == u)
                self.cpt[y, :, u] = ((held * v).sum(axis=0) + 0.5) / (held.sum(axis=0) + 1)
        self.prior = float(np.clip(mass[1].sum() / max(mass.sum(), 1e-12), 1e-4, 1 - 1e-4))

    def _log_joint(self, v: np.ndarray) -> np.ndarray:
        out = np.empty((2, len(v)))
        above = np.where(self.parent >= 0, v[:, np.maximum(self.parent, 0)], 0)
        for y in (0, 1):
            p = self.cpt[y, np.arange(VOTERS), above]
            out[y] = np.log(self.prior if y else 1 - self.prior) + np.log(np.where(v == 1, p, 1 - p)).sum(axis=1)
        return out

    def posterior(self, v: np.ndarray) -> np.ndarray:
        a, b = self._log_joint(v)
        return 1 / (1 + np.exp(np.clip(a - b, -500, 500)))

    def _em(self, v: np.ndarray, counts: np.ndarray, rounds: int) -> None:
        for _ in range(rounds):
            self._update(v, self.posterior(v), counts)

    def _forest(self, v: np.ndarray, counts: np.ndarray, least: float) -> None:
        """Maximum spanning forest over what a pair of voters tells of each other given the class, in nats."""
        post, told = self.posterior(v), np.zeros((VOTERS, VOTERS))
        for share, w in ((1 - self.prior, counts * (1 - post) + self.known[0]), (self.prior, counts * post + self.known[1])):
            w = w / max(w.sum(), 1e-12)
            for a in (0, 1):
                for b in (0, 1):
                    both = np.einsum("n,ni,nj->ij", w, (v == a) * 1.0, (v == b) * 1.0)
                    alone = np.outer(w @ (v == a), w @ (v == b))
                    told += share * np.where(both > 1e-12, both * np.log(np.maximum(both, 1e-12) / np.maximum(alone, 1e-12)), 0)
        np.fill_diagonal(told, 0)
        self.told, seen = told, set()
        for root in range(VOTERS):
            if root in seen:
                continue
            seen.add(root)
            reach = [root]
            while True:
                links = [(told[i, j], i, j) for i in reach for j in range(VOTERS) if j not in seen and told[i, j] > least]
                if not links:
                    break
                _, i, j = max(links)
                self.parent[j] = i
                seen.add(j)
                reach.append(j)
        # a voter's vote given its parent's starts as what it is given the class alone
        self.cpt = np.repeat(self.cpt[:, :, :1], 2, axis=2)

    def accuracies(self, v: np.ndarray, counts: np.ndarray) -> np.ndarray:
        """P(class a voter votes for | it votes)."""
        post = self.posterior(v)
        agree = np.where(np.arange(VOTERS) == VOTERS - 1, ((1 - post) * counts) @ v, (post * counts) @ v)
        return agree / np.maximum(counts @ v, 1e-12)


def linear_fit(x: np.ndarray, target: np.ndarray, weight: np.ndarray, ridge: float = 1.0, rounds: int = 25) -> np.ndarray:
    """Logistic regression on soft labels by Newton's method; the last entry is the constant."""
    x = np.hstack([x, np.ones((len(x), 1), dtype=x.dtype)])
    beta, penalty = np.zeros(x.shape[1]), np.full(x.shape[1], ridge)
    penalty[-1] = 1e-6
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        slope = x.T @ (weight * (p - target)) + penalty * beta
        bend = (x * (weight * np.maximum(p * (1 - p), 1e-6))[:, None]).T @ x + np.diag(penalty)
        step = np.linalg.solve(bend, slope)
        beta -= np.clip(step, -4, 4)
        if np.abs(step).max() < 1e-6:
            break
    return beta


# ---- on tables --------------------------------------------------------------------------------------------


def labelled_sample(labels: DataFrame, per_class: int) -> DataFrame:
    """doc_id and toxic of training-fold rows: the first ``per_class`` of each class by a hash of the id."""
    train = (
        labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic"))
        .filter("doc_id is not null and toxic is not null")
        .groupBy("doc_id")
        .agg(F.max("toxic").alias("toxic"))
        .filter(fold() != 0)
    )
    first = [train.filter(F.col("toxic") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class) for y in (0, 1)]
    return first[0].unionByName(first[1])


def induce_lexicon(texts: DataFrame, entries: int, least: int = 8) -> tuple[list[str], int, int]:
    """texts: (text, toxic) of the bounded sample. The features with the largest z of their log odds, and rows by class."""

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: Counter = Counter()
        for pdf in batches:
            for text, toxic in zip(pdf["text"], pdf["toxic"]):
                held["", int(toxic)] += 1
                own: Counter = Counter()
                for w, n in Counter(text.lower().split()).items():
                    for f in features_of(w):
                        own[f] += n
                for f, n in own.items():
                    for e in levels(f, n):
                        held[e, int(toxic)] += 1
            if len(held) > 500_000:
                yield pd.DataFrame([(f, y, n) for (f, y), n in held.items()], columns=["f", "y", "n"])
                held.clear()
        if held:
            yield pd.DataFrame([(f, y, n) for (f, y), n in held.items()], columns=["f", "y", "n"])

    sums = (
        texts.dropDuplicates(["text", "toxic"])
        .mapInPandas(frugal(count), "f string, y int, n long")
        .groupBy("f")
        .agg(F.sum(F.expr("if(y = 1, n, 0)")).alias("a"), F.sum(F.expr("if(y = 1, 0, n)")).alias("b"))
    )
    sums = written(sums.filter((F.col("a") >= least) | (F.col("f") == "")), "feature-counts")
    total = sums.filter("f = ''").first()
    n1, n0 = (total["a"], total["b"]) if total else (0, 0)
    if not n1 or not n0:
        return [], n1, n0
    a, b = F.col("a"), F.col("b")
    odds = F.log((a + 0.5) / (n1 - a + 0.5)) - F.log((b + 0.5) / (n0 - b + 0.5))
    z = odds / F.sqrt(1 / (a + 0.5) + 1 / (b + 0.5))
    top = sums.filter("f <> ''").withColumn("odds", odds).withColumn("z", z).filter("odds > 2 and z > 3").orderBy(F.desc("z"), "f").limit(entries)
    return [r["f"] for r in top.collect()], n1, n0


def score_toxicity(docs: DataFrame, labels: DataFrame, per_class: int = 6000, entries: int = 384, text_column: str = "text") -> DataFrame:
    """doc_id, held_out, score, predicted, and the label model's posterior (weak_label) of each row of ``docs``."""
    spark = docs.sparkSession
    arrow_batches(spark)
    rows = rows_of(docs, text_column=text_column)
    sample = written(labelled_sample(labels, per_class), "toxicity-sample")
    marked = written(rows.join(F.broadcast(sample), "doc_id"), "toxicity-texts")  # the sample has 2 x per_class rows at most
    lexicon, n1, n0 = induce_lexicon(marked.select("text", "toxic"), entries)
    every = labels.filter("toxic is not null").filter(fold() != 0).agg(F.avg(F.col("toxic").cast("double"))).first()[0]
    prior = float(every) if every is not None else 0.0

    def spot(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        find = Spotter(lexicon)
        for pdf in batches:
            found = [find(t) for t in pdf["text"]]
            yield pd.DataFrame({"doc_id": pdf["doc_id"].astype("Int64"), "entries": [e for e, _ in found], "pattern": [v for _, v in found]})

    spotted = written(rows.mapInPandas(frugal(spot), "doc_id long, entries array<int>, pattern int"), "toxicity-votes")
    held = spotted.select("doc_id", (fold() == 0).alias("held_out"), "entries", "pattern")
    if not lexicon:
        return held.select("doc_id", "held_out", F.lit(prior).alias("score"), F.lit(int(prior >= 0.5)).alias("predicted"), F.lit(prior).alias("weak_label"))

    # one row an id, so 2 x per_class rows at most
    labelled = spotted.join(F.broadcast(sample), "doc_id").groupBy("doc_id").agg(F.min(F.struct("pattern", "entries", "toxic")).alias("x")).select("x.*").toPandas()
    free = held.filter("not held_out").join(F.broadcast(sample.select("doc_id")), "doc_id", "left_anti")
    cast = {r["pattern"]: r["count"] for r in free.groupBy("pattern").count().collect()}  # 2^VOTERS rows at most, that is 65,536
    seen = np.array(sorted(set(cast) | set(labelled["pattern"])), dtype=np.int64)
    share = labelled["toxic"].mean()
    weigh = lambda y: np.where(y == 1, prior / max(share, 1e-9), (1 - prior) / max(1 - share, 1e-9))
    known = np.zeros((2, len(seen)))
    for p, y in zip(labelled["pattern"], labelled["toxic"]):
        known[y, np.searchsorted(seen, p)] += weigh(y)
    bits = lambda p: (np.asarray(p, dtype=np.int64)[:, None] >> np.arange(VOTERS)) & 1
    model = LabelModel(prior).fit(bits(seen), np.array([cast.get(p, 0) for p in seen], dtype=float), known)

    # the labelled rows and as many others, the first by a hash; targets of both are posteriors of their votes
    more = free.orderBy(F.xxhash64("doc_id"), "doc_id").limit(2 * per_class).select("entries", "pattern").toPandas()
    x = np.zeros((len(labelled) + len(more), len(lexicon)), dtype=np.float32)
    for i, e in enumerate([*labelled["entries"], *more["entries"]]):
        x[i, list(e)] = 1
    target = model.posterior(bits([*labelled["pattern"], *more["pattern"]]))
    beta = linear_fit(x, target, np.concatenate([weigh(labelled["toxic"].to_numpy()), np.ones(len(more))]))

    def score(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            logit = np.array([beta[-1] + sum(beta[i] for i in e) for e in pdf["entries"]], dtype=float)
            p = 1 / (1 + np.exp(-np.clip(logit, -500, 500)))
            weak = model.posterior(bits(pdf["pattern"].to_numpy())) if len(pdf) else p
            yield pd.DataFrame({"doc_id": pdf["doc_id"].astype("Int64"), "held_out": pdf["held_out"], "score": p, "predicted": (p >= 0.5).astype("int32"), "weak_label": weak})

    return held.mapInPandas(frugal(score), "doc_id long, held_out boolean, score double, predicted int, weak_label double")
