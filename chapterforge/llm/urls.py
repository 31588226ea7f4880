"""URL filter: explicit rules first, then a ratio of two character language models.

Models: for accepted and for rejected URLs, Markov models over characters whose order varies with what was seen: each
context's counts are mixed with those of the context one character shorter by Witten-Bell weights, down to a uniform
alphabet. They learn from the URLs that rules decide: the first ``per_rule`` distinct ones of each rule by a hash. What rules
name is taken out of every text that is learnt or scored (the labels of rules' hosts, and rules' paths where a path begins with
one), so that the models learn what URLs look like and not the rules again. A URL's score is the difference of its
log likelihoods, for each character.

The cut is calibrated over rules: each rule's URLs are scored by models that learnt from the other rules alone, and the cut is the one
with the largest mean of both classes' shares judged right. ``rule_report`` gives what a rule's URLs would be judged without it.

Defined results: a null url, or one without ``://``, has an empty host and path and no rule; it is scored as the
empty text, at 0 with no cut taken off, so it is allowed. A rule needs no URLs of its own; without samples of both classes every score
is 0. Scores at the cut are allowed. Texts of any length are scored whole. Repeated rows and ids are judged each; an empty table
gives no rows; other columns are not read, whatever their names.
"""

from __future__ import annotations

import math
from collections import Counter, defaultdict
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow_batches, frugal

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: (action, rule); a rule is a host, then a path from its first slash on
RULES = (("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/"))


def host_of(url: Column) -> Column:
    at = F.instr(url, "://")
    return F.when(at > 0, F.translate(F.regexp_extract(F.substring(url, at + 3, F.length(url)), r"\A[^/?#]*", 0), UPPER, LOWER)).otherwise("")


def path_of(url: Column) -> Column:
    at = F.instr(url, "://")
    return F.when(at > 0, F.regexp_extract(F.substring(url, at + 3, F.length(url)), r"\A[^/?#]*([^?#]*)", 1)).otherwise("")


def rule_for(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """The longest rule that fits and its action, null if none does."""
    rule, action = F.lit(None).cast("string"), F.lit(None).cast("string")
    for kind, text in sorted(rules, key=lambda r: len(r[1])):
        name, slash, rest = text.partition("/")
        fits = ((host == name) | host.endswith("." + name)) & path.startswith(slash + rest)
        rule, action = F.when(fits, text).otherwise(rule), F.when(fits, kind).otherwise(action)
    return rule, action


class CharModel:
    """Witten-Bell mixture over contexts of 0 to ``order`` characters."""

    def __init__(self, order: int = 5, alphabet: int = 256):
        self.order, self.alphabet = order, alphabet
        self.seen: dict[str, Counter] = defaultdict(Counter)
        self.sums: Counter = Counter()

    def learn(self, texts: list[str]) -> CharModel:
        for t in texts:
            t = "\x02" + t + "\x03"
            for i in range(1, len(t)):
                for n in range(min(self.order, i) + 1):
                    self.seen[t[i - n : i]][t[i]] += 1
        self.sums = Counter({c: sum(s.values()) for c, s in self.seen.items()})
        return self

    def log_p(self, context: str, char: str) -> float:
        p = 1 / self.alphabet
        for n in range(len(context) + 1):
            held = self.seen.get(context[len(context) - n :])
            if held is None:
                break
            kinds, total = len(held), self.sums[context[len(context) - n :]]
            p = (held.get(char, 0) + kinds * p) / (total + kinds)
        return math.log(p)


def neutral(host: Column, path: Column, rules=RULES) -> Column:
    """Host and path without what rules name: labels of their hosts, and the longest of their paths that this one begins with."""
    names = sorted({label for _, text in rules for label in text.partition("/")[0].split(".")})
    labels = F.filter(F.split(host, r"\."), lambda x: ~x.isin(names))
    rest = path
    for begin in sorted({"/" + text.partition("/")[2] for _, text in rules}, key=len):
        if begin != "/":
            rest = F.when(path.startswith(begin), F.concat(F.lit("/"), F.substring(path, F.lit(len(begin) + 1), F.length(path)))).otherwise(rest)
    return F.concat(F.array_join(labels, "."), rest)


def best_cut(accepted: list[float], rejected: list[float]) -> float:
    """The cut with the largest mean of the shares of accepted scores at or above it and of rejected ones below it."""
    both = sorted([(s, 1) for s in accepted] + [(s, 0) for s in rejected])
    best, cut, right1, right0 = -1.0, 0.0, len(accepted), 0
    for i, (s, y) in enumerate(both):  # cut at s: what is below it is rejected
        if (i == 0 or both[i - 1][0] < s) and right1 / len(accepted) + right0 / len(rejected) > best:
            best, cut = right1 / len(accepted) + right0 / len(rejected), (s + both[i - 1][0]) / 2 if i else s
        right1, right0 = right1 - y, right0 + (1 - y)
    return cut


class UrlRatio:
    """accepted and rejected models; ``score`` is per character, above 0 for what looks accepted."""

    def __init__(self, accepted: list[str], rejected: list[str], order: int = 5):
        self.order, self.cut = order, 0.0
        self.models = [CharModel(order).learn(x) for x in (accepted, rejected)] if accepted and rejected else []
        self.memo: dict[str, float] = {}

    def score(self, text: str) -> float:
        if not text or not self.models:
            return 0.0
        t, total, memo = "\x02" + text + "\x03", 0.0, self.memo
        for i in range(1, len(t)):
            key = t[max(0, i - self.order) : i + 1]
            d = memo.get(key)
            if d is None:
                if len(memo) > 150_000:
                    memo.clear()
                d = memo[key] = self.models[0].log_p(key[:-1], key[-1]) - self.models[1].log_p(key[:-1], key[-1])
            total += d
        return total / (len(t) - 1)


def fit(samples: dict[tuple[str, str], list[str]], order: int = 5) -> tuple[UrlRatio, list[tuple[str, str, int, float]]]:
    """samples: (rule, action) -> texts. The models of all rules with their calibrated cut, and (rule, action, texts, share judged
    right by the models of the other rules at that cut)."""

    def of(action: str, without: str | None = None) -> list[str]:
        return [t for (rule, a), texts in samples.items() if a == action and rule != without for t in texts]

    whole, scores = UrlRatio(of("allow"), of("block"), order), {}
    for (rule, action), texts in samples.items():
        others = UrlRatio(of("allow", rule), of("block", rule), order)
        if others.models:
            scores[rule, action] = [others.score(t) for t in texts]
    sides = [[s for (_, a), x in scores.items() if a == side for s in x] for side in ("allow", "block")]
    if all(sides):
        whole.cut = best_cut(*sides)
    right = lambda s, a: (s >= whole.cut) == (a == "allow")
    return whole, [(r, a, len(x), sum(right(s, a) for s in x) / max(len(x), 1)) for (r, a), x in scores.items()]


def _judged(pages: DataFrame, rules, id_column: str, url_column: str) -> DataFrame:
    """page_id, host, path, text (what models see), rule, action."""
    url = F.coalesce(F.col(url_column).cast("string"), F.lit(""))
    parts = pages.select(F.col(id_column).cast("long").alias("page_id"), host_of(url).alias("host"), path_of(url).alias("path"))
    rule, action = rule_for(F.col("host"), F.col("path"), rules)
    return parts.select("page_id", "host", "path", neutral(F.col("host"), F.col("path"), rules).alias("text"), rule.alias("rule"), action.alias("action"))


def _learnt(judged: DataFrame, rules, per_rule: int, order: int):
    known = judged.filter("action is not null and text <> ''").select("rule", "action", "text").distinct()
    place = F.row_number().over(Window.partitionBy("rule").orderBy(F.xxhash64("text"), "text"))
    first = known.withColumn("place", place).filter(F.col("place") <= per_rule).orderBy("rule", "place").collect()  # per_rule rows a rule
    samples: dict = {(rule, action): [] for action, rule in rules}
    for r in first:
        samples[r["rule"], r["action"]].append(r["text"])
    return fit(samples, order)


def rule_report(pages: DataFrame, rules=RULES, per_rule: int = 4000, order: int = 5, id_column: str = "page_id", url_column: str = "url") -> DataFrame:
    """rule, action, urls, right: the share of a rule's sampled URLs that models of the other rules judge as it does. 0.5 is chance."""
    _, found = _learnt(_judged(pages, rules, id_column, url_column), rules, per_rule, order)
    return pages.sparkSession.createDataFrame(found, "rule string, action string, urls long, right double")


def judge_urls(pages: DataFrame, rules=RULES, per_rule: int = 4000, order: int = 5, id_column: str = "page_id", url_column: str = "url") -> DataFrame:
    """page_id, host, path, rule, verdict, ratio (the models' score less the cut) of each row of ``pages``."""
    spark = pages.sparkSession
    arrow_batches(spark, 4096)
    judged = _judged(pages, rules, id_column, url_column)
    held = spark.sparkContext.broadcast(_learnt(judged, rules, per_rule, order)[0])

    def score(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ratio = held.value
        for pdf in batches:
            pdf["ratio"] = [ratio.score(t) - ratio.cut if t else 0.0 for t in pdf.pop("text")]
            pdf["page_id"] = pdf["page_id"].astype("Int64")
            yield pdf

    scored = judged.mapInPandas(frugal(score), "page_id long, host string, path string, rule string, action string, ratio double")
    return scored.select("page_id", "host", "path", "rule", F.coalesce("action", F.when(F.col("ratio") >= 0, "allow").otherwise("block")).alias("verdict"), "ratio")
