"""Near duplicates of whole texts by BagMinHash signatures, bands and exact multiset overlap.

A text is the multiset of its five-word shingles (words: runs of letters and digits, lower-cased; a shorter text is one
shingle of all its words). Texts with equal words are one node. A node's signature has ``SIZE`` components, unbiased
for weighted Jaccard similarity: each shingle's weight axis is cut into dyadic intervals [0,1), [1,2), [2,4), ...; each
interval has its own Poisson process, seeded by shingle and interval, whose points arrive in order of time at a
random component and weight; points above the shingle's count are passed over, and a process ends once its time is
past all components' minima. A component is the time of its first point. The law is that of one process over the whole weight axis that is
split at its points; here the levels are independent processes from the start, which needs no parent's points to draw a child's.

Nodes that agree on a band of ``ROWS`` components are compared. Buckets of up to ``SMALL`` nodes compare all pairs. Larger
ones first compare their smallest node with the others, which makes a group of near copies one class in linear work. Those
whose members then lie in more than one class are joined where they share nodes, and dealt in chunks of ``CHUNK`` nodes: a task has two
chunks, with their multisets, and compares all pairs of different classes, so no link that could join two classes is lost. Pairs
that the whole signature puts more than five standard deviations below the threshold are dropped; the rest are decided by
exact multiset overlap.

Defined results: null texts are empty, and empty texts are one class; repeated rows (or ids) are of one class if their
texts are; a class is named by its smallest doc_id (null only if it has no other); an empty table gives no rows; other
columns are not read.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_batches, frugal, rows_of, small, written

WORDS, THRESHOLD = 5, 0.8
BANDS, ROWS = 24, 5
SIZE = BANDS * ROWS
SMALL, CHUNK = 32, 512

_WORD = re.compile(r"[^\W_]+")
_ODD = np.uint64(0x9E3779B97F4A7C15)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that scatters them (the public splitmix64 finalizer)."""
    x = x + _ODD
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class WordHashes(dict):
    """Word -> 64-bit hash, remembered for ``most`` words."""

    most = 150_000

    def __missing__(self, word: str) -> int:
        if len(self) >= self.most:
            self.clear()
        h = self[word] = int.from_bytes(hashlib.blake2b(word.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "little")
        return h


def grams_of(texts: list[str], hashes: WordHashes, n: int = WORDS) -> tuple[np.ndarray, np.ndarray, list[bytes]]:
    """(text's number, gram) for all texts, one after the other, and the hash of each text's words."""
    runs, names = [], []
    for t in texts:
        run = np.fromiter(map(hashes.__getitem__, _WORD.findall(t.lower())), dtype=np.uint64)
        names.append(hashlib.blake2b(run.tobytes(), digest_size=16).digest())
        if 0 < len(run) < n:  # all its words are one gram
            run = np.concatenate([run, np.arange(1, n - len(run) + 1, dtype=np.uint64)])
        runs.append(run)
    sizes = np.array([len(r) for r in runs])
    flat = np.concatenate(runs) if len(runs) else np.empty(0, dtype=np.uint64)
    owner = np.repeat(np.arange(len(runs)), sizes)
    if len(flat) < n:
        return np.empty(0, dtype=np.int64), np.empty(0, dtype=np.uint64), names
    h = flat[: len(flat) - n + 1].copy()
    for k in range(1, n):
        h = mix(h) + flat[k : len(flat) - n + 1 + k]
    inside = owner[: len(flat) - n + 1] == owner[n - 1 :]
    return owner[: len(flat) - n + 1][inside], mix(h[inside]), names


def counted(owner: np.ndarray, grams: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (owner, gram) and how often each occurs; sorted."""
    if not len(owner):
        return owner, grams, np.empty(0, dtype=np.int64)
    order = np.lexsort((grams, owner))
    owner, grams = owner[order], grams[order]
    first = np.flatnonzero(np.concatenate([[True], (owner[1:] != owner[:-1]) | (grams[1:] != grams[:-1])]))
    return owner[first], grams[first], np.diff(np.append(first, len(owner)))


def bag_signatures(owner: np.ndarray, grams: np.ndarray, weight: np.ndarray, texts: int, size: int = SIZE) -> np.ndarray:
    """First arrival times, a row for each text; infinite for texts without grams."""
    out = np.full(texts * size, np.inf)
    if not len(owner):
        return out.reshape(texts, size)
    # one process for each dyadic interval of the weight axis that a gram's weight reaches
    intervals = 1 + np.ceil(np.log2(weight)).astype(np.int64)
    at = np.repeat(np.arange(len(owner)), intervals)
    level = np.arange(len(at)) - np.repeat(np.cumsum(intervals) - intervals, intervals)
    low = np.where(level > 0, 1 << np.maximum(level - 1, 0), 0)
    width = np.where(level > 0, low, 1)
    own, w = owner[at], weight[at]
    seed = mix(grams[at] + mix(level.astype(np.uint64)))
    time, k = np.zeros(len(at)), 0
    while len(at):
        k += 1
        r = mix(seed + np.array([k], dtype=np.uint64) * _ODD)
        time = time - np.log(((r >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53) / width
        s = mix(r)
        place = (s >> np.uint64(32)) % np.uint64(size)
        height = low + ((s & np.uint64(0xFFFFFFFF)) % width.astype(np.uint64)).astype(np.int64)
        ok = height < w
        np.minimum.at(out, own[ok] * size + place[ok].astype(np.int64), time[ok])
        last = out.reshape(texts, size).max(axis=1)
        live = time <= last[own]
        if not live.all():
            at, own, w, low, width, seed, time = (x[live] for x in (at, own, w, low, width, seed, time))
    return out.reshape(texts, size)


def band_keys(signatures: np.ndarray, bands: int = BANDS, rows: int = ROWS) -> np.ndarray:
    bits = signatures.view(np.uint64).reshape(len(signatures), bands, rows)
    h = np.broadcast_to(mix(np.arange(bands, dtype=np.uint64)), bits.shape[:2]).copy()
    for i in range(rows):
        h = mix(h ^ bits[:, :, i])
    return h.view(np.int64)


def short_signatures(signatures: np.ndarray) -> np.ndarray:
    """One byte of each component."""
    return (mix(signatures.view(np.uint64)) >> np.uint64(56)).astype(np.uint8)


def tagged(owner: np.ndarray, grams: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Multisets as sets: the k-th occurrence of a gram is an element of its own."""
    at = np.repeat(np.arange(len(owner)), weight)
    nth = np.arange(len(at)) - np.repeat(np.cumsum(weight) - weight, weight)
    return owner[at], mix(grams[at] + mix(nth.astype(np.uint64)) * (nth > 0).astype(np.uint64))


# ---- passes over tables -----------------------------------------------------------------------------------


def signed_rows(rows: DataFrame) -> DataFrame:
    """doc_id, text_key, node, short (signature), keys (of the bands; none for empty texts)."""

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in batches:
            owner, grams, names = grams_of(batch.column(1).to_pylist(), hashes)
            found = bag_signatures(*counted(owner, grams), len(names))
            keys, short = band_keys(found), short_signatures(found)
            some = np.isfinite(found[:, 0])
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(2), pa.array(names, pa.binary()), pa.array([s.tobytes() for s in short], pa.binary()), pa.array([k if ok else [] for k, ok in zip(keys, some)], pa.list_(pa.int64()))],
                ["doc_id", "text_key", "node", "short", "keys"],
            )

    return rows.select("doc_id", "text", F.md5("text").alias("text_key")).mapInArrow(frugal(sign), "doc_id long, text_key string, node binary, short binary, keys array<long>")


def multisets(rows: DataFrame) -> DataFrame:
    """node and its multiset of shingles as sorted 64-bit numbers."""

    def lay(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in batches:
            owner, grams, names = grams_of(batch.column(1).to_pylist(), hashes)
            who, what = tagged(*counted(owner, grams))
            ends = np.searchsorted(who, np.arange(len(names) + 1))
            sets = [np.sort(what[a:b]).tobytes() for a, b in zip(ends[:-1], ends[1:])]
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.binary()), pa.array(sets, pa.binary())], ["node", "grams"])

    return rows.mapInArrow(frugal(lay), "node binary, grams binary")


def _paired(pairs: DataFrame, table: DataFrame, value: str) -> DataFrame:
    """pairs (a, b) with the value of both."""
    one = table.select(F.col("node").alias("a"), F.col(value).alias("of_a"))
    two = table.select(F.col("node").alias("b"), F.col(value).alias("of_b"))
    return pairs.join(one, "a").join(two, "b").select("a", "b", "of_a", "of_b")


def likely(pairs: DataFrame, nodes: DataFrame, threshold: float) -> DataFrame:
    """Pairs whose signatures agree on enough components."""
    least = _least(threshold)

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = (np.frombuffer(b"".join(batch.column(i).to_pylist()), dtype=np.uint8).reshape(-1, SIZE) for i in (2, 3))
            yield batch.select(["a", "b"]).filter(pa.array((a == b).sum(axis=1) >= least))

    return _paired(pairs, nodes, "short").mapInArrow(frugal(compare), "a binary, b binary")


def overlaps(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """a, b, similarity: what the multisets share of what they have together."""

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for a, b in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist()):
                x, y = np.frombuffer(a, dtype=np.uint64), np.frombuffer(b, dtype=np.uint64)
                both = len(np.intersect1d(x, y, assume_unique=True))
                out.append(both / max(len(x) + len(y) - both, 1))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out, pa.float64())], ["a", "b", "similarity"])

    return _paired(pairs, sets, "grams").mapInArrow(frugal(compare), "a binary, b binary, similarity double")


def _least(threshold: float) -> int:
    return int(np.floor(SIZE * threshold - 5 * np.sqrt(SIZE * threshold * (1 - threshold))))


def linked_by_chunks(groups: DataFrame, threshold: float) -> DataFrame:
    """a, b, similarity: links that join all classes of a group that can be joined. groups: group, size, node, class, short, grams.

    A task holds two chunks at most. Within it, pairs that its own links have joined already are passed over.
    """
    chunks = F.ceil(F.col("size") / CHUNK).cast("int")
    dealt = groups.withColumn("c", F.pmod(F.xxhash64("node"), chunks).cast("int")).withColumn("x", F.explode(F.sequence(F.lit(0), chunks - 1)))
    dealt = dealt.select("group", F.least("c", "x").alias("lo"), F.greatest("c", "x").alias("hi"), "c", "node", "class", "short", "grams")
    least = _least(threshold)

    def compare(pdf: pd.DataFrame) -> pd.DataFrame:
        lo, hi = int(pdf["lo"].iloc[0]), int(pdf["hi"].iloc[0])
        pdf = pdf.sort_values(["c", "node"]).reset_index(drop=True)
        short = np.frombuffer(b"".join(pdf["short"]), dtype=np.uint8).reshape(-1, SIZE)
        sets = [np.frombuffer(g, dtype=np.uint64) for g in pdf["grams"]]
        sizes, first = np.array([len(x) for x in sets]), int((pdf["c"] == lo).sum())
        parent: dict = {}

        def root(x):
            while parent.get(x, x) != x:
                parent[x] = x = parent.get(parent[x], parent[x])
            return x

        out, names = [], pdf["class"].tolist()
        for i in range(first):
            start = i + 1 if lo == hi else first
            fits = np.minimum(sizes[start:], sizes[i]) >= threshold * np.maximum(sizes[start:], sizes[i])
            at = np.flatnonzero(fits)
            at = at[(short[start + at] == short[i]).sum(axis=1) >= least] + start
            for j in at:
                p, q = root(names[i]), root(names[j])
                if p == q:
                    continue
                both = len(np.intersect1d(sets[i], sets[j], assume_unique=True))
                similarity = both / (sizes[i] + sizes[j] - both)
                if similarity >= threshold:
                    parent[p] = q
                    out.append((pdf["node"][i], pdf["node"][j], similarity))
        return pd.DataFrame(out, columns=["a", "b", "similarity"])

    return dealt.groupBy("group", "lo", "hi").applyInPandas(compare, "a binary, b binary, similarity double")


def components(links: DataFrame) -> DataFrame:
    """node, class (the smallest node it is linked with): large and small stars in turn, each written, until nothing changes."""
    edges = written(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u <> v").distinct(), "edges")
    state = None
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        big = both.join(least, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()
        big = written(big, "large-star")
        least = big.groupBy("u").agg(F.min("v").alias("m"))
        rest = big.join(least, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        edges = written(rest.unionByName(least.select("u", F.col("m").alias("v"))).distinct(), "small-star")
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == state:
            break
        state = now
    return edges.select(F.col("u").alias("node"), F.col("v").alias("class"))


def find_classes(docs: DataFrame, threshold: float = THRESHOLD, text_column: str = "text") -> DataFrame:
    """doc_id, class_id (smallest doc_id of the class), n_links (that were found on the way from its text to others) of each row."""
    return _classes(docs, threshold, text_column).select("doc_id", "class_id", "n_links")


def _classes(docs: DataFrame, threshold: float, text_column: str = "text") -> DataFrame:
    """The same with the md5 of each row's text and the class itself, which has a name even if all its ids are null."""
    spark: SparkSession = docs.sparkSession
    arrow_batches(spark, 256)
    rows = rows_of(docs, text_column=text_column)
    signed = written(signed_rows(rows), "signatures")
    nodes = signed.groupBy("node").agg(F.first("short").alias("short"), F.min("doc_id").alias("doc_id"))
    keyed = signed.select("node", F.explode("keys").alias("key")).distinct()
    sizes = keyed.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1")
    members = written(keyed.join(sizes, "key"), "buckets")

    def sets_of(wanted: DataFrame) -> DataFrame:
        """Multisets of these nodes, from one document of each."""
        ids = written(nodes.join(wanted, "node", "left_semi").select(F.col("doc_id").alias("wanted_id")), "wanted")
        texts = rows.join(small(ids), F.col("doc_id").eqNullSafe(F.col("wanted_id")), "left_semi")
        return written(multisets(texts).dropDuplicates(["node"]), "multisets")

    # small buckets: all pairs; large ones: their smallest node with the others
    few = F.col("n") <= SMALL
    least = members.filter(~few).groupBy("key").agg(F.min("node").alias("pivot"))
    pairs = members.filter(few).select("key", F.col("node").alias("pivot")).unionByName(least)
    pairs = members.join(pairs, "key").filter("node > pivot").select(F.col("pivot").alias("a"), F.col("node").alias("b")).distinct()
    close = written(likely(written(pairs, "pairs"), nodes, threshold), "likely-pairs")
    wanted = close.select(F.col("a").alias("node")).unionByName(close.select(F.col("b").alias("node"))).distinct()
    links = written(overlaps(close, sets_of(wanted)).filter(F.col("similarity") >= threshold), "links")
    classes = components(links)

    # large buckets whose members lie in different classes
    held = members.filter(~few).join(classes, "node", "left").withColumn("class", F.coalesce("class", "node"))
    spread = held.groupBy("key").agg(F.min("class").alias("x"), F.max("class").alias("y"), F.min("node").alias("pivot")).filter("x <> y").select("key", "pivot")
    rest = written(held.join(spread, "key").select("node", "class", "pivot"), "open-buckets")
    if not rest.isEmpty():
        near = components(rest.select(F.col("node").alias("a"), F.col("pivot").alias("b"))).withColumnRenamed("class", "group")
        groups = rest.select("node", "class").distinct().join(near, "node", "left").withColumn("group", F.coalesce("group", "node"))
        groups = written(groups.join(nodes.select("node", "short"), "node"), "groups")
        sizes = groups.groupBy("group").agg(F.count("*").alias("size"))
        dealt = groups.join(sizes, "group").join(sets_of(groups.select("node")), "node")
        links = links.unionByName(written(linked_by_chunks(dealt, threshold), "chunk-links"))
        classes = components(links)

    degree = links.select(F.explode(F.array("a", "b")).alias("node")).groupBy("node").agg(F.count("*").alias("n_links"))
    by_class = nodes.select("node", "doc_id").join(classes, "node", "left").withColumn("class", F.coalesce("class", "node"))
    names = by_class.groupBy("class").agg(F.min("doc_id").alias("class_id"))
    named = by_class.join(names, "class").join(degree, "node", "left").select("node", "class", "class_id", F.coalesce("n_links", F.lit(0)).alias("n_links"))
    return signed.select("doc_id", "text_key", "node").join(named, "node").select("doc_id", "text_key", "class", "class_id", "n_links")


def keep_one(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """``docs`` with one row of each class: that of the smallest doc_id, null last, and of its texts the one with the smallest md5. Rows
    are told apart by id and text, so rows that repeat an id with other texts are judged each."""
    found = written(_classes(docs, threshold).select("doc_id", "text_key", "class"), "classes")
    row = F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id").alias("id"), F.col("text_key").alias("key"))
    first = found.groupBy("class").agg(F.min(row).alias("first"))
    judged = found.join(first, "class").select(F.col("doc_id").alias("__id"), F.col("text_key").alias("__key"), (row == F.col("first")).alias("__first"))
    counts = written(judged.groupBy("__id", "__key").agg(F.max("__first").alias("__first"), F.count("*").alias("__n")), "judged-rows")
    same = F.col("doc_id").cast("long").eqNullSafe(F.col("__id")) & (F.md5(F.coalesce(F.col("text").cast("string"), F.lit(""))) == F.col("__key"))
    kept = docs.join(small(counts.filter("not __first")), same, "left_anti")
    twice = small(counts.filter("__first and __n > 1"))
    once = kept.join(twice, same, "left_anti")
    again = kept.join(twice, same, "inner").dropDuplicates(["__id", "__key"])
    return once.unionByName(again.select(*[F.col(f"`{c}`") for c in docs.columns]))
