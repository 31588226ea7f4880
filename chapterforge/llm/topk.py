"""Exact top-k search: BM25 over an inverted index with block-max pruning, by shard, merged exactly.

A shard is what one task reads of the documents, in parts of ``SHARD`` documents. Its index is one row: term hashes, postings sorted by term and
place, term frequencies and lengths. Document frequencies, number and mean length are global, so shards' scores can be merged.

Queries go out in blocks of about ``BLOCK`` rows, a bounded broadcast each. Within a shard, documents lie in blocks of ``PLACES`` places, the same
for all terms. Of the ``DENSE`` most frequent terms, those with ``FULL`` postings or more in a block are a row of that block's matrix, and their largest
weight there is known; all other postings are rare. A query's rare postings are summed first, over the whole shard; the largest of these sums in a
block and the largest weights of the frequent terms there bound what the block can give. A query's cursor goes from block to block, those of the largest
bounds first, and its pivot is the next one whose bound reaches the query's k-th best score so far: block-max WAND whose pivots are blocks
instead of documents, as blocks of places are alike for all terms. What is skipped can't reach the k-th best, so the top k are exact. An eighth of the
shards goes first; its k-th best scores are where the others begin.

Up to ``TOGETHER`` alike queries go through a shard side by side, and a block's matrix meets all that stop there in one product. That is in single
precision, whose error is bounded (all products are positive): it only tells which documents can't be among the k best. The others, some k a
query and shard and fewer where there is a floor, are scored again from their own postings in double precision.

Words are split by white space, lower-cased, stripped of marks, and stand for themselves by 64-bit hashes. Scores are rounded to 6 digits;
equal ones are ordered by doc_id.

Defined results: null and empty texts are indexed without terms and as queries find nothing; queries with fewer than k documents that share
a word return those; rows that repeat an id are documents (and queries) each; an empty table gives no rows; columns other than id and text
are not read, whatever their names.
"""

from __future__ import annotations

import hashlib
import string
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow_batches, frugal, rows_of, written

K1, B = 1.2, 0.75
SHARD, BLOCK, PLACES, DENSE, FULL, TOGETHER, TERMS, RARE = 8192, 8192, 256, 2048, 8, 256, 400_000, 65_536
MARKS = string.punctuation + "…«»“”„’‘¿¡"


class TermHashes(dict):
    most = 150_000

    def __missing__(self, word: str) -> int:
        if len(self) >= self.most:
            self.clear()
        w = word.strip(MARKS)
        h = self[word] = int.from_bytes(hashlib.blake2b(w.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "little", signed=True) if w else 0
        return h


def terms_of(text: str, hashes: TermHashes) -> Counter:
    found = Counter(map(hashes.__getitem__, text.lower().split()))
    found.pop(0, None)
    return found


def index_rows(rows: DataFrame, shard: int = SHARD) -> DataFrame:
    """One row for each part of a task's documents: ids, lengths, terms, ends (of each term's postings), places, tfs."""
    schema = pa.schema([("ids", pa.list_(pa.int64())), *[(n, pa.binary()) for n in ("lengths", "terms", "ends", "places", "tfs")]])

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, ids, lengths, parts = TermHashes(), [], [], []

        def out() -> pa.RecordBatch:
            # alike documents side by side: by their most frequent term (which tells languages apart), then by length; so blocks differ
            # in what they can score
            top = np.array([p[0][np.lexsort((p[0], -p[1]))[0]] if len(p[0]) else 0 for p in parts], np.int64)
            by = np.lexsort((np.array(lengths), top))
            ids[:], lengths[:], parts[:] = ([x[i] for i in by] for x in (ids, lengths, parts))
            term = np.concatenate([p[0] for p in parts]) if parts else np.empty(0, np.int64)
            tf = np.concatenate([p[1] for p in parts]) if parts else np.empty(0, np.int32)
            place = np.repeat(np.arange(len(ids), dtype=np.int32), [len(p[0]) for p in parts])
            order = np.lexsort((place, term))
            kinds, first = np.unique(term[order], return_index=True)
            ends = np.append(first[1:], len(order)).astype(np.int64) if len(kinds) else np.empty(0, np.int64)
            cells = [np.array(lengths, np.int64), kinds, ends, place[order], tf[order].astype(np.int32)]
            return pa.RecordBatch.from_arrays([pa.array([ids], pa.list_(pa.int64())), *[pa.array([c.tobytes()], pa.binary()) for c in cells]], schema=schema)

        for batch in batches:
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                found = terms_of(text, hashes)
                ids.append(doc_id)
                lengths.append(sum(found.values()))
                parts.append((np.fromiter(found.keys(), np.int64, len(found)), np.fromiter(found.values(), np.int32, len(found))))
                if len(ids) >= shard:
                    yield out()
                    ids, lengths, parts = [], [], []
        if ids:
            yield out()

    return rows.mapInArrow(frugal(build), "ids array<long>, lengths binary, terms binary, ends binary, places binary, tfs binary")


class Shard:
    """A part of the index, with weights by global statistics; query weights carry the terms' idf."""

    def __init__(self, row: dict, mean: float):
        self.ids = np.array([-(2**63) if i is None else i for i in row["ids"]], dtype=np.int64)
        self.null = np.array([i is None for i in row["ids"]])
        self.n = len(self.ids)
        lengths = np.frombuffer(row["lengths"], np.int64)
        self.terms, ends = np.frombuffer(row["terms"], np.int64), np.frombuffer(row["ends"], np.int64)
        self.start, self.end = np.concatenate([[0], ends[:-1]]).astype(np.int64) if len(ends) else ends, ends
        self.places = np.frombuffer(row["places"], np.int32)
        tf = np.frombuffer(row["tfs"], np.int32).astype(float)
        norm = K1 * (1 - B + B * lengths / max(mean, 1e-9))
        self.weight = tf * (K1 + 1) / (tf + norm[self.places])
        self.blocks, size = -(-self.n // PLACES), self.end - self.start
        # the frequent terms' cells: the blocks where each is; a cell of FULL postings is a row of its block's matrix, zeros between
        dense = np.sort(np.argsort(-size, kind="stable")[:DENSE])
        self.slot = np.full(len(self.terms), -1)
        self.slot[dense] = np.arange(len(dense))
        at = _runs(self.start[dense], self.end[dense])
        key = np.repeat(np.arange(len(dense), dtype=np.int32) * max(self.blocks, 1), size[dense]) + self.places[at] // PLACES
        first = np.flatnonzero(np.diff(key, prepend=-1))
        filled = np.diff(first, append=len(key))
        cells = np.flatnonzero(filled >= FULL)
        column, block = np.divmod(key[first[cells]], max(self.blocks, 1))
        self.cell_block = block.astype(np.int16) if self.blocks < 1 << 15 else block  # numpy sorts short keys by their digits
        order = np.argsort(self.cell_block, kind="stable")
        self.cell_column, self.cell_end = column[order], np.append(0, np.cumsum(np.bincount(block, minlength=self.blocks)))
        del key
        row_of = np.full(len(first), -1, np.int32)
        row_of[cells[order]] = np.arange(len(cells))
        row_of = np.repeat(row_of, filled)
        at, row_of = at[row_of >= 0], row_of[row_of >= 0]
        self.matrix = np.zeros((len(cells), PLACES), np.float32)
        self.matrix[row_of, self.places[at] % PLACES] = self.weight[at]
        self.maxima, self.filled = (np.zeros((len(dense), self.blocks), np.float32) for _ in range(2))
        self.maxima[column, block], self.filled[column, block] = self.matrix.max(axis=1)[np.argsort(order)] if len(cells) else 0, filled[cells]
        # all other postings by term
        rare = np.ones(len(self.places), bool)
        rare[at] = False
        self.rare = self.places[rare].astype(np.int64) << 32 | self.weight[rare].astype(np.float32).view(np.uint32)  # place and weight, read at once
        del at, row_of
        ends = np.append(0, np.cumsum(rare))
        self.rare_start, self.rare_end = ends[self.start], ends[self.end]
        # each document's postings, for exact scores
        by = np.argsort(self.places.astype(np.int16) if self.n < 1 << 15 else self.places, kind="stable")
        self.doc_terms, self.doc_weights = np.repeat(np.arange(len(self.terms), dtype=np.int32), size)[by], self.weight[by]
        self.doc_end = np.append(0, np.cumsum(np.bincount(self.places, minlength=self.n)))
        # single precision: a sum of so many positive products is off by this share at most
        self.off = (int(np.diff(self.cell_end).max(initial=0)) + 16) * 2.0**-24
        self.postings_read = self.postings_met = 0  # of the queries' terms: summed, and all there are

    def find(self, terms: np.ndarray) -> np.ndarray:
        """Where each term is among this shard's, -1 if it is not there."""
        at = np.searchsorted(self.terms, terms)
        ok = at < len(self.terms)
        ok[ok] = self.terms[at[ok]] == terms[ok]
        return np.where(ok, at, -1)

    def search(self, queries: list[tuple[np.ndarray, np.ndarray]], k: int, floors: list[float]) -> list[tuple[np.ndarray, np.ndarray]]:
        """queries: term hashes and idf weights of each. Places and scores of each one's k best here that reach its floor."""
        terms, weights = (np.concatenate([q[i] for q in queries]) for i in (0, 1))
        return self.ranked(self.find(terms), weights, np.array([len(q[0]) for q in queries]), k, np.array(floors, dtype=float))

    def ranked(self, at: np.ndarray, weights: np.ndarray, sizes: np.ndarray, k: int, floors: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
        """``search`` for terms by their places among this shard's, -1 for others; sizes: how many are each query's.

        The rare postings' sums come first. With the largest weights of the frequent terms they bound what a block can give; the queries'
        cursors go through the blocks side by side, the most promising first, and at a block stop those whose pivot it is: one product in
        single precision gives their scores up to ``off``. What may be among the k best by that is scored again exactly.
        """
        m, none, width = len(sizes), (np.empty(0, np.int64), np.empty(0)), self.blocks * PLACES
        owner, ok = np.repeat(np.arange(m), sizes), at >= 0
        at, weights, owner = at[ok], weights[ok], owner[ok]
        if not len(at):
            return [none] * m
        slot, begin, end = self.slot[at], self.rare_start[at], self.rare_end[at]
        q = np.zeros((len(self.maxima), m), np.float32)
        q[slot[slot >= 0], owner[slot >= 0]] = weights[slot >= 0]
        first = np.searchsorted(owner, np.arange(m + 1))
        many = np.append(0, np.cumsum(end - begin))
        self.postings_read += int(many[-1])
        self.postings_met += int((self.end[at] - self.start[at]).sum())
        rare, x = np.zeros((m, width), np.float32), 0
        while x < m:  # a few queries' postings at a time
            y = max(x + 1, int(np.searchsorted(many[first], many[first[x]] + RARE, "right")) - 1)
            mine = slice(first[x], first[y])
            length = end[mine] - begin[mine]
            postings = self.rare[_runs(begin[mine], end[mine])]
            sums = postings.astype(np.uint32).view(np.float32) * np.repeat(weights[mine], length)
            postings >>= 32
            postings += np.repeat((owner[mine] - x) * width, length)
            rare[x:y] = np.bincount(postings, sums, minlength=(y - x) * width).reshape(y - x, width)
            x = y
        rare = rare.reshape(m, self.blocks, PLACES)
        bound = (rare.max(axis=2) + q.T @ self.maxima) * np.float32(1 + 4 * self.off)
        filled = (q > 0).astype(np.float32).T @ self.filled
        # what a score in single precision has to reach: the floor, and the k-th best so far; a result rounds to above 0
        need = np.maximum(floors * (1 - 2 * self.off) - 1e-6, 4e-7).astype(np.float32)
        best = np.zeros((m, k), np.float32)
        found: list[list] = [[] for _ in range(m)]
        for b in np.argsort(-bound.sum(axis=0), kind="stable").tolist():
            live = np.flatnonzero(bound[:, b] >= need)  # the queries whose pivot is this block
            if not len(live):
                continue
            mine = slice(self.cell_end[b], self.cell_end[b + 1])
            if 2 * len(live) > live[-1] + 1 - live[0]:  # alike queries are neighbours
                live = slice(live[0], live[-1] + 1)
            asked = q[self.cell_column[mine], live] if isinstance(live, slice) else q[self.cell_column[mine]].take(live, axis=1)
            sums = rare[live, b] + (self.matrix[mine].T @ asked).T
            self.postings_read += int(filled[live, b].sum())
            some = np.flatnonzero(sums.max(axis=1) >= need[live])
            if not len(some):
                continue
            rows, sums = np.arange(m)[live][some], sums[some]
            good = sums >= need[rows, None]
            r, place = np.nonzero(good)
            values, cut = sums[r, place], np.searchsorted(r, np.arange(len(rows) + 1)).tolist()
            for i, x, y in zip(rows.tolist(), cut, cut[1:]):
                found[i].append((place[x:y] + b * PLACES, values[x:y]))
            every_score = np.concatenate([best[rows], np.where(good, sums, 0)], axis=1)
            best[rows] = np.partition(every_score, -k, axis=1)[:, -k:]
            need[rows] = np.maximum(need[rows], best[rows].min(axis=1) * (1 - 4 * self.off) - 2e-6)
        out, by_term = [], np.zeros(len(self.terms))
        for i in range(m):
            places, sums = (np.concatenate(x) for x in zip(*found[i])) if found[i] else none
            places = places[sums >= need[i]]
            if not len(places):
                out.append(none)
                continue
            mine = slice(first[i], first[i + 1])
            by_term[at[mine]] = weights[mine]
            start, stop = self.doc_end[places], self.doc_end[places + 1]
            where = _runs(start, stop)
            scores = np.bincount(np.repeat(np.arange(len(places)), stop - start), by_term[self.doc_terms[where]] * self.doc_weights[where], minlength=len(places))
            by_term[at[mine]] = 0
            scores = np.round(scores, 6)
            good = (scores >= floors[i]) & (scores > 0)
            places, scores = places[good], scores[good]
            order = np.lexsort((self.ids[places], -scores))[:k]
            out.append((places[order], scores[order]))
        return out


def _runs(begin: np.ndarray, end: np.ndarray) -> np.ndarray:
    """begin[0], ..., end[0] - 1, begin[1], ..., one after the other."""
    some = end > begin
    begin, end = begin[some], end[some]
    steps = np.ones(int((end - begin).sum()), np.int64)
    if len(begin):
        steps[0] = begin[0]
        steps[np.cumsum(end - begin)[:-1]] = begin[1:] - end[:-1] + 1
    return np.cumsum(steps, out=steps)


def _together(queries: list[tuple]) -> Iterator[list[tuple]]:
    """Runs of at most ``TOGETHER`` queries and ``TERMS`` terms; a query of more terms is alone."""
    few, terms = [], 0
    for query in queries:
        if few and (len(few) == TOGETHER or terms + len(query[2]) > TERMS):
            yield few
            few, terms = [], 0
        few.append(query)
        terms += len(query[2])
    if few:
        yield few


def _asked(rows: pa.Table) -> tuple[list[tuple], np.ndarray, np.ndarray]:
    """Queries (q, query_id, places of its terms in the vocabulary), alike ones side by side; the vocabulary, sorted; its idf weights."""
    lists = [rows.column(n).combine_chunks() for n in ("term", "w")]
    sizes = np.diff(lists[0].offsets.to_numpy())
    terms, weights = (x.flatten().to_numpy() for x in lists)
    vocabulary, one, at = np.unique(terms, return_index=True, return_inverse=True)
    ends = np.cumsum(sizes)
    # by the most frequent term (which tells languages apart), then by length: they stop at the same blocks
    order = np.lexsort((sizes, np.minimum.reduceat(weights, ends - sizes))) if len(sizes) else ends
    ids, parts = list(zip(*(rows.column(n).to_pylist() for n in ("q", "query_id")))), np.split(at.astype(np.int32), ends[:-1])
    return [(*ids[i], parts[i]) for i in order], vocabulary, weights[one]


def _looked_up(index: DataFrame, held, floors: np.ndarray, k: int, mean: float) -> DataFrame:
    """q, query_id, doc_id, score of the k best of each shard that reach the query's floor. held: what ``_asked`` gives, broadcast."""

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        queries, vocabulary, idf = held.value
        q, null = np.array([x[0] for x in queries], np.int64), np.array([x[1] is None for x in queries])
        query_id = np.array([x[1] or 0 for x in queries], np.int64)
        reached, groups = floors.copy(), []  # a shard's k-th best is a floor for the next ones of its task
        for few in _together(queries):
            at = np.concatenate([x[2] for x in few])
            groups.append((at, idf[at], np.array([len(x[2]) for x in few])))
        for batch in batches:
            rows = batch.to_pylist()
            while rows:
                shard, best = Shard(rows.pop(), mean), []
                there = shard.find(vocabulary)
                for at, weights, sizes in groups:
                    best += shard.ranked(there[at], weights, sizes, k, reached[len(best) : len(best) + len(sizes)])
                for i, (_, scores) in enumerate(best):
                    if len(scores) == k:
                        reached[i] = max(reached[i], scores[-1])
                owner = np.repeat(np.arange(len(best)), [len(x) for x, _ in best])
                places, scores = (np.concatenate([x[i] for x in best]) for i in (0, 1))
                yield pa.RecordBatch.from_arrays(
                    [pa.array(q[owner]), pa.array(query_id[owner], mask=null[owner]), pa.array(shard.ids[places], mask=shard.null[places]), pa.array(scores)],
                    ["q", "query_id", "doc_id", "score"],
                )

    return index.mapInArrow(frugal(look), "q long, query_id long, doc_id long, score double")


def search_all(docs: DataFrame, queries: DataFrame, k: int = 10, block: int = BLOCK, text_column: str = "text") -> DataFrame:
    """query_id, rank, doc_id, score: the k documents of the largest BM25 score for each row of ``queries`` (doc_id, text)."""
    spark = docs.sparkSession
    arrow_batches(spark, 256)
    index = written(index_rows(rows_of(docs, text_column=text_column)), "search-index")

    def lengths(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                n = np.frombuffer(row["lengths"], np.int64)
                yield pa.RecordBatch.from_arrays([pa.array([len(n)]), pa.array([int(n.sum())])], ["n", "words"])

    def document_frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                ends = np.frombuffer(row["ends"], np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(row["terms"], np.int64)), pa.array(np.diff(ends, prepend=0))], ["term", "df"])

    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "1")  # an index row is a whole part
    n, words = index.select("lengths").mapInArrow(lengths, "n long, words long").agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum("words"), F.lit(0))).first()
    mean = words / max(n, 1)
    frequencies = written(index.select("terms", "ends").mapInArrow(document_frequencies, "term long, df long").groupBy("term").agg(F.sum("df").alias("df")), "document-frequencies")

    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "256")

    def query_terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = TermHashes()
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([list(terms_of(t, hashes)) for t in batch.column(2).to_pylist()], pa.list_(pa.int64()))], ["q", "query_id", "terms"])

    # numbered by the order of id and text, so that rows that repeat an id are told apart
    asked = rows_of(queries, text_column=text_column).select(F.monotonically_increasing_id().alias("q"), F.col("doc_id").alias("query_id"), "text")
    asked = written(asked.mapInArrow(query_terms, "q long, query_id long, terms array<long>"), "queries")
    idf = F.log(1 + (F.lit(float(n)) - F.col("df") + 0.5) / (F.col("df") + 0.5))
    weighed = asked.select("q", "query_id", F.explode("terms").alias("term")).join(frequencies, "term")
    weighed = weighed.groupBy("q", "query_id").agg(F.array_sort(F.collect_list(F.struct("term", idf.alias("w")))).alias("terms"))  # one query's words
    weighed = written(weighed.withColumn("block", F.pmod(F.xxhash64("q"), F.lit(max(1, -(-asked.count() // block))))), "weighed-queries")

    place = F.row_number().over(Window.partitionBy("q").orderBy(F.desc("score"), F.col("doc_id").asc_nulls_first()))
    best = lambda found: found.withColumn("rank", place).filter(F.col("rank") <= k)
    out = None
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "1")
    # an eighth of the shards first: a query's k-th best score there is a floor for all others, which prune by it from the start
    # and return only what reaches it
    early = F.pmod(F.xxhash64("lengths"), F.lit(8)) == 0
    for b in range(max(1, -(-asked.count() // block))):
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "1024")
        asked_now = _asked(weighed.filter(F.col("block") == b).select("q", "query_id", "terms.term", "terms.w").toArrow())  # about ``block`` queries
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "1")
        if not asked_now[0]:
            continue
        held, numbers = spark.sparkContext.broadcast(asked_now), [x[0] for x in asked_now[0]]
        del asked_now
        first = written(best(_looked_up(index.filter(early), held, np.zeros(len(numbers)), k, mean)), "first-shards")
        floors = {r["q"]: r["score"] for r in first.filter(F.col("rank") == k).collect()}  # a row a query of the block
        floors = np.array([floors.get(x, 0.0) for x in numbers])
        one = written(best(first.drop("rank").unionByName(_looked_up(index.filter(~early), held, floors, k, mean))), "found")
        held.unpersist()  # this block's results are written
        out = one if out is None else out.unionByName(one)
    if out is None:
        return spark.createDataFrame([], "query_id long, rank int, doc_id long, score double")
    return out.select("query_id", "rank", "doc_id", "score")


def pruning_report(docs: DataFrame, queries: DataFrame, k: int = 10, text_column: str = "text") -> tuple[int, int]:
    """(postings summed, postings of the queries' terms) over all shards, from the results' own floors. For tables that fit the
    driver; it tells what pruning saves."""
    ranks = {}
    for r in search_all(docs, queries, k, text_column=text_column).filter(F.col("rank") == k).collect():
        ranks[r["query_id"]] = r["score"]
    arrow_batches(docs.sparkSession, 256)
    parts, hashes = index_rows(rows_of(docs, text_column=text_column)).collect(), TermHashes()
    n = sum(len(p["ids"]) for p in parts)
    words = sum(int(np.frombuffer(p["lengths"], np.int64).sum()) for p in parts)
    df: Counter = Counter()
    for p in parts:
        df.update(dict(zip(np.frombuffer(p["terms"], np.int64).tolist(), np.diff(np.frombuffer(p["ends"], np.int64), prepend=0).tolist())))
    shards, read, met = [Shard(p.asDict(), words / max(n, 1)) for p in parts], 0, 0
    for r in rows_of(queries, text_column=text_column).collect():
        terms = np.array(sorted(terms_of(r["text"], hashes)), np.int64)
        weights = np.array([np.log(1 + (n - df[t] + 0.5) / (df[t] + 0.5)) for t in terms.tolist()])
        for shard in shards:
            shard.search([(terms, weights)], k, [ranks.get(r["doc_id"], 0.0)])
    for shard in shards:
        read, met = read + shard.postings_read, met + shard.postings_met
    return read, met
