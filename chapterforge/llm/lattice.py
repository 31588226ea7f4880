"""Language-model scores by subword lattices.

A word's probability is the sum over all its segmentations into pieces of an existing vocabulary, by a forward
recursion in log space. Piece weights start from the vocabulary's own order (its scores are ranks: the weight of rank r is
taken as 1 / (r + 10)) and are re-estimated by ``passes`` rounds of expected counts over all training words. Characters without
a piece go by the vocabulary's byte pieces. A document's log-probability adds its words' and that of its end.

Words are what stands between ASCII white space, A-Z lower-cased. The ``head`` most frequent training words are looked up in
each task; the others are joined, so that no table that grows with the corpus is broadcast and no frequent word makes
a key of its own.

Defined results: null texts are empty (their end is their only token); repeated rows and ids are scored each; without training
rows each piece weight comes from its rank, and an end has probability one half; an empty table gives no rows; other
columns are not read.
"""

from __future__ import annotations

import math
from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_batches, fold, frugal, written
from .tokens import tokenizer_path

HEAD = 100_000
LONG = 48  # longer words are walked one at a time
START = "▁"
LOG10 = math.log(10)
_STEP = np.uint64(0x9E3779B97F4A7C15)


def vocabulary(path: str) -> tuple[list[str], np.ndarray]:
    """Pieces and their starting natural log weights; control pieces get none."""
    import sentencepiece

    held = sentencepiece.SentencePieceProcessor(model_file=path)
    n = held.get_piece_size()
    pieces = [held.id_to_piece(i) for i in range(n)]
    use = np.array([not (held.is_control(i) or held.is_unknown(i)) for i in range(n)])
    weight = np.where(use, 1 / (np.array([max(-held.get_score(i), 0.0) for i in range(n)]) + 10), 0)
    with np.errstate(divide="ignore"):
        return pieces, np.log(weight / weight.sum())


class Lattice:
    def __init__(self, pieces: list[str], log_p: np.ndarray):
        self.log_p = np.append(log_p, -np.inf)  # the last is no piece
        self.byte = {int(p[3:5], 16): i for i, p in enumerate(pieces) if len(p) == 6 and p.startswith("<0x")}
        self.id = {p: i for i, p in enumerate(pieces) if np.isfinite(log_p[i]) and i not in set(self.byte.values())}
        self.longest = max(map(len, self.id))
        self._table()
        self.chars: dict[int, tuple[int, ...]] = {}

    # -- two-choice hash table from a piece's hash to its id --
    def _table(self) -> None:
        self.bits = max(12, int(np.ceil(np.log2(len(self.id) * 8))))
        self.keys = np.zeros(1 << self.bits, dtype=np.uint64)
        self.ids = np.full(1 << self.bits, len(self.log_p) - 1, dtype=np.int32)
        full = np.zeros(1 << self.bits, dtype=bool)
        for piece, i in self.id.items():
            h, held = self.hash_of(piece), i
            at = self._places(h)[0]
            for _ in range(500):
                if not full[at]:
                    break
                h, self.keys[at], held, self.ids[at] = int(self.keys[at]), np.uint64(h), int(self.ids[at]), held
                one, two = self._places(h)
                at = two if at == one else one
            else:
                raise ValueError(f"no place for piece {piece!r}: the table is too full")
            self.keys[at], self.ids[at], full[at] = np.uint64(h), held, True

    def _places(self, h: int) -> tuple[int, int]:
        return h & ((1 << self.bits) - 1), (h >> 32) & ((1 << self.bits) - 1)

    @staticmethod
    def hash_of(text: str) -> int:
        h = 0
        for c in text:
            h = ((h ^ ord(c)) * int(_STEP)) & 0xFFFFFFFFFFFFFFFF
            h ^= h >> 29
        return h

    def _find(self, h: np.ndarray) -> np.ndarray:
        mask = np.uint64((1 << self.bits) - 1)
        one, two = (h & mask).astype(np.int64), ((h >> np.uint64(32)) & mask).astype(np.int64)
        none = np.int32(len(self.log_p) - 1)
        return np.where(self.keys[one] == h, self.ids[one], np.where(self.keys[two] == h, self.ids[two], none))

    def by_bytes(self, char: str) -> tuple[int, ...]:
        """The byte pieces of a character."""
        return tuple(self.byte[b] for b in char.encode("utf-8", "surrogatepass"))

    def _edges(self, codes: np.ndarray) -> dict[tuple[int, int], np.ndarray]:
        """Piece ids of all stretches [i, j) of words of one length."""
        n, length = codes.shape
        out = {}
        for i in range(length):
            h = np.zeros(n, dtype=np.uint64)
            for j in range(i + 1, min(length, i + self.longest) + 1):
                h = (h ^ codes[:, j - 1]) * _STEP
                h ^= h >> np.uint64(29)
                found = self._find(h)
                if j == i + 1 or (found < len(self.log_p) - 1).any():
                    out[i, j] = found
        return out

    def _single(self, codes: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, list]:
        """Log weights of one-character stretches, where bytes stand in; and (row, byte pieces) of those."""
        lp, rare = self.log_p[ids], []
        for r in np.flatnonzero(ids == len(self.log_p) - 1):
            b = self.by_bytes(chr(int(codes[r])))
            lp[r] = sum(self.log_p[x] for x in b)
            rare.append((r, b))
        return lp, rare

    def _walk(self, word: str) -> float:
        """One long word."""
        a = [0.0] + [-math.inf] * len(word)
        for j in range(1, len(word) + 1):
            terms = []
            for i in range(max(0, j - self.longest), j):
                k = self.id.get(word[i:j])
                if k is not None:
                    terms.append(a[i] + self.log_p[k])
                elif j == i + 1:
                    terms.append(a[i] + sum(self.log_p[x] for x in self.by_bytes(word[i])))
            top = max(terms)
            a[j] = top + math.log(sum(math.exp(t - top) for t in terms))
        return float(a[-1])

    def score(self, words: list[str], expect: np.ndarray | None = None, counts: np.ndarray | None = None) -> np.ndarray:
        """Natural log marginal of each word (with the start sign). ``expect`` gathers expected piece counts, ``counts`` times."""
        out = np.empty(len(words))
        by_length: dict[int, list[int]] = defaultdict(list)
        for k, w in enumerate(words):
            by_length[len(w) + 1].append(k)
        for length, rows in by_length.items():
            if length > LONG and expect is None:
                for k in rows:
                    out[k] = self._walk(START + words[k])
                continue
            for at in range(0, len(rows), 4096):
                some = rows[at : at + 4096]
                codes = np.frombuffer("".join(START + words[k] for k in some).encode("utf-32-le", "surrogatepass"), dtype="<u4").reshape(len(some), length).astype(np.uint64)
                edges = self._edges(codes)
                lp, rare = {}, {}
                for (i, j), ids in edges.items():
                    if j == i + 1:
                        lp[i, j], rare[i] = self._single(codes[:, i], ids)
                    else:
                        lp[i, j] = self.log_p[ids]
                a = np.full((length + 1, len(some)), -np.inf)
                a[0] = 0
                for j in range(1, length + 1):
                    for i in range(max(0, j - self.longest), j):
                        if (i, j) in lp:
                            a[j] = np.logaddexp(a[j], a[i] + lp[i, j])
                out[some] = a[length]
                if expect is not None:
                    b = np.full((length + 1, len(some)), -np.inf)
                    b[length] = 0
                    weight = counts[some]
                    for i in range(length - 1, -1, -1):
                        for j in range(i + 1, min(length, i + self.longest) + 1):
                            if (i, j) in lp:
                                b[i] = np.logaddexp(b[i], b[j] + lp[i, j])
                                share = weight * np.exp(a[i] + lp[i, j] + b[j] - a[length])
                                np.add.at(expect, edges[i, j], share)
                                if j == i + 1:
                                    for r, pieces in rare[i]:
                                        np.add.at(expect, list(pieces), share[r])
        return out


def lowered(text: str) -> list[bytes]:
    """bytes.lower and bytes.split know ASCII alone, as wanted."""
    return text.encode("utf-8", "surrogatepass").lower().split()


def score_corpus(docs: DataFrame, path: str | None = None, held_fold: int = 1, head: int = HEAD, passes: int = 3, text_column: str = "text") -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of each row; trains on the other folds."""
    spark = docs.sparkSession
    arrow_batches(spark)
    path = path or tokenizer_path("piece_bpe_32k.model")
    rows = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), (fold() == held_fold).alias("held_out"), F.coalesce(F.col(text_column).cast("string"), F.lit("")).alias("text")
    )

    def tally(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        train, rest = Counter(), set()

        def out() -> pa.RecordBatch:
            only = [w for w in rest if w not in train]
            return pa.RecordBatch.from_arrays([pa.array([*train, *only], pa.binary()), pa.array([*train.values(), *([0] * len(only))], pa.int64())], ["word", "c"])

        for batch in batches:
            for held, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                rest.update(lowered(text)) if held else train.update(lowered(text))
            if len(train) + len(rest) > 500_000:
                yield out()
                train, rest = Counter(), set()
        yield out()

    words = rows.select("held_out", "text").mapInArrow(frugal(tally), "word binary, c long").groupBy("word").agg(F.sum("c").alias("c"))
    words = written(words, "words")
    ends = rows.filter("not held_out").count()
    total, kinds = words.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.expr("if(c > 0, 1, null)"))).first()
    train_tokens, kinds = total + ends, kinds + (ends > 0)

    # piece weights: expected counts over all training words
    pieces, start = vocabulary(path)

    def expected(log_p: np.ndarray):
        def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            lattice, held = Lattice(pieces, log_p), np.zeros(len(pieces) + 1)
            for batch in batches:
                lattice.score([w.decode("utf-8", "surrogatepass") for w in batch.column(0).to_pylist()], held, batch.column(1).to_numpy(zero_copy_only=False).astype(float))
            some = np.flatnonzero(held[:-1])
            yield pa.RecordBatch.from_arrays([pa.array(some, pa.int64()), pa.array(held[some], pa.float64())], ["piece", "n"])

        return gather

    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "20000")
    log_p = start
    for _ in range(passes):
        gathered = words.filter("c > 0").mapInArrow(frugal(expected(log_p)), "piece long, n double").groupBy("piece").agg(F.sum("n").alias("n")).collect()  # a row a piece
        counts = np.where(np.isfinite(start), np.exp(start) * len(pieces) * 0.1, 0)
        for r in gathered:
            counts[r["piece"]] += r["n"]
        with np.errstate(divide="ignore"):
            log_p = np.log(counts / counts.sum())
    p_end = ends / train_tokens if 0 < ends < train_tokens else 0.5
    rare = train_tokens + 0.5 * (kinds + 1)

    def rate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lattice = Lattice(pieces, log_p)
        for batch in batches:
            c = batch.column(1).to_numpy(zero_copy_only=False)
            s = lattice.score([w.decode("utf-8", "surrogatepass") for w in batch.column(0).to_pylist()]) / LOG10 + math.log10(1 - p_end)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array((c > 0).astype("int64")), pa.array(np.log10((c + 0.5) / rare)), pa.array(s), batch.column(1)], ["word", "known", "base", "lp", "c"])

    lexicon = written(words.mapInArrow(frugal(rate), "word binary, known long, base double, lp double, c long"), "lexicon")
    top = lexicon.filter("c > 1").orderBy(F.desc("c"), "word").limit(head).select("word", "base", "lp").collect()  # head rows
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "512")
    frequent = spark.sparkContext.broadcast({r["word"]: (r["base"], r["lp"]) for r in top})
    base_end, score_end = math.log10((ends + 0.5) / rare), math.log10(p_end)
    schema = "row long, doc_id long, held_out boolean, n_tokens long, n_known long, base double, lp double, words array<binary>, times array<long>"
    kinds_of = [pa.int64(), pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.list_(pa.binary()), pa.list_(pa.int64())]
    names = [x.split()[0] for x in schema.split(", ")]

    def look_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, row = frequent.value, TaskContext.get().partitionId() << 40
        for batch in batches:
            out = [[] for _ in names]
            for doc_id, held, text in zip(*(batch.column(i).to_pylist() for i in range(3))):
                n = n_known = 0
                base = lp = 0.0
                other, times = [], []
                for w, k in Counter(lowered(text)).items():
                    n += k
                    found = known.get(w)
                    if found:
                        n_known += k
                        base += k * found[0]
                        lp += k * found[1]
                    else:
                        other.append(w)
                        times.append(k)
                for column, value in zip(out, (row, doc_id, held, n + 1, n_known + (ends > 0), base + base_end, lp + score_end, other, times)):
                    column.append(value)
                row += 1
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, kinds_of)], names)

    parts = written(rows.mapInArrow(frugal(look_up), schema), "document-parts")
    tail = parts.select("row", F.explode(F.arrays_zip("words", "times")).alias("x")).select("row", F.col("x.words").alias("word"), F.col("x.times").alias("k"))
    tail = tail.join(lexicon, "word").groupBy("row").agg(F.sum(F.col("k") * F.col("known")).alias("k1"), F.sum(F.col("k") * F.col("base")).alias("b1"), F.sum(F.col("k") * F.col("lp")).alias("s1"))
    none = F.lit(0)
    return parts.drop("words", "times").join(tail, "row", "left").select(
        "doc_id",
        "held_out",
        "n_tokens",
        (F.col("n_known") + F.coalesce("k1", none)).alias("n_known"),
        F.lit(int(train_tokens)).cast("long").alias("train_tokens"),
        (F.col("base") + F.coalesce("b1", none)).alias("base_score"),
        (F.col("lp") + F.coalesce("s1", none)).alias("score"),
    )
