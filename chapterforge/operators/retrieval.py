"""Sparse and dense ranking of a pool for a set of questions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.text import tokens


class TextIndex:
    """postings (id, term, tf), lengths (id, len), terms (term, df), pool size and mean length."""

    def __init__(self, postings: DataFrame, lengths: DataFrame):
        self.postings, self.lengths = postings, lengths
        self.terms = postings.groupBy("term").agg(F.count("*").alias("df"))
        self.size, mean = lengths.agg(F.count("*"), F.avg("len")).first()
        self.mean = mean or 1.0


def build_text_index(pool: DataFrame, path: str | None = None, append: bool = False) -> TextIndex:
    """pool: id, text. With a path, postings are written by term bucket and can be appended to."""
    words = pool.select("id", tokens(F.col("text")).alias("tokens"))
    postings = words.select("id", F.explode("tokens").alias("term")).groupBy("id", "term").agg(F.count("*").alias("tf"))
    lengths = words.select("id", F.size("tokens").cast("long").alias("len"))
    if path:
        mode, spark = "append" if append else "overwrite", pool.sparkSession
        postings.withColumn("bucket", F.pmod(F.xxhash64("term"), F.lit(64)).cast("int")).write.mode(mode).partitionBy("bucket").parquet(f"{path}/postings")
        lengths.write.mode(mode).parquet(f"{path}/lengths")
        postings, lengths = spark.read.parquet(f"{path}/postings").drop("bucket"), spark.read.parquet(f"{path}/lengths")
    return TextIndex(postings, lengths)


def bm25_rank(questions: DataFrame, pool: DataFrame | TextIndex, k: int | None = 10, k1: float = 1.2, b: float = 0.75, score: str = "bm25") -> DataFrame:
    """q_id, id, score (6 digits), rank; ties by id. questions: q_id, text; pool: id, text.

    Equi-joins on terms; question terms are joined with document frequencies first, so that only their postings move.
    score cosine_sparse: the cosine of tf-idf vectors instead.
    """
    index = pool if isinstance(pool, TextIndex) else build_text_index(pool)
    wanted = questions.select("q_id", F.explode(F.array_distinct(tokens(F.col("text")))).alias("term"))
    terms = wanted.select("term").distinct().join(index.terms, "term")
    idf = F.log(1 + (index.size - F.col("df") + 0.5) / (F.col("df") + 0.5))
    postings = index.postings.join(terms, "term").join(index.lengths, "id")
    if score == "bm25":
        weight = idf * F.col("tf") * (k1 + 1) / (F.col("tf") + k1 * (1 - b + b * F.col("len") / F.lit(float(index.mean))))
        hits = wanted.join(postings.select("id", "term", weight.alias("w")), "term")
        scored = hits.groupBy("q_id", "id").agg(F.round(F.sum("w"), 6).alias("score"))
    else:
        norms = index.postings.join(index.terms, "term").groupBy("id").agg(F.sqrt(F.sum(F.pow(F.col("tf") * idf, 2))).alias("norm"))
        asked = wanted.join(terms, "term").select("q_id", "term", idf.alias("qw"))
        lengths = asked.groupBy("q_id").agg(F.sqrt(F.sum(F.pow("qw", 2))).alias("q_norm"))
        hits = asked.join(postings.select("id", "term", (F.col("tf") * idf).alias("w")), "term")
        scored = hits.groupBy("q_id", "id").agg(F.sum(F.col("qw") * F.col("w")).alias("dot")).join(norms, "id").join(lengths, "q_id")
        scored = scored.select("q_id", "id", F.round(F.col("dot") / (F.col("norm") * F.col("q_norm")), 6).alias("score"))
    return ranked(scored, k)


def ranked(scored: DataFrame, k: int | None) -> DataFrame:
    place = F.row_number().over(W.partitionBy("q_id").orderBy(F.desc("score"), "id"))
    out = scored.withColumn("rank", place)
    return out.filter(F.col("rank") <= k) if k else out


def dense_rank(q_vecs: DataFrame, t_vecs: DataFrame, k: int = 1, block_rows: int = 2000, pool_rows: int = 20000) -> DataFrame:
    """q_id, id, score (cosine of unit vectors, 6 digits), rank; ties by id. Exact.

    Questions are dealt into blocks of about ``block_rows`` by a hash, the pool into blocks of about ``pool_rows``. A task multiplies one
    of each and keeps each question's k best there, so every block of the pool meets every block of questions once, whatever
    their number, and nothing but two counts reaches the driver. Vectors move as often as the other side has blocks.
    """
    return ranked(_by_blocks(q_vecs, t_vecs, _best_of_blocks(k), block_rows, pool_rows), k)


def _by_blocks(q_vecs: DataFrame, t_vecs: DataFrame, best, block_rows: int, pool_rows: int) -> DataFrame:
    """What ``best`` gives for each block of questions with each block of the pool, a task each."""
    q_blocks, t_blocks = (max(1, -(-df.count() // rows)) for df, rows in ((q_vecs, block_rows), (t_vecs, pool_rows)))
    dealt = lambda name, blocks: F.pmod(F.xxhash64(name), F.lit(blocks)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    asked = q_vecs.select("q_id", "embedding", dealt("q_id", q_blocks).alias("q_block"), every(t_blocks).alias("t_block"))
    held = t_vecs.select("id", "embedding", dealt("id", t_blocks).alias("t_block"), every(q_blocks).alias("q_block"))
    return asked.groupBy("q_block", "t_block").cogroup(held.groupBy("q_block", "t_block")).applyInPandas(best, _found(q_vecs, t_vecs))


def _found(q_vecs: DataFrame, t_vecs: DataFrame) -> str:
    return f"q_id {q_vecs.schema['q_id'].dataType.simpleString()}, id {t_vecs.schema['id'].dataType.simpleString()}, score double"


def _best_of_blocks(k: int, together: int = 256):
    """For ``cogroup``: each question's k best of a block of the pool, by one matrix product for ``together`` questions."""
    import numpy as np
    import pandas as pd

    def best(questions, pool):
        ids, names, scores = [], [], []
        if len(questions) and len(pool):
            q_ids, t_ids = questions["q_id"].to_numpy(), pool["id"].to_numpy()
            q, t = (np.vstack(x["embedding"].to_numpy()).astype(float) for x in (questions, pool))
            for at in range(0, len(q), together):
                s = np.round(q[at : at + together] @ t.T, 6)
                least = np.partition(s, -k, axis=1)[:, -k] if s.shape[1] > k else np.full(len(s), -np.inf)
                for i, row in enumerate(s):
                    top = np.flatnonzero(row >= least[i])  # the k best and what ties with the last
                    top = top[np.lexsort((t_ids[top], -row[top]))[:k]]
                    ids.append(np.repeat(q_ids[at + i], len(top)))
                    names.append(t_ids[top])
                    scores.append(row[top])
        flat = lambda x: np.concatenate(x) if x else []
        return pd.DataFrame({"q_id": flat(ids), "id": flat(names), "score": flat(scores)})

    return best


def dense_rank_sql(q_vecs: DataFrame, t_vecs: DataFrame, k: int = 1) -> DataFrame:
    """The same by expressions alone, for question sets small enough to broadcast."""
    dot = F.aggregate(F.zip_with("embedding", "q_embedding", lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda a, x: a + x)
    pairs = t_vecs.crossJoin(F.broadcast(q_vecs.select("q_id", F.col("embedding").alias("q_embedding"))))
    return ranked(pairs.select("q_id", "id", F.round(dot, 6).alias("score")), k)


def ivf_rank(q_vecs: DataFrame, t_vecs: DataFrame, k: int = 1, lists: int = 16, probes: int = 4, seed: int = 3, pool_rows: int = 20000) -> DataFrame:
    """Inverted lists over k-means centres: a question looks into its ``probes`` nearest lists alone.

    A list is dealt into parts of about ``pool_rows``; a task multiplies the questions that look into a list with one part of it.
    """
    import numpy as np
    import pandas as pd
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    as_vector = lambda df: df.withColumn("v", array_to_vector("embedding"))
    model = KMeans(k=lists, seed=seed, featuresCol="v", predictionCol="list", maxIter=10).fit(as_vector(t_vecs))
    centres = np.array([c / max(np.linalg.norm(c), 1e-12) for c in model.clusterCenters()])
    held = model.transform(as_vector(t_vecs)).select("id", "embedding", "list")
    sizes = {r["list"]: r["count"] for r in held.groupBy("list").count().collect()}  # a row a list
    parts = F.get(F.array(*[F.lit(max(1, -(-sizes.get(i, 0) // pool_rows))) for i in range(len(centres))]), "list")

    def nearest(batches):
        for batch in batches:
            if len(batch):
                close = np.round(np.vstack(batch["embedding"].to_numpy()).astype(float) @ centres.T, 6)
                for at in np.argsort(-close, axis=1, kind="stable")[:, :probes].T:
                    yield pd.DataFrame({"q_id": batch["q_id"], "embedding": batch["embedding"], "list": at.astype("int32")})

    asked = q_vecs.select("q_id", "embedding")
    asked = asked.mapInPandas(nearest, asked.schema.simpleString()[7:-1].replace(":", " ") + ", list int")
    asked = asked.select("*", F.explode(F.sequence(F.lit(0), parts - 1)).alias("part"))
    held = held.withColumn("part", F.pmod(F.xxhash64("id"), parts).cast("int"))
    found = asked.groupBy("list", "part").cogroup(held.groupBy("list", "part")).applyInPandas(_best_of_blocks(k), _found(q_vecs, t_vecs))
    return ranked(found, k)


def lsh_rank(q_vecs: DataFrame, t_vecs: DataFrame, k: int = 1, tables: int = 12, bits: int = 8, seed: int = 5, block_rows: int = 2000, pool_rows: int = 20000) -> DataFrame:
    """Sign hashes: vectors that share one of ``tables`` keys of ``bits`` signs are compared, in blocks as ``dense_rank`` has them."""
    return ranked(_by_blocks(q_vecs, t_vecs, _best_of_keys(k, tables, bits, seed), block_rows, pool_rows), k)


def _best_of_keys(k: int, tables: int, bits: int, seed: int, together: int = 64):
    """For ``cogroup``: each question's k best among those of a block of the pool that share a key with it."""
    import numpy as np
    import pandas as pd

    def best(questions, pool):
        out = []
        if len(questions) and len(pool):
            q_ids, t_ids = questions["q_id"].to_numpy(), pool["id"].to_numpy()
            q, t = (np.vstack(x["embedding"].to_numpy()).astype(float) for x in (questions, pool))
            planes = np.random.default_rng(seed).standard_normal((tables * bits, q.shape[1]))
            q_keys, t_keys = (((x @ planes.T >= 0).reshape(len(x), tables, bits) @ (1 << np.arange(bits))).T for x in (q, t))
            order = [np.argsort(keys, kind="stable") for keys in t_keys]
            kept = [keys[o] for keys, o in zip(t_keys, order)]
            for at in range(0, len(q), together):
                shares = np.zeros((len(q[at : at + together]), len(t)), dtype=bool)
                for keys, o, mine in zip(kept, order, q_keys[:, at : at + together]):
                    for i, (a, b) in enumerate(zip(np.searchsorted(keys, mine), np.searchsorted(keys, mine, "right"))):
                        shares[i, o[a:b]] = True
                for i, row in enumerate(shares):
                    some = np.flatnonzero(row)
                    s = np.round(t[some] @ q[at + i], 6)
                    top = np.lexsort((t_ids[some], -s))[:k]
                    out.append(pd.DataFrame({"q_id": np.repeat(q_ids[at + i], len(top)), "id": t_ids[some[top]], "score": s[top]}))
        return pd.concat(out) if out else pd.DataFrame({"q_id": [], "id": [], "score": []})

    return best


def hash_encode(texts: DataFrame, dim: int = 64, seed: int = 1) -> DataFrame:
    """id, embedding: hashed term counts with random signs, unit length; stands for a trained encoder."""
    h = F.xxhash64("term", F.lit(seed))
    counts = texts.select("id", F.explode(tokens(F.col("text"))).alias("term")).groupBy("id", "term").agg(F.count("*").alias("tf"))
    cells = counts.groupBy("id", F.pmod(h, F.lit(dim)).cast("int").alias("cell")).agg(F.sum(F.when(F.pmod(F.shiftright(h, 20), F.lit(2)) == 0, F.col("tf")).otherwise(-F.col("tf"))).cast("double").alias("v"))
    held = cells.groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("cell", "v"))).alias("m"), F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("norm"))
    value = lambda i: (F.coalesce(F.element_at("m", i), F.lit(0.0)) / F.greatest(F.col("norm"), F.lit(1e-12))).cast("float")
    return held.select("id", F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), value).alias("embedding"))


def top1_as_set(ranks: DataFrame) -> DataFrame:
    return ranks.filter("rank = 1").select("q_id", F.array("id").alias("predicted"))


def candidate_recall(ranks: DataFrame, gold: DataFrame, k: int = 10) -> DataFrame:
    """questions, top1 (share with gold first), recall (in the first k), mean reciprocal rank. gold: q_id, id."""
    best = ranks.filter(F.col("rank") <= k).join(gold, ["q_id", "id"]).groupBy("q_id").agg(F.min("rank").alias("rank"))
    every = gold.select("q_id").distinct().join(best, "q_id", "left")
    top1 = F.avg(F.coalesce(F.col("rank") == 1, F.lit(False)).cast("double")).alias("top1")
    return every.agg(F.count("*").alias("questions"), top1, F.avg(F.col("rank").isNotNull().cast("double")).alias("recall"), F.avg(F.coalesce(1 / F.col("rank"), F.lit(0.0))).alias("mrr"))


def cutoff_sets(ranks: DataFrame, policy: str = "fixed", k: int = 3, share: float = 0.5) -> DataFrame:
    """Sets where the size is not known: the first k; scores of at least a share of the best; all before the largest gap."""
    q = W.partitionBy("q_id")
    if policy == "fixed":
        kept = ranks.filter(F.col("rank") <= k)
    elif policy == "threshold":
        kept = ranks.withColumn("top", F.max("score").over(q)).filter(F.col("score") >= share * F.col("top"))
    elif policy == "gap":
        gap = ranks.withColumn("gap", F.col("score") - F.lead("score").over(q.orderBy("rank")))
        cut = gap.groupBy("q_id").agg(F.coalesce(F.max_by("rank", F.struct(F.col("gap"), -F.col("rank"))), F.lit(1)).alias("cut"))
        kept = gap.join(cut, "q_id").filter(F.col("rank") <= F.col("cut"))
    else:
        raise ValueError(f"unknown policy {policy!r}")
    return kept.groupBy("q_id").agg(F.array_sort(F.collect_list("id")).alias("predicted"))  # a ranking's length at most
