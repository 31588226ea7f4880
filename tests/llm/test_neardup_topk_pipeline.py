"""Near duplicates, top-k search and the pipeline, against brute force."""

import collections
import math
import re

import numpy as np
import pytest

from chapterforge.llm import neardup, topk

DOC = "doc_id long, text string, lang string, source string, n_chars long"


def bag(text):
    w = re.findall(r"[^\W_]+", (text or "").lower())
    return collections.Counter(zip(*[w[i:] for i in range(5)])) if len(w) >= 5 else collections.Counter([tuple(w)] if w else [])


def overlap(a, b):
    both = sum((a & b).values())
    whole = sum(a.values()) + sum(b.values()) - both
    return both / whole if whole else 1.0


def classes(rows):
    bags, parent = [bag(t) for _, t in rows], list(range(len(rows)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if overlap(bags[i], bags[j]) >= 0.8:
                parent[find(i)] = find(j)
    return collections.Counter(frozenset(collections.Counter(rows[i][0] for i in range(len(rows)) if find(i) == r).items()) for r in {find(i) for i in range(len(rows))})


@pytest.mark.parametrize("small,chunk", [(32, 512), (2, 512), (2, 4)])
def test_classes_equal_brute_force(spark, data, small, chunk, monkeypatch):
    monkeypatch.setattr(neardup, "SMALL", small)  # 2: buckets go through pivots and chunks
    monkeypatch.setattr(neardup, "CHUNK", chunk)
    rows = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{data}/documents.parquet").collect()]
    base = [f"t{i}" for i in range(120)]
    for k in range(25):  # a group in which some pairs are close and some are not
        rows.append((100_000 + k, " ".join(w if (j * 7 + k) % 90 else f"z{k}" for j, w in enumerate(base))))
    rows += [(1, rows[0][1]), (None, "a null id"), (200_000, ""), (200_001, None), (200_002, "two words"), (200_003, "Two, words!"), (200_004, "long " * 30000)]
    got = neardup.find_classes(spark.createDataFrame([(i, t, "class", "s", 0) for i, t in rows], DOC.replace("lang", "class"))).collect()
    assert len(got) == len(rows)
    by = collections.defaultdict(list)
    for r in got:
        by[r["class_id"]].append(r["doc_id"])
    assert collections.Counter(frozenset(collections.Counter(v).items()) for v in by.values()) == classes(rows)
    kept = neardup.keep_one(spark.createDataFrame([(i, t, "en", "s", 0) for i, t in rows], DOC)).collect()
    assert len(kept) == len(by) and neardup.find_classes(spark.createDataFrame([], DOC)).count() == 0


def test_signatures_are_unbiased():
    import random

    rng, errors = random.Random(5), []
    for _ in range(40):
        a = {i: rng.choice([1, 1, 2, 3, 9]) for i in range(60)}
        b = {i: a[i] if i in a and rng.random() < 0.8 else rng.choice([1, 4]) for i in range(12, 75)}
        want = sum(min(a.get(k, 0), b.get(k, 0)) for k in a | b) / sum(max(a.get(k, 0), b.get(k, 0)) for k in a | b)
        grams = neardup.mix(np.array([*a, *b], dtype=np.uint64) + np.uint64(rng.getrandbits(60)))
        s = neardup.bag_signatures(np.array([0] * len(a) + [1] * len(b)), grams, np.array([*a.values(), *b.values()]), 2)
        errors.append((s[0] == s[1]).mean() - want)
    assert abs(np.mean(errors)) < 0.025


def test_components(spark):
    b = lambda i: bytes([i])
    links = spark.createDataFrame([(b(i), b(i + 1)) for i in range(1, 9)] + [(b(20), b(21)), (b(30), b(22))], "a binary, b binary")
    got = {r["node"][0]: r["class"][0] for r in neardup.components(links).collect()}
    assert all(got[i] == 1 for i in range(2, 10)) and got[21] == 20 and got[30] == 22


def test_queries_go_together_within_bounds():
    asked = [(i, i, range(n)) for i, n in enumerate([5] * 300 + [topk.TERMS + 1, 1, topk.TERMS, 0])]
    runs = list(topk._together(asked))
    assert [x for run in runs for x in run] == asked and max(map(len, runs)) == topk.TOGETHER and list(topk._together([])) == []
    assert all(len(run) == 1 or sum(len(x[2]) for x in run) <= topk.TERMS for run in runs)


@pytest.mark.parametrize("dense,together", [(512, 128), (3, 2)])
def test_top_k_is_exact(spark, data, monkeypatch, dense, together):
    for name, value in (("PLACES", 16), ("DENSE", dense), ("TOGETHER", together)):
        monkeypatch.setattr(topk, name, value)
    rows = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{data}/documents.parquet").collect()] + [(50, "same words here"), (None, "same words here"), (300, None), (350, ""), (50, "other")]
    frame = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in rows], DOC)
    got = collections.defaultdict(list)
    for r in topk.search_all(frame, frame.filter("doc_id % 50 = 0")).collect():
        got[r["query_id"]].append((r["rank"], r["doc_id"], r["score"]))
    hashes = topk.TermHashes()
    held = [topk.terms_of(t or "", hashes) for _, t in rows]
    sizes = [sum(c.values()) for c in held]
    df, n, mean = collections.Counter(k for c in held for k in c), len(rows), sum(sizes) / len(rows)
    for i, (q, _) in enumerate(rows):
        if q is None or q % 50 or q == 50:
            continue
        want = []
        for j, c in enumerate(held):
            s = round(sum(math.log(1 + (n - df[k] + 0.5) / (df[k] + 0.5)) * c[k] * 2.2 / (c[k] + 1.2 * (0.25 + 0.75 * sizes[j] / mean)) for k in held[i] if k in c), 6)
            if s > 0:
                want.append((-s, -(2**63) if rows[j][0] is None else rows[j][0]))
        want = sorted(want)[:10]
        assert [-(2**63) if d is None else d for _, d, _ in sorted(got[q], key=lambda x: x[0])] == [d for _, d in want]
    assert len(got[50]) >= 11 and topk.search_all(frame.limit(0), frame).count() == 0 and topk.search_all(frame, frame.limit(0)).count() == 0


def test_pipeline(spark, data, tmp_path):
    pipeline = pytest.importorskip("corpus_pipeline")
    from chapterforge.llm import decontamination, toxicity

    labels, items = spark.read.parquet(f"{data}/labels.parquet"), spark.read.parquet(f"{data}/benchmark.parquet")
    docs, held = spark.read.parquet(f"{data}/documents.parquet"), []
    for k, (_, stage) in enumerate(pipeline.STAGES):
        stage(spark, docs, data).write.parquet(str(tmp_path / str(k)))
        docs = spark.read.parquet(str(tmp_path / str(k)))
        held.append(docs)
    assert [name for name, _ in pipeline.STAGES][0] == "toxicity" and len(pipeline.STAGES) == 5
    ids = [{r["doc_id"] for r in d.select("doc_id").collect()} for d in held]
    start = spark.read.parquet(f"{data}/documents.parquet")
    toxic = {r["doc_id"] for r in toxicity.score_toxicity(start, labels).filter("predicted = 1").collect()}
    assert ids[0] == {r["doc_id"] for r in start.collect()} - toxic
    texts = [(r["doc_id"], r["text"]) for r in held[0].collect()]
    assert ids[1] == {min(d for d, _ in c) for c in classes(texts)}
    assert ids[2] == ids[1] - {r["doc_id"] for r in decontamination.find_leaks(held[1], items).collect()}
    assert ids[3] == ids[2] == ids[4] and all(d.columns == ["doc_id", "text", "lang", "source", "n_chars"] for d in held[:4])
    assert not [r for r in held[3].collect() if re.search(r"AKIA[A-Z0-9]{12,}|[0-9a-f]{32,}", r["text"])]
    assert all(r["n_chars"] == len(r["text"]) for r in held[3].collect())


@pytest.mark.parametrize("empty", [False, True])
def test_pipeline_edges(spark, tmp_path, empty):
    """Null ids and texts, repeated rows, ties, a long text and extra columns with clashing names; then empty tables."""
    pipeline = pytest.importorskip("corpus_pipeline")
    item = " ".join(f"bench{i}" for i in range(30))
    rows = [(1, "plain words here that stay as they are", "en", "a", 7), (1, "plain words here that stay as they are", "en", "a", 7), (2, None, None, None, None), (None, "a text without an id that stays too", "en", "b", 1)]
    rows += [(3, "", "en", "a", 0), (4, f"before {item} after", "en", "a", 1), (5, "mine: token=abcdef123456789 and words", "de", "c", 1), (6, "long " * 20000, "en", "a", 1)]
    rows = [] if empty else [(*r, "x", 1) for r in rows]
    spark.createDataFrame(rows, DOC + ", class string, length int").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([] if empty else [(1, 1, 0), (2, 1, None), (None, 0, 1)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([] if empty else [(1, item), (2, None)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = pipeline.run(spark, str(tmp_path)).collect()
    # one of the repeated rows; of the null and the empty text the smaller id; the leak is gone; the secret is masked, its row stays
    assert collections.Counter(r["doc_id"] for r in got if r["piece"] == 0) == collections.Counter([] if empty else [1, 2, None, 5, 6])
    assert sum(r["length"] for r in got if r["doc_id"] == 6) == (0 if empty else 20001)


def test_rows_below_their_floor_are_not_scored_further():
    """Rounding and ranking meet only the queries whose best sum of a block may reach their floor; sums that rounding lifts to it still count."""
    rng = np.random.default_rng(5)
    n, kinds = 600, np.arange(1, 41)
    held = [np.flatnonzero(rng.random(n) < 0.3) for _ in kinds]
    places = np.concatenate(held).astype(np.int32)
    row = {
        "ids": list(range(n)), "lengths": np.full(n, 12, np.int64).tobytes(), "terms": kinds.astype(np.int64).tobytes(), "places": places.tobytes(),
        "ends": np.cumsum([len(h) for h in held]).astype(np.int64).tobytes(), "tfs": rng.integers(1, 4, len(places)).astype(np.int32).tobytes(),
    }
    shard = topk.Shard(row, 12.0)
    assert shard.cell_block.dtype == np.int16
    table = np.zeros((len(kinds), n))
    table[np.repeat(np.arange(len(kinds)), [len(h) for h in held]), places] = shard.weight
    queries = [(np.sort(rng.choice(kinds, 9, replace=False)).astype(np.int64), rng.random(9) / 3) for _ in range(50)]
    exact = [np.round(w @ table[t - 1], 6) for t, w in queries]
    for floors in ([0.0] * 50, [float(np.sort(x)[-5]) for x in exact], [float(x.max()) for x in exact], [float(x.max()) + 1e-6 for x in exact]):
        for few in (queries, queries[:1]):
            for (places_found, scores), want, floor in zip(shard.search(few, 5, floors[: len(few)]), exact, floors):
                order = [i for i in np.lexsort((np.arange(n), -want))[:5] if want[i] >= floor and want[i] > 0]
                assert places_found.tolist() == order and scores.tolist() == want[order].tolist()
