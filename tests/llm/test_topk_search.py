"""op8: a shard's search in single precision, exact by scoring again."""

import numpy as np
import pyarrow as pa
import pytest

from chapterforge.llm import topk


def shard_of(held: list[np.ndarray], n: int, rng, lengths=None) -> tuple[topk.Shard, np.ndarray]:
    """A shard whose term i + 1 stands in the documents held[i]; its weights as a table, terms by documents."""
    kinds, places = np.arange(1, len(held) + 1, dtype=np.int64), np.concatenate(held).astype(np.int32)
    row = {
        "ids": list(range(n)), "lengths": (np.full(n, 12, np.int64) if lengths is None else lengths).tobytes(), "terms": kinds.tobytes(), "places": places.tobytes(),
        "ends": np.cumsum([len(h) for h in held]).astype(np.int64).tobytes(), "tfs": rng.integers(1, 4, len(places)).astype(np.int32).tobytes(),
    }
    shard = topk.Shard(row, 12.0)
    table = np.zeros((len(held), n))
    table[np.repeat(kinds - 1, [len(h) for h in held]), places] = shard.weight
    return shard, table


def agrees(shard, table, queries, k, floors):
    for (places, scores), (terms, weights), floor in zip(shard.search(queries, k, floors), queries, floors):
        want = np.round(weights @ table[terms - 1], 6)
        order = [i for i in np.lexsort((np.arange(len(want)), -want))[:k] if want[i] >= floor and want[i] > 0]
        assert places.tolist() == order and np.allclose(scores, want[order], rtol=0, atol=1.1e-6)


def test_a_block_holds_only_the_terms_it_has():
    """Two languages side by side: no block's matrix has rows for the other's words, and words of few postings are no rows at all."""
    rng, n = np.random.default_rng(2), 4 * topk.PLACES
    half = lambda low, p: low + np.flatnonzero(rng.random(n // 2) < p)
    held = [half(i % 2 * n // 2, p) for p in (0.5, 0.1, 0.01) for i in range(60)] + [np.sort(rng.choice(n, 3, replace=False)) for _ in range(40)]
    held = [h for h in held if len(h)]
    shard, table = shard_of(held, n, rng)
    assert shard.matrix.size <= 4 * 60 * topk.PLACES  # 60 of a language in each of four blocks; 220 terms in all
    queries = [(np.sort(rng.choice(len(held), s, replace=False)).astype(np.int64) + 1, rng.random(s) * 5) for s in rng.integers(1, 90, 60)]
    for k in (1, 10, n + 5):
        agrees(shard, table, queries, k, [0.0] * len(queries))
    tenth = [float(np.sort(np.round(w @ table[t - 1], 6))[-10]) for t, w in queries]
    agrees(shard, table, queries, 10, tenth)
    read, met = shard.postings_read, shard.postings_met
    assert 0 < read <= met


@pytest.mark.parametrize("full", [1, 10**6])
def test_scores_that_single_precision_cannot_tell_apart(monkeypatch, full):
    """Sums near 3,000 that differ by two millionths: single precision has steps of 0.0002 there. All postings frequent, then all rare."""
    monkeypatch.setattr(topk, "FULL", full)
    rng, n = np.random.default_rng(3), 300
    held = [np.arange(n)] * 3 + [np.array([d]) for d in range(n)]
    shard, table = shard_of(held, n, np.random.default_rng(3))
    wide = 1000.0 / table[:3].max()
    for _ in range(20):
        terms = np.arange(1, len(held) + 1, dtype=np.int64)
        # each document's own word brings it to the same sum, but for a few millionths
        base = wide * table[:3].sum(axis=0)
        own = (base.max() + 10 + rng.permutation(n) * 2e-6 - base) / table[np.arange(3, 3 + n), np.arange(n)]
        weights = np.concatenate([np.full(3, wide), own])
        agrees(shard, table, [(terms, weights)], 10, [0.0])
        agrees(shard, table, [(terms, weights)], 10, [float(np.sort(np.round(weights @ table, 6))[-4])])


def test_runs_may_be_empty():
    begin, end = np.array([5, 2, 7, 0, 9]), np.array([8, 2, 9, 3, 9])
    assert topk._runs(begin, end).tolist() == [5, 6, 7, 7, 8, 0, 1, 2] and topk._runs(begin[:0], end[:0]).tolist() == [] and topk._runs(begin[1:2], end[1:2]).tolist() == []


def test_alike_queries_are_side_by_side():
    rows = pa.table({
        "q": pa.array([7, 8, 9, 10], pa.int64()), "query_id": pa.array([1, None, 3, 0], pa.int64()),
        "term": pa.array([[5, 6, 9], [2, 9], [4, 6], [2]], pa.list_(pa.int64())), "w": pa.array([[3.0, 0.5, 4.0], [0.25, 4.0], [2.0, 0.5], [0.25]], pa.list_(pa.float64())),
    })
    queries, vocabulary, idf = topk._asked(pa.concat_tables([rows.slice(0, 1), rows.slice(1)]))
    assert [x[0] for x in queries] == [10, 8, 9, 7] and [x[1] for x in queries] == [0, None, 3, 1]
    assert [vocabulary[x[2]].tolist() for x in queries] == [[2], [2, 9], [4, 6], [5, 6, 9]]
    assert dict(zip(vocabulary.tolist(), idf.tolist())) == {2: 0.25, 4: 2.0, 5: 3.0, 6: 0.5, 9: 4.0}
    assert topk._asked(rows.slice(0, 0))[0] == []
