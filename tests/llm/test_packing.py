import random
import zlib
from collections import Counter

import numpy as np
import pytest

from chapterforge.llm import packing
from chapterforge.llm.tokens import WordIds, tokenizer_path


def used(histogram, plan, capacity):
    held = Counter()
    for items, times in plan:
        assert sum(items) <= capacity
        for p in items:
            held[p] += times
    assert held == Counter({k: v for k, v in histogram.items() if v})
    return sum(t for _, t in plan)


def one_by_one(histogram, capacity):
    """Best-fit-decreasing, piece by piece."""
    rooms = []
    for length in sorted((x for k, v in histogram.items() for x in [k] * v), reverse=True):
        fits = [r for r in rooms if r >= length]
        room = min(fits) if fits else capacity
        if fits:
            rooms.remove(room)
        rooms.append(room - length)
    return len(rooms)


@pytest.mark.parametrize("capacity,n,most", [(10, 6, 10), (20, 15, 20), (50, 60, 50), (100, 300, 40), (1000, 400, 900)])
def test_plans(capacity, n, most):
    for seed in range(5):
        rng = random.Random(seed)
        h = Counter(rng.randint(1, most) for _ in range(n))
        fit = used(h, packing.best_fit_plan(h, capacity), capacity)
        assert fit == one_by_one(h, capacity)
        assert packing.fewest(h, capacity) <= used(h, packing.completion_plan(h, capacity), capacity) <= fit


def optimum(histogram, capacity):
    """The fewest sequences, by trying all ways."""
    items = sorted((x for k, v in histogram.items() for x in [k] * v), reverse=True)
    n = -(-sum(items) // capacity)
    while True:
        rooms = [capacity] * n

        def go(i, rooms=rooms):
            if i == len(items):
                return True
            for j in {r: j for j, r in enumerate(rooms) if r >= items[i]}.values():
                rooms[j] -= items[i]
                if go(i + 1):
                    return True
                rooms[j] += items[i]
            return False

        if go(0):
            return n
        n += 1


def test_completion_is_minimal():
    wins = 0
    for seed in range(120):
        rng = random.Random(seed)
        capacity = rng.choice([20, 50, 100])
        h, report = Counter(rng.randint(max(1, capacity // 8), capacity // 2 + 3) for _ in range(rng.randint(5, 12))), {}
        found = used(h, packing.completion_plan(h, capacity, report=report), capacity)
        assert found == optimum(h, capacity) and report["proven"]
        wins += found < used(h, packing.best_fit_plan(h, capacity), capacity)
    assert wins >= 3


def test_completion_beats_best_fit():
    h = {8: 1, 4: 2, 5: 3, 13: 1, 2: 1, 3: 1, 10: 1}  # best fit needs four, three suffice
    assert used(h, packing.best_fit_plan(h, 20), 20) == 4 and used(h, packing.completion_plan(h, 20), 20) == 3
    rng = random.Random(1)
    h = Counter(rng.randint(40, 400) for _ in range(400))  # many pieces a sequence
    assert used(h, packing.completion_plan(h, 1000), 1000) == packing.fewest(h, 1000) < used(h, packing.best_fit_plan(h, 1000), 1000)
    assert packing.completion_plan({}, 10) == [] and packing.best_fit_plan({}, 10) == []


def test_budget_keeps_best_fit():
    rng, report = random.Random(0), {}
    h = Counter(rng.randint(100, 700) for _ in range(300))
    plan = packing.completion_plan(h, 1000, budget=3, report=report)
    assert used(h, plan, 1000) <= used(h, packing.best_fit_plan(h, 1000), 1000) and report["nodes"] <= 3


def test_fillings_are_the_undominated_ones():
    for seed in range(60):
        rng = random.Random(seed)
        h, room = Counter(rng.randint(1, 12) for _ in range(7)), 15
        lengths = sorted(h)
        every = {()}
        for x in (x for k, v in h.items() for x in [k] * v):
            every |= {tuple(sorted((*s, x), reverse=True)) for s in every if sum(s) + x <= room}
        got = list(packing.fillings(room, lengths, [h[x] for x in lengths], room))
        assert [w for w, _ in got] == sorted(w for w, _ in got) and len({s for _, s in got}) == len(got)
        assert {s for _, s in got} <= every and all(room - sum(s) == w for w, s in got)

        def beaten(s):
            spare = [x for x in h if h[x] > Counter(s)[x]]
            parts = {()}
            for x in s:
                parts |= {(*p, x) for p in parts}
            return any(sum(p) <= x <= sum(p) + room - sum(s) and p != (x,) for p in parts if p for x in spare) or any(x <= room - sum(s) for x in spare)

        assert {s for _, s in got} >= {s for s in every if not beaten(s)}


def test_ids_are_the_tokenizers():
    words = WordIds(tokenizer_path(), most_bytes=300_000, stretch=5000)
    texts = ["", " ", "Don't, I'll.", "a\x1cb", "cafe\u0301 naïve!!", "<|endoftext|> x<|endoftext|>", "ΑΣ ΟΔΟΣ.", "İ K ſ", "x " * 3000, *(f"w{i} Ab{i}, c.d" for i in range(2500))]
    got = words.batch(texts) + words.batch(texts[:5])
    want = [words.tokenizer.encode(t, add_special_tokens=False).ids for t in texts + texts[:5]]
    assert [np.frombuffer(b, "<u4").tolist() for b in got] == want


ROWS = [(1, "one two three", "x"), (2, None, "x"), (3, "", None), (1, "one two three", "x"), (None, "hello there", "x"), (4, "word " * 10000, "x"), (5, "tie", "x"), (6, "tie", "x")]


def frame(spark, rows=ROWS):
    return spark.createDataFrame(rows, "doc_id long, text string, length string")  # a name that clashes


def test_pack_documents(spark):
    got = packing.pack_documents(frame(spark)).collect()
    words = WordIds(tokenizer_path())
    ids = {i: words.batch([t])[0] for i, t in enumerate(["word " * 10000])}
    assert sum(r["length"] for r in got) == sum(len(words.batch([t or ""])[0]) // 4 + 1 for _, t, _ in ROWS)
    by = {}
    for r in got:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for spans in by.values():
        at = 0
        for offset, length in sorted(spans):
            assert offset == at
            at += length
        assert at <= 4096
    cut = sorted((r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in got if r["doc_id"] == 4)
    whole = ids[0] + (1).to_bytes(4, "little")
    assert [c[:3] for c in cut] == [(0, 0, 4096), (1, 4096, 4096), (2, 8192, len(whole) // 4 - 8192)]
    assert all(zlib.crc32(whole[4 * s : 4 * (s + n)]) == c for _, s, n, c in cut)
    assert packing.pack_documents(frame(spark, [])).count() == 0


def test_matrix_round_trip(spark, tmp_path):
    packed = packing.packed_matrix(frame(spark))
    seen = {}
    for r in packing.positions(packed).collect():
        ids = np.frombuffer(r["ids"], "<u4")
        assert len(ids) == r["n_tokens"] == r["cu_seqlens"][-1] and r["cu_seqlens"][:-1] == r["position_resets"]
        assert r["position_ids"] == [i for a, b in zip(r["cu_seqlens"], r["cu_seqlens"][1:]) for i in range(b - a)]
        for d, p, a, b in zip(r["doc_ids"], r["pieces"], r["cu_seqlens"], r["cu_seqlens"][1:]):
            seen.setdefault((d, p), []).append(ids[a:b].tolist())
    words = WordIds(tokenizer_path())
    whole = np.frombuffer(words.batch(["word " * 10000])[0], "<u4").tolist() + [1]
    assert sum((seen[4, p][0] for p in range(3)), []) == whole
    packing.write_matrix(packed, str(tmp_path / "m"))
    import pyarrow.parquet as pq

    assert packing.read_matrix(pq.read_table(str(tmp_path / "m"))).shape == (packed.count(), 4096)


def segments_are_gapless(rows):
    by = {}
    for sequence, offset, length in rows:
        by.setdefault(sequence, []).append((offset, length))
    for spans in by.values():
        at = 0
        for offset, length in sorted(spans):
            assert offset == at
            at += length
        assert at <= 4096
    return len(by)


def test_whole_table(spark, data):
    """Every piece of every document once, with its crc, and rows of the matrix that give all ids back."""
    docs = spark.read.parquet(f"{data}/documents.parquet")
    edges = [(10**6, "word " * 4095, 1), (10**6 + 1, "word " * 4096, 1), (10**6 + 2, "word " * 8191, 1), (10**6 + 3, None, 1)] + [(10**6 + 4, "same length", k) for k in range(50)]
    docs = docs.select("doc_id", "text", "n_chars").unionByName(spark.createDataFrame(edges, "doc_id long, text string, n_chars long"))
    words, want = WordIds(tokenizer_path()), Counter()
    for r in docs.collect():
        ids = words.tokenizer.encode(r["text"] or "", add_special_tokens=False).ids + [1]
        for k, at in enumerate(range(0, len(ids), 4096)):
            raw = np.array(ids[at : at + 4096], "<u4").tobytes()
            want[r["doc_id"], k, at, len(raw) // 4, zlib.crc32(raw)] += 1
    got = packing.pack_documents(docs).collect()
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in got) == want
    sequences = segments_are_gapless((r["sequence_id"], r["offset"], r["length"]) for r in got)
    h = Counter(r["length"] for r in got)
    assert packing.fewest(h) <= sequences <= used(h, packing.best_fit_plan(h), 4096)
    matrix = packing.packed_matrix(docs).collect()
    spans = [(r["sequence_id"], a, b - a, d, p, zlib.crc32(r["ids"][4 * a : 4 * b])) for r in matrix for d, p, a, b in zip(r["doc_ids"], r["pieces"], r["cu_seqlens"], r["cu_seqlens"][1:])]
    assert Counter((d, p, n, c) for _, _, n, d, p, c in spans) == Counter((d, p, n, c) for d, p, _, n, c in want.elements())
    segments_are_gapless(x[:3] for x in spans)


def test_letters_go_to_the_model_alone():
    """New words of letters don't go through normal form and split; ids are the tokenizer's own. Other tokenizers take the whole way."""
    words = WordIds(tokenizer_path())
    through, encode = [], words._encode
    words._encode = lambda some: through.extend(some) or encode(some)
    rng = np.random.default_rng(3)
    letters = [chr(x) for x in (*range(0x61, 0x7B), *range(0xDF, 0xF7), *range(0xF8, 0x100))]
    made = ["".join(rng.choice(letters, rng.integers(1, 30))) for _ in range(9000)]
    texts = [" ".join(made), "".join(letters), "ÄÖÜSS Straße ÉTÉ! don't Œuvre ß", " ".join(w.upper() + "?!" for w in made[:500]), "x" * 5000]
    want = [words._whole(t) for t in texts]
    assert words.batch(texts) == want
    assert words.alone is not None and not set(made) & set(through)
    whole = WordIds(tokenizer_path())
    whole.alone = None
    assert whole.batch(texts) == want
    words = WordIds(tokenizer_path())
    words.last = np.zeros_like(words.last)  # as if no end were known
    assert words.batch(texts) == want
