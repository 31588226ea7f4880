"""Packing of tokenized documents into sequences of a fixed number of tokens.

Two planners over the histogram of piece lengths: best-fit-decreasing with a segment tree over free capacity
(``best_fit_plan``) and bin completion by branch and bound (``completion_plan``). A plan is a list of
patterns, each with the lengths that one sequence holds and how many sequences are filled that way. It has at
most a few entries for each distinct length, so it doesn't grow with the number of documents; the histogram has
``capacity`` rows at most. Pieces get their place from their rank among pieces of the same length.

Defined results: a null text is the empty one; an empty text is the end id alone; repeated rows (even of one
``doc_id``, or a null one) are packed each; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow_batches, frugal, rows_of, written
from .tokens import WordIds, tokenizer_path

CAPACITY, END_ID = 4096, 1
Plan = list[tuple[tuple[int, ...], int]]
#: levels of the search that keep what they know of sums, a megabyte each at most
KEPT_LEVELS = 8


# ---- planners ---------------------------------------------------------------------------------------------


class FreeSpace:
    """Segment tree over capacities 0..n: how many open groups have that much room; finds the tightest that fits."""

    def __init__(self, n: int):
        self.size = 1 << n.bit_length()
        self.sums = [0] * (2 * self.size)

    def add(self, room: int, by: int) -> None:
        i = room + self.size
        while i:
            self.sums[i] += by
            i >>= 1

    def tightest(self, least: int) -> int | None:
        """The smallest room of at least ``least`` that an open group has."""
        i = least + self.size
        if self.sums[i]:
            return least
        while i > 1:
            if i % 2 == 0 and self.sums[i + 1]:
                i += 1
                while i < self.size:
                    i = 2 * i if self.sums[2 * i] else 2 * i + 1
                return i - self.size
            i >>= 1
        return None


def best_fit_plan(histogram: dict[int, int], capacity: int = CAPACITY) -> Plan:
    """Best-fit-decreasing, where sequences filled alike are handled together."""
    tree, groups, done = FreeSpace(capacity), {}, []

    def put(items: tuple[int, ...], room: int, times: int) -> None:
        if times:
            groups.setdefault(room, []).append((items, times))
            tree.add(room, 1)

    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        while left:
            room = tree.tightest(length)
            if room is None:
                each = capacity // length
                put((length,) * each, capacity - each * length, left // each)
                put((length,) * (left % each), capacity - left % each * length, 1 if left % each else 0)
                break
            items, times = groups[room].pop()
            tree.add(room, -1)
            used = min(times, left)
            left -= used
            put(items + (length,), room - length, used)
            put(items, room, times - used)
    for found in groups.values():
        done += found
    return done


def fewest(histogram: dict[int, int], capacity: int = CAPACITY) -> int:
    """A lower bound on the number of sequences: for each threshold t, pieces longer than capacity - t stand
    alone against pieces shorter than t, and what else is there must fit in their room (Martello and Toth's L2)."""
    n = np.zeros(capacity + 1, dtype=np.int64)
    for length, times in histogram.items():
        n[length] = times
    return _least_sequences(n, capacity)


def _least_sequences(n: np.ndarray, capacity: int) -> int:
    """``fewest`` of counts by length, for all thresholds at once."""
    count, total = np.cumsum(n), np.cumsum(n * np.arange(capacity + 1))
    t = np.arange(capacity // 2 + 1)
    huge, middle = count[-1] - count[capacity - t], capacity // 2
    large, large_sum = count[capacity - t] - count[middle], total[capacity - t] - total[middle]
    small_sum = total[middle] - np.concatenate([[0], total])[t]
    more = -((large * capacity - large_sum - small_sum) // capacity)
    return max(-(-int(total[-1]) // capacity), int((huge + large + np.maximum(more, 0)).max()))


def _spread(bits: int, least: int, most: int, inside: int) -> int:
    """Bits moved up by each of least..most places: what sums of ``bits`` reach with that much added."""
    if most < least:
        return 0
    out, wide, goal = bits << least, 1, most - least + 1
    while wide < goal:
        step = min(wide, goal - wide)
        out |= out << step
        wide += step
    return out & inside


def _dominated(filling: tuple[int, ...], slack: int, spare: int, inside: int) -> bool:
    """Whether a spare length takes the place of some of the filling's lengths and fills no less: one of a larger
    length for one, or one for several that together are at most as long, in both cases with at most ``slack`` more."""
    one, several, sums = 0, 0, 1  # sums of one length, of several, of any number
    for x in filling:
        several |= ((sums & ~1) << x) & inside
        one |= 1 << x
        sums |= sums << x
    return bool(spare & (_spread(one, 1, slack, inside) | _spread(several, 0, slack, inside)))


def fillings(room: int, lengths: list[int], counts: list[int], waste: int) -> Iterator[tuple[int, tuple[int, ...]]]:
    """All undominated fillings of ``room`` that waste at most ``waste``, as (waste, lengths), those of least waste first."""
    return ((slack, found) for slack, found, dominated in _looked_at(room, lengths, counts, waste) if not dominated)


def _exactly(held: list[tuple[int, int]], reach: list[int], most: int, goal: int) -> Iterator[tuple[int, ...]]:
    """Multisets of the first ``most`` lengths with this sum, longest lengths first. On its own, as a function inside another that
    calls itself would keep ``reach`` until the next collection of cycles."""
    if not goal:
        yield ()
        return
    for i in range(most, 0, -1):
        if not reach[i] >> goal & 1:
            return
        x, n = held[i - 1]
        for k in range(min(n, goal // x), 0, -1):
            if reach[i - 1] >> (goal - k * x) & 1:
                for rest in _exactly(held, reach, i - 1, goal - k * x):
                    yield (x,) * k + rest


def _looked_at(room: int, lengths: list[int], counts: list[int], waste: int) -> Iterator[tuple[int, tuple[int, ...], bool]]:
    """All fillings of at most this waste, and whether each is dominated.

    lengths: ascending, with how many of each are left. Which sums the lengths up to each can reach is known
    beforehand, as bits, so the search for a sum never goes where nothing is. Any number of lengths may go in.
    """
    inside = (1 << (room + 1)) - 1
    held = [(x, min(n, room // x)) for x, n in zip(lengths, counts) if x <= room and n > 0]
    spare_of = {x: n for x, n in zip(lengths, counts) if x <= room and n > 0}
    reach = [1]  # by the number of lengths that may be used
    for x, n in held:
        bits, step = reach[-1], 1
        while n:  # binary parts of the count
            part = min(step, n)
            bits |= (bits << (part * x)) & inside
            n, step = n - part, step * 2
        reach.append(bits)

    for slack in range(min(waste, room) + 1):
        if not reach[-1] >> (room - slack) & 1:
            continue
        for found in _exactly(held, reach, len(held), room - slack):
            used, spare = Counter(found), 0
            for x, n in spare_of.items():
                if n > used[x]:
                    spare |= 1 << x
            yield slack, found, _dominated(found, slack, spare, inside)


def completion_plan(histogram: dict[int, int], capacity: int = CAPACITY, budget: int | None = None, report: dict | None = None) -> Plan:
    """Bin completion: take the longest piece left, enumerate the undominated fillings of its sequence by rising waste, search
    depth first. The incumbent starts as the best-fit-decreasing plan; a branch ends when its waste, or the lower bound of what
    is left, leaves no room below the incumbent. A filling is used as often as pieces allow, then once less, and so on
    down to once; with what follows, fillings already tried around the same longest piece aren't tried again.

    No filling is left out, so where the search ends by itself the plan has the fewest sequences. ``budget`` bounds the nodes
    it visits (by default two for each distinct length and 1,000 more) and 50 times that the fillings it looks at; beyond it the best
    plan so far holds, never worse than best fit. ``report`` gets nodes, sequences, bound (a lower one) and whether the plan is proven (minimal).
    """
    best = best_fit_plan(histogram, capacity)
    sequences, bound = sum(times for _, times in best), fewest(histogram, capacity)
    total = sum(k * v for k, v in histogram.items())
    budget = 2 * len(histogram) + 1000 if budget is None else budget
    left = np.zeros(capacity + 1, dtype=np.int64)
    for length, n in histogram.items():
        left[length] = n
    # a level: longest piece, its fillings still to come, those tried, the current one, how often, what it wastes each time
    levels: list[dict] = []
    tried: set[tuple[int, ...]] = set()  # of all levels; a filling has its longest piece in it
    nodes, looked, used, waste, ended = 0, 0, 0, 0, False

    def allowed() -> int:
        """Waste that a plan of one sequence less than the incumbent may have."""
        return (sequences - 1) * capacity - total

    def move(items: tuple[int, ...], by: int) -> None:
        for x, n in Counter(items).items():
            left[x] += by * n

    def coming(longest: int) -> Iterator:
        live = np.flatnonzero(left)
        rest = left[live].tolist()
        rest[-1] -= 1
        return _looked_at(capacity - longest, live.tolist(), rest, allowed() - waste)

    def descend() -> None:
        levels.append({"longest": int(np.flatnonzero(left)[-1]), "coming": None, "mine": [], "items": None, "times": 0, "waste": 0})
        if len(levels) > KEPT_LEVELS:  # what these know takes much memory; it is found again on the way back
            levels[-1 - KEPT_LEVELS]["coming"] = None

    def ascend() -> None:
        tried.difference_update(levels.pop()["mine"])

    if sequences > bound and histogram:
        descend()
    else:
        ended = True
    while levels and sequences > bound and nodes < budget and looked < 50 * budget:
        at = levels[-1]
        if at["times"]:  # back from below: the same filling once less, then the next one
            move(at["items"], at["times"])
            used, waste = used - at["times"], waste - at["times"] * at["waste"]
            at["times"] -= 1
        if not at["times"]:
            at["coming"] = at["coming"] or coming(at["longest"])
            for slack, filling, dominated in at["coming"]:
                looked += 1
                items = (at["longest"], *filling)
                if not dominated and items not in tried:
                    at["items"], at["waste"] = items, slack
                    at["times"] = min(int(left[x]) // n for x, n in Counter(items).items())
                    at["mine"].append(items)
                    tried.add(items)
                    break
                if looked >= 50 * budget:
                    break
            else:
                ascend()
                continue
            if not at["times"]:
                break
        room = allowed() - waste
        if at["waste"]:
            at["times"] = min(at["times"], room // at["waste"])
        if room < 0 or at["times"] <= 0:
            at["times"] = 0
            ascend()  # fillings come by rising waste: the others waste no less
            continue
        nodes += 1
        move(at["items"], -at["times"])
        used, waste = used + at["times"], waste + at["times"] * at["waste"]
        if not left.any():
            if used < sequences:
                best, sequences = [(x["items"], x["times"]) for x in levels], used
        elif used + _least_sequences(left, capacity) < sequences:
            descend()
    if report is not None:
        report.update(nodes=nodes, sequences=sequences, bound=bound, proven=ended or not levels or sequences <= bound)
    return best


# ---- pieces -----------------------------------------------------------------------------------------------


def piece_table(docs: DataFrame, path: str, capacity: int = CAPACITY, end_id: int = END_ID, keep_ids: bool = False, text_column: str = "text") -> DataFrame:
    """Tokenize whole texts; one row a piece: doc_id, piece, start, length, ids_crc32, (ids,) part, nth.

    part and nth: the task and the rank among its pieces of that length. Only texts longer than ``capacity`` are cut.
    """
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long, part int, nth long" + ", ids binary" * keep_ids
    names = [x.split()[0] for x in schema.split(", ")]
    end, step = int(end_id).to_bytes(4, "little"), 4 * capacity

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, part, seen = WordIds.shared(path), TaskContext.get().partitionId(), Counter()
        for batch in batches:
            out = [[] for _ in names]
            for doc_id, ids in zip(batch.column(0).to_pylist(), words.each(batch.column(1).to_pylist())):
                ids += end
                for k, at in enumerate(range(0, len(ids), step)):
                    piece = ids[at : at + step]
                    n = len(piece) // 4
                    row = (doc_id, k, at // 4, n, zlib.crc32(piece), part, seen[n]) + ((piece,) if keep_ids else ())
                    seen[n] += 1
                    for column, value in zip(out, row):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, types)], names)

    kinds = {"long": pa.int64(), "int": pa.int32(), "binary": pa.binary()}
    types = [kinds[x.split()[1]] for x in schema.split(", ")]
    arrow_batches(docs.sparkSession)
    return rows_of(docs, text_column=text_column).mapInArrow(frugal(cut), schema)


def placed(pieces: DataFrame, planner, capacity: int = CAPACITY) -> DataFrame:
    """``pieces`` (a written table) with sequence_id and offset, by the planner's plan over all lengths.

    The driver reads the histogram: at most ``capacity`` rows. A piece's rank among those of its length is its
    rank in its task plus the counts of earlier tasks. The slots that are broadcast hold at most a few rows for
    each distinct length of each pattern, whatever the number of pieces.
    """
    spark = pieces.sparkSession
    counts = written(pieces.groupBy("part", "length").agg(F.count("*").alias("n")), "length-counts")
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.select("part", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("rank_before"))
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    slots, taken, first = [], Counter(), 0
    for items, times in planner(histogram, capacity):
        offset = 0
        for length in items:
            slots.append((length, taken[length], taken[length] + times, first - taken[length], offset))
            taken[length] += times
            offset += length
        first += times
    slots = spark.createDataFrame(slots, "slot_length long, rank_from long, rank_to long, sequence_shift long, offset long")
    ranked = pieces.join(base, ["part", "length"]).withColumn("rank", F.col("nth") + F.col("rank_before"))
    return (
        ranked.join(F.broadcast(slots), (F.col("length") == F.col("slot_length")) & (F.col("rank") >= F.col("rank_from")) & (F.col("rank") < F.col("rank_to")))
        .withColumn("sequence_id", F.col("rank") + F.col("sequence_shift"))
        .drop("slot_length", "rank_from", "rank_to", "sequence_shift", "rank", "rank_before", "part", "nth")
    )


def pack_documents(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID, planner=completion_plan, text_column: str = "text") -> DataFrame:
    """Best-fit packing by bin completion: doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    pieces = written(piece_table(docs, path or tokenizer_path(), capacity, end_id, text_column=text_column), "pieces")
    return placed(pieces, planner, capacity).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


def packed_matrix(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID, text_column: str = "text") -> DataFrame:
    """Best-fit-decreasing packing into id rows: one row a sequence.

    sequence_id, n_tokens, doc_ids and pieces (by place), ids (little-endian unsigned 32-bit, the pieces one after
    the other, unpadded), cu_seqlens (0, then each segment's end), position_resets (where a segment starts and
    positions begin at 0 again). ``fixed_rows`` pads, ``positions`` expands.
    """
    pieces = written(piece_table(docs, path or tokenizer_path(), capacity, end_id, keep_ids=True, text_column=text_column), "id-pieces")
    held = F.struct("offset", "doc_id", "piece", "length", "ids")
    rows = placed(pieces, best_fit_plan, capacity).groupBy("sequence_id").agg(F.array_sort(F.collect_list(held)).alias("held"))
    ends = F.transform("held", lambda x: (x["offset"] + x["length"]).cast("int"))
    return rows.select(
        "sequence_id",
        F.element_at(ends, -1).alias("n_tokens"),
        F.transform("held", lambda x: x["doc_id"]).alias("doc_ids"),
        F.transform("held", lambda x: x["piece"]).alias("pieces"),
        F.aggregate("held", F.lit(b""), lambda a, x: F.concat(a, x["ids"])).alias("ids"),
        F.concat(F.array(F.lit(0)), ends).alias("cu_seqlens"),
        F.transform("held", lambda x: x["offset"].cast("int")).alias("position_resets"),
    )


def positions(packed: DataFrame) -> DataFrame:
    """``packed_matrix`` rows with position_ids: each token's place in its own segment."""
    spans = F.arrays_zip(F.col("position_resets").alias("a"), F.slice("cu_seqlens", 2, F.size("position_resets")).alias("b"))
    return packed.withColumn("position_ids", F.flatten(F.transform(spans, lambda s: F.sequence(F.lit(0), s["b"] - s["a"] - 1))))


def fixed_rows(packed: DataFrame, capacity: int = CAPACITY, pad_id: int = 0) -> DataFrame:
    """``packed_matrix`` rows whose ids all have ``capacity`` entries: a matrix when read one after the other."""
    pad = F.lit(int(pad_id).to_bytes(4, "little"))
    return packed.withColumn("ids", F.concat("ids", F.unhex(F.repeat(F.hex(pad), F.lit(capacity) - F.col("n_tokens")))))


def write_matrix(packed: DataFrame, path: str, capacity: int = CAPACITY, pad_id: int = 0) -> None:
    """Write fixed rows as Parquet; row groups read back with ``read_matrix``."""
    fixed_rows(packed, capacity, pad_id).write.parquet(path)


def read_matrix(batch: pa.Table, capacity: int = CAPACITY) -> np.ndarray:
    """Ids of a table read from ``write_matrix``'s files as a matrix without copying each row twice."""
    return np.frombuffer(b"".join(batch.column("ids").to_pylist()), dtype="<u4").reshape(-1, capacity)
