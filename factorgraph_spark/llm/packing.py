"""Packing tokenised documents into sequences: dominance reduction, then best fit, on the histogram of lengths.

Documents become pieces of at most ``capacity`` tokens. Only the histogram of piece lengths (at most ``capacity`` numbers, whatever the
corpus) decides the packing, so the driver plans patterns, each with a multiplicity, and no task ever sees a group of pieces that grows
with the corpus:

1. Dominance: with the longest open length ``a``, let ``b`` be the longest length that fits beside it. If nothing fits, or ``a + b`` fills
   the sequence, or no two pieces fit beside ``a``, the pattern (a) or (a, b) dominates every other use of that ``a`` and is fixed. If two
   but not three fit and ``b`` is at least as long as the best fitting pair, (a, b) is fixed as well. Each rule is applied to as many
   pieces at once as the counts allow; the instance shrinks and the rules are tried again.
2. The rest is packed best fit, longest first, in bulk: groups of equal open sequences take pieces together.

Pieces are then numbered within their length (counts per hash bucket, prefix sums over buckets, row numbers within a bucket: no window
holds more than a bucket or a row per bucket), and the number finds the piece's sequence and offset in the plan by binary search.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, strings, tidy
from .tokens import WordTokens

# The id after each document's tokens, and tokens in a sequence.
END_ID = 1
CAPACITY = 4096
#: Pieces that a hash bucket holds on average when they are numbered.
PER_BUCKET = 50_000


def pieces(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", vocabulary: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """doc_id, piece, start, length and ids_crc32 of every piece. Null text is empty: one piece that holds END_ID alone."""

    @tidy
    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens = WordTokens(vocabulary)
        end = np.array([END_ID], dtype="<u4").tobytes()
        for batch in batches:
            row, piece, start, length, crc = [], [], [], [], []
            for k, ids in enumerate(tokens.encode_many(strings(batch.column("t")))):
                ids += end
                for p, s in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[s : s + 4 * capacity]
                    row.append(k)
                    piece.append(p)
                    start.append(s // 4)
                    length.append(len(part) // 4)
                    crc.append(zlib.crc32(part))
            yield pa.RecordBatch.from_arrays(
                [batch.column("id").take(pa.array(row, pa.int64())), pa.array(piece, pa.int32()), *[pa.array(x, pa.int64()) for x in (start, length, crc)]],
                ["id", "piece", "start", "length", "ids_crc32"],
            )

    kind = dict(docs.select(doc_id).dtypes)[doc_id]
    rows = docs.select(F.col(doc_id).alias("id"), F.col(text).alias("t"))
    return rows.mapInArrow(split, f"id {kind}, piece int, start long, length long, ids_crc32 long")


class Plan:
    """Patterns with multiplicities: every pattern is a list of (length, copies) in order of their place in the sequence."""

    def __init__(self, capacity: int):
        self.capacity, self.patterns = capacity, []

    def add(self, runs: list[tuple[int, int]], times: int) -> None:
        if times:
            self.patterns.append((runs, times))

    @property
    def sequences(self) -> int:
        return sum(t for _, t in self.patterns)

    def slots(self) -> list[tuple[int, int, int, int, int]]:
        """length, first number, pieces per sequence, first sequence, offset: sorted by length and number."""
        used: dict[int, int] = {}
        out, base = [], 0
        for runs, times in self.patterns:
            at = 0
            for length, copies in runs:
                out.append((length, used.get(length, 0), copies, base, at))
                used[length] = used.get(length, 0) + copies * times
                at += length * copies
            base += times
        return sorted(out)


def reduce_dominated(counts: dict[int, int], plan: Plan) -> dict[int, int]:
    """Fixes dominating patterns; what is left of the counts."""
    counts, lengths = {k: n for k, n in counts.items() if n}, sorted(k for k, n in counts.items() if n)
    top = len(lengths) - 1

    def take(length: int, n: int) -> None:
        counts[length] -= n
        if not counts[length]:
            del counts[length]
            del lengths[bisect_left(lengths, length)]

    def smallest(most: int, skip: int) -> list[int]:
        """Lengths of the ``most`` smallest pieces, one piece of ``skip`` left out."""
        out: list[int] = []
        for length in lengths:
            out += [length] * min(most - len(out), counts[length] - (length == skip))
            if len(out) >= most:
                break
        return out

    while top >= 0:
        a = lengths[top]
        room = plan.capacity - a
        at = bisect_left(lengths, room + 1) - 1  # the longest length that fits beside a
        while at >= 0 and lengths[at] == a and counts[a] < 2:
            at -= 1
        if at < 0:
            n = counts[a]
            plan.add([(a, 1)], n)
            take(a, n)
            top = min(top, len(lengths)) - 1
            continue
        b = lengths[at]
        low = smallest(3, a)
        two, three = len(low) > 1 and low[0] + low[1] <= room, len(low) > 2 and sum(low) <= room
        fixed = b == room or not two
        if not fixed and not three:
            best, j = 0, len(lengths) - 1
            for i, small in enumerate(lengths):  # the best pair that fits
                while j >= i and (small + lengths[j] > room):
                    j -= 1
                if j < i:
                    break
                k = j
                need = lambda x, y: (counts[x] - (x == a)) >= 1 + (x == y) and (counts[y] - (y == a)) >= 1 + (x == y)
                while k >= i and not need(small, lengths[k]):
                    k -= 1
                if k >= i:
                    best = max(best, small + lengths[k])
            fixed = b >= best
        if not fixed:
            top -= 1
            continue
        n = counts[a] // 2 if a == b else min(counts[a], counts[b])
        plan.add([(a, 2)] if a == b else [(a, 1), (b, 1)], n)
        if a == b:
            take(a, 2 * n)
        else:
            take(a, n)
            take(b, n)
        top = len(lengths) - 1 if len(lengths) <= top or lengths[top] != a else top  # a smaller instance: try the longest again
    return counts


def best_fit(counts: dict[int, int], plan: Plan) -> None:
    """Best fit, longest first; groups of equal open sequences take pieces together."""
    rooms: list[int] = []
    groups: dict[int, list[tuple[list[tuple[int, int]], int]]] = {}

    def put(room: int, runs: list[tuple[int, int]], times: int) -> None:
        if not times:
            return
        if not room:
            plan.add(runs, times)
            return
        if room not in groups:
            insort(rooms, room)
            groups[room] = []
        groups[room].append((runs, times))

    for length in sorted(counts, reverse=True):
        left = counts[length]
        while left:
            at = bisect_left(rooms, length)
            if at == len(rooms):
                each = plan.capacity // length
                put(plan.capacity - each * length, [(length, each)], left // each)
                if left % each:
                    put(plan.capacity - left % each * length, [(length, left % each)], 1)
                break
            room = rooms[at]
            runs, times = groups[room].pop()
            if not groups[room]:
                del groups[room]
                del rooms[at]
            each = room // length
            full = min(times, left // each)
            put(room - each * length, [*runs, (length, each)], full)
            left, times = left - full * each, times - full
            if left and times:
                put(room - left * length, [*runs, (length, left)], 1)
                left, times = 0, times - 1
            put(room, runs, times)
    for room in rooms:
        for runs, times in groups[room]:
            plan.add(runs, times)


def plan_packing(counts: dict[int, int], capacity: int = CAPACITY) -> Plan:
    plan = Plan(capacity)
    best_fit(reduce_dominated(counts, plan), plan)
    return plan


def assign(parts: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """parts with sequence_id and offset. Equal rows are separate pieces; an empty table gives an empty result."""
    histogram = {r["length"]: r["n"] for r in parts.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # capacity rows at most
    slots = np.array(plan_packing(histogram, capacity).slots(), dtype=np.int64).reshape(-1, 5)
    buckets = max(1, sum(histogram.values()) // PER_BUCKET)
    dealt = parts.withColumn("bucket", F.pmod(F.xxhash64("id", "piece", "ids_crc32"), F.lit(buckets)))
    before = (
        dealt.groupBy("length", "bucket")
        .agg(F.count(F.lit(1)).alias("n"))
        .select("length", "bucket", (F.sum("n").over(Window.partitionBy("length").orderBy("bucket")) - F.col("n")).alias("before"))
    )
    inside = F.row_number().over(Window.partitionBy("bucket", "length").orderBy("id", "piece")) - 1
    numbered = dealt.withColumn("inside", inside).join(before, ["length", "bucket"]).withColumn("number", F.col("before") + F.col("inside"))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # One ascending key for (length, number): lengths follow each other in steps no number reaches.
        step = 1 << 48
        keys = slots[:, 0] * step + slots[:, 1]
        for batch in batches:
            length, number = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("length", "number"))
            at = np.searchsorted(keys, length * step + number, side="right") - 1
            inner = number - slots[at, 1]
            copies = slots[at, 2]
            yield pa.RecordBatch.from_arrays(
                [*[batch.column(c) for c in ("id", "piece", "start", "length", "ids_crc32")], pa.array(slots[at, 3] + inner // copies), pa.array(slots[at, 4] + inner % copies * length)],
                ["id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"],
            )

    kind = dict(parts.dtypes)["id"]
    rows = numbered.select("id", "piece", "start", "length", "ids_crc32", "number")
    return rows.mapInArrow(place, f"id {kind}, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")


def pack(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", vocabulary: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """Every piece of every document with its place. Other columns of docs are not read."""
    parts = cut(pieces(docs, doc_id=doc_id, text=text, vocabulary=vocabulary, capacity=capacity))
    return assign(parts, capacity).withColumnRenamed("id", doc_id)
