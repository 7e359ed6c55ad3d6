"""Packing of token sequences into windows by minimum bin slack.

A document's ids, with the end id, are cut into full windows and a remainder. Remainders are told apart by length alone,
so a window plan needs only how many there are of each length: at most `capacity - 1` counts, whatever the data's size.
The planner repeatedly takes the largest length left, and a subset-sum over bit sets (bounded counts, cut into powers of
two) finds the multiset of other lengths that comes closest to filling the window; the counts of that multiset are
traced back, and the pattern is used as often as the counts allow. Windows that stay under-filled give their items up:
these are cut into grains of a sixteenth of the window and what is left over, and planned once more.

Documents then look their places up: the n-th remainder of a length lies in a known window at a known offset. Numbers
within a length come from counts by input partition, so no task sees all documents of one length.

Defined cases: a null text is empty and holds the end id alone; rows that repeat an id are packed each; an empty table
gives no pieces; columns other than doc_id and text are ignored.
"""

from __future__ import annotations

import zlib
from collections import defaultdict
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from edgefold.llm.shared import long_id, pieces, prepare, settle, table
from edgefold.llm.vocabulary import WordIds, default_path

CAPACITY = 4096
END_ID = 2
#: Windows filled less than this are dissolved and their items cut.
FULL_ENOUGH = 0.995
#: Grains to a window.
GRAINS = 16
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def closest_fill(counts: dict[int, int], room: int) -> dict[int, int]:
    """The multiset of lengths, within their counts, whose sum comes closest to `room` without passing it."""
    reach, limit, steps = 1, (1 << (room + 1)) - 1, []
    for length in sorted((x for x in counts if x <= room), reverse=True):
        left, lot = min(counts[length], room // length), 1
        while left:
            lot = min(lot, left)
            more = (reach << (lot * length)) & limit
            steps.append((length, lot, reach))
            reach |= more
            left -= lot
            lot *= 2
        if reach >> room & 1:
            break
    at, used = reach.bit_length() - 1, defaultdict(int)
    for length, lot, before in reversed(steps):
        if not before >> at & 1:
            used[length] += lot
            at -= lot * length
    return dict(used)


@dataclass
class Plan:
    """Runs of windows of one pattern. For each length, runs in order of the items' numbers."""

    capacity: int
    windows: int = 0
    runs: dict[int, list[tuple[int, int, int, int]]] = field(default_factory=lambda: defaultdict(list))
    taken: dict[int, int] = field(default_factory=lambda: defaultdict(int))
    #: From this number on, items of a length are cut into grains; numbers of the grains and of what is left over.
    cut: dict[int, tuple[int, int, int]] = field(default_factory=dict)

    def use(self, pattern: dict[int, int], times: int) -> None:
        offset = 0
        for length, each in pattern.items():
            self.runs[length].append((self.taken[length], each, self.windows, offset))
            self.taken[length] += each * times
            offset += each * length
        self.windows += times


def _fill(plan: Plan, counts: dict[int, int], least: int) -> dict[int, int]:
    """Plan the windows; returns the items of windows filled less than `least`, which are not planned."""
    counts, poor = dict(counts), defaultdict(int)
    while counts:
        top = max(counts)
        rest = dict(counts)
        rest[top] -= 1
        if not rest[top]:
            del rest[top]
        pattern = defaultdict(int, {top: 1})
        for length, n in closest_fill(rest, plan.capacity - top).items():
            pattern[length] += n
        times = min(counts[x] // n for x, n in pattern.items())
        if sum(x * n for x, n in pattern.items()) >= least:
            plan.use(pattern, times)
        else:
            for x, n in pattern.items():
                poor[x] += n * times
        for x, n in pattern.items():
            counts[x] -= n * times
            if not counts[x]:
                del counts[x]
    return poor


def make_plan(counts: dict[int, int], capacity: int = CAPACITY) -> Plan:
    plan, grain = Plan(capacity), capacity // GRAINS
    poor = _fill(plan, counts, int(capacity * FULL_ENOUGH))
    cut, small = {}, defaultdict(int)
    for length in sorted(poor):
        if length > grain:
            cut[length] = poor[length]
            small[grain] += length // grain * poor[length]
            if length % grain:
                small[length % grain] += poor[length]
        else:
            small[length] += poor[length]
    # Whole items of a length come first, then grains and leftovers, by the length they were cut from.
    numbered = defaultdict(int, plan.taken)
    for length in poor:
        if length <= grain:
            numbered[length] += poor[length]
    for length, n in cut.items():
        plan.cut[length] = (plan.taken[length], numbered[grain], numbered[length % grain])
        numbered[grain] += length // grain * n
        if length % grain:
            numbered[length % grain] += n
    _fill(plan, small, 0)
    return plan


class Places:
    """Where the item of a length and number lies: window and offset."""

    def __init__(self, plan: Plan):
        self.capacity, self.cut = plan.capacity, plan.cut
        self.runs = {k: np.asarray(v, dtype=np.int64) for k, v in plan.runs.items()}

    def of(self, length: int, number: int) -> tuple[int, int]:
        runs = self.runs[length]
        first, each, window, offset = runs[np.searchsorted(runs[:, 0], number, side="right") - 1].tolist()
        return window + (number - first) // each, offset + (number - first) % each * length

    def pieces(self, length: int, number: int) -> list[tuple[int, int, int, int]]:
        """(start in the item, length, window, offset) of each part of the item."""
        first, grains, rest = self.cut.get(length, (number + 1, 0, 0))
        if number < first:
            return [(0, length, *self.of(length, number))]
        grain, k = self.capacity // GRAINS, number - first
        whole = length // grain
        out = [(i * grain, grain, *self.of(grain, grains + k * whole + i)) for i in range(whole)]
        if length % grain:
            out.append((whole * grain, length % grain, *self.of(length % grain, rest + k)))
        return out


MEASURED = "doc_id long, n long, part int, full_before long, rest int, number long, full_crc array<long>, rest_crc long, grain_crc array<long>"


def _measure(path: str, end_id: int, capacity: int):
    end, grain = np.asarray([end_id], dtype="<u4").tobytes(), capacity // GRAINS

    def run(batches):
        from pyspark import TaskContext

        words, part = WordIds.opened(path), TaskContext.get().partitionId()
        numbers, full_before = defaultdict(int), 0

        def rows():
            for b in batches:
                yield from zip(b.column(0).to_pylist(), (x.as_py() or "" for x in b.column(1)), strict=True)

        for some in pieces(rows()):
            out = []
            for (doc, _), ids in zip(some, words.encode([t for _, t in some]), strict=True):
                raw = memoryview(ids + end)
                n = len(raw) // 4
                full, rest = divmod(n, capacity)
                tail = raw[full * capacity * 4 :]
                out.append((
                    doc, n, part, full_before, rest, numbers[rest],
                    [zlib.crc32(raw[i * capacity * 4 : (i + 1) * capacity * 4]) for i in range(full)],
                    zlib.crc32(tail), [zlib.crc32(tail[i : i + grain * 4]) for i in range(0, rest * 4, grain * 4)],
                ))
                numbers[rest] += 1
                full_before += full
            names = [x.split()[0] for x in MEASURED.split(", ")]
            kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.list_(pa.int64()), pa.int64(), pa.list_(pa.int64())]
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*out, strict=True), kinds, strict=True)], names)

    return run


def pack(docs: DataFrame, *, vocabulary: str | None = None, end_id: int = END_ID, capacity: int = CAPACITY) -> DataFrame:
    """Pieces of all documents with their sequences: full windows first, then packed remainders.

    The texts are read once and never shuffled; lengths and checksums alone go on.
    """
    spark = docs.sparkSession
    prepare(spark)
    source = long_id(docs.select("doc_id", "text"), "doc_id")
    measured = settle(source.mapInArrow(_measure(vocabulary or default_path(), end_id, capacity), MEASURED))
    by_part = measured.groupBy("part", "rest").agg(
        F.count("*").alias("items"), F.sum(F.size("full_crc").cast("long")).alias("full")
    )
    before = Window.partitionBy("rest").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    by_part = settle(by_part.withColumn("base", F.coalesce(F.sum("items").over(before), F.lit(0))))
    # Both results are bounded: one row for each length below the capacity, and one for each input partition.
    counts = {r["rest"]: r["items"] for r in by_part.groupBy("rest").agg(F.sum("items").alias("items")).collect() if r["rest"]}
    full_of, total = {}, 0
    for r in by_part.groupBy("part").agg(F.sum("full").alias("full")).orderBy("part").collect():
        full_of[r["part"]] = total
        total += r["full"]
    places = spark.sparkContext.broadcast(Places(make_plan(counts, capacity)))

    def place(batches):
        plan = places.value
        for b in batches:
            out = []
            for r in b.to_pylist():
                doc, n, first = r["doc_id"], r["n"], full_of[r["part"]] + r["full_before"]
                for i, crc in enumerate(r["full_crc"]):
                    out.append((doc, i * capacity, capacity, crc, n, first + i, 0))
                if r["rest"]:
                    base = len(r["full_crc"]) * capacity
                    parts = plan.pieces(r["rest"], r["base"] + r["number"])
                    crcs = [r["rest_crc"]] if len(parts) == 1 else r["grain_crc"]
                    for (at, length, window, offset), crc in zip(parts, crcs, strict=True):
                        out.append((doc, base + at, length, crc, n, total + window, offset))
            if out:
                names = [x.split()[0] for x in PIECES.split(", ")]
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*out, strict=True)], names)

    placed = measured.join(by_part.select("part", "rest", "base"), ["part", "rest"])
    return placed.mapInArrow(place, PIECES)


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents", "doc_id", "text"))
