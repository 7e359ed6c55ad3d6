"""Removal of repeated byte strings by suffix arrays over all documents.

A byte goes if a string of L bytes that covers it starts earlier as well, in an earlier document or earlier in the same
one. Strings are judged on the input, and never cross documents.

Suffixes that can share L bytes must meet in one task without the text's being sent to every task. Each window of L
bytes has an anchor: the least hash among its k-byte strings, leftmost first. Equal windows have equal anchors at equal
places, so windows are dealt by their anchor's hash. Neighbouring windows mostly share an anchor; they travel as one
context, the bytes that they cover.

1. Anchors of whole texts go out with a hash of their context, without text. Contexts that are copies of each other are
   settled there: all but the first go whole. Anchors met once hold no repeat.
2. Anchors whose contexts differ fetch their contexts, once for each distinct one. A task sorts the suffixes of the contexts it
   got by external induced sorting (`induced_sort`), in runs of whole anchors: texts, suffix tuples and shared prefixes are
   on disk where memory does not hold them. Windows that share L bytes are neighbours; all but the first go.
3. What goes, from both, is gathered for each document and cut out.

A copy of a context has its anchor's hash, its length and 96 more bits of hash in common with it; bytes are not compared.
An anchor with more than HOT distinct contexts (a phrase that very many documents share) is not sent to one task: each of
its windows goes by a hash of its own, and windows that agree in 128 bits of hash are equal.

Defined cases: a null text is empty; null ids come first; rows that repeat an id are ordered by the first 64 characters
of their texts, then by a hash of these, and count as documents each; texts shorter than L stay whole; an empty table gives no rows; columns other than doc_id and text are
ignored by `repeats`, and kept by `remove_repeats`.
"""

from __future__ import annotations

import hashlib
import tempfile

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgefold.llm import induced_sort
from edgefold.llm.induced_sort import Room, suffixes
from edgefold.llm.shared import long_id, numbered, partitions, prepare, settle, table

LENGTH = 100
ANCHOR = 24
#: Windows whose anchors are worked out at a time; bytes of contexts that are sorted at a time.
WINDOWS, SORTED = 1 << 20, 2 << 20
#: Distinct contexts of an anchor that one task may get.
HOT = 1_024
_FIRST = -(1 << 63)
_LOW = np.uint64((1 << 24) - 1)


def _hashes(raw: np.ndarray) -> np.ndarray:
    """A hash of each string of ANCHOR bytes."""
    n = len(raw) - ANCHOR + 1
    words = [np.ndarray((n,), dtype="<u8", buffer=raw.data, offset=8 * i, strides=(1,)) for i in range(3)]
    h = words[0] * np.uint64(0x9E3779B97F4A7C15)
    for word, factor in ((words[1], 0xBF58476D1CE4E5B9), (words[2], 0x94D049BB133111EB)):
        h ^= h >> np.uint64(31)
        h += word
        h *= np.uint64(factor)
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(32)
    return h


def anchors(raw: bytes, length: int = LENGTH):
    """For each run of windows with one anchor: the anchor's hash, the first window's start, the number of windows."""
    data, width = np.frombuffer(raw, dtype=np.uint8), length - ANCHOR + 1
    total = len(data) - length + 1
    for at in range(0, total, WINDOWS):
        n = min(WINDOWS, total - at)
        h = _hashes(data[at : at + n + length - 1])
        least = (h & ~_LOW) | np.arange(len(h), dtype=np.uint64)
        span = 1
        while span * 2 <= width:
            least = np.minimum(least[:-span], least[span:])
            span *= 2
        least = np.minimum(least[:n], least[width - span : width - span + n])
        place = least & _LOW
        starts = np.concatenate([[0], np.flatnonzero(place[1:] != place[:-1]) + 1])
        yield h[place[starts].astype(np.int64)].view(np.int64), starts + at, np.diff(np.append(starts, n))


_ROWS = "h long, c long, more int, n int, doc long, nth int, start long, gone boolean"
_NAMES = [x.split()[0] for x in _ROWS.split(", ")]
_KINDS = [pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.bool_()]


def _anchors(length: int):
    """Rows of anchors. Copies of a context that a task meets together are settled at once: all but the first are gone."""

    def settled(held):
        rows = [np.concatenate(x) for x in zip(*held, strict=True)]
        order = np.lexsort(rows[::-1])
        rows = [x[order] for x in rows]
        gone = np.zeros(len(order), dtype=bool)
        gone[1:] = np.logical_and.reduce([x[1:] == x[:-1] for x in rows[:4]])
        return pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip([*rows, gone], _KINDS, strict=True)], _NAMES)

    def run(batches):
        for b in batches:
            held, size = [], 0
            for doc, nth, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), strict=True):
                raw = (text.as_py() or "").encode("utf-8")
                for h, starts, n in anchors(raw, length):
                    ends = (starts + n + (length - 1)).tolist()
                    digests = b"".join([xxhash.xxh3_128_digest(raw[s:e]) for s, e in zip(starts.tolist(), ends, strict=True)])
                    c = np.frombuffer(digests, dtype="<i8").reshape(-1, 2)
                    held.append((h, c[:, 0], c[:, 1].astype(np.int32), n, np.full(len(h), doc), np.full(len(h), nth), starts))
                    size += len(h)
                if size > 1 << 17:
                    yield settled(held)
                    held, size = [], 0
            if held:
                yield settled(held)

    return run


def _settle_copies(batches):
    """Rows sorted by gone and all of _ROWS. Later copies of a context go; first ones of anchors with several stay.

    Rows that are gone already pass; those of an anchor's context lie in other places than its first ones.
    """
    last: np.ndarray | None = None  # what tells contexts, in the row before
    waiting: np.ndarray | None = None  # the latest first copy, not known to share its anchor
    shared = False  # whether the one before it has its anchor

    def batch(rows: np.ndarray, gone: np.ndarray):
        return pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip([*rows, gone], _KINDS, strict=True)], _NAMES)

    def many():
        """Batches put together: they are small, as those of texts must be."""
        held, size = [], 0
        for b in batches:
            held.append(b)
            size += b.num_rows
            if size >= 1 << 16:
                yield pa.Table.from_batches(held).combine_chunks()
                held, size = [], 0
        if size:
            yield pa.Table.from_batches(held).combine_chunks()

    for b in many():
        rows = np.stack([b.column(i).to_numpy().astype(np.int64) for i in range(8)])
        known = rows[7].astype(bool)
        if known.any():
            yield batch(rows[:7, known], known[known])
        rows = rows[:7, ~known]
        if not rows.shape[1]:
            continue
        copy = np.zeros(rows.shape[1], dtype=bool)
        copy[1:] = (rows[:4, 1:] == rows[:4, :-1]).all(axis=0)
        copy[0] = last is not None and bool((rows[:4, 0] == last).all())
        last = rows[:4, -1].copy()
        if copy.any():
            yield batch(rows[:, copy], np.ones(int(copy.sum()), dtype=bool))
        first = rows[:, ~copy]
        if not first.shape[1]:
            continue
        if waiting is not None:
            first = np.concatenate([waiting[:, None], first], axis=1)
        alike = first[0, 1:] == first[0, :-1]
        before = np.concatenate([[shared if waiting is not None else False], alike])
        keep = before[:-1] | alike
        waiting, shared = first[:, -1].copy(), bool(before[-1])
        if keep.any():
            yield batch(first[:, :-1][:, keep], np.zeros(int(keep.sum()), dtype=bool))
    if waiting is not None and shared:
        yield batch(waiting[:, None], np.zeros(1, dtype=bool))


_CUT = "h long, c long, doc long, nth int, start long, context binary"


def _cut_contexts(length: int):
    """Contexts to sort (c is null), hashed windows of hot anchors (context is null), and of these such as are gone (both are)."""
    names = [x.split()[0] for x in _CUT.split(", ")]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.binary()]

    def contexts(out):
        h, doc, nth, start, context = zip(*out, strict=True)
        return pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip([h, [None] * len(h), doc, nth, start, context], kinds, strict=True)], names)

    def windows(out):
        rows = [np.concatenate(x) for x in zip(*out, strict=True)]
        order = np.lexsort(rows[::-1])
        rows = [x[order] for x in rows]
        gone = np.zeros(len(order), dtype=bool)
        gone[1:] = (rows[0][1:] == rows[0][:-1]) & (rows[1][1:] == rows[1][:-1])
        columns = [pa.array(rows[0]), pa.array(rows[1], mask=gone), *map(pa.array, rows[2:]), pa.nulls(len(gone), pa.binary())]
        return pa.RecordBatch.from_arrays([x.cast(k) for x, k in zip(columns, kinds, strict=True)], names)

    def run(batches):
        for b in batches:
            out, size, hashed = [], 0, []
            for doc, nth, text, wanted in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), b.column(3), strict=True):
                raw = (text.as_py() or "").encode("utf-8")
                for x in wanted.as_py():
                    s, n = x["start"], x["n"]
                    if x["hot"]:
                        digests = b"".join([xxhash.xxh3_128_digest(raw[i : i + length]) for i in range(s, s + n)])
                        c = np.frombuffer(digests, dtype="<i8").reshape(-1, 2)
                        hashed.append((c[:, 0], c[:, 1], np.full(n, doc), np.full(n, nth), np.arange(s, s + n)))
                    else:
                        out.append((x["h"], doc, nth, s, raw[s : s + n + length - 1]))
                        size += len(out[-1][-1])
                if size > 1 << 22:
                    yield contexts(out)
                    out, size = [], 0
            if out:
                yield contexts(out)
            if hashed:
                yield windows(hashed)

    return run


class _Joined:
    """Contexts one after another, a separator after each, for one sort; on disk beyond a part of the sort's memory."""

    def __init__(self, limit: int):
        self.limit, self.parts, self.held, self.file = limit, [], 0, None
        self.size, self.about = 0, []  # size: bytes of contexts

    def add(self, about: np.ndarray, contexts: pa.Array) -> None:
        """about: doc, nth and start of each."""
        cuts = np.frombuffer(contexts.buffers()[1], dtype=np.int32)[contexts.offset : contexts.offset + len(contexts) + 1].astype(np.int64)
        sizes = np.diff(cuts)
        text = np.zeros(int(sizes.sum()) + len(sizes), dtype=np.uint16)
        inside = np.ones(len(text), dtype=bool)
        inside[np.cumsum(sizes + 1) - 1] = False
        text[inside] = np.frombuffer(contexts.buffers()[2], dtype=np.uint8)[cuts[0] : cuts[-1]].astype(np.uint16) + 1
        self.about.append(np.vstack([about, sizes[None, :]]))
        self.size += int(sizes.sum())
        self.parts.append(text)
        self.held += text.nbytes
        if self.held > self.limit // 4:
            self.file = self.file or tempfile.TemporaryFile(prefix="edgefold-contexts-")
            for part in self.parts:
                self.file.write(part.tobytes())
            self.parts, self.held = [], 0

    def text(self) -> np.ndarray:
        if self.file is None:
            return np.concatenate(self.parts)
        for part in self.parts:
            self.file.write(part.tobytes())
        self.file.flush()
        return np.memmap(self.file, dtype=np.uint16, mode="r")


def repeated_windows(joined: _Joined, length: int, room: Room):
    """Runs of windows that an earlier one of the joined contexts equals, in pieces: document, nth, and range of bytes."""
    text, about = joined.text(), np.concatenate(joined.about, axis=1)
    doc, nth, start, sizes = about
    bounds = np.cumsum(sizes + 1) - sizes - 1
    gone = room.array(len(text), bool, 0)
    gone[:] = False
    far = len(text)
    least = far  # the first of the windows that are equal to what was met last
    for positions, shared in suffixes(text, length, 257, room):
        positions = positions.astype(np.int64)
        of = np.searchsorted(bounds, positions, side="right") - 1
        place = np.where(positions - bounds[of] <= sizes[of] - length, positions, far)
        new = shared < length
        heads = np.flatnonzero(new)
        heads = heads if new[0] else np.concatenate([[0], heads])
        first = np.minimum.reduceat(place, heads)
        if not new[0]:
            if first[0] < least < far:
                gone[least] = True
            first[0] = min(first[0], least)
        least = int(first[-1])
        again = place[(place < far) & (place > np.repeat(first, np.diff(np.append(heads, len(place)))))]
        gone[again] = True
    for a in range(0, far, induced_sort.PIECE):
        again = np.flatnonzero(gone[a : a + induced_sort.PIECE]) + a
        if not len(again):
            continue
        of = np.searchsorted(bounds, again, side="right") - 1
        head = np.flatnonzero(np.concatenate([[True], (np.diff(again) != 1) | (of[1:] != of[:-1])]))
        tail, of = np.append(head[1:], len(again)) - 1, of[head]
        begins = start[of] + again[head] - bounds[of]
        yield doc[of], nth[of], begins, begins + (again[tail] - again[head]) + length


def _sort_contexts(length: int):
    """Rows of _CUT, sorted: windows that are repeats, as ranges of their documents' bytes."""

    def ranges(doc, nth, start, end):
        return pa.RecordBatch.from_arrays([pa.array(doc), pa.array(nth).cast(pa.int32()), pa.array(start), pa.array(end)], ["doc", "nth", "start", "end"])

    def solve(joined):
        return (ranges(*x) for x in repeated_windows(joined, length, Room()))

    def run(batches):
        joined, latest, last = _Joined(induced_sort.LIMIT), None, None
        for b in batches:
            columns = {k: b.column(i).to_numpy(zero_copy_only=False) for i, k in enumerate(("h", "c", "doc", "nth", "start"))}
            sorts = b.column(5).is_valid().to_numpy(zero_copy_only=False)
            hashed = b.column(1).is_valid().to_numpy(zero_copy_only=False)
            again = ~sorts & ~hashed
            if hashed.any():
                at = np.flatnonzero(hashed)
                pair = np.stack([columns["h"][at], np.asarray(b.column(1).filter(pa.array(hashed)))])
                before = np.concatenate([pair[:, :1] if last is None else last, pair[:, :-1]], axis=1)
                equal = (pair == before).all(axis=0)
                equal[0] &= last is not None
                again[at[equal]] = True
                last = pair[:, -1:].copy()
            if again.any():
                start = columns["start"][again]
                yield ranges(columns["doc"][again], columns["nth"][again], start, start + length)
            if not sorts.any():
                continue
            h, contexts = columns["h"][sorts], b.column(5).filter(pa.array(sorts))
            about = np.stack([columns[k][sorts].astype(np.int64) for k in ("doc", "nth", "start")])
            upto = np.concatenate([[0], np.cumsum(np.asarray(pc.binary_length(contexts)))])
            other = np.concatenate([[h[0] != latest], h[1:] != h[:-1]])
            latest, a = h[-1], 0
            while True:  # close runs where an anchor ends
                full = np.flatnonzero(other[a:] & (joined.size + upto[a:-1] - upto[a] >= SORTED))
                e = a + int(full[0]) if len(full) else len(h)
                if e > a:
                    joined.add(about[:, a:e], contexts.slice(a, e - a))
                if e == len(h):
                    break
                yield from solve(joined)
                joined, a = _Joined(induced_sort.LIMIT), e
        if joined.size:
            yield from solve(joined)

    return run


def _keyed(docs: DataFrame) -> DataFrame:
    """doc (null ids first), nth among rows that repeat an id, text, and row: the other columns of docs, whatever their names."""
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns if c != "text"]).alias("row")
    keyed = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(_FIRST)).alias("doc"), "text", row)
    out = numbered(keyed, ["doc"], [F.substring("text", 1, 64), F.xxhash64("text")])
    return out.withColumn("nth", F.col("nth").cast("int"))


def gone_ranges(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """docs: as _keyed gives them. doc, nth, start, end of byte ranges that go; they may overlap."""
    spark = docs.sparkSession
    n = partitions(spark)
    small = docs.select("doc", "nth", "text")
    found = small.mapInArrow(_anchors(length), _ROWS)
    # an anchor that very many places share comes once from each task's batch; what is settled goes anywhere
    place = F.when(F.col("gone"), F.xxhash64("doc", "nth", "start")).otherwise(F.col("h"))
    dealt = found.repartition(n, place).sortWithinPartitions("gone", *_NAMES[:-1])
    settled = settle(dealt.mapInArrow(_settle_copies, _ROWS))
    copies = settled.where("gone").select("doc", "nth", "start", (F.col("start") + F.col("n") + (length - 1)).alias("end"))
    open_ones = settled.where("NOT gone")
    hot = open_ones.groupBy("h").agg(F.count("*").alias("contexts")).where(F.col("contexts") > HOT).select("h", F.lit(True).alias("hot"))
    wanted = open_ones.join(hot, "h", "left").groupBy("doc", "nth").agg(F.collect_list(F.struct("h", "start", "n", "hot")).alias("wanted"))
    # all columns go along: then this shuffle of the texts is the one that `_gone` needs as well, and is made once
    texts = docs.join(wanted, ["doc", "nth"]).select("doc", "nth", "text", "wanted", "row")
    contexts = texts.mapInArrow(_cut_contexts(length), _CUT)
    place = F.when(F.col("context").isNull() & F.col("c").isNull(), F.xxhash64("doc", "nth", "start")).otherwise(F.col("h"))
    sorted_contexts = contexts.repartition(n, place).sortWithinPartitions("h", "c", "doc", "nth", "start")
    more = sorted_contexts.mapInArrow(_sort_contexts(length), "doc long, nth int, start long, end long")
    return copies.unionByName(more)


def _gone(docs: DataFrame, length: int) -> DataFrame:
    """docs with the sorted list of what goes (null where nothing does)."""
    ranges = gone_ranges(docs, length).groupBy("doc", "nth").agg(F.array_sort(F.collect_list(F.struct("start", "end"))).alias("gone"))
    return docs.join(ranges, ["doc", "nth"], "left")


def spans(ranges: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Sorted ranges merged where they overlap or touch."""
    out: list[list[int]] = []
    for s, e in ranges:
        if out and s <= out[-1][1]:
            out[-1][1] = max(out[-1][1], e)
        else:
            out.append([s, e])
    return [tuple(x) for x in out]


def kept_bytes(raw: bytes, gone: list[tuple[int, int]]) -> bytes:
    at, out = 0, []
    for s, e in gone:
        out.append(raw[at:s])
        at = e
    out.append(raw[at:])
    return b"".join(out)


def repeats(docs: DataFrame, *, length: int = LENGTH) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256: a row for each document."""
    prepare(docs.sparkSession)

    def run(batches):
        for b in batches:
            out = []
            for doc, text, gone in zip(b.column(0).to_pylist(), b.column(1), b.column(2), strict=True):
                raw = (text.as_py() or "").encode("utf-8")
                cut = spans([(x["start"], x["end"]) for x in gone.as_py() or []])
                kept = kept_bytes(raw, cut)
                out.append((doc, len(raw), len(raw) - len(kept), len(cut), hashlib.sha256(kept).hexdigest()))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), [pa.int64()] * 4 + [pa.string()], strict=True)], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    keyed = _keyed(long_id(docs.select("doc_id", "text"), "doc_id"))
    found = _gone(keyed, length).select("row.doc_id", "text", "gone")
    return found.mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def remove_repeats(docs: DataFrame, *, length: int = LENGTH) -> DataFrame:
    """The documents, all columns kept, with what is left of their texts; a character that is cut through goes too.

    n_chars, where there is such a column, follows the text. A null text stays null.
    """
    prepare(docs.sparkSession)

    @F.pandas_udf("string")
    def cut(texts, gone):
        import pandas as pd

        out = []
        for text, ranges in zip(texts, gone, strict=True):
            if text is None or ranges is None:
                out.append(text)
            else:
                merged = spans([(int(x["start"]), int(x["end"])) for x in ranges])
                out.append(kept_bytes(text.encode("utf-8"), merged).decode("utf-8", "ignore"))
        return pd.Series(out, dtype=object)

    found = _gone(_keyed(docs), length)
    text = F.when(F.col("gone").isNull(), F.col("text")).otherwise(cut("text", "gone"))
    found = found.select("row", text.alias("left"))
    changed = {"text": F.col("left")}
    if "n_chars" in docs.columns:
        changed["n_chars"] = F.coalesce(F.length("left").cast(docs.schema["n_chars"].dataType), F.col("row.n_chars"))
    return found.select(*[changed.get(c, F.col("row").getField(c)).alias(c) for c in docs.columns])


def op3_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats(table(spark, sf_dir, "documents", "doc_id", "text"))
