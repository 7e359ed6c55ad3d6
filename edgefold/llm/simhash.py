"""Near-duplicates by 64-bit similarity fingerprints of word shingles.

Fingerprints are taken over whole texts. Two that differ in at most d bits agree in at least 8 - d of their 8 bytes, so
an inverted index over (position, byte) finds them by counting shared positional bytes. Keys of single positions would
list a 256th of all fingerprints each; the index therefore lists by combinations of positions, chosen so that any
8 - d shared bytes hold one of them, and as long as the number of fingerprints asks for. A candidate pair's shared
positional bytes are tallied, those with fewer than the guaranteed count go, and the rest are verified bit by bit.

Copies cost nothing: the index holds each distinct fingerprint once. A list with many members is cut into chunks, and
each pair of chunks is compared by itself, so no task gets an unbounded list. From a list come not its pairs but links
that join what is linked in it.

Defined cases: null and empty texts have no words and fingerprint zero, and link like any other; nulls in doc_id link
but never name a component, which is null where all its ids are; repeated rows are kept; other columns are ignored by
`cluster` and kept by `keep_one`, which finds its groups by wider SimHash fingerprints in parts (`near_copies`).
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgefold.llm import near_copies
from edgefold.llm.components import components, union_find
from edgefold.llm.shared import long_id, partitions, prepare, settle, table

SEED = 42
BITS = 4
SHINGLE_WORDS = 4
#: Members of a list that are compared in one piece.
CHUNK = 2_048
#: Hashes of a text that are counted at a time.
_COUNTED = 1 << 18


def _hashes(words: list[bytes], size: int) -> np.ndarray:
    text = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    digest, n = xxhash.xxh64_intdigest, max(1, len(words) - size + 1)
    lows, highs = starts[:n].tolist(), ends[size - 1 :].tolist() if len(words) >= size else [len(text)]
    return np.fromiter([digest(text[a:b], SEED) for a, b in zip(lows, highs, strict=True)], np.uint64, n)


def fingerprint(text: str | None, size: int = SHINGLE_WORDS) -> int:
    """Bit b is set if it is set in over half the hashes of the text's shingles; zero if there are no words.

    Words are runs of bytes other than ASCII white space, A-Z lowered.
    """
    words = (text or "").encode("utf-8").lower().split()
    if not words:
        return 0
    values = _hashes(words, size)
    counts = np.zeros(64, dtype=np.int64)
    for at in range(0, len(values), _COUNTED):
        bits = np.unpackbits(values[at : at + _COUNTED].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        counts += bits.sum(axis=0, dtype=np.int64)
    return int(sum(1 << b for b in np.flatnonzero(counts * 2 > len(values)).tolist()))


def with_fingerprints(docs: DataFrame, size: int = SHINGLE_WORDS) -> DataFrame:
    """doc_id, fp (the 64 bits as a signed long)."""

    def run(batches):
        for b in batches:
            found = np.asarray([fingerprint(t.as_py(), size) for t in b.column(1)], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(found)], ["doc_id", "fp"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, fp long")


def position_sets(bits: int, size: int) -> list[tuple[int, ...]]:
    """Few sets of `size` byte positions such that any 8 - bits positions hold one of them.

    The 8 positions are dealt into groups; by Turan's bound on the pairs, and greedily for longer sets.
    """
    wanted = {frozenset(x) for x in combinations(range(8), 8 - bits)}
    if not 1 <= size <= 8 - bits:
        raise ValueError("a key can't have more positions than a linked pair is sure to share")
    out, sets = [], list(combinations(range(8), size))
    while wanted:
        best = max(sets, key=lambda s: (sum(x.issuperset(s) for x in wanted), [-p for p in s]))
        out.append(best)
        wanted = {x for x in wanted if not x.issuperset(best)}
    return out


def key_size(distinct: int, bits: int) -> int:
    """Positions in a key: enough that a list holds few unrelated fingerprints, as far as the guarantee allows."""
    size = 1
    while size < 8 - bits and distinct >> (8 * size - 2):
        size += 1
    return size


def _pairs(values: np.ndarray, first: int, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Positions (i, j), i < j, that are linked among one or between two chunks (the first has `first` members)."""
    low, high = [], []
    step = max(1, (1 << 21) // max(1, len(values)))
    for at in range(0, first, step):
        rows = values[at : min(at + step, first)]
        other = values[first:] if first < len(values) else values
        apart = rows[:, None] ^ other[None, :]
        shared = (apart.view(np.uint8).reshape(*apart.shape, 8) == 0).sum(axis=2, dtype=np.uint8)  # the tally
        i, j = np.nonzero(shared >= 8 - bits)
        near = np.bitwise_count(apart[i, j]) <= bits
        i, j = i[near] + at, j[near] + (first if first < len(values) else 0)
        low.append(i[i < j])
        high.append(j[i < j])
    return np.concatenate(low), np.concatenate(high)


def links(fps: DataFrame, *, bits: int = BITS, chunk: int = CHUNK) -> DataFrame:
    """Links (a, b) between names such that fingerprints joined by chains of at most `bits` bits share a component.

    fps: fp and name, each fp once. Every linked pair is met in one list at least, and each list's links join all that
    is linked within it.
    """
    spark = fps.sparkSession
    sets = position_sets(bits, key_size(fps.count(), bits))

    def masked(positions: tuple[int, ...]):
        mask = sum(255 << (8 * p) for p in positions)
        return F.col("fp").bitwiseAND(F.lit(mask - (1 << 64) if mask >> 63 else mask))

    keys = F.posexplode(F.array(*[masked(s) for s in sets])).alias("set", "key")
    listed = settle(fps.select(keys, "fp", "name"))
    sizes = listed.groupBy("set", "key").agg(F.count("*").alias("n")).where("n > 1")
    met = listed.join(sizes, ["set", "key"])
    chunks = F.ceil(F.col("n") / chunk).cast("int")
    mine = F.when(chunks > 1, F.pmod(F.xxhash64("fp", F.lit("chunk")), chunks)).otherwise(F.lit(0)).cast("int")
    other = F.explode(F.sequence(F.lit(0), chunks - 1)).alias("other")
    dealt = met.select("set", "key", "fp", "name", mine.alias("mine"), other)
    dealt = dealt.select(
        "set", "key", F.least("mine", "other").alias("c1"), F.greatest("mine", "other").alias("c2"), "mine", "fp", "name"
    )
    place = ["set", "key", "c1", "c2"]
    dealt = dealt.repartition(partitions(spark), *place).sortWithinPartitions(*place, "mine", "fp")

    def run(batches):
        held: list[np.ndarray] | None = None

        def columns(b):
            return np.stack([b.column(k).to_numpy().astype(np.int64) for k in range(7)])

        def compare(part: np.ndarray):
            """Lists one after another; a list is rows that share the first four columns."""
            cuts = np.flatnonzero((part[:4, 1:] != part[:4, :-1]).any(axis=0)) + 1
            starts, ends = np.concatenate([[0], cuts]), np.concatenate([cuts, [part.shape[1]]])
            pair = ends - starts == 2
            x, y = starts[pair], starts[pair] + 1
            apart = part[5, x].view(np.uint64) ^ part[5, y].view(np.uint64)
            shared = (np.ascontiguousarray(apart).view(np.uint8).reshape(-1, 8) == 0).sum(axis=1)
            near = (shared >= 8 - bits) & (np.bitwise_count(apart) <= bits)
            out = [(part[6, x[near]], part[6, y[near]])]
            for s, e in zip(starts[ends - starts > 2].tolist(), ends[ends - starts > 2].tolist(), strict=True):
                first = int((part[4, s:e] == part[2, s]).sum())
                i, j = _pairs(np.ascontiguousarray(part[5, s:e]).view(np.uint64), first, bits)
                if len(i):
                    nodes, least = union_find(i, j)
                    joined = nodes != least
                    out.append((part[6, s:e][nodes[joined]], part[6, s:e][least[joined]]))
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate([o[k] for o in out])) for k in (0, 1)], ["a", "b"])

        for b in batches:
            part = columns(b)
            if held is not None:
                part = np.concatenate([held, part], axis=1)
            last = np.flatnonzero((part[:4, 1:] != part[:4, :-1]).any(axis=0))
            if len(last):
                yield compare(part[:, : last[-1] + 1])
                held = part[:, last[-1] + 1 :]
            else:
                held = part
        if held is not None:
            yield compare(held)

    return dealt.mapInArrow(run, "a long, b long")


def cluster(docs: DataFrame, *, bits: int = BITS, shingle_words: int = SHINGLE_WORDS, chunk: int = CHUNK) -> DataFrame:
    """doc_id, fp, component_id (the least doc_id reachable by links, itself included): a row for each document."""
    prepare(docs.sparkSession)
    found = settle(with_fingerprints(long_id(docs.select("doc_id", "text"), "doc_id"), shingle_words))
    named = settle(found.groupBy("fp").agg(F.min("doc_id").alias("least_id")))
    joined = components(links(named.select("fp", F.col("fp").alias("name")), bits=bits, chunk=chunk))
    placed = named.join(joined.withColumnRenamed("node", "fp"), "fp", "left")
    placed = settle(placed.select("fp", "least_id", F.coalesce("component", "fp").alias("component")))
    least = placed.groupBy("component").agg(F.min("least_id").alias("component_id"))
    of_fp = settle(placed.join(least, "component").select("fp", "component_id"))
    return found.join(of_fp, "fp").select("doc_id", "fp", "component_id")


def hex_fingerprint(fp) -> F.Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def shingle_set(text: str | None, size: int) -> np.ndarray:
    """Sorted distinct hashes of the shingles of a text, words as for its fingerprint."""
    words = (text or "").encode("utf-8").lower().split()
    return np.unique(_hashes(words, size)) if words else np.empty(0, np.uint64)


def keep_one(docs: DataFrame, *, shingle_words: int = 5) -> DataFrame:
    """All columns of one document of each group of near copies (shingle similarity of 0.8 or more, in chains): the one
    with its least doc_id, and all without an id."""
    kept = near_copies.cluster(docs, lambda text: shingle_set(text, shingle_words))
    kept = kept.where("doc_id IS NULL OR doc_id = component_id").select(F.col("doc_id").alias("kept_id")).distinct()
    same = docs["doc_id"].cast("long").eqNullSafe(kept["kept_id"])
    return docs.join(kept, same, "left_semi")


def op1_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = cluster(table(spark, sf_dir, "documents", "doc_id", "text"))
    return found.select("doc_id", hex_fingerprint("fp").alias("fingerprint"), "component_id")
