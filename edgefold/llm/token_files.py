"""Token-id files: every id in the fewest bits that the vocabulary needs, with offsets for random access.

A file set is a Parquet folder written by Spark, so that it lands whole in any store and a lost executor's attempt
leaves nothing. A row is a block: its shard (shards follow ascending doc_id), its number in the shard, the bits of an
id, its documents with their token counts, the ids of the shard before it, and the packed ids. A document's ids start at
a known value of a known block, and `bitpack.unpack` reads just those.

Defined cases: a null text is empty and yields the end id alone; null ids come first; rows that repeat an id stay apart,
ordered by text; an empty table gives an empty file set; columns other than doc_id and text are ignored.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgefold.llm import bitpack
from edgefold.llm.shared import long_id, partitions, pieces, prepare, settle, table
from edgefold.llm.vocabulary import WordIds, default_path

END_ID = 2
BLOCK_IDS = 1 << 19
BLOCKS = "shard int, block int, bits int, doc_ids array<long>, doc_tokens array<long>, before long, packed binary"


def _blocks(path: str, end_id: int, block_ids: int):
    end = np.asarray([end_id], dtype="<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        words, shard = WordIds.opened(path), TaskContext.get().partitionId()
        bits = bitpack.width(max(words.size, end_id + 1))
        held: list[tuple[int | None, bytes]] = []
        done = {"block": 0, "before": 0, "held": 0}

        def block() -> pa.RecordBatch:
            counts = [len(x) // 4 for _, x in held]
            values = np.frombuffer(b"".join(x for _, x in held), dtype="<u4")
            row = [shard, done["block"], bits, [d for d, _ in held], counts, done["before"], bitpack.pack(values, bits)]
            kinds = [pa.int32(), pa.int32(), pa.int32(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.int64(), pa.binary()]
            done["block"] += 1
            done["before"] += len(values)
            done["held"] = 0
            held.clear()
            names = [x.split()[0] for x in BLOCKS.split(", ")]
            return pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(row, kinds, strict=True)], names)

        def rows():
            for b in batches:
                yield from zip(b.column(0).to_pylist(), (x.as_py() or "" for x in b.column(1)), strict=True)

        for some in pieces(rows()):
            for (doc, _), ids in zip(some, words.encode([t for _, t in some]), strict=True):
                held.append((doc, ids + end))
                done["held"] += len(ids) // 4 + 1
                if done["held"] >= block_ids:
                    yield block()
        if held:
            yield block()

    return run


def write_token_files(
    docs: DataFrame, path: str, *, vocabulary: str | None = None, end_id: int = END_ID, block_ids: int = BLOCK_IDS
) -> None:
    """Encode whole texts in ascending doc_id and write the file set. One shuffle, by ranges of doc_id."""
    spark = docs.sparkSession
    prepare(spark)
    ordered = (
        long_id(docs.select("doc_id", "text"), "doc_id")
        .repartitionByRange(partitions(spark), "doc_id")
        .sortWithinPartitions("doc_id", "text")
    )
    blocks = ordered.mapInArrow(_blocks(vocabulary or default_path(), end_id, block_ids), BLOCKS)
    blocks.write.mode("overwrite").parquet(path)


def shard_starts(spark: SparkSession, path: str) -> dict[int, int]:
    """Ids of all shards before each; as many entries as the file set has shards."""
    sizes = (
        spark.read.parquet(path)
        .select("shard", F.aggregate("doc_tokens", F.lit(0).cast("long"), lambda a, x: a + x).alias("n"))
        .groupBy("shard")
        .agg(F.sum("n").alias("n"))
        .orderBy("shard")
        .collect()
    )
    out, total = {}, 0
    for r in sizes:
        out[r["shard"]] = total
        total += r["n"]
    return out


def read_digest(spark: SparkSession, path: str) -> DataFrame:
    """Per document, from the files alone: doc_id, start, n_tokens, ids_crc32."""
    starts = shard_starts(spark, path)

    def run(batches):
        for b in batches:
            for row in b.to_pylist():
                n = np.asarray(row["doc_tokens"], dtype=np.int64)
                at = np.concatenate([[0], np.cumsum(n)])
                values = bitpack.unpack(row["packed"], row["bits"], 0, int(at[-1])).astype("<u4")
                raw = memoryview(values.tobytes())
                crc = [zlib.crc32(raw[a * 4 : z * 4]) for a, z in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]
                start = at[:-1] + row["before"] + starts[row["shard"]]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(row["doc_ids"], pa.int64()), pa.array(start), pa.array(n), pa.array(crc, pa.int64())],
                    ["doc_id", "start", "n_tokens", "ids_crc32"],
                )

    return spark.read.parquet(path).mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def read_ids(spark: SparkSession, path: str, doc_ids: list[int]) -> DataFrame:
    """Random access: doc_id and ids of the named documents, reading only their blocks' rows and their groups of bits."""
    wanted = F.array(*[F.lit(int(d)).cast("long") for d in doc_ids])

    def run(batches):
        for b in batches:
            for row in b.to_pylist():
                at = np.concatenate([[0], np.cumsum(row["doc_tokens"])]).tolist()
                for d, a, z in zip(row["doc_ids"], at[:-1], at[1:], strict=True):
                    if d in doc_ids:
                        ids = bitpack.unpack(row["packed"], row["bits"], a, z - a)
                        yield pa.RecordBatch.from_arrays(
                            [pa.array([d], pa.int64()), pa.array([ids.tolist()], pa.list_(pa.int64()))], ["doc_id", "ids"]
                        )

    blocks = spark.read.parquet(path).where(F.arrays_overlap("doc_ids", wanted))
    return blocks.mapInArrow(run, "doc_id long, ids array<long>")


def op7_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    path = f"{spark.sparkContext.getCheckpointDir()}/token-files-{uuid.uuid4().hex}"
    write_token_files(docs, path)
    digest = settle(read_digest(spark, path))
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)
    return digest
