"""Mixing of sources to target weights by pivotal dependent rounding.

A source's target is its share of all sizes by weight, stopped at a few times the source's own size; what is over is
shared again by weight until no source is above. A document then wants target / source size copies: the whole part is
certain, the fraction is a copying probability. Pivotal rounding meets documents two at a time and moves probability
from one to the other, at random and without bias, until one of them is 0 or 1; the other goes on. The sum of the
probabilities never changes, so the copies of a source come out at the number that was asked for.

Blocks of a source, of documents of like size, are rounded by themselves; each leaves one document open at most.
Those residuals meet in a reduction tree: groups of up to FAN_IN blocks of a source are rounded in the next level, again
until one is left for the source. Draws are hashes of the ids and a seed, and blocks depend on hashes of ids alone, so
a rerun agrees however the input is partitioned. Rows that repeat an id have numbers of their own and hash by these as
well, so no task gets more than a block, whatever share a source or an id has.

Defined cases: a null text has size 0; null sources are a source of their own, after the others; sources of size 0 get
target 0 and none of their documents is taken; rows that repeat an id are documents each; an empty table gives no rows;
columns other than doc_id, source and text are ignored by `mix`.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, StructField, StructType

from edgefold.llm.shared import long_id, numbered, prepare, settle, table

WEIGHTS = (1.0, 2.0, 3.0)
MOST_TIMES = 3.0
BLOCK = 1_024
FAN_IN = 256
SEED = 7


def word_count(text) -> F.Column:
    """Runs of characters other than ASCII white space."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def targets(sizes: DataFrame, *, weights: tuple[float, ...] = WEIGHTS, most_times: float = MOST_TIMES) -> DataFrame:
    """source, source_size, n, target. sizes: a row for each source, with its size and number of documents.

    Sources take the weights in turn, by code point, null last. What stops at its cap is known from sorting sources
    by cap over weight: with the first k stopped, the rest share what is left by weight, and the right k is the least
    for which none of the rest passes its cap. Windows here run over one row for each source.
    """
    turn = Window.orderBy(F.col("source").asc_nulls_last())
    order = Window.orderBy("ratio", F.col("source").asc_nulls_last())
    upto = order.rowsBetween(Window.unboundedPreceding, -1)
    every = Window.orderBy(F.lit(0)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(F.row_number().over(turn) - 1, F.lit(len(weights))) + 1).cast("int"))
    out = sizes.withColumn("weight", weight).withColumn("cap", F.col("source_size") * F.lit(float(most_times)))
    out = out.withColumn("ratio", F.col("cap") / F.col("weight"))
    left = F.sum("source_size").over(every) - F.coalesce(F.sum("cap").over(upto), F.lit(0.0))
    heavy = F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(upto), F.lit(0.0))
    out = out.withColumn("level", left / heavy)
    level = F.min(F.when(F.col("ratio") >= F.col("level"), F.struct("ratio", "level"))).over(every)["level"]
    out = out.withColumn("final", F.coalesce(level, F.lit(float("inf"))))
    return out.select("source", "source_size", "n", F.least("cap", F.col("final") * F.col("weight")).alias("target"))


def pivotal(p: np.ndarray, draws: np.ndarray) -> tuple[np.ndarray, int]:
    """Round probabilities in order; returns 0s and 1s, and the position left open (-1 if none), with its probability."""
    out, open_at, open_p = p.copy(), -1, 0.0
    for i, (q, u) in enumerate(zip(p.tolist(), draws.tolist(), strict=True)):
        if q <= 0.0 or q >= 1.0:
            continue
        if open_at < 0:
            open_at, open_p = i, q
            continue
        both = open_p + q
        if both < 1.0:  # one of them loses all
            if u * both < open_p:
                out[i], open_p = 0.0, both
            else:
                out[open_at], open_at, open_p = 0.0, i, both
        elif u * (2.0 - both) < 1.0 - q:  # one of them wins a whole copy
            out[open_at], open_at, open_p = 1.0, i, both - 1.0
        else:
            out[i], open_p = 1.0, both - 1.0
        if open_p <= 1e-12 or open_p >= 1.0 - 1e-12:
            out[open_at], open_at = round(open_p), -1
    if open_at >= 0:
        out[open_at] = open_p
    return out, open_at


def _draws(ids: pd.Series, level: int, seed: int) -> np.ndarray:
    return np.asarray([xxhash.xxh64_intdigest(f"{i}:{level}", seed) for i in ids.tolist()], dtype=np.float64) / 2.0**64


def _round_blocks(rows: DataFrame, block: list[str], level: int, seed: int) -> DataFrame:
    """Round p within each block, documents in order of size: those next to each other stand in for each other."""

    def run(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values(["size", "row"], kind="stable")
        p, open_at = pivotal(group["p"].to_numpy(), _draws(group["row"], level, seed))
        return group.assign(p=p, open=np.arange(len(group)) == open_at)

    return rows.groupBy(*block).applyInPandas(run, StructType([*rows.schema.fields, StructField("open", BooleanType())]))


def _numbered(docs: DataFrame) -> DataFrame:
    """docs with nth: its number among rows of one id. Those of one source and size may stand in for each other."""
    return numbered(docs, ["doc_id"], [F.col("source"), F.col("size")])


def copies(docs: DataFrame, *, seed: int = SEED, weights: tuple[float, ...] = WEIGHTS, most_times: float = MOST_TIMES) -> DataFrame:
    """doc_id, size, source_size, target, nth, copies. docs: doc_id, source, size, and nth where rows have numbers already."""
    docs = long_id(docs, "doc_id")
    keyed = (docs if "nth" in docs.columns else _numbered(docs)).select("doc_id", "source", "size", "nth")
    sizes = keyed.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n"))
    aims = settle(targets(sizes, weights=weights, most_times=most_times))
    source_key = F.xxhash64(F.coalesce(keyed["source"], F.lit("")), keyed["source"].isNull())
    ratio = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    # Sources that have the same name in both; the smaller side has a row for each source.
    joined = keyed.join(aims, keyed["source"].eqNullSafe(aims["source"])).select(
        "doc_id", keyed["source"], "size", "nth", "source_size", "target", source_key.alias("source_key"), ratio.alias("ratio"), "n"
    )
    salt = F.pmod(F.xxhash64("doc_id", "nth", F.lit(seed)), F.ceil(F.col("n") / BLOCK))
    base = F.floor("ratio")
    wanted = settle(
        joined.withColumn("base", base.cast("long")).select(
            "doc_id", "source", "size", "nth", "source_size", "target", "source_key", "base",
            (F.col("ratio") - F.col("base")).alias("p"),
            F.xxhash64("doc_id", "size", "nth").alias("row"),
            F.floor(F.log2(F.col("size") + 1)).cast("long").alias("bucket"), salt.cast("long").alias("salt"),
        )
    )
    done, level = [], 0
    now = _round_blocks(wanted, ["source_key", "bucket", "salt"], level, seed)
    while True:
        now = settle(now)
        done.append(now.where("NOT open").drop("open"))
        rest = now.where("open").drop("open")
        left = rest.groupBy("source_key").agg(F.count("*").alias("n"))
        widest = left.agg(F.max("n")).first()[0] or 0
        level += 1
        if widest <= 1:
            last = F.xxhash64("row", F.lit(level), F.lit(seed)).cast("double") / 2.0**64 + 0.5
            done.append(rest.withColumn("p", F.when(last < F.col("p"), 1.0).otherwise(0.0)))
            break
        # The next level's blocks: FAN_IN residuals of a source on average.
        block = F.pmod(F.xxhash64("row", F.lit(level)), F.ceil(F.col("n") / FAN_IN))
        rest = rest.join(left, "source_key").withColumn("salt", block.cast("long")).drop("n")
        now = _round_blocks(rest, ["source_key", "salt"], level, seed)
    whole = done[0]
    for more in done[1:]:
        whole = whole.unionByName(more)
    return whole.select("doc_id", "source", "size", "nth", "source_size", "target", (F.col("base") + F.col("p").cast("long")).alias("copies"))


def mix(docs: DataFrame, *, seed: int = SEED, weights: tuple[float, ...] = WEIGHTS, most_times: float = MOST_TIMES) -> DataFrame:
    """The documents of the mix with all their columns, each as often as it is taken."""
    prepare(docs.sparkSession)
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")
    mine = _numbered(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "source", word_count("text").alias("size"), row))
    taken = copies(mine.select("doc_id", "source", "size", "nth"), seed=seed, weights=weights, most_times=most_times)
    taken = taken.where("copies > 0").select(*[F.col(c).alias(f"of_{c}") for c in ("doc_id", "source", "size", "nth")], "copies")
    same = [mine[c].eqNullSafe(taken[f"of_{c}"]) for c in ("doc_id", "source", "size", "nth")]
    times = F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))).alias("time")
    return mine.join(taken, same).select("row", times).select("row.*")


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "source", "text")
    out = copies(docs.select("doc_id", "source", word_count("text").alias("size")))
    return out.select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"))
