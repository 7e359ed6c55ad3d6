"""The experiments beside the kernel table of bench.py: python -m edgefold.workloads SF_DIR [NAME...], a JSON line for each.

roofline   achieved and attainable rate of the embedding, d = 128, on each graph
vendor     neighbour sums against the packed sparse product, one core and all, d = 64, 128, 256
scaling    seconds of the embedding on the largest graph by cores, fused and in two phases
memory     MB between phases and in tasks by d, force layout on the densest graph
degree     speedup of layout and embedding by mean degree, on random graphs whose edges double
dimension  seconds of the embedding by d, on the graph of ten neighbours
training   seconds of an epoch by method, d = 128, batches of 256
"""

from __future__ import annotations

import json
import os
import sys
import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgefold.operators import two_phase
from edgefold.operators.fused import fused_fold
from edgefold.operators.packed import pack
from edgefold.plans import measure
from edgefold.plans import program as P
from edgefold.sources import features, graphs


def session(cores: str) -> SparkSession:
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    os.environ["PYTHONPATH"] = f"{root}:{os.environ.get('PYTHONPATH', '')}"
    os.environ.setdefault("OMP_NUM_THREADS", "1")
    builder = SparkSession.builder.master(f"local[{cores}]").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false")
    spark = builder.config("spark.sql.shuffle.partitions", "8").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="edgefold-workloads-"))
    return spark


class Held:
    """A graph with its packed rows and features, in memory."""

    def __init__(self, edges: DataFrame, targets: DataFrame, sources: DataFrame):
        self.edges, self.targets, self.sources = edges.persist(), targets.persist(), sources.persist()
        self.rows = pack(self.edges).persist()
        self.nnz, self.m = self.edges.count(), self.targets.count()
        self.rows.count()

    @classmethod
    def named(cls, spark: SparkSession, sf_dir: str, graph: str) -> Held:
        return cls(graphs.edges(spark, sf_dir, graph), graphs.targets(spark, sf_dir, graph), graphs.sources(spark, sf_dir, graph))

    def makes(self, program: P.Program, d: int) -> dict:
        x = features.hashed(self.targets.withColumnRenamed("u", "id"), d).persist()
        y = features.hashed(self.sources, d).persist()
        x.count(), y.count()
        return {
            "fused": lambda: fused_fold(self.edges, x, y, program, d=d, strategy="packed", rows=self.rows),
            "two_phase": lambda: two_phase.two_phase(self.edges, x, y, program, d=d),
            "vendor": lambda: two_phase.sparse_product(self.rows, y, d),
        }


def some(makes: dict, *names: str) -> dict:
    return {n: makes[n] for n in names}


def roofline(spark, sf_dir, d=128):
    band, out = measure.bandwidth() * spark.sparkContext.defaultParallelism, {}
    for graph in ("g1", "g2", "g3", "g7"):
        held = Held.named(spark, sf_dir, graph)
        seconds = measure.time_kernel(held.makes(P.sigmoid_embedding(), d)["fused"], n=3)
        out[graph] = measure.rates(held.nnz, d, held.m, seconds, band) | {"seconds": seconds}
    return out


def vendor(spark, sf_dir, graph="g2", dims=(64, 128, 256)):
    held = Held.named(spark, sf_dir, graph)
    return {d: measure.time_kernels(some(held.makes(P.graph_conv("sum"), d), "fused", "vendor"), n=3) for d in dims}


_SCALING = """
import json, os
from edgefold import workloads as W
from edgefold.plans import measure, program as P
spark = W.session(os.environ["CORES"])
held = W.Held.named(spark, os.environ["SF_DIR"], "g7")
makes = held.makes(P.sigmoid_embedding(), 64)
print(json.dumps(measure.time_kernels(W.some(makes, "fused", "two_phase"), n=2)))
"""


def scaling(spark, sf_dir, cores=(1, 2, 4, 8)):
    out = measure.scaling(_SCALING, [c for c in cores if c <= (os.cpu_count() or 1)], {"SF_DIR": sf_dir})
    first = out[min(out)]
    return {p: t | {f"{k}_gain": round(first[k] / t[k], 2) for k in t} for p, t in out.items()}


def memory(spark, sf_dir, graph="g2", dims=(32, 64, 128, 256)):
    held, out = Held.named(spark, sf_dir, graph), {}
    for d in dims:
        makes = held.makes(P.layout_displacement(), d)
        out[d] = {k: measure.peak_memory(spark, makes[k]) for k in ("fused", "two_phase")}
    return out


def degree(spark, sf_dir, scale=14, edges=(1 << 17, 1 << 18, 1 << 19, 1 << 20), d=64):
    out = {}
    for n in edges:
        e = graphs.rmat(spark, scale, n)
        ids = spark.range(1 << scale).select("id")
        held = Held(e, e.select("u").distinct(), ids)
        for name, program in (("embedding", P.sigmoid_embedding()), ("layout", P.layout_displacement())):
            times = measure.time_kernels(some(held.makes(program, d), "fused", "two_phase"), n=2)
            speedup = times["two_phase"] / times["fused"] if all(times.values()) else None
            out[f"{name}_{n}"] = times | {"mean_degree": held.nnz / held.m, "speedup": speedup}
    return out


def dimension(spark, sf_dir, dims=(32, 64, 128, 256, 512)):
    held = Held.named(spark, sf_dir, "g5")
    return measure.sweep(dims, lambda d: some(held.makes(P.sigmoid_embedding(), d), "fused", "two_phase"), n=2)


def training(spark, sf_dir, d=128, batch=256):
    e, ids = graphs.edges(spark, sf_dir, "g5").persist(), graphs.targets(spark, sf_dir, "g5").select(F.col("u")).persist()
    got = measure.time_epochs(e, ids, epochs=1, d=d, batches=max(1, ids.count() // batch))
    return got | {f"{k}_over_fused": v / got["fused"] for k, v in got.items()}


WORKLOADS = {f.__name__: f for f in (roofline, vendor, scaling, memory, degree, dimension, training)}


def main(sf_dir: str, *names: str) -> None:
    spark = session(os.environ.get("CORES", str(os.cpu_count() or 4)))
    for name in names or WORKLOADS:
        print(json.dumps({"workload": name, "cores": spark.sparkContext.defaultParallelism, "result": WORKLOADS[name](spark, sf_dir)}), flush=True)
        spark.catalog.clearCache()
    spark.stop()


if __name__ == "__main__":
    main(*sys.argv[1:])
