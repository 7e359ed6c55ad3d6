"""Headline workloads; prints one JSON line. BENCH_SF_DIR and BENCH_CPUS choose tables and cores.

Kernels of a group take turns, ten each unless the budget ends them, after a warm run. fused: packed rows and the
specialised kernel; general: the same without specialisation; two_phase: messages written to Parquet between relational
phases; two_phase_packed: the same between kernels on packed rows; relational: fused in generated code; with_packing: fused, and its rows
packed each time. Published ratios stand beside ours in `detail`.
"""

from __future__ import annotations

import json
import math
import os
import sys
import tempfile
import time

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"
os.environ.setdefault("OMP_NUM_THREADS", "1")
SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "4")
ROUNDS = int(os.environ.get("BENCH_ROUNDS", "10"))
BUDGET_S = float(os.environ.get("BENCH_BUDGET_S", "420"))
#: Seconds of turns that a group may begin.
GROUP_S = float(os.environ.get("BENCH_GROUP_S", "4"))
#: Published speedups of the vectorised kernel over two phases: dense, sparse and large graph, by d.
PUBLISHED = {
    ("embedding", "g2"): {32: 3.385, 64: 5.655, 128: 9.488, 512: 13.433},
    ("embedding", "g3"): {32: 4.255, 64: 7.258, 128: 8.463, 512: 11.647},
    ("embedding", "g7"): {32: 5.089, 64: 6.381, 128: 7.202, 512: 6.856},
    ("layout", "g2"): {32: 11.487, 64: 19.737, 128: 34.389},
    ("layout", "g3"): {32: 7.899, 64: 10.29, 128: 11.174, 512: 13.045},
    ("layout", "g7"): {32: 12.372, 64: 15.192, 128: 14.414},
    ("graph_conv", "g2"): {32: 7.535, 64: 13.475, 128: 22.349},
    ("graph_conv", "g3"): {32: 4.789, 64: 4.8, 128: 5.541, 512: 10.963},
    ("graph_conv", "g7"): {32: 6.967, 64: 7.975, 128: 8.854},
}


def session(cpus: str = CPUS):
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.driver.memory", "8g")
        .config("spark.sql.shuffle.partitions", "8")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="edgefold-bench-"))
    return spark


def main() -> None:
    spark = session()
    from edgefold.operators import two_phase
    from edgefold.operators.fused import fused_fold
    from edgefold.operators.packed import pack
    from edgefold.plans import cost, measure
    from edgefold.plans import program as P
    from edgefold.sources import features, graphs

    began, seconds, rounds = time.time(), {}, {}
    detail = {"graphs": {}, "two_phase_over_fused": {}, "published": {}, "general_over_fused": {}, "like_with_like": {}, "rates": {}}
    programs = {"embedding": P.sigmoid_embedding(), "layout": P.layout_displacement(), "graph_conv": P.graph_conv("sum")}
    wide = {"g1": (32,), "g2": (32, 128, 512), "g3": (32, 128), "g7": (32, 128)}
    band = measure.bandwidth()
    for graph, role in (("g1", "medium"), ("g2", "dense"), ("g3", "sparse"), ("g7", "large")):
        if time.time() - began > BUDGET_S:
            break
        e = graphs.edges(spark, SF, graph).persist()
        t = graphs.targets(spark, SF, graph).persist()
        ids = graphs.sources(spark, SF, graph).persist()
        m, n, nnz = t.count(), ids.count(), e.count()
        rows = pack(e).persist()  # preprocessing, as the row index of a sparse matrix is
        rows.count()
        detail["graphs"][graph] = {"role": role, "m": m, "n": n, "nnz": nnz, "mean_degree": round(nnz / m, 2)}
        for d in wide[graph]:
            if time.time() - began > BUDGET_S:
                break
            x = features.hashed(t.withColumnRenamed("u", "id"), d).persist()
            y = features.hashed(ids, d).persist()
            x.count(), y.count()
            for name, program in programs.items():
                if time.time() - began > BUDGET_S:
                    continue
                key = f"{name}_{graph}_d{d}"
                makes = {
                    "fused": lambda p=program: fused_fold(e, x, y, p, d=d, strategy="packed", rows=rows),
                    "general": lambda p=program: fused_fold(e, x, y, p, d=d, strategy="packed", specialise=False, rows=rows),
                }
                if d <= 128 and not (graph == "g7" and d > 32 and name == "layout"):
                    makes["two_phase"] = lambda p=program: two_phase.two_phase(e, x, y, p, d=d)
                if graph == "g1" or (graph == "g2" and d == 128):
                    makes["relational"] = lambda p=program: fused_fold(e, x, y, p, d=d, strategy="relational")
                    makes["two_phase_packed"] = lambda p=program: two_phase.two_phase_packed(rows, x, y, p, d=d)
                    makes["with_packing"] = lambda p=program: fused_fold(e, x, y, p, d=d, strategy="packed")
                if name == "graph_conv" and d == 128:
                    makes["vendor"] = lambda: two_phase.vendor_product(e, y, d)
                got = measure.time_kernels(makes, ROUNDS, budget_s=GROUP_S)
                seconds |= {f"{key}_{k}": round(v, 3) for k, v in got.items() if v is not None}
                ratio = lambda k, of="fused": round(got[k] / got[of], 2) if got.get(k) and got.get(of) else None
                detail["general_over_fused"][key] = ratio("general")
                if "two_phase" in got:
                    detail["two_phase_over_fused"][key] = ratio("two_phase")
                    published = PUBLISHED.get((name, graph), {}).get(d)
                    if published:
                        detail["published"][key] = published
                if "relational" in got:
                    detail["like_with_like"][key] = {"relational": ratio("two_phase", "relational"), "packed": ratio("two_phase_packed"), "packing_counted": ratio("two_phase", "with_packing")}
                if got.get("fused"):
                    r = measure.rates(nnz, d, m, got["fused"], band * int(CPUS))
                    detail["rates"][key] = {k: round(v, 3) for k, v in r.items()}
            x.unpersist(), y.unpersist()
        e.unpersist(), t.unpersist(), ids.unpersist(), rows.unpersist()
    if time.time() - began < BUDGET_S:
        e, ids = graphs.edges(spark, SF, "g5").persist(), graphs.targets(spark, SF, "g5").persist()
        got = measure.time_epochs(e, ids, epochs=1, d=32, batches=2)
        seconds |= {f"epoch_g5_d32_{k}": round(v, 3) for k, v in got.items()}
        detail["epochs_over_fused"] = {k: round(v / got["fused"], 2) for k, v in got.items()}
    short = [detail["published"][k] / detail["two_phase_over_fused"][k] for k in detail["published"] if detail["two_phase_over_fused"].get(k)]
    gains = [v for v in detail["general_over_fused"].values() if v]
    mean = lambda values: round(math.exp(sum(map(math.log, values)) / len(values)), 3) if values else None
    detail |= {"published_over_ours_geomean": mean(short), "general_over_fused_geomean": mean(gains), "bandwidth_one_core_gb_s": round(band, 2)}
    print(json.dumps({"metric": "total_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": SF.rsplit("sf", 1)[-1], "cpus": CPUS, "detail": detail}))
    spark.stop()


if __name__ == "__main__":
    main()
