"""A few registered queries against their SQL; the driver checks them all."""

import duckdb
import pytest

import __spark_entry__ as entry

NAMES = ["sigmoid_embedding_g1", "two_phase_layout_g4", "balanced_parts_g6", "graph_conv_mean_g5", "asof_event", "interval_edges", "cost_model", "streaming_fold_mean", "rmat_g8", "f1_micro_lang"]


@pytest.mark.parametrize("name", NAMES)
def test_query(spark, sf, name):
    con = duckdb.connect()
    for t in ("customer", "part", "orders", "lineitem", "supplier", "events", "embeddings", "documents"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    got = entry.queries()[name](spark, sf)
    want = con.execute(entry.oracle_sql()[name])
    columns = [c[0] for c in want.description]
    clean = lambda r: tuple(None if v is None else round(v, 9) + 0.0 if isinstance(v, float) else v for v in r)
    assert sorted(map(clean, want.fetchall()), key=str) == sorted((clean(r[c] for c in columns) for r in got.collect()), key=str)


def test_oracles_belong_to_queries(spark):
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert entry.entry(spark).limit(1).count() == 1
