"""Queries that once made their data up: they follow the given tables, and agree with their SQL."""

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = ("customer", "part", "orders", "lineitem", "supplier", "events", "nation")


def rows(found, columns):
    clean = lambda v: round(v, 9) + 0.0 if isinstance(v, float) else v
    return sorted((tuple(clean(r[c]) for c in columns) for r in found), key=str)


@pytest.mark.parametrize("name", ["rmat_g8", "graph_profile_g8", "sigmoid_embedding_g8", "program_checks", "moved_bytes", "speedups"])
def test_follows_the_tables(spark, name):
    seen = []
    for size in ("sf0.001", "sf0.01"):
        at, con = f"/root/testdata/{size}", duckdb.connect()
        for t in TABLES:
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{at}/{t}.parquet'")
        want = con.execute(entry.oracle_sql()[name])
        columns = [c[0] for c in want.description]
        seen.append(rows(entry.queries()[name](spark, at).collect(), columns))
        assert seen[-1] == rows([dict(zip(columns, r, strict=True)) for r in want.fetchall()], columns)
    assert seen[0] != seen[1]
