"""part_range_join gives every target its part, at every size."""

import duckdb
import pytest

import __spark_entry__ as entry
from edgefold.sources import graphs


@pytest.mark.parametrize("size", ["sf0.01", "sf0.1"])
def test_every_target_has_its_part(spark, size):
    at = f"/root/testdata/{size}"
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{at}/events.parquet'")
    counts = con.execute(f"SELECT u, count(*) FROM ({graphs.SQL['g4']}) GROUP BY u ORDER BY u").fetchall()
    want, before = [], 0
    for u, n in counts:
        want.append((u, before // 1000))
        before += n
    got = entry.queries()["part_range_join"](spark, at)
    assert got.schema["part"].dataType.simpleString() == "int"
    assert sorted((r["u"], r["part"]) for r in got.collect()) == want
