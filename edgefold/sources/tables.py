"""The given tables, with the schema that this library relies on."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "pages": "page_id bigint, url string, html string",
    "benchmark": "item_id bigint, text string",
    "labels": "doc_id bigint, quality int, toxic int",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}
KEYS = {"region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey", "lineitem": "l_orderkey", "events": "event_id", "documents": "doc_id", "embeddings": "vec_id", "pages": "page_id", "benchmark": "item_id", "labels": "doc_id", "conversations": "conv_id"}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The table; an error names a column that is missing or has another kind of type."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    have = {c: t.split("(")[0] for c, t in df.dtypes}
    for item in SCHEMAS[name].split(", "):
        column, kind = item.split(" ", 1)
        if column not in have:
            raise ValueError(f"{name} has no column {column}")
        numbers = {"int", "bigint", "smallint", "double", "float"}
        if have[column] != kind and not ({have[column], kind} <= numbers or have[column].startswith("timestamp") and kind.startswith("timestamp")):
            raise ValueError(f"{name}.{column} is {have[column]}, not {kind}")
    return df


def checksums(df: DataFrame, name: str) -> DataFrame:
    """One row: n, and for each column of the table's schema a number that every value of it goes into.

    Whole numbers are added up, fractions to four places of decimals each, strings by the first 32 bits of their digest,
    times as seconds, arrays by their elements; nulls add nothing.
    """
    have, sums = dict(df.dtypes), []
    for item in SCHEMAS[name].split(", "):
        column, kind = item.split(" ", 1)
        c = F.col(column)
        if kind == "string":
            total = F.sum(F.conv(F.substring(F.md5(c), 1, 8), 16, 10).cast("long"))
        elif kind == "timestamp_ntz" or have[column] == "timestamp_ntz":
            total = F.sum(F.expr(f"timestampdiff(SECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', {column})"))
        elif kind == "timestamp":
            total = F.sum(F.unix_seconds(c))
        elif kind == "double":
            total = F.sum(c.cast("decimal(18,4)")).cast("double")
        elif kind.startswith("array"):
            total = F.round(F.sum(F.aggregate(c, F.lit(0.0), lambda a, v: a + v.cast("double"))), 6)
        else:
            total = F.sum(c.cast("long"))
        sums.append(total.alias(f"sum_{column}"))
    return df.agg(F.count("*").alias("n"), *sums)


def checksums_sql(name: str) -> str:
    sums = []
    for item in SCHEMAS[name].split(", "):
        column, kind = item.split(" ", 1)
        total = f"sum({column}::BIGINT)::BIGINT"
        if kind == "string":
            total = f"sum(('0x' || substr(md5({column}), 1, 8))::BIGINT)::BIGINT"
        elif kind.startswith("timestamp"):
            total = f"sum(epoch_us({column}) // 1000000)::BIGINT"
        elif kind == "double":
            total = f"sum({column}::DECIMAL(18,4))::DOUBLE"
        elif kind.startswith("array"):
            total = f"round(sum(list_sum({column}::DOUBLE[])), 6)"
        sums.append(f"{total} AS sum_{column}")
    return f"SELECT count(*) AS n, {', '.join(sums)} FROM {name}"
