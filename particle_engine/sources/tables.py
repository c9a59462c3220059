"""Declared schemas of the given tables, and readers and writers for other formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

SCHEMAS = {
    "events": "event_id long, ts timestamp, user_id long, event_type string, value double, props string",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "region": "r_regionkey int, r_name string",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "labels": "doc_id long, quality int, toxic int",
    "pages": "page_id long, url string, html string",
    "conversations": "conv_id long, turn long, role string, text string",
    "benchmark": "item_id long, text string",
}
FORMATS = ("parquet", "orc", "json", "csv", "text")


def schema(name: str) -> T.StructType:
    return T.StructType.fromDDL(SCHEMAS[name])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Scan of a given table; the declared schema spares inference over the files."""
    return spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir}/{name}.parquet")


def read_any(spark: SparkSession, path: str, fmt: str, ddl: str | None = None) -> DataFrame:
    """Read one of ``FORMATS``; text formats other than ``text`` need a schema, which is never inferred."""
    if fmt not in FORMATS:
        raise ValueError(f"unknown format {fmt}; one of {FORMATS}")
    if fmt in ("json", "csv") and not ddl:
        raise ValueError(f"{fmt} needs a schema")
    reader = spark.read.format(fmt)
    if ddl and fmt != "text":
        reader = reader.schema(ddl)
    return reader.option("header", True).load(path) if fmt == "csv" else reader.load(path)


def write_any(df: DataFrame, path: str, fmt: str, partition_by: list[str] | None = None, mode: str = "errorifexists") -> None:
    if fmt not in FORMATS:
        raise ValueError(f"unknown format {fmt}; one of {FORMATS}")
    writer = df.write.format(fmt).mode(mode)
    if fmt == "csv":
        writer = writer.option("header", True)
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.save(path)


def drain(df: DataFrame) -> None:
    """Run a plan without output (timing)."""
    df.write.format("noop").mode("overwrite").save()
