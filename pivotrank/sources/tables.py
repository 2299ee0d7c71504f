"""Reading the given tables with fixed schemas, and writing and reading indexes."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "labels": "doc_id long, quality int, toxic int",
    "conversations": "conv_id long, turn long, role string, text string",
}


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    """A table by name, with its fixed schema; the readers of Spark see the path, so any store will do."""
    return spark.read.schema(SCHEMAS[name]).parquet(f"{folder}/{name}.parquet")


def write_index(frame: DataFrame, path: str, keys: list[str], order: list[str] | None = None, **manifest) -> None:
    """An index dealt by ``keys`` and sorted within files, so that min and max values skip row groups.

    The manifest (parameters and counts) goes beside it as one JSON file.
    """
    frame.repartitionByRange(*keys).sortWithinPartitions(*(order or keys)).write.mode("overwrite").parquet(f"{path}/data")
    frame.sparkSession.createDataFrame([(json.dumps(manifest, sort_keys=True),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")


def read_index(spark: SparkSession, path: str) -> tuple[DataFrame, dict]:
    return spark.read.parquet(f"{path}/data"), json.loads(spark.read.text(f"{path}/manifest").first()["value"])


def write_bucketed(frame: DataFrame, name: str, keys: list[str], buckets: int, order: list[str] | None = None) -> DataFrame:
    """A table in the warehouse dealt into buckets by ``keys``, so that joins and aggregates by them need no shuffle."""
    frame.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*(order or keys)).format("parquet").saveAsTable(name)
    return frame.sparkSession.table(name)


def read_points(spark: SparkSession, path: str, kind: str, schema: str) -> DataFrame:
    """Points from csv, json, orc, parquet or text files, with a fixed schema."""
    reader = spark.read.schema(schema)
    return reader.option("header", True).csv(path) if kind == "csv" else reader.format(kind).load(path)


def write_points(points: DataFrame, path: str, kind: str) -> None:
    """Points to files; csv takes arrays and structs as JSON text."""
    if kind in ("csv", "text"):
        nested = [f.name for f in points.schema.fields if f.dataType.typeName() in ("array", "struct", "map")]
        points = points.withColumns({c: F.to_json(c) for c in nested})
        if kind == "text":
            points = points.select(F.to_json(F.struct("*")).alias("value"))
    writer = points.write.mode("overwrite").format(kind)
    (writer.option("header", True) if kind == "csv" else writer).save(path)
