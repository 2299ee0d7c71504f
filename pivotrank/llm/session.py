"""What the operators ask of the session: a shared checkpoint folder, sizes, partition counts."""

from __future__ import annotations

import math
import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """The folder that spark.checkpoint.dir names, which all executors share.

    Where it is unset, a temporary folder of the driver if driver and executors are one machine, as in
    tests; elsewhere executors could not share it, and ValueError is raised.
    """
    context = spark.sparkContext
    held = context._jsc.sc().getCheckpointDir()
    if held.isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not context.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoint-"))
        held = context._jsc.sc().getCheckpointDir()
    return held.get()


def cut(df: DataFrame) -> DataFrame:
    """The rows written to the shared folder and read from there."""
    shared_folder(df.sparkSession)
    return df.checkpoint()


def small_batches(df: DataFrame, rows: int = 1000) -> None:
    """Batches between Spark and Python of ``rows`` rows at most, for whole texts; a setting that sessions may change as they run."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    conf = df.sparkSession.conf
    if not 0 < int(conf.get(key)) <= rows:
        conf.set(key, str(rows))


def text_bytes(docs: DataFrame, text: str = "text") -> int:
    """UTF-8 bytes of a column's texts."""
    return docs.agg(F.sum(F.octet_length(text)).alias("b")).first()["b"] or 0


def parts_for(size: float, each: float) -> int:
    """How many parts of ``each`` a size makes, one at least."""
    return max(1, math.ceil(size / each))


def part_of(parts: int, *columns: str):
    """A part number from 0, by hash of columns."""
    return F.pmod(F.xxhash64(*map(F.col, columns)), F.lit(parts)).cast("int")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
