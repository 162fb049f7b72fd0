"""Readers and writers.  Readers name the columns they need, so scans stay narrow."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, folder: str, name: str, *columns: str) -> DataFrame:
    """A Parquet table of ``folder``; all columns when none are named."""
    read = spark.read.parquet(f"{folder}/{name}.parquet")
    return read.select(*columns) if columns else read


def shared_folder(spark: SparkSession) -> str:
    """Folder that the driver and every executor see, ``spark.checkpoint.dir``; a local session without one gets a folder of its own."""
    known = spark.conf.get("spark.checkpoint.dir", None)
    if not known:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        known = "file://" + tempfile.mkdtemp(prefix="weft-shared-")
    return known.rstrip("/")


def documents(spark: SparkSession, path: str, glob: str = "*.xml") -> DataFrame:
    """Whole files as (path, text): raw markup, whose sibling order a parsed reader would lose."""
    return spark.read.option("wholetext", True).option("pathGlobFilter", glob).text(path).select(F.input_file_name().alias("path"), F.col("value").alias("text"))


def write_schemas(schemas: DataFrame, path: str, mode: str = "overwrite") -> None:
    """Parquet, one folder per learner."""
    schemas.write.mode(mode).partitionBy("learner").parquet(path)


def write_registry(schemas: DataFrame, path: str, mode: str = "overwrite") -> None:
    """JSON lines (element, learner, text, factors)."""
    schemas.select("element", "learner", "text", "factors").write.mode(mode).json(path)


def read_schemas(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)
