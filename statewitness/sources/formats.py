"""Ledgers in other formats: written to the shared scratch folder and read back with a given schema."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def scratch_path(spark: SparkSession, name: str) -> str:
    """A new folder below spark.checkpoint.dir; below the warehouse where that is unset; local only under a local master."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        root = tempfile.gettempdir() + "/ledgers" if spark.sparkContext.master.startswith("local") else spark.conf.get("spark.sql.warehouse.dir")
    return f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex[:12]}"


def round_trip(df: DataFrame, fmt: str, **options) -> DataFrame:
    """The frame written as ``fmt`` and read back."""
    path = scratch_path(df.sparkSession, fmt)
    df.write.format(fmt).options(**options).save(path)
    reader = df.sparkSession.read.format(fmt).options(**options)
    return reader.load(path) if fmt == "text" else reader.schema(df.schema).load(path)


def partitioned(df: DataFrame, by: str, only: str) -> DataFrame:
    """A ledger partitioned by a column, one partition of it rewritten (dynamic overwrite), one read back."""
    path = scratch_path(df.sparkSession, "partitioned")
    df.write.partitionBy(by).parquet(path)
    df.filter(f"{by} = '{only}'").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(by).parquet(path)
    return df.sparkSession.read.parquet(path).filter(f"{by} = '{only}'")
