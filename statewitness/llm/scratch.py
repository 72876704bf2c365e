"""Scratch tables in the folder that driver and executors share.

``spark.checkpoint.dir`` names the folder on a cluster. Only where it is unset and the master is
local (tests) is a folder of this machine used; on a cluster without the setting the warehouse is.
A scratch table cuts lineage: a lost executor costs one task, not the stages before it.
"""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def shared_root(spark: SparkSession) -> str:
    """The folder for scratch tables; reads the setting, and sets one only where there is none."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    hadoop_dir = spark.sparkContext._jsc.sc().getCheckpointDir()
    if hadoop_dir.isDefined():
        return hadoop_dir.get().rstrip("/")
    if spark.sparkContext.master.startswith("local"):
        root = tempfile.mkdtemp(prefix="scratch-")
    else:
        root = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_scratch"
    spark.sparkContext.setCheckpointDir(root)
    return root


#: Rows of an Arrow batch that goes to a Python worker: buffers of both sides hold one batch a task.
BATCH_ROWS = 2000
BATCH_SETTING = "spark.sql.execution.arrow.maxRecordsPerBatch"


class Scratch:
    """Named Parquet tables of one run; leaving the block deletes all that ``keep`` has not named."""

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.root = f"{shared_root(spark)}/run-{uuid.uuid4().hex[:12]}"
        self.paths: dict[str, str] = {}
        self.kept: set[str] = set()

    def __enter__(self) -> "Scratch":
        return self

    def __exit__(self, *_exc) -> None:
        self.drop_all()

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def save(self, df: DataFrame, name: str, keep: bool = False, **options) -> DataFrame:
        """Write ``df`` as Parquet and return the table read back (schema given, so no inference job)."""
        if name in self.paths:
            self.drop(name)
        path, rows = self.path(name), self.spark.conf.get(BATCH_SETTING)
        self.spark.conf.set(BATCH_SETTING, str(min(BATCH_ROWS, int(rows)) if int(rows) > 0 else BATCH_ROWS))
        try:
            df.write.options(**options).parquet(path)
        finally:
            self.spark.conf.set(BATCH_SETTING, rows)
        self.paths[name] = path
        if keep:
            self.kept.add(name)
        return self.spark.read.schema(df.schema).parquet(path)

    def save_seen(self, df: DataFrame, name: str, *measures: Column, keep: bool = False) -> tuple[DataFrame, dict]:
        """``save``, and aggregates over the rows that were written, from the same job (``n``: their number)."""
        seen = Observation()
        table = self.save(df.observe(seen, F.count("*").alias("n"), *measures), name, keep)
        return table, seen.get

    def drop_all(self) -> None:
        """Delete all tables but those kept."""
        for name in [x for x in self.paths if x not in self.kept]:
            self.drop(name)
        self.release()

    def release(self) -> None:
        """Let the driver forget plans, broadcasts and shuffles of what has ended (its cleaner follows collections)."""
        gc.collect()
        self.spark.sparkContext._jvm.System.gc()

    def drop(self, name: str) -> None:
        path = self.paths.pop(name, None)
        if path:
            delete(self.spark, path)


def delete(spark: SparkSession, path: str) -> None:
    """Delete a folder of any Hadoop file system."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
