"""A log-structured index of fingerprint counts.

A batch's fingerprints become one immutable run: a Parquet table of (g, n), bucketed and sorted by the
fingerprint, so a run and a new batch, or two runs, meet in a merge join without moving the run again.
``compact`` merges the runs into one. Runs are never changed in place: a lost executor or a failed
write leaves the runs before it whole.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from statewitness.llm.scratch import delete

BUCKETS = 32


class FingerprintIndex:
    """Runs of fingerprint counts under ``root``; the catalog entries are dropped by ``close``."""

    def __init__(self, spark: SparkSession, root: str, buckets: int = BUCKETS):
        self.spark, self.root, self.buckets = spark, root, buckets
        self.runs: list[tuple[str, str]] = []

    def _write(self, counts: DataFrame) -> tuple[str, str]:
        name = f"run_{uuid.uuid4().hex[:12]}"
        path = f"{self.root}/{name}"
        dealt = counts.select("g", "n").repartition(self.buckets, "g")
        dealt.write.bucketBy(self.buckets, "g").sortBy("g").format("parquet").option("path", path).saveAsTable(name)
        return name, path

    def ingest(self, counts: DataFrame) -> None:
        """Add a batch: ``counts`` holds each fingerprint once (g, n)."""
        self.runs.append(self._write(counts))

    def known(self, batch: DataFrame) -> DataFrame:
        """Rows of ``batch`` (g, ...) whose fingerprint a run holds, with the number ``n`` of its occurrences there."""
        return batch.join(self.counts().hint("merge"), "g")

    def counts(self) -> DataFrame:
        """(g, n) over all runs, by merge joins of one run after the other."""
        if not self.runs:
            return self.spark.createDataFrame([], "g long, n long")
        out = self.spark.table(self.runs[0][0])
        for name, _ in self.runs[1:]:
            more = self.spark.table(name).select("g", F.col("n").alias("m")).hint("merge")
            out = out.join(more, "g", "full_outer").select("g", (F.coalesce("n", F.lit(0)) + F.coalesce("m", F.lit(0))).alias("n"))
        return out

    def compact(self) -> None:
        """Merge all runs into one and delete the old ones."""
        if len(self.runs) > 1:
            merged = self._write(self.counts())
            old, self.runs = self.runs, [merged]
            self._drop(old)

    def _drop(self, runs: list[tuple[str, str]]) -> None:
        for name, path in runs:
            self.spark.sql(f"DROP TABLE IF EXISTS {name}")
            delete(self.spark, path)

    def close(self) -> None:
        self._drop(self.runs)
        self.runs = []
