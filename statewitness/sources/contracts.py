"""Contract files as a table: a Python data source that reads a folder of JSON contract files.

``spark.dataSource.register(ContractSource)``, then ``spark.read.format("tool_contract").load(folder)``.
Files are listed and read with Spark's own reader when they lie in a store that Spark alone opens
(``load``); the data source is for local and mounted folders.
"""

from __future__ import annotations

from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from statewitness.operators.contract import Contract, from_json, to_json

ROW = "tool string, clause_id string, predicate string, arg string, biconditional boolean, surface string, quote string"


def _rows(text: str) -> list[tuple]:
    c = from_json(text)
    return [(c.tool, x.clause_id, x.predicate, x.arg, c.biconditional, x.provenance.surface, x.provenance.quote) for x in c.clauses]


class ContractReader(DataSourceReader):
    def __init__(self, options: dict):
        self.folder = options["path"]

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(str(p)) for p in sorted(Path(self.folder).glob("*.json"))]

    def read(self, partition: InputPartition):
        yield from _rows(Path(partition.value).read_text())


class ContractSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "tool_contract"

    def schema(self) -> str:
        return ROW

    def reader(self, schema) -> DataSourceReader:
        return ContractReader(self.options)


def write(contracts: list[Contract], folder: str) -> None:
    Path(folder).mkdir(parents=True, exist_ok=True)
    for c in contracts:
        (Path(folder) / f"{c.tool}.json").write_text(to_json(c))


def load(spark: SparkSession, folder: str) -> DataFrame:
    """The same rows through Spark's file reader, for any file system it knows."""
    import pandas as pd

    def run(batches):
        for b in batches:
            yield pd.DataFrame([r for t in b["value"] for r in _rows(t)], columns=[x.split()[0] for x in ROW.split(", ")])

    return spark.read.text(folder, wholetext=True).mapInPandas(run, ROW)
