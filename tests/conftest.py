import os
import sys

import duckdb
import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.driver.memory", "4g").config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    return s


@pytest.fixture(scope="session")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def canonical(frame) -> list:
    """Rows as sortable tuples: numbers rounded, missing values as None, columns by name."""
    import numpy as np

    out = []
    for row in frame[sorted(frame.columns)].itertuples(index=False):
        cells = []
        for v in row:
            if v is None or (isinstance(v, float) and v != v) or str(v) in ("NaT", "<NA>"):
                cells.append(None)
            elif isinstance(v, (int, float, np.integer, np.floating)) and not isinstance(v, (bool, np.bool_)):
                cells.append(round(float(v), 6))
            else:
                cells.append(str(v))
        out.append(tuple(cells))
    return sorted(out, key=str)
