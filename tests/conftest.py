import os
import sys

import duckdb
import pytest
from pyspark.sql import SparkSession

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

SMALL = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="session")
def spark():
    s = (
        SparkSession.builder.master("local[8]").appName("tests").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "6g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SMALL}/{t}.parquet')")
    return c


def canon(df):
    """Rows in a form that both engines' frames share, sorted."""
    import math

    import pandas as pd

    out = []
    for row in df[sorted(df.columns)].itertuples(index=False, name=None):
        cells = []
        for x in row:
            if x is None or x is pd.NaT or x is pd.NA or (isinstance(x, float) and math.isnan(x)):
                cells.append("NULL")
            elif isinstance(x, float):
                cells.append(str(int(x)) if x == int(x) else repr(x))
            elif hasattr(x, "isoformat"):
                cells.append(str(pd.Timestamp(x)))
            elif hasattr(x, "tolist"):
                cells.append(repr(x.tolist()))
            else:
                cells.append(str(x))
        out.append("|".join(cells))
    return sorted(out)
