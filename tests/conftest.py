import os
import sys
from collections import Counter

import duckdb
import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false")
        .config("spark.driver.memory", "4g").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false")
        .config("spark.checkpoint.dir", str(tmp_path_factory.mktemp("shared"))).config("spark.sql.warehouse.dir", str(tmp_path_factory.mktemp("warehouse")))
        .getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from read_parquet('{SMALL}/{t}.parquet')")
    return c


def rows_of(frame) -> Counter:
    """Order-free rows with columns sorted by name."""

    def text(v):
        if v is None or str(v) in ("<NA>", "NaT", "nan"):
            return "null"
        return repr(float(v)) if isinstance(v, float) and not float(v).is_integer() else str(int(v)) if isinstance(v, float) else str(v)

    frame = frame[sorted(frame.columns)]
    return Counter(tuple(text(v) for v in r) for r in frame.itertuples(index=False, name=None))


@pytest.fixture(scope="session")
def same_rows():
    def check(spark_df, sql_frame):
        got = spark_df.toPandas()
        assert sorted(got.columns) == sorted(sql_frame.columns)
        assert rows_of(got) == rows_of(sql_frame)

    return check
