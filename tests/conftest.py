import os
import sys

import pytest

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = ROOT + os.pathsep + os.environ.get("PYTHONPATH", "")
SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[4]")
        .config("spark.sql.shuffle.partitions", "4")
        .config("spark.driver.memory", "3g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", f"file://{tmp_path_factory.mktemp('shared')}")
        .getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def duck():
    import duckdb

    c = duckdb.connect()
    for n in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        c.execute(f"create view {n} as select * from '{SF}/{n}.parquet'")
    return c


@pytest.fixture(scope="session")
def same(duck):
    """Whether a DataFrame holds the rows of a SQL text, as a multiset."""

    def check(df, sql):
        duck.register("got", df.toArrow())
        duck.execute(f"create or replace table want as {sql}").fetchall()
        cols = ", ".join(f'"{c}"' for c in sorted(df.columns))
        assert sorted(df.columns) == sorted(r[0] for r in duck.execute("describe want").fetchall())
        n = duck.execute(f"select (select count(*) from got), (select count(*) from want), (select count(*) from (select {cols} from got except all select {cols} from want))").fetchall()[0]
        assert n[0] == n[1] and n[2] == 0, n

    return check
