from __future__ import annotations

import os
import sys
from pathlib import Path

import duckdb
import pytest
from pyspark.sql import SparkSession

sys.path.insert(0, str(Path(__file__).parent.parent))
SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    shared = tmp_path_factory.mktemp("shared")
    session = (
        SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false")
        .config("spark.checkpoint.dir", f"file://{shared}").config("spark.sql.warehouse.dir", str(shared / "warehouse")).config("spark.driver.memory", "4g").getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    return session


@pytest.fixture(scope="session")
def tables():
    """The tables in another engine."""
    c = duckdb.connect()
    for name in os.listdir(SF):
        c.execute(f"CREATE VIEW {name.removesuffix('.parquet')} AS SELECT * FROM read_parquet('{SF}/{name}')")
    return c


def comparable(rows) -> list[str]:
    """Rows as sorted text; doubles to nine digits."""
    def value(x):
        if isinstance(x, float):
            return None if x != x else round(x, 9) + 0.0
        return x

    return sorted(repr([value(x) for x in r]) for r in rows)


def same(spark_frame, connection, sql: str) -> None:
    names = sorted(spark_frame.columns)
    mine = comparable(spark_frame.select(*[f"`{n}`" for n in names]).collect())
    other = connection.execute(sql)
    order = [d[0] for d in other.description]
    assert sorted(order) == names
    at = [order.index(n) for n in names]
    assert mine == comparable([[r[i] for i in at] for r in other.fetchall()])
