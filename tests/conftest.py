from __future__ import annotations

import os
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parent.parent
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"

SMALL, MEDIUM = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    session = (
        SparkSession.builder.master("local[8]")
        .config("spark.sql.shuffle.partitions", "8")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "4g")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()


def normal(frame, columns):
    """Rows as sorted strings, whatever the engine's types; -0.0 and 0.0 are one."""
    d = frame[columns].copy()
    for c in columns:
        if d[c].dtype.kind == "f":
            d[c] = (d[c] + 0.0).map(lambda x: "nan" if x != x else repr(int(x)) if x == int(x) else repr(float(x)))
    d = d.astype(str).replace({"None": "nan", "<NA>": "nan", "True": "true", "False": "false"})
    return d.sort_values(columns).reset_index(drop=True)


@pytest.fixture(scope="session")
def same_as_sql():
    import duckdb

    def check(query, sql: str, spark, sf: str) -> int:
        con = duckdb.connect()
        for name in os.listdir(sf):
            con.execute(f"create view {name[:-8]} as select * from '{sf}/{name}'")
        got, want = query(spark, sf).toPandas(), con.execute(sql).fetchdf()
        columns = sorted(got.columns)
        assert columns == sorted(want.columns)
        a, b = normal(got, columns), normal(want, columns)
        assert a.equals(b), a.merge(b, how="outer", indicator=True).query("_merge != 'both'").head(5).to_string()
        return len(got)

    return check
