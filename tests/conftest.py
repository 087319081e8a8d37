import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[4]")
        .config("spark.sql.shuffle.partitions", "4")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "4g")
        .getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s
    from wordset.functions.store import clean

    clean(s)


@pytest.fixture(scope="session")
def sf():
    return SF


@pytest.fixture(scope="session")
def duck():
    import duckdb

    c = duckdb.connect()
    for p in Path(SF).glob("*.parquet"):
        c.execute(f"create view {p.stem} as select * from '{p}'")
    return c


def cell(v):
    if v is None or v != v:
        return None
    if isinstance(v, bool):
        return v
    return round(float(v), 5) if isinstance(v, (int, float)) or hasattr(v, "dtype") else str(v)


def same_rows(df, duck, sql):
    """Whether a frame and a DuckDB query have the same rows, in any order, and the same column names."""
    rel = duck.execute(sql)
    names = [c[0] for c in rel.description]
    assert sorted(df.columns) == sorted(names)
    order = sorted(names)
    key = lambda r: tuple(map(str, r))
    ours = sorted((tuple(cell(r[c]) for c in order) for r in df.collect()), key=key)
    theirs = sorted((tuple(cell(r[names.index(c)]) for c in order) for r in rel.fetchall()), key=key)
    assert ours == theirs
    return ours
