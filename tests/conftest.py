import math
import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))

DATA = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    from nzspan.session import local_session

    session = local_session(cores=4, partitions=8, memory="6g")
    session.sparkContext.setLogLevel("ERROR")
    return session


@pytest.fixture(scope="session")
def duck():
    import duckdb

    from nzspan.surroundings import TABLES

    connection = duckdb.connect()
    for name in TABLES:
        connection.execute(f"CREATE VIEW {name} AS SELECT * FROM '{DATA}/{name}.parquet'")
    return connection


def plain(value):
    if isinstance(value, float):
        return "nan" if math.isnan(value) else value
    return value if isinstance(value, (int, str, bool, type(None))) else str(value)


@pytest.fixture(scope="session")
def same_rows(spark, duck):
    """Assert that a query and its SQL give the same columns and rows."""

    def check(make, sql):
        df = make(spark, DATA)
        columns = sorted(df.columns)
        ours = sorted((tuple(plain(r[c]) for c in columns) for r in df.collect()), key=str)
        result = duck.execute(sql)
        names = [c[0] for c in result.description]
        assert sorted(names) == columns
        theirs = sorted((tuple(plain(r[names.index(c)]) for c in columns) for r in result.fetchall()), key=str)
        assert ours == theirs

    return check
