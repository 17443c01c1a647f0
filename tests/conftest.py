import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))
SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    from quadpost.session import local_session

    session = local_session(4, "4g", 4)
    yield session
    session.stop()


@pytest.fixture(scope="session")
def duck():
    import glob
    import os

    import duckdb

    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for path in glob.glob(f"{SMALL}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM read_parquet('{path}')")
    return con


@pytest.fixture(scope="session")
def same(spark, duck):
    """Compares a query with its oracle on the smallest tables."""

    def norm(v):
        if isinstance(v, float):
            return repr(round(v, 6))
        if isinstance(v, (list, tuple)):
            return "[" + ",".join(map(norm, v)) + "]"
        return str(v)

    def check(name, queries, oracles):
        df = queries[name](spark, SMALL)
        cursor = duck.execute(oracles[name])
        names = [c[0] for c in cursor.description]
        assert sorted(names) == sorted(df.columns)
        order = sorted(df.columns)
        ours = sorted(tuple(norm(r[c]) for c in order) for r in df.collect())
        theirs = sorted(tuple(norm(r[names.index(c)]) for c in order) for r in cursor.fetchall())
        assert ours == theirs

    return check
