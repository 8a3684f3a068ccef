"""All queries of the registry with SQL, side by side with DuckDB on the smallest tables."""

import duckdb
import pytest

from roadsnap.plans import flagship, queries, queries_ops  # noqa: F401
from roadsnap.sources.tables import SCHEMAS


def value(v):
    if hasattr(v, "tolist") and not isinstance(v, (str, bytes)):
        v = v.tolist()
    if isinstance(v, (list, tuple)):
        return [value(x) for x in v]
    return round(v, 6) + 0.0 if isinstance(v, float) else v


def rows(names, data):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted((str([str(value(r[i])) for i in order]) for r in data))


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in SCHEMAS:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", sorted(queries.SQL))
def test_same_rows(spark, sf, con, name):
    df = queries.QUERIES[name](spark, sf)
    cur = con.execute(queries.SQL[name])
    names = [d[0] for d in cur.description]
    assert sorted(df.columns) == sorted(names)
    assert rows(df.columns, [tuple(r) for r in df.collect()]) == rows(names, cur.fetchall())


def test_flagship(spark, sf):
    out = flagship.typical_quarters(spark, sf).collect()
    assert len(out) == 28 and len({r["cluster"] for r in out}) == 6
