"""Every registered query on the smallest tables; those with SQL must equal it."""

import duckdb
import pytest

from lookalike.plans import method_queries, operator_queries  # noqa: F401
from lookalike.plans.registry import QUERIES, SQL
from lookalike.sources.tables import SCHEMAS


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in SCHEMAS:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def text(rows, names, cols):
    return sorted(str([(float(v) if isinstance(v, float) else v) for v in (dict(zip(names, r, strict=True))[c] for c in cols)]) for r in rows)


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query(spark, sf, duck, name):
    got = QUERIES[name](spark, sf)
    rows = [tuple(r) for r in got.collect()]
    if name not in SQL:
        return
    want = duck.execute(SQL[name])
    names = [d[0] for d in want.description]
    assert sorted(names) == sorted(got.columns)
    assert text(rows, got.columns, sorted(names)) == text(want.fetchall(), names, sorted(names))


def test_entry_has_the_keys():
    import __spark_entry__ as e

    assert set(QUERIES) <= set(e.queries()) and set(e.oracle_sql()) <= set(e.queries())


def test_streaming_assignment_equals_batch(spark, sf):
    a = sorted(map(tuple, QUERIES["stream_assign"](spark, sf).collect()))
    assert a == sorted(map(tuple, QUERIES["choose_home"](spark, sf).collect()))
