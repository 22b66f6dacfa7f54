"""Every query with a SQL definition gives that SQL's rows."""

import math

import duckdb
import pytest
from conftest import DATA

from meshcut.plans import experiment_queries, measure_queries, partition_queries, relational_queries, stream_queries  # noqa: F401
from meshcut.plans.registry import ORACLES, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SF = f"{DATA}/sf0.001"


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return c


def rows(names, data):
    order = sorted(range(len(names)), key=names.__getitem__)

    def cell(v):
        if v is None or isinstance(v, float) and math.isnan(v):
            return None
        if isinstance(v, float):
            return round(v, 6) + 0.0
        return v

    return sorted(([cell(r[i]) for i in order] for r in data), key=repr)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_same_rows(spark, con, name):
    df = QUERIES[name](spark, SF)
    got = rows(df.columns, df.collect())
    sql = con.execute(ORACLES[name])
    want = rows([c[0] for c in sql.description], sql.fetchall())
    assert sorted(df.columns) == sorted(c[0] for c in sql.description)
    assert got == want


def test_class_ratios_compute_their_reports_side_by_side(spark, monkeypatch):
    """Each report waits until all five have begun."""
    import threading

    from meshcut.plans import experiment_queries as EQ

    begun = threading.Barrier(len(EQ.CLASSES), timeout=20)

    def report(s, d):
        begun.wait()
        return s.createDataFrame([(m, w, w, w) for m, w in (("kmeans", 2), ("hash", 6))], "method string, cut long, max_comm long, total_comm long")

    for name in EQ.CLASSES:
        monkeypatch.setitem(EQ.QUERIES, name, report)
    assert {tuple(r) for r in EQ.w6_class_ratios(spark, "none").collect()} == {(c, "hash", 3.0, 3.0, 3.0) for c in ("2d", "2.5d", "3d")}
