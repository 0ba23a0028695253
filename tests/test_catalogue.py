"""Every query of the spatial engine against its SQL oracle, and the shapes of plans."""

import datetime
import decimal
import glob
import math
import os

import duckdb
import pytest

from cellfleet import catalogue


def norm(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else round(v, 6)
    if isinstance(v, decimal.Decimal):
        return round(float(v), 6)
    if isinstance(v, datetime.datetime):
        return v.replace(tzinfo=None)
    return v


@pytest.fixture(scope="module")
def con(d):
    c = duckdb.connect()
    c.sql("set TimeZone = 'UTC'")
    for f in glob.glob(f"{d}/*.parquet"):
        c.sql(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    return c


@pytest.mark.parametrize("name", sorted(catalogue.oracle_sql()))
def test_oracle(spark, d, con, name):
    df = catalogue.queries()[name](spark, d)
    r = con.sql(catalogue.oracle_sql()[name])
    cols = sorted(df.columns)
    assert cols == sorted(r.columns)
    mine = sorted((tuple(norm(x[c]) for c in cols) for x in df.collect()), key=repr)
    order = [r.columns.index(c) for c in cols]
    theirs = sorted((tuple(norm(x[i]) for i in order) for x in r.fetchall()), key=repr)
    assert mine == theirs


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_assignment_has_no_shuffle(spark, d):
    from cellfleet.operators import pivots
    from cellfleet.plans.index_queries import chosen

    at = pivots.assign(*chosen(spark, d))
    assert "Exchange" not in plan(at) and "Join" not in plan(at)
    assert plan(pivots.stats(at)).count("Exchange") == 1


def test_range_joins_are_no_products(spark, d):
    for name in ("range_query", "knn_8", "kd_range_query_small", "within_distance_join", "stream_standing_ranges"):
        assert "CartesianProduct" not in plan(catalogue.queries()[name](spark, d))


def test_columns_are_pruned(spark, d):
    p = catalogue.queries()["pivot_assign"](spark, d)._jdf.queryExecution().toString()
    assert "ReadSchema: struct<l_partkey:bigint,l_extendedprice:double>" in p


def test_entry(spark, d):
    assert catalogue.entry(spark, d).count() > 0


@pytest.mark.parametrize("name", ["op_recursive", "update_messages"])
def test_reads_a_table(spark, d, name):
    assert catalogue.queries()[name](spark, d).inputFiles()
