"""Whole query batches without SQL of their own against brute force on the smallest tables; test_catalogue runs the others."""

import pytest
from test_catalogue import con, norm  # noqa: F401

from cellfleet import catalogue
from cellfleet.plans import batch_queries
from cellfleet.sources import views


@pytest.mark.parametrize("name", sorted(n for n in batch_queries.SMALL if f"{n}_batch" not in catalogue.oracle_sql()))
def test_whole_batch(spark, d, con, name):  # noqa: F811
    df = catalogue.queries()[f"{name}_batch"](spark, d)
    r = con.sql(batch_queries.batch_sql(batch_queries.SMALL[name]))
    cols = sorted(df.columns)
    mine = sorted((tuple(norm(x[c]) for c in cols) for x in df.collect()), key=repr)
    order = [r.columns.index(c) for c in cols]
    assert mine == sorted((tuple(norm(x[i]) for i in order) for x in r.fetchall()), key=repr)


def test_batches_grow(spark, d):
    from cellfleet.plans import fleet_queries

    with views.whole_batches():
        q, s = views.uniform_queries(spark, d), fleet_queries.skewed_queries(spark, d, 1.0)
    assert q.count() == views.table(spark, d, "orders").where("o_orderkey % 50 = 0").count()
    assert s.count() == views.table(spark, d, "customer").where("c_custkey % 50 = 0").count()
    assert views.uniform_queries(spark, d).count() == 50
