"""Queries against their SQL on tables that hold what only larger ones do: order lines alike, values beyond 655.35, servers over all tiers."""

import duckdb
import pytest
from test_catalogue import norm

from cellfleet import catalogue

TABLES = {
    "lineitem": "select * from t union all select * from t where l_orderkey % 7 = 0",
    "events": "select event_id + 1000 * i as event_id, ts, user_id, event_type, case when event_id % 97 = 3 then value + 656 else value end as value, props from t, (select unnest(range(60)) as i)",
}


@pytest.fixture(scope="module")
def larger(d, tmp_path_factory):
    out, c = str(tmp_path_factory.mktemp("larger")), duckdb.connect()
    c.sql("set TimeZone = 'UTC'")
    for name in ("customer", "supplier", "part", "orders", "lineitem", "events", "nation", "region"):
        rows = TABLES.get(name, "select * from t").replace("from t", f"from '{d}/{name}.parquet' t")
        c.sql(f"copy ({rows}) to '{out}/{name}.parquet'")
        c.sql(f"create view {name} as select * from '{out}/{name}.parquet'")
    return out, c


def same(spark, larger, name):
    df = catalogue.queries()[name](spark, larger[0])
    r = larger[1].sql(catalogue.oracle_sql()[name])
    cols = sorted(df.columns)
    order = [r.columns.index(c) for c in cols]
    mine = sorted((tuple(norm(x[c]) for c in cols) for x in df.collect()), key=repr)
    assert mine == sorted((tuple(norm(x[i]) for i in order) for x in r.fetchall()), key=repr)


@pytest.mark.parametrize("name", ["idle_time", "tier_choice", "day_cost"])
def test_servers_over_all_tiers(spark, larger, name):
    same(spark, larger, name)


@pytest.mark.parametrize("name", ["border_copies_kd", "availability_rows", "plan_query_work_small", "plan_query_work_middle_batch", "plan_query_work_large"])
def test_values_beyond_the_codes(spark, larger, name):
    same(spark, larger, name)


@pytest.mark.parametrize("name", ["pivot_assign", "partition_counts", "partition_stats_8_10", "partition_stats_32_10", "partition_stats_8_250", "partition_stats_32_250"])
def test_order_lines_alike(spark, larger, name):
    same(spark, larger, name)


@pytest.mark.parametrize("name", ["plan_query_work_large_batch", "plan_query_work_middle"])
def test_other_batches_beyond_the_codes(spark, larger, name):
    same(spark, larger, name)
