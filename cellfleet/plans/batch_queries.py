"""The search queries asked by whole batches: every order or customer whose id is divisible by 50, as many as the table has.

They stand beside the queries of small batches under the same name and ``_batch``. SQL that ranks all pairs of points and
queries is too slow on such batches; those have none, and tests hold them to the same SQL on the smallest tables."""

from __future__ import annotations

from functools import wraps

from cellfleet.plans import fleet_queries, index_queries, operator_queries, study_queries, variant_queries  # noqa: F401  (they register what is batched here)
from cellfleet.plans.registry import ORACLES, QUERIES, Query, query
from cellfleet.sources import views
from cellfleet.sources.views import SQL

CAPPED = {SQL["uniform_queries"]: SQL["uniform_query_batch"]} | {f"from customer where c_custkey <= {n})": f"from customer where c_custkey % {views.EVERY} = 0)" for n in (50, 200)}


def batch_sql(sql: str) -> str:
    """``sql`` asked by the whole batch; the same text if it has no small one."""
    for small, whole in CAPPED.items():
        sql = sql.replace(small, whole)
    return sql


def in_whole(f: Query) -> Query:
    @wraps(f)
    def run(spark, d):
        with views.whole_batches():
            return f(spark, d)

    return run


#: (query, SQL) with a small batch.
SMALL = {name: sql for name, sql in ORACLES.items() if batch_sql(sql) != sql}
for _name, _sql in SMALL.items():
    query(f"{_name}_batch", None if "as rank from pts" in _sql else batch_sql(_sql))(in_whole(QUERIES[_name]))
