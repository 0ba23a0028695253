"""Point and query views over the given tables: long fixed-point coordinates, so that squared distances are exact."""

from __future__ import annotations

import math
from collections.abc import Iterator
from contextlib import contextmanager
from contextvars import ContextVar

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def table(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def fixed(expr: str) -> str:
    return f"cast(floor({expr}*100+0.5) as bigint)"


def uniform(spark: SparkSession, d: str) -> DataFrame:
    """Nearly uniform points from order lines; (part, price) is a key."""
    parts = table(spark, d, "part").count()
    return table(spark, d, "lineitem").selectExpr(f"l_partkey*16777216 + {fixed('l_extendedprice')} as oid", f"{fixed('l_extendedprice')} as x", f"l_partkey*{10_000_000 // max(1, parts)} as y")


def skewed(spark: SparkSession, d: str) -> DataFrame:
    """Points crowded towards one side, with duplicate locations, from events."""
    return table(spark, d, "events").selectExpr("event_id as oid", f"{fixed('value')} as x", "cast(get_json_object(props, '$.k') as bigint)*500 as y")


def reports(spark: SparkSession, d: str) -> DataFrame:
    """Position reports of moving objects: (obj, event_id, ts, x, y)."""
    return table(spark, d, "events").selectExpr("user_id as obj", "event_id", "ts", f"{fixed('value')} as x", "cast(get_json_object(props, '$.k') as bigint)*500 as y")


def gaussian(spark: SparkSession, d: str) -> DataFrame:
    """One Gaussian hotspot from the first two embedding components."""
    c = lambda i: f"cast(floor(cast(embedding[{i}] as double)*1e6) as bigint)"
    return table(spark, d, "embeddings").selectExpr("vec_id as oid", f"{c(0)} as x", f"{c(1)} as y")


def hotspots(spark: SparkSession, d: str, n: int, varied: bool = False, sigma: float = 800.0) -> DataFrame:
    """Points in ``n`` Gaussian hotspots within 65,536 x 65,536: centres from customers in digest order, offsets by the polar
    method on digests of order lines. ``varied``: the first hotspots are far larger than the last ones."""
    n = min(n, table(spark, d, "customer").count())  # as many hotspots as there are centres, so that no point is without one
    c = customers(spark, d).orderBy(F.md5(F.concat(F.lit("h:"), F.col("oid").cast("string"))), "oid").limit(n)
    c = c.select((F.row_number().over(Window.orderBy(F.md5(F.concat(F.lit("h:"), F.col("oid").cast("string"))), "oid")) - 1).alias("k"), ((F.col("x") + 100_000) / 1_100_000 * 60_000 + 2_500).alias("cx"), (F.col("y") / 1_000_000 * 60_000 + 2_500).alias("cy"))
    u = lambda a: (F.conv(F.substring(F.md5(F.concat(F.lit("g:"), F.col("oid").cast("string"))), a, 7), 16, 10).cast("double") + 1) / (16.0**7 + 1)
    p = uniform(spark, d).select("oid", u(1).alias("u1"), u(8).alias("u2"), u(15).alias("u3"))
    p = p.withColumn("k", F.floor(F.lit(n) * (F.col("u3") * F.col("u3") if varied else F.col("u3"))).cast("int"))
    r, turn = F.sqrt(-2 * F.log("u1")) * sigma, 2 * math.pi * F.col("u2")
    held = lambda v: F.least(F.lit(65_535), F.greatest(F.lit(0), F.floor(v))).cast("long")
    return p.join(F.broadcast(c), "k").select("oid", held(F.col("cx") + r * F.cos(turn)).alias("x"), held(F.col("cy") + r * F.sin(turn)).alias("y"))


def suppliers(spark: SparkSession, d: str) -> DataFrame:
    n = table(spark, d, "supplier").count()
    return table(spark, d, "supplier").selectExpr("s_suppkey as oid", f"{fixed('s_acctbal')} as x", f"s_suppkey*{1_000_000 // max(1, n)} as y")


def customers(spark: SparkSession, d: str) -> DataFrame:
    n = table(spark, d, "customer").count()
    return table(spark, d, "customer").selectExpr("c_custkey as oid", f"{fixed('c_acctbal')} as x", f"c_custkey*{1_000_000 // max(1, n)} as y")


def orders(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").selectExpr("o_orderkey as oid", f"{fixed('o_totalprice')} as x", "cast(datediff(o_orderdate, date'1992-01-01') as bigint)*4000 as y")


#: In whole batches every order or customer whose id this divides asks a query, so that batches grow with the tables.
EVERY = 50
_WHOLE = ContextVar("whole", default=False)


@contextmanager
def whole_batches() -> Iterator[None]:
    """Query views made in here are whole batches."""
    before = _WHOLE.set(True)
    try:
        yield
    finally:
        _WHOLE.reset(before)


def asking(key: str, most: int) -> str:
    """The condition on the ids that ask: up to ``most``, or a whole batch."""
    return f"{key} % {EVERY} = 0" if _WHOLE.get() else f"{key} <= {most}"


def uniform_queries(spark: SparkSession, d: str, n: int = 50) -> DataFrame:
    """``n`` query points over the uniform view: those of least digest; or a whole batch."""
    c = table(spark, d, "customer").count()
    q = table(spark, d, "orders").selectExpr("o_orderkey as qid", f"{fixed('o_totalprice')} div 5 as x", f"o_custkey*{10_000_000 // max(1, c)} as y")
    if _WHOLE.get():
        return q.where(f"qid % {EVERY} = 0")
    return q.orderBy(F.md5(F.concat(F.lit("q:"), F.col("qid").cast("string"))), "qid").limit(n)


# The same views in SQL.
_F = "cast(floor({}*100+0.5) as bigint)"
_K = "cast(json_extract_string(props, '$.k') as bigint)*500"
SQL = {
    "uniform": f"select l_partkey*16777216 + {_F.format('l_extendedprice')} as oid, {_F.format('l_extendedprice')} as x, l_partkey*(10000000 // (select count(*) from part)) as y from lineitem",
    "skewed": f"select event_id as oid, {_F.format('value')} as x, {_K} as y from events",
    "reports": f"select user_id as obj, event_id, ts, {_F.format('value')} as x, {_K} as y from events",
    "gaussian": "select vec_id as oid, cast(floor(cast(embedding[1] as double)*1e6) as bigint) as x, cast(floor(cast(embedding[2] as double)*1e6) as bigint) as y from embeddings",
    "suppliers": f"select s_suppkey as oid, {_F.format('s_acctbal')} as x, s_suppkey*(1000000 // (select count(*) from supplier)) as y from supplier",
    "customers": f"select c_custkey as oid, {_F.format('c_acctbal')} as x, c_custkey*(1000000 // (select count(*) from customer)) as y from customer",
    "uniform_queries": f"select o_orderkey as qid, {_F.format('o_totalprice')} // 5 as x, o_custkey*(10000000 // (select count(*) from customer)) as y from orders order by md5('q:' || o_orderkey), o_orderkey limit 50",
}
SQL["uniform_query_batch"] = f"select o_orderkey as qid, {_F.format('o_totalprice')} // 5 as x, o_custkey*(10000000 // (select count(*) from customer)) as y from orders where o_orderkey % {EVERY} = 0"
