"""The relational, window, scalar and streaming operators around the methods, one query each."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellfleet.functions import udfs
from cellfleet.functions.geometry import micro
from cellfleet.operators import pivots, range_query, tiles
from cellfleet.plans.index_queries import MICRO, R, chosen
from cellfleet.lineage import shared_dir
from cellfleet.plans.registry import query
from cellfleet.sources import formats, views
from cellfleet.sources.views import SQL, table
from cellfleet.streaming import positions


def shared(spark: SparkSession, kind: str) -> str:
    """A new folder that all executors reach, below the checkpoint folder."""
    base = shared_dir(spark)
    return f"{base.rstrip('/')}/{kind}-{uuid.uuid4().hex}"


@query("op_scan_pruned", "select c_custkey, c_nationkey from customer")
def op_scan_pruned(spark, d):
    return table(spark, d, "customer").select("c_custkey", "c_nationkey")


for _format in ("csv", "json", "orc", "text", "parquet"):

    @query(f"op_round_trip_{_format}", "select c_custkey as k, c_name as s, c_acctbal as v from customer")
    def op_round_trip(spark, d, kind=_format):
        rows = table(spark, d, "customer").selectExpr("c_custkey as k", "c_name as s", "c_acctbal as v")
        return formats.round_trip(rows, kind, shared(spark, kind))


@query("op_partitioned_read", f"with pts as ({SQL['uniform']}) select oid, x, y, (oid % 16)::int as pid from pts where oid % 16 = 3")
def op_partitioned_read(spark, d):
    """Written by piece; a read of one piece lists one folder."""
    path = shared(spark, "pieces")
    views.uniform(spark, d).withColumn("pid", (F.col("oid") % 16).cast("int")).repartition("pid").write.partitionBy("pid").parquet(path)
    return spark.read.schema("oid long, x long, y long, pid int").parquet(path).where("pid = 3")


@query("op_sorted_layout", f"with pts as ({SQL['uniform']}) select oid, x from pts where x between 1000000 and 1200000")
def op_sorted_layout(spark, d):
    """Sorted files, so that a range filter skips row groups."""
    path = shared(spark, "sorted")
    views.uniform(spark, d).repartitionByRange(4, "x").sortWithinPartitions("x").write.parquet(path)
    return spark.read.parquet(path).where("x between 1000000 and 1200000").select("oid", "x")


@query("op_filter", "select o_orderkey from orders where o_totalprice between 100000 and 200000 and o_orderstatus in ('O', 'F') and not o_custkey <= 10")
def op_filter(spark, d):
    return table(spark, d, "orders").where("o_totalprice between 100000 and 200000 and o_orderstatus in ('O', 'F') and not o_custkey <= 10").select("o_orderkey")


@query("op_null_safe", "select count(*) filter (nullif(o_orderstatus, 'F') is not distinct from null) as nulls, count(*) filter (nullif(o_orderstatus, 'F') is not null) as others from orders")
def op_null_safe(spark, d):
    s = F.expr("nullif(o_orderstatus, 'F')")
    return table(spark, d, "orders").agg(F.count_if(s.eqNullSafe(F.lit(None))).alias("nulls"), F.count_if(s.isNotNull()).alias("others"))


@query("op_text_and_range", "select doc_id, n_chars from documents where regexp_matches(text, '(^|\\s)(the|der|que)\\s') and n_chars between 200 and 1000")
def op_text_and_range(spark, d):
    return table(spark, d, "documents").where(F.col("text").rlike(r"(^|\s)(the|der|que)\s") & F.col("n_chars").between(200, 1000)).select("doc_id", "n_chars")


_LO = "select o.o_orderkey, count(*) as n, floor(sum(l.l_quantity)*1e3+0.5)/1e3 as q from lineitem l join orders o on l.l_orderkey = o.o_orderkey group by o.o_orderkey"
for _hint in ("broadcast", "merge", "shuffle_hash", "shuffle_replicate_nl"):
    if _hint != "shuffle_replicate_nl":

        @query(f"op_join_{_hint}", _LO)
        def op_join(spark, d, hint=_hint):
            lines, o = table(spark, d, "lineitem").select("l_orderkey", "l_quantity"), table(spark, d, "orders").select("o_orderkey")
            joined = lines.join(o.hint(hint), lines.l_orderkey == o.o_orderkey)
            return joined.groupBy("o_orderkey").agg(F.count("*").alias("n"), (F.floor(F.sum("l_quantity") * 1e3 + 0.5) / 1e3).alias("q"))


for _how, _sqlhow in (("left", "left"), ("right", "right"), ("full_outer", "full outer")):

    @query(f"op_join_{_how}", f"select c.c_custkey, s.s_suppkey from customer c {_sqlhow} join supplier s on c.c_custkey = 2 * s.s_suppkey and c.c_nationkey <> s.s_nationkey")
    def op_outer(spark, d, how=_how):
        c, s = table(spark, d, "customer"), table(spark, d, "supplier")
        return c.join(s, (c.c_custkey == 2 * s.s_suppkey) & (c.c_nationkey != s.s_nationkey), how).select("c_custkey", "s_suppkey")


for _how, _neg in (("left_semi", ""), ("left_anti", "not ")):

    @query(f"op_join_{_how}", f"select doc_id, n_chars from documents d where {_neg}exists (select 1 from labels l where l.doc_id = d.doc_id and l.quality = 1)")
    def op_semi(spark, d, how=_how):
        return table(spark, d, "documents").select("doc_id", "n_chars").join(table(spark, d, "labels").where("quality = 1"), "doc_id", how)


@query("op_interval_join", "select s.slot, count(*) as n from (select unnest(range(30))::bigint as slot) s join events e on e.ts >= timestamp '2024-01-01' + s.slot * interval 1 day and e.ts < timestamp '2024-01-01' + (s.slot + 1) * interval 1 day group by s.slot")
def op_interval_join(spark, d):
    slots = spark.range(30).selectExpr("id as slot", "timestamp'2024-01-01 00:00:00' + make_dt_interval(cast(id as int)) as a", "timestamp'2024-01-01 00:00:00' + make_dt_interval(cast(id + 1 as int)) as b")
    e = table(spark, d, "events").select("ts")
    return e.join(F.broadcast(slots), (F.col("ts") >= F.col("a")) & (F.col("ts") < F.col("b"))).groupBy("slot").agg(F.count("*").alias("n"))


@query("op_asof_join", f"with rep as ({SQL['reports']}), t as (select obj, timestamp '2024-01-01' + k * interval 5 day as tick from (select distinct obj from rep) o, (select unnest(range(1, 6)) as k) k) select t.obj, t.tick, max(r.event_id) as event_id from t join rep r on r.obj = t.obj and r.ts <= t.tick where (r.obj, t.tick, r.ts) in (select a.obj, b.tick, max(a.ts) from rep a join t b on a.obj = b.obj and a.ts <= b.tick group by all) group by t.obj, t.tick")
def op_asof_join(spark, d):
    """The last report of each object at each tick: both in one sort by time, the last one carried forward."""
    r = views.reports(spark, d).select("obj", "ts", "event_id", F.lit(0).alias("tick"))
    ticks = r.select("obj").distinct().withColumn("day", F.explode(F.sequence(F.lit(5), F.lit(25), F.lit(5))))
    ticks = ticks.select("obj", F.expr("timestamp'2024-01-01 00:00:00' + make_dt_interval(day)").alias("ts"), F.lit(None).cast("long").alias("event_id"), F.lit(1).alias("tick"))
    w = Window.partitionBy("obj").orderBy("ts", "tick", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = r.unionByName(ticks).withColumn("last", F.last("event_id", ignorenulls=True).over(w))
    return last.where("tick = 1 and last is not null").select("obj", F.col("ts").alias("tick"), F.col("last").alias("event_id"))


@query("op_lateral_top", "select c.c_custkey, o.o_orderkey from customer c, lateral (select o_orderkey from orders where o_custkey = c.c_custkey order by o_totalprice desc, o_orderkey limit 2) o")
def op_lateral_top(spark, d):
    c, o = table(spark, d, "customer").select("c_custkey"), table(spark, d, "orders")
    best = o.where(F.col("o_custkey") == F.col("c_custkey").outer()).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(2).select("o_orderkey")
    return c.lateralJoin(best)


@query("op_distinct_places", f"with pts as ({SQL['skewed']}) select count(distinct (x, y)) as places, count(*) as objects from pts")
def op_distinct_places(spark, d):
    return views.skewed(spark, d).agg(F.countDistinct("x", "y").alias("places"), F.count("*").alias("objects"))


@query("op_approx_distinct_within", f"with pts as ({SQL['skewed']}) select count(*) as objects, true as within from pts")
def op_approx_distinct(spark, d):
    return views.skewed(spark, d).agg(F.count("*").alias("objects"), (F.abs(F.approx_count_distinct("oid", 0.02) / F.count("*") - 1) < 0.1).alias("within"))


for _kind in ("cube", "rollup"):

    @query(f"op_{_kind}", f"select r.r_name as region, hour(e.ts)::int as hour, count(*) as n from events e join nation t on t.n_nationkey = e.user_id % 25 join region r on r.r_regionkey = t.n_regionkey group by {_kind}(r.r_name, hour(e.ts)::int)")
    def op_grouped(spark, d, kind=_kind):
        e = table(spark, d, "events").select((F.col("user_id") % 25).alias("k"), F.hour("ts").alias("hour"))
        t = table(spark, d, "nation").join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", F.col("r_name").alias("region"))
        return getattr(e.join(F.broadcast(t), F.col("k") == F.col("n_nationkey")), kind)("region", "hour").agg(F.count("*").alias("n"))


@query("op_grouping_sets", "select event_type, hour(ts)::int as hour, count(*) as n from events group by grouping sets ((event_type), (hour(ts)::int), ())")
def op_grouping_sets(spark, d):
    e = table(spark, d, "events").select("event_type", F.hour("ts").alias("hour"))
    return spark.sql("select event_type, hour, count(*) as n from {e} group by grouping sets ((event_type), (hour), ())", e=e)


@query("op_pivot", "select user_id % 5 as k, count(*) filter (event_type = 'click') as click, count(*) filter (event_type = 'error') as error from events group by 1")
def op_pivot(spark, d):
    p = table(spark, d, "events").groupBy((F.col("user_id") % 5).alias("k")).pivot("event_type", ["click", "error"]).count()
    return p.select("k", F.coalesce("click", F.lit(0)).cast("long").alias("click"), F.coalesce("error", F.lit(0)).cast("long").alias("error"))


@query("op_unpivot", "select s_suppkey, 'nation' as name, s_nationkey::bigint as value from supplier union all select s_suppkey, 'key', s_suppkey from supplier")
def op_unpivot(spark, d):
    s = table(spark, d, "supplier").select("s_suppkey", F.col("s_nationkey").cast("long").alias("nation"), F.col("s_suppkey").alias("key"))
    return s.unpivot("s_suppkey", ["nation", "key"], "name", "value")


@query("op_arg_extremes", "select o_custkey, max_by(o_orderkey, (o_totalprice, o_orderkey)) as most, min_by(o_orderkey, (o_totalprice, o_orderkey)) as least from orders group by o_custkey")
def op_arg_extremes(spark, d):
    by = F.struct("o_totalprice", "o_orderkey")
    return table(spark, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", by).alias("most"), F.min_by("o_orderkey", by).alias("least"))


@query("op_percentiles", f"select {MICRO.format('quantile_cont(o_totalprice, 0.25)')} as q1, {MICRO.format('quantile_cont(o_totalprice, 0.5)')} as q2, {MICRO.format('quantile_cont(o_totalprice, 0.9)')} as q9 from orders")
def op_percentiles(spark, d):
    q = lambda p: micro(F.percentile("o_totalprice", F.lit(p)))
    return table(spark, d, "orders").agg(q(0.25).alias("q1"), q(0.5).alias("q2"), q(0.9).alias("q9"))


@query("op_histogram", "select least(11, greatest(0, floor((o_totalprice - 0) / 50000) + 1))::bigint as bucket, count(*) as n from orders group by 1")
def op_histogram(spark, d):
    return table(spark, d, "orders").groupBy(F.width_bucket("o_totalprice", F.lit(0.0), F.lit(500000.0), F.lit(10)).alias("bucket")).agg(F.count("*").alias("n"))


@query("op_ranks", "select s_suppkey, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, ntile(4) over w as nt from supplier window w as (partition by s_nationkey order by s_suppkey // 10, s_suppkey)")
def op_ranks(spark, d):
    w = Window.partitionBy("s_nationkey").orderBy(F.floor(F.col("s_suppkey") / 10), "s_suppkey")
    cols = {"rn": F.row_number(), "rk": F.rank(), "dr": F.dense_rank(), "nt": F.ntile(4)}
    return table(spark, d, "supplier").select("s_suppkey", *[c.over(w).cast("long").alias(n) for n, c in cols.items()])


@query("op_neighbour_rows", "select event_id, lag(event_id) over w as before, lead(event_id) over w as after, first_value(event_id) over w as first, nth_value(event_id, 2) over (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following) as second from events window w as (partition by user_id order by ts, event_id)")
def op_neighbour_rows(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(whole).alias("second"))


@query("op_rows_frame", "select event_id, sum(event_id) over (partition by user_id order by ts, event_id rows between 3 preceding and 3 following)::bigint as s from events")
def op_rows_frame(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-3, 3)
    return table(spark, d, "events").select("event_id", F.sum("event_id").over(w).alias("s"))


@query("op_range_frame", "select event_id, count(*) over (partition by user_id % 5 order by epoch_us(ts) // 1000000 range between 1800 preceding and current row) as n from events")
def op_range_frame(spark, d):
    w = Window.partitionBy(F.col("user_id") % 5).orderBy(F.unix_seconds(F.col("ts").cast("timestamp"))).rangeBetween(-1800, 0)
    return table(spark, d, "events").select("event_id", F.count("*").over(w).alias("n"))


@query("op_top_and_offset", "select o_orderkey from orders order by o_totalprice desc, o_orderkey limit 20 offset 10")
def op_top_and_offset(spark, d):
    return table(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(10).limit(20).select("o_orderkey")


@query("op_top_of_group", "select o_custkey, o_orderkey from orders qualify row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) <= 2")
def op_top_of_group(spark, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, d, "orders").withColumn("k", F.row_number().over(w)).where("k <= 2").select("o_custkey", "o_orderkey")


for _name, _f, _s in (("intersect", "intersect", "intersect"), ("intersect_all", "intersectAll", "intersect all"), ("except", "subtract", "except"), ("except_all", "exceptAll", "except all"), ("union_all", "unionAll", "union all")):

    @query(f"op_{_name}", f"select c_nationkey as k from customer {_s} select s_nationkey from supplier")
    def op_set(spark, d, f=_f):
        a = table(spark, d, "customer").select(F.col("c_nationkey").alias("k"))
        return getattr(a, f)(table(spark, d, "supplier").select(F.col("s_nationkey").alias("k")))


@query("op_strings", "select c_custkey, upper(substr(c_name, 1, 8)) as a, lpad(c_custkey::varchar, 8, '0') as b, md5(c_name) as c, regexp_extract(c_name, '#0*([0-9]+)', 1) as e, split_part(c_name, '#', 2) as f from customer")
def op_strings(spark, d):
    return table(spark, d, "customer").select(
        "c_custkey", F.upper(F.substring("c_name", 1, 8)).alias("a"), F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("b"), F.md5("c_name").alias("c"),
        F.regexp_extract("c_name", "#0*([0-9]+)", 1).alias("e"), F.split_part("c_name", F.lit("#"), F.lit(2)).alias("f"),
    )


@query("op_dates", "select o_orderkey, date_trunc('month', o_orderdate)::timestamp as m, hour(o_orderdate + interval 25 minute)::int as h, (dayofweek(o_orderdate) + 1)::int as w, epoch_us(o_orderdate) as us from orders")
def op_dates(spark, d):
    o = F.col("o_orderdate")
    return table(spark, d, "orders").select("o_orderkey", F.date_trunc("month", o).alias("m"), F.hour(o + F.expr("interval 25 minutes")).alias("h"), F.dayofweek(o).alias("w"), F.unix_micros(o.cast("timestamp")).alias("us"))


@query("op_arrays", "select s_suppkey, list_sum(list_transform(range(1, s_suppkey % 5 + 2), lambda x: x*x))::bigint as a, list_contains(range(1, s_suppkey % 5 + 2), 3) as b from supplier")
def op_arrays(spark, d):
    seq = F.sequence(F.lit(1).cast("long"), F.col("s_suppkey") % 5 + 1)
    squares = F.transform(seq, lambda x: x * x)
    return table(spark, d, "supplier").select("s_suppkey", F.aggregate(squares, F.lit(0).cast("long"), lambda a, x: a + x).alias("a"), F.exists(seq, lambda x: x == 3).alias("b"))


@query("op_json", "select event_id, json_extract_string(props, '$.k')::int as k from events")
def op_json(spark, d):
    return table(spark, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("op_maps", "select s_nationkey, count(*) as n from supplier group by s_nationkey")
def op_maps(spark, d):
    m = table(spark, d, "supplier").groupBy("s_nationkey").agg(F.count("*").alias("n")).agg(F.map_from_entries(F.collect_list(F.struct("s_nationkey", "n"))).alias("m"))
    return m.select(F.explode(F.transform_values("m", lambda k, v: v)).alias("s_nationkey", "n"))


@query("op_recursive", "with recursive r(k, i, v) as (select o_custkey % 16, 1, sum(o_orderkey)::bigint from orders group by 1 union all select k, i + 1, v * 2 from r where i < 10) select k, i, v from r")
def op_recursive(spark, d):
    """Sums of the orders' keys, doubled level by level."""
    o = table(spark, d, "orders")
    return spark.sql("with recursive r(k, i, v) as (select o_custkey % 16, 1, sum(o_orderkey) from {o} group by 1 union all select k, i + 1, v * 2 from r where i < 10) select k, i, v from r", o=o)


@query("op_scalar_subquery", "select c_custkey from customer where c_acctbal > (select avg(c_acctbal) from customer) and exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 400000)")
def op_scalar_subquery(spark, d):
    c, o = table(spark, d, "customer"), table(spark, d, "orders")
    return spark.sql("select c_custkey from {c} where c_acctbal > (select avg(c_acctbal) from {c}) and exists (select 1 from {o} where o_custkey = c_custkey and o_totalprice > 400000)", c=c, o=o)


@query("op_sample_by_digest", "select event_id from events where ('0x' || substr(md5('3:' || event_id), 1, 7))::bigint % 10 = 0")
def op_sample(spark, d):
    h = F.conv(F.substring(F.md5(F.concat(F.lit("3:"), F.col("event_id").cast("string"))), 1, 7), 16, 10).cast("long")
    return table(spark, d, "events").where(h % 10 == 0).select("event_id")


@query("op_udf_flatness", "select user_id % 10 as k, sum(abs(v))::double as delta from (select user_id, floor(value) - lag(floor(value)) over (partition by user_id % 10 order by event_id) as v from events) group by 1")
def op_udf_flatness(spark, d):
    """A grouped aggregate of its own over values in the order of their ids."""
    e = table(spark, d, "events").select((F.col("user_id") % 10).alias("k"), "event_id", F.floor("value").cast("double").alias("v"))
    return e.groupBy("k").agg(udfs.flatness("event_id", "v").alias("delta"))


@query("op_udtf_ranges", f"with pts as ({SQL['uniform']}) select oid from pts where x between 1000000 and 3000000 and y between 500000 and 900000")
def op_udtf_ranges(spark, d):
    """A table function gives the code ranges of a box; codes are joined to them, and the box is tested."""
    from cellfleet.functions import zorder

    udfs.register(spark)
    found = spark.sql("select * from zorder_ranges(1000000, 500000, 3000000, 900000)")
    z = views.uniform(spark, d).withColumn("z", zorder.encode(F.col("x"), F.col("y")))
    return z.join(F.broadcast(found), F.col("z").between(F.col("lo"), F.col("hi"))).where("x between 1000000 and 3000000 and y between 500000 and 900000").select("oid")


@query("op_observed_counts", f"with pts as ({SQL['uniform']}) select count(*) as n from pts")
def op_observed(spark, d):
    from pyspark.sql import Observation

    seen = Observation(f"points-{uuid.uuid4().hex}")
    views.uniform(spark, d).observe(seen, F.count("*").alias("n")).write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(seen.get["n"],)], "n long")


def streamed(spark: SparkSession, df: DataFrame, mode: str = "append") -> DataFrame:
    """The rows a stream has given when its input is used up. Rows that are only added go to files and not to the driver."""
    if mode == "append":
        path = shared(spark, "rows")
        df.writeStream.format("parquet").option("path", path).option("checkpointLocation", shared(spark, "stream")).trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(path)
    name = f"s{uuid.uuid4().hex}"
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", shared(spark, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def event_stream(spark: SparkSession, d: str) -> DataFrame:
    path = shared(spark, "events")
    table(spark, d, "events").selectExpr("event_id", "cast(ts as timestamp) as ts", "user_id", "event_type", "value", "props").repartitionByRange(4, "ts").sortWithinPartitions("ts").write.parquet(path)
    return positions.read(spark, path, 10)


@query("stream_tumbling", "select time_bucket(interval '5 minutes', ts) as start, count(*) as n from events group by 1")
def stream_tumbling(spark, d):
    return streamed(spark, positions.accesses(event_stream(spark, d)), "complete")


@query("stream_sliding", "select time_bucket(interval '5 minutes', ts) - k * interval '5 minutes' as start, count(*) as n from events, (select unnest(range(6)) as k) group by 1")
def stream_sliding(spark, d):
    return streamed(spark, positions.accesses(event_stream(spark, d), window="30 minutes", slide="5 minutes"), "complete")


@query("stream_sessions", "with e as (select user_id as obj, ts, case when ts - lag(ts) over w < interval 6 hour then 0 else 1 end as new from events window w as (partition by user_id order by ts, event_id)), s as (select *, sum(new) over (partition by obj order by ts rows unbounded preceding) as k from e) select obj, min(ts) as start, max(ts) + interval 6 hour as end, count(*) as n from s group by obj, k")
def stream_sessions(spark, d):
    return streamed(spark, positions.sessions(event_stream(spark, d)), "complete")


@query("stream_latest", f"with rep as ({SQL['reports']}) select obj as oid, x, y from rep qualify row_number() over (partition by obj order by ts desc, event_id desc) = 1")
def stream_latest(spark, d):
    return streamed(spark, positions.latest(event_stream(spark, d)), "complete").select("oid", "x", "y")


@query("stream_distinct", "select count(*) as n, count(distinct event_id) as ids from events")
def stream_distinct(spark, d):
    s = event_stream(spark, d)
    return streamed(spark, positions.distinct(s.unionByName(s))).agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("ids"))


@query("stream_standing_ranges", f"with pts as ({SQL['skewed']}), q as (select c_custkey as qid, cast(floor((c_acctbal+1000)*5) as bigint) as x, (c_custkey % 1000)*49 as y from customer where c_custkey <= 50), h as (select qid, oid, (p.x-q.x)*(p.x-q.x) + (p.y-q.y)*(p.y-q.y) as d2 from pts p, q) select * from h where d2 <= 2000::bigint*2000")
def stream_standing_ranges(spark, d):
    """Standing range queries over the stream of reports, through the targets of the live index."""
    _, piv = chosen(spark, d, "skewed")
    q = table(spark, d, "customer").where(views.asking("c_custkey", 50)).selectExpr("c_custkey as qid", "cast(floor((c_acctbal+1000)*5) as bigint) as x", "(c_custkey % 1000)*49 as y", "2000.0D as r")
    return streamed(spark, positions.inside(event_stream(spark, d), q, piv))


@query("stream_rebuild", f"with rep as ({SQL['reports']}) select count(distinct obj) as objects from rep")
def stream_rebuild(spark, d):
    """Batches of latest positions become published snapshots; the current one holds every object."""
    from cellfleet.operators import snapshot

    path = shared(spark, "snapshots")
    q = positions.latest(event_stream(spark, d)).writeStream.outputMode("complete").foreachBatch(positions.rebuild(path, 4)).option("checkpointLocation", shared(spark, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    return snapshot.current(spark, path)[1].agg(F.countDistinct("oid").alias("objects"))


@query("sql_surface", f"with pts as ({SQL['uniform']}), q as ({SQL['uniform_queries']}), h as (select qid, oid, (p.x-q.x)*(p.x-q.x) + (p.y-q.y)*(p.y-q.y) as d2 from pts p, q) select qid, count(*) as n from h where d2 <= {R}::double*{R} group by qid")
def sql_surface(spark, d):
    """The index as views, asked in SQL with parameters."""
    pts, piv = chosen(spark, d)
    q = views.uniform_queries(spark, d).withColumn("r", F.lit(float(R)))
    over = tiles.over(pts)
    return spark.sql(
        "select /*+ shuffle_hash(t) */ t.qid, count(*) as n from {index} i join {targets} t using (pid, tile) where (i.x-t.qx)*(i.x-t.qx) + (i.y-t.qy)*(i.y-t.qy) <= :r * :r group by t.qid",
        args={"r": float(R)}, index=tiles.tiled(pivots.assign(pts, piv), over), targets=tiles.targets(range_query.targets(q, piv), over),
    )
