"""Queries of the studies: graph searches, baselines that must agree with the index, cost measures, and streams with state."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from cellfleet.functions.geometry import micro
from cellfleet.operators import borders, cells, kdpart, knn, pivots, range_query, routing, snapshot
from cellfleet.plans import fleet_queries as fq
from cellfleet.plans.index_queries import _DELAUNAY, BORDER, MICRO, QUERY_TARGETS, _TARGETS, assigned_sql, chosen, knn_sql, pivots_sql, range_sql, ranged
from cellfleet.plans.operator_queries import event_stream, shared, streamed
from cellfleet.plans.registry import query
from cellfleet.sources import views
from cellfleet.sources.views import SQL

PROVIDER = "spark.sql.streaming.stateStore.providerClass"
_PIVOT_DELAUNAY = "with " + pivots_sql("uniform", 16, 10) + ", " + _DELAUNAY[_DELAUNAY.index("p2 as") :].replace("select oid, x::hugeint as x, y::hugeint as y from p)", "select pid as oid, x::hugeint as x, y::hugeint as y from piv)")


@query("pivot_neighbours", _PIVOT_DELAUNAY + " select distinct least(u, v)::bigint as a, greatest(u, v)::bigint as b from (select a as u, b as v from e union all select b, c from e union all select a, c from e)")
def pivot_neighbours(spark, d):
    _, piv = chosen(spark, d, "uniform", 16)
    near = routing.neighbours(piv)
    return spark.createDataFrame([(i, j) for i, js in near.items() for j in js if i < j], "a long, b long")


_WALK = "with recursive " + pivots_sql("uniform", 32, 10) + ", " + _DELAUNAY[_DELAUNAY.index("p2 as") :].replace("select oid, x::hugeint as x, y::hugeint as y from p)", "select pid as oid, x::hugeint as x, y::hugeint as y from piv)") + f""",
    nb as materialized (select distinct u, v from (select a as u, b as v from e union all select b, a from e union all select b, c from e union all select c, b from e union all select a, c from e union all select c, a from e)),
    q as materialized ({SQL['uniform_queries']}), qn as materialized (select q.qid, v.pid, (q.x-v.x)*(q.x-v.x) + (q.y-v.y)*(q.y-v.y) as d2 from q, piv v),
    st as materialized (select u, qn.qid, arg_min(v, (d2, v)) as best, min((d2, v)) as k from nb join qn on qn.pid = nb.v group by u, qn.qid),
    wk as (select qid, 0::bigint as pid, 0::bigint as hops from q union all select wk.qid, st.best, hops + 1 from wk join st on st.u = wk.pid and st.qid = wk.qid join qn on qn.qid = wk.qid and qn.pid = wk.pid where st.k < (qn.d2, wk.pid))"""


@query("route_by_walk", _WALK + " select qid, arg_max(pid, hops)::bigint as pid, max(hops)::bigint as hops from wk group by qid")
def route_by_walk(spark, d):
    """A walk over neighbouring pivots ends at the nearest one, in a number of hops about the root of the pivots."""
    _, piv = chosen(spark, d, "uniform", 32)
    return routing.walk(views.uniform_queries(spark, d), piv, routing.neighbours(piv))


@query("range_targets_walk", f"with {assigned_sql('uniform')}, {QUERY_TARGETS} {_TARGETS}")
def range_targets_walk(spark, d):
    _, piv = chosen(spark, d)
    return routing.targets_by_walk(ranged(spark, d), piv, routing.neighbours(piv))


_RECALL = f"""{assigned_sql('uniform', 32, 10)}, {QUERY_TARGETS}, hit as (select q.qid, a.oid, a.pid from q join asg a on (a.x-q.x)*(a.x-q.x) + (a.y-q.y)*(a.y-q.y) <= 400000::double*400000::double),
    ru as (select 'none' as rule, qid, pid from qt where hp <= 400000 union all select 'far', qid, qt.pid from qt join far using (pid) where hp <= 400000 and sqrt(d2::double) <= f + 400000
      union all select 'far_as_printed', qid, qt.pid from qt join far using (pid) join piv h on h.pid = home join piv o on o.pid = qt.pid where hp <= 400000 and sqrt(((h.x-o.x)*(h.x-o.x) + (h.y-o.y)*(h.y-o.y))::double) <= f + 400000)"""


@query("range_recall_figures", f"with {_RECALL} select rule, (select count(*) from hit h join ru r on r.qid = h.qid and r.pid = h.pid where r.rule = ru.rule)::bigint as answers, count(*) as pieces_asked from ru group by rule")
def range_recall_figures(spark, d):
    """(rule, answers, pieces_asked): answers found by borders alone, by the sound rule and by the printed one, which loses some."""
    pts, piv = chosen(spark, d, "uniform", 32)
    index = pivots.assign(pts, piv)
    far = [(r["pid"], r["f2"]) for r in pivots.stats(index).collect()]
    out = None
    for rule, stats in (("none", None), ("far", far), ("far_as_printed", far)):
        t = range_query.targets(ranged(spark, d), piv, stats, rule)
        row = range_query.answers(index, t).agg(F.lit(rule).alias("rule"), F.count("*").alias("answers")).join(t.agg(F.count("*").alias("pieces_asked")))
        out = row if out is None else out.unionByName(row)
    return out


@query("knn_sequential_8", f"with s as ({SQL['suppliers']}), q as ({SQL['customers']}), r as (select q.oid as qid, s.oid, (s.x-q.x)*(s.x-q.x) + (s.y-q.y)*(s.y-q.y) as d2, row_number() over (partition by q.oid order by (s.x-q.x)*(s.x-q.x) + (s.y-q.y)*(s.y-q.y), s.oid) as rank from s, q qualify rank <= 8) select qid, rank, oid, d2 from r")
def knn_sequential(spark, d):
    pts, piv = chosen(spark, d, "suppliers", 4)
    return routing.sequential_knn(cells.diagram(pts, piv, whole=True), views.customers(spark, d).withColumnRenamed("oid", "qid"), 8)


@query("knn_kd_8", f"with pts as ({SQL['skewed']}), {fq._QS}, r as (select qid, oid, (p.x-q.x)*(p.x-q.x) + (p.y-q.y)*(p.y-q.y) as d2, row_number() over (partition by qid order by (p.x-q.x)*(p.x-q.x) + (p.y-q.y)*(p.y-q.y), oid) as rank from pts p, q qualify rank <= 8) select qid, rank, oid, d2 from r")
def knn_kd(spark, d):
    """Nearest neighbours over kd leaves: a bound from counts, then one range over the leaves' boxes."""
    pts, boxed = fq.leaves(spark, d)
    q = knn.grid_bounds(fq.skewed_queries(spark, d, 1.0).select("qid", "x", "y"), knn.count_grid(pts), 8)
    from cellfleet.functions.geometry import box_disk_d2, dist2

    named = q.select("qid", F.col("x").alias("qx"), F.col("y").alias("qy"), "r")
    meets = box_disk_d2(F.col("qx"), F.col("qy"), F.col("x0"), F.col("y0"), F.col("x1"), F.col("y1")) <= F.col("r") * F.col("r")
    t = named.join(F.broadcast(boxed.select("pid", "x0", "y0", "x1", "y1")), meets).select("qid", "qx", "qy", "r", "pid")
    found = kdpart.assign(pts, boxed, fq.BITS).join(t, "pid").withColumn("d2", dist2(F.col("x"), F.col("y"), F.col("qx"), F.col("qy")))
    return knn.nearest(found.where(F.col("d2") <= F.col("r") * F.col("r")).select("qid", "oid", "d2"), 8)


@query("cells_build_then_cut", f"with {assigned_sql('customers')} select pid, count(distinct (x, y)) as cells, 0::bigint as differing from asg group by pid")
def cells_build_then_cut(spark, d):
    """The whole diagram made in one task and cut afterwards has the cells that pieces make and repair."""
    pts, piv = chosen(spark, d, "customers")
    whole = cells.single_thread(pts).select("oid", F.col("nbrs").alias("n0"))
    made = cells.diagram(pts, piv, 20_000.0).select("oid", "pid", F.col("nbrs").alias("n1"))
    return whole.join(made, "oid", "full_outer").groupBy("pid").agg(F.count("*").alias("cells"), F.count_if(~F.col("n0").eqNullSafe(F.col("n1"))).alias("differing"))


_MARGINS = "(values (0.0), (5000.0), (20000.0)) m(margin)"


@query("repair_messages", f"with {assigned_sql('customers')}, {BORDER}, pl as (select a.*, row_number() over (partition by x, y order by oid) as k from asg a) select m.margin::double as margin, (select count(*) from pl where k = 1) as objects, (select count(*) from pl where k = 1 and oid % 8 <> pid) as moved, (select count(*) from brd join pl using (oid) where pl.k = 1 and m.margin > 0 and brd.hp <= m.margin) as copies from {_MARGINS}")
def repair_messages(spark, d):
    """(margin, objects, moved, copies): what a rebuild sends before repair: objects that change nodes, and replicas."""
    pts, piv = chosen(spark, d, "customers")
    at, out = pivots.assign(cells.places(pts), piv), None
    for margin in (0.0, 5_000.0, 20_000.0):
        placed = borders.replicate(at, piv, margin) if margin else at.withColumn("is_replica", F.lit(False))
        row = placed.agg(F.lit(margin).alias("margin"), F.count_if(~F.col("is_replica")).alias("objects"), F.count_if(~F.col("is_replica") & (F.col("oid") % len(piv) != F.col("pid"))).alias("moved"), F.count_if("is_replica").alias("copies"))
        out = row if out is None else out.unionByName(row)
    return out


@query("repair_requests")
def repair_requests(spark, d):
    """(margin, requests): questions of inexact cells to other pieces."""
    pts, piv = chosen(spark, d, "customers")
    at, box, out = pivots.assign(cells.places(pts), piv), cells.box_of(pts), None
    for margin in (0.0, 5_000.0, 20_000.0):
        placed = borders.replicate(at, piv, margin) if margin else at.withColumn("is_replica", F.lit(False)).select("oid", "x", "y", "pid", "is_replica")
        row = cells.requests(cells.local(placed, piv, box, margin).where("not exact"), piv).agg(F.lit(margin).alias("margin"), F.count("*").alias("requests"))
        out = row if out is None else out.unionByName(row)
    return out


@query("repartition_policies")
def repartition_policies(spark, d):
    """(policy, day, new, deviation): how uneven pieces get as objects move, with pivots kept, elected anew, or as needed."""
    r, out = views.reports(spark, d), []
    for policy in ("always", "never", "auto"):
        piv = None
        for day in ("2024-01-03", "2024-01-08", "2024-01-15", "2024-01-22", "2024-01-29"):
            at, piv, new = snapshot.cycle(snapshot.latest(r, f"{day} 00:00:00"), piv, 4, policy, 0.6)
            n = [x["n"] for x in pivots.stats(at).collect()]
            mean = sum(n) / 4
            out.append((policy, day, new, round((sum((v - mean) ** 2 for v in n + [0] * (4 - len(n))) / 4) ** 0.5 / mean, 6)))
    return spark.createDataFrame(out, "policy string, day string, new boolean, deviation double")


@query("grid_drift", f"with rep as ({SQL['reports']}), day as (select unnest([5, 15, 25]) as day), l as (select day, obj, x, y from rep, day where ts <= timestamp '2024-01-01' + day * interval 1 day qualify row_number() over (partition by day, obj order by ts desc, event_id desc) = 1) select day::int as day, (x // 6000)::bigint as gx, (y // 12500)::bigint as gy, count(*) as n from l group by all")
def grid_drift(spark, d):
    """Objects of each fixed grid cell as they move."""
    r, out = views.reports(spark, d), None
    for day in (5, 15, 25):
        at = snapshot.latest(r, f"2024-01-{day + 1:02d} 00:00:00")
        n = at.groupBy(F.lit(day).alias("day"), F.floor(F.col("x") / 6000).alias("gx"), F.floor(F.col("y") / 12500).alias("gy")).agg(F.count("*").alias("n"))
        out = n if out is None else out.unionByName(n)
    return out


def objective_sql(view: str, objective: str, mult: int, p: int = 16) -> str:
    best = {"first": "select 0 as s", "sum_dist": None, "sum_sq": f"select s from (select s, {p}*sum((x*x+y*y)::double) - sum(x::double)*sum(x::double) - sum(y::double)*sum(y::double) as score from sets group by s having count(*) = {p}) order by score desc, s limit 1"}[objective]
    whole = assigned_sql(view, p, mult)
    if best is not None:
        before, after = whole.index("sc as ("), whole.index("piv as materialized")
        whole = f"{whole[:before]}best as ({best}),\n    {whole[after:]}"
    return f"select * from (with {whole}, c as (select pid, count(*) as n from asg group by pid) select '{view}' as view, '{objective}' as objective, {mult}::int as sets, {MICRO.format(f'sqrt(sum(n*n)::double/{p} - power(sum(n)::double/{p}, 2)) / (sum(n)::double/{p})')} as deviation from c)"


_VARIANTS = [(v, o, m) for v in ("uniform", "skewed") for o in ("sum_dist", "sum_sq", "first") for m in (1, 10, 50)]


@query("objective_variants", " union all ".join(objective_sql(*x) for x in _VARIANTS))
def objective_variants(spark, d):
    """(view, objective, sets, deviation): balance of pieces by how pivots are elected and from how many candidates."""
    out = None
    for view, objective, mult in _VARIANTS:
        pts = getattr(views, view)(spark, d)
        b = pivots.balance(pivots.assign(pts, pivots.choose(pts, 16, mult, objective=objective)), 16)
        row = b.select(F.lit(view).alias("view"), F.lit(objective).alias("objective"), F.lit(mult).alias("sets"), micro(F.col("std_n") / F.col("avg_n")).alias("deviation"))
        out = row if out is None else out.unionByName(row)
    return out


class LastReport(StatefulProcessor):
    """Keeps the last report of an object by (ts, event_id), and how many it has had."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.kept = handle.getValueState("kept", "us long, event_id long, x long, y long, n long")

    def handleInputRows(self, key: tuple, rows: Iterator[pd.DataFrame], timers: object) -> Iterator[pd.DataFrame]:
        last, n = None, 0
        if self.kept.exists():
            *last, n = self.kept.get()
        for b in rows:
            at = b.sort_values(["us", "event_id"]).iloc[-1]
            new = [int(at[c]) for c in ("us", "event_id", "x", "y")]
            last, n = (new if last is None else max(list(last), new)), n + len(b)
        self.kept.update((*last, n))
        yield pd.DataFrame({"obj": [key[0]], "event_id": [last[1]], "x": [last[2]], "y": [last[3]], "reports": [n]})

    def close(self) -> None:
        pass


@query("stream_stateful_latest", f"with rep as ({SQL['reports']}) select obj, arg_max(event_id, (ts, event_id)) as event_id, arg_max(x, (ts, event_id)) as x, arg_max(y, (ts, event_id)) as y, count(*) as reports from rep group by obj")
def stream_stateful_latest(spark, d):
    """The last report of each object, by time and not by arrival, and the number of its reports, kept in state by a processor of its own."""
    before = spark.conf.get(PROVIDER, None)
    spark.conf.set(PROVIDER, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        s = event_stream(spark, d).select("obj", "event_id", "x", "y", F.unix_micros("ts").alias("us"))
        kept = s.groupBy("obj").transformWithStateInPandas(LastReport(), "obj long, event_id long, x long, y long, reports long", "Update", "None")
        got = streamed(spark, kept, "update")
    finally:
        spark.conf.unset(PROVIDER) if before is None else spark.conf.set(PROVIDER, before)
    return got.groupBy("obj").agg(F.max_by(F.struct("event_id", "x", "y", "reports"), "reports").alias("b")).select("obj", "b.*")


@query("stream_stream_join", "select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and a.event_type = 'signup' and b.event_type = 'error' and b.ts between a.ts and a.ts + interval 6 hour")
def stream_stream_join(spark, d):
    """An object's error within six hours of its signup, from two streams under watermarks."""
    s = event_stream(spark, d)
    a = s.where("event_type = 'signup'").select(F.col("obj").alias("ao"), F.col("event_id").alias("a"), F.col("ts").alias("at")).withWatermark("at", "1 day")
    b = s.where("event_type = 'error'").select(F.col("obj").alias("bo"), F.col("event_id").alias("b"), F.col("ts").alias("bt")).withWatermark("bt", "1 day")
    joined = a.join(b, F.expr("ao = bo and bt >= at and bt <= at + interval 6 hours"))
    return streamed(spark, joined.select("a", "b"))


@query("stream_late_rows", "select count(*) as n from events where event_id % 2 = 0")
def stream_late_rows(spark, d):
    """Half of the reports come after the watermark has passed them, and are left out of windows; the rest are counted once."""
    path = shared(spark, "late")
    e = views.table(spark, d, "events").selectExpr("event_id", "cast(ts as timestamp) as ts", "user_id", "event_type", "value", "props")
    end = spark.createDataFrame([(-1, "2030-01-01 00:00:00")], "event_id long, t string").selectExpr("event_id", "cast(t as timestamp) as ts", "cast(0 as bigint) as user_id", "'x' as event_type", "cast(0 as double) as value", "'{}' as props")
    from cellfleet.streaming import positions

    for name, part in (("a", e.where("event_id % 2 = 0")), ("b", end), ("c", e.where("event_id % 2 = 1"))):
        part.coalesce(1).write.mode("append").parquet(f"{path}/{name}")
    name, checkpoint = f"s{uuid.uuid4().hex}", shared(spark, "stream")
    folder = f"{path}/all"
    for part in ("a", "b", "c"):  # one trigger each, from the same checkpoint
        spark.read.parquet(f"{path}/{part}").write.mode("append").parquet(folder)
        out = positions.accesses(positions.read(spark, folder, 100), "1 hour")
        q = out.writeStream.format("parquet").option("path", f"{path}/out").outputMode("append").option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
        q.awaitTermination()
    return spark.read.parquet(f"{path}/out").where("start < timestamp'2029-01-01 00:00:00'").agg(F.sum("n").cast("long").alias("n"))
