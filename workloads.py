"""Timed experiments: construction, updates, scale, cycles and throughput. Prints one JSON line for each row.

    python workloads.py [folder] [cores] [seconds]

Rows: construction with cells against the hashed snapshot, the tree overlay and updates in place, with messages counted and measured
shares of objects that change nodes and that a repair sends; construction by objects, by pieces and by cores; cycles of moving
objects by policy; range throughput by selectivity and by nodes for three systems, neighbour throughput by k. Times exclude a
warm-up run; throughput is measured for ``seconds`` after half as long of warm-up (the reference takes 120 after 60)."""

from __future__ import annotations

import json
import math
import sys
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellfleet.baselines import hashed, indexes, trees
from cellfleet.lineage import cut
from cellfleet.operators import borders, cells, knn, pivots, range_query, snapshot
from cellfleet.plans import variant_queries
from cellfleet.sources import views

SIDE, PIECES_A_NODE = 10_000_000.0, 32


def timed(f: Callable[[], object]) -> float:
    f()
    began = time.time()
    f()
    return round(time.time() - began, 3)


def run(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def throughput(f: Callable[[], object], queries: int, seconds: float) -> float:
    """Queries a second: batches asked again and again for half of ``seconds`` unmeasured, then for ``seconds``."""
    for measured, limit in ((False, seconds / 2), (True, seconds)):
        began, n = time.time(), 0
        while not n or time.time() - began < limit:
            f()
            n += 1
        if measured:
            return round(n * queries / (time.time() - began), 1)
    return 0.0


def session(cores: str) -> SparkSession:
    spark = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", cores).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "8g").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def say(**row: object) -> None:
    print(json.dumps(row), flush=True)


def construction(spark: SparkSession, d: str, view: str) -> None:
    pts = getattr(views, view)(spark, d).cache()
    n = pts.count()
    piv = pivots.choose(pts, 32)
    build = lambda p: run(pivots.distribute(pivots.assign(pts, p), 32).sortWithinPartitions("pid", "x", "y"))
    ours = timed(lambda: build(piv))
    say(workload="construction", view=view, objects=n, elect=timed(lambda: pivots.choose(pts, 32)), distribute=ours, hashed=timed(lambda: run(hashed.snapshot(pts, 32))), tree=timed(lambda: run(trees.build(pts, 4, 8))))
    # cells and their repair, on as many places as a node of the reference's cluster holds for a core
    some = cut(pts.where(pivots.draw(5) < F.lit("02" + "f" * 30)).select("oid", "x", "y"))
    few = pivots.choose(some, 32)
    at = cut(pivots.assign(cells.places(some), few))
    box = cells.box_of(some)
    alpha = math.inf
    for ratio in (0.0, 0.05, 0.2, 0.4):
        margin = borders.lambda_for(at, few, ratio) if ratio else 0.0
        placed = cut(borders.replicate(at, few, margin) if ratio else at.select("oid", "x", "y", "pid", F.lit(False).alias("is_replica")))
        told, copies = cells.traffic(placed, at, few, box, margin).first(), placed.where("is_replica").count()
        moved = (told["sent"] + copies) / max(1, told["cells"])
        say(workload="cells", view=view, cells=told["cells"], replicated=ratio, copies=copies, inexact=told["inexact"], answers=told["answers"], sent=told["sent"], share=round(moved, 4))
        alpha = min(alpha, moved)
    placed = at.select("oid", "x", "y", "pid", F.lit(False).alias("is_replica"))
    made = cut(cells.local(placed, few, box))
    beta = pivots.assign(pts, piv).agg(F.avg((F.pmod(F.col("oid"), F.lit(32)) != F.col("pid")).cast("int"))).first()[0]
    say(workload="cell times", view=view, cells=told["cells"], local=timed(lambda: run(cells.local(placed, few, box))), repair=timed(lambda: run(cells.repair(made, at, few, box))))
    for share in (0.01, 0.02, 0.04, 0.06, 0.08, 0.10):
        index = cut(trees.build(pts, 4, 8))
        moves = cut(variant_queries.steps(pts, share, SIDE / 1e9 if view == "uniform" else 0.05))
        after = cut(trees.update(index, moves))
        cost = trees.update_cost(index, after, 32).first()
        say(
            workload="updates", view=view, share=share, updates=cost["updates"], update_seconds=timed(lambda: run(trees.boxes(trees.update(index, moves), "node", "leaf"))), rebuild_seconds=ours,  # noqa: B023
            counted_messages=round(cost["messages"]), formula_messages=round(cost["updates"] * indexes.overlay_update_messages(128)), rebuild_messages=round((alpha + beta) * n), beta=round(beta, 4), alpha=round(alpha, 4),
            break_even=round(indexes.break_even(128, beta, alpha), 4),
        )
    for part in (5, 4, 3, 2, 1):
        fewer = pts.where(pivots.draw(5) < F.lit(f"{min(15, 16 * (6 - part) // 5):x}" + "f" * 31)).cache()
        say(workload="objects", view=view, objects=fewer.count(), construction=timed(lambda: run(pivots.distribute(pivots.assign(fewer, piv), 32))))  # noqa: B023
    for p in (4, 8, 16, 32, 64, 128, 1024):
        say(workload="pieces", view=view, pieces=p, construction=timed(lambda: run(pivots.distribute(pivots.assign(pts, pivots.choose(pts, p)), 32))))  # noqa: B023
    pts.unpersist()


def queries(spark: SparkSession, d: str, view: str, seconds: float) -> None:
    pts = getattr(views, view)(spark, d).cache()
    with views.whole_batches():
        q = views.uniform_queries(spark, d) if view == "uniform" else spark.createDataFrame([(i, i * 37 % 10_000, i * 251 % 50_000) for i in range(3000)], "qid long, x long, y long")
    q = cut(q)
    batch, side = q.count(), SIDE if view == "uniform" else 50_000.0
    for nodes in (4, 8, 16, 32):
        piv = pivots.choose(pts, nodes * PIECES_A_NODE)  # many small pieces, grouped on nodes
        index, held, tree = pivots.assign(pts, piv).cache(), hashed.snapshot(pts, nodes).cache(), trees.build(pts, 4, nodes // 4).cache()
        far = [(r["pid"], r["f2"]) for r in pivots.stats(index).collect()]
        held.count(), tree.count()
        tiles, leaves = cut(trees.boxes(tree, "node")), cut(trees.boxes(tree, "node", "leaf"))
        for share in (0.01, 0.05, 0.10) if nodes == 32 else (0.01,):
            asked = cut(q.withColumn("r", F.lit(math.sqrt(share / 100 * side * side / math.pi))))
            ours = throughput(lambda: run(range_query.answers(index, range_query.targets(asked, piv, far))), batch, seconds)  # noqa: B023
            say(workload="range", view=view, nodes=nodes, percent=share, batch=batch, pivots=ours, hashed=throughput(lambda: run(hashed.range_(held, asked)), batch, seconds), tree=throughput(lambda: run(trees.search(tree, asked, tiles, leaves)), batch, seconds))  # noqa: B023
        if nodes == 32:
            grid = knn.count_grid(pts)
            for k in (1, 2, 4, 8, 16, 32):
                ours = throughput(lambda: run(knn.nearest(range_query.answers(index, range_query.targets(knn.grid_bounds(q, grid, k), piv, far)), k)), batch, seconds)  # noqa: B023
                say(workload="knn", view=view, k=k, batch=batch, pivots=ours, hashed=throughput(lambda: run(hashed.nearest(held, q, k)), batch, seconds), tree=throughput(lambda: run(trees.nearest(tree, q, k)), batch, seconds))  # noqa: B023
        for x in (index, held, tree):
            x.unpersist()


def cycles(spark: SparkSession, d: str, days: tuple[int, ...] = (3, 8, 15, 22, 29)) -> None:
    """Rebuilds as objects move: seconds, deviation of pieces and whether pivots are new."""
    reports = views.reports(spark, d)
    for policy in ("always", "never", "auto"):
        piv = None
        for day in days:
            pts = cut(snapshot.latest(reports, f"2024-01-{day:02d} 00:00:00"))
            began = time.time()
            at, piv, new = snapshot.cycle(pts, piv, 32, policy)
            run(pivots.distribute(at, 32))
            took = round(time.time() - began, 3)
            b = pivots.balance(at, 32).first()
            say(workload="cycle", policy=policy, day=day, seconds=took, new=new, deviation=round(b["std_n"] / b["avg_n"], 4))


def main(d: str = "/root/testdata/sf0.1", cores: str = "8", seconds: str = "4") -> None:
    spark = session(cores)
    for view in ("uniform", "skewed"):
        construction(spark, d, view)
        queries(spark, d, view, float(seconds))
    cycles(spark, d)
    spark.stop()
    for c in (1, 2, 4, 8):
        if c <= int(cores):
            spark = session(str(c))
            for view in ("uniform", "skewed"):
                pts = getattr(views, view)(spark, d).cache()
                piv = pivots.choose(pts, 32)
                say(workload="cores", view=view, cores=c, construction=timed(lambda: run(pivots.distribute(pivots.assign(pts, piv), 32).sortWithinPartitions("pid", "x", "y"))))  # noqa: B023
            spark.stop()


if __name__ == "__main__":
    main(*sys.argv[1:])
