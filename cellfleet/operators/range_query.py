"""Batches of circular range queries: a query table (qid, x, y, r) against assigned points."""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellfleet.functions.geometry import dist2
from cellfleet.operators import borders, pivots, tiles
from cellfleet.operators.pivot_grid import PivotGrid
from cellfleet.operators.pivots import Pivot

#: Target rows that may be broadcast; a larger batch of queries is joined by shuffle.
BROADCAST_ROWS = 200_000


def route(queries: DataFrame, piv: Sequence[Pivot], nodes: int) -> DataFrame:
    """(qid, n_init, pid, owner, msgs): round-robin start, owner of the query's piece, one message if they differ."""
    q = pivots.assign(queries, piv).withColumn("n_init", F.col("qid") % nodes).withColumn("owner", F.col("pid") % nodes)
    return q.select("qid", "n_init", "pid", "owner", (F.col("n_init") != F.col("owner")).cast("long").alias("msgs"))


def targets(queries: DataFrame, piv: Sequence[Pivot], stats: Sequence[tuple[int, int]] | None = None, rule: str = "far") -> DataFrame:
    """(qid, x, y, r, home, pid): pieces a query may find objects in: its own, and those whose border is within r.

    ``stats``: (pid, squared distance of the furthest object); then pieces beyond that distance plus r are left out.
    ``rule`` ``far`` measures from the query point, which is sound; ``far_as_printed`` from the pivot of its piece, which
    may lose answers and is here for study only. Few pivots are compared in the plan, many by a kernel."""
    if len(piv) > pivots.LITERAL_PIVOTS and [i for i, *_ in piv] == list(range(len(piv))):
        return _targets_by_kernel(queries, piv, stats, rule)
    q = pivots.assign(queries, piv)
    home = F.array(F.struct(F.col("pid").alias("pid"), F.lit(0.0).alias("hp")))
    out = q.select("qid", "x", "y", "r", F.col("pid").alias("home"), F.inline(F.concat(home, F.filter(borders.to_others(piv), lambda o: o["hp"] <= F.col("r")))))
    if stats is not None:
        far = dict(stats)
        at = F.array(*[F.lit(far.get(i)).cast("long") for i, *_ in piv])
        there = F.get(pivots.literal(piv), F.col("pid").cast("int"))
        start = F.get(pivots.literal(piv), F.col("home").cast("int"))
        d2 = dist2(F.col("x"), F.col("y"), there["x"], there["y"]) if rule == "far" else dist2(start["x"], start["y"], there["x"], there["y"])
        f2 = F.get(at, F.col("pid").cast("int"))
        out = out.where(f2.isNotNull() & (F.sqrt(d2.cast("double")) <= F.sqrt(f2.cast("double")) + F.col("r")))
    return out.select("qid", "x", "y", "r", "home", "pid")


def _targets_by_kernel(queries: DataFrame, piv: Sequence[Pivot], stats: Sequence[tuple[int, int]] | None, rule: str) -> DataFrame:
    at = borders.table(piv)
    far = np.full(len(piv), np.inf)
    if stats is not None:
        known = dict(stats)
        far = np.array([math.sqrt(f) if (f := known.get(i)) is not None else -np.inf for i in range(len(piv))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grid = PivotGrid(np.arange(len(at)), at[:, 0], at[:, 1])
        for b in batches:
            x, y, r = (b.column(i).to_numpy(zero_copy_only=False) for i in (1, 2, 3))
            home, d2 = grid.nearest(x, y)
            own = (np.arange(len(x)), home, d2)
            for i, pid, f2 in (own, *borders.crossing(grid, at, x, y, home, d2, r)):
                start = np.sqrt((f2 if rule == "far" else ((at[home[i]] - at[pid]) ** 2).sum(axis=1)).astype(np.float64))
                kept = start <= far[pid] + r[i]
                taken = b.take(pa.array(i[kept]))
                yield pa.RecordBatch.from_arrays([*taken.columns, pa.array(home[i[kept]], pa.int64()), pa.array(pid[kept], pa.int64())], names=["qid", "x", "y", "r", "home", "pid"])

    kind = queries.schema["qid"].dataType.simpleString()
    typed = queries.select("qid", F.col("x").cast("long").alias("x"), F.col("y").cast("long").alias("y"), F.col("r").cast("double").alias("r"))
    return typed.mapInArrow(run, f"qid {kind}, x bigint, y bigint, r double, home bigint, pid bigint")


def answers(index: DataFrame, targeted: DataFrame, rows: int | None = None) -> DataFrame:
    """(qid, oid, d2) within r, inclusive, from pieces ``index(oid, x, y, pid)``. ``rows``: how many target rows there are, if
    known; few are broadcast so that the index isn't shuffled."""
    t = targeted.select("qid", F.col("x").alias("qx"), F.col("y").alias("qy"), "r", "pid")
    if rows is not None and rows <= BROADCAST_ROWS:
        t = F.broadcast(t)
    d2 = dist2(F.col("x"), F.col("y"), F.col("qx"), F.col("qy"))
    return index.join(t, "pid").withColumn("d2", d2).where(F.col("d2") <= F.col("r") * F.col("r")).select("qid", "oid", "d2")


def run(pts: DataFrame, queries: DataFrame, piv: Sequence[Pivot], prune: bool = True) -> DataFrame:
    index = pivots.assign(pts, piv)
    far = [(r["pid"], r["f2"]) for r in pivots.stats(index).collect()] if prune else None
    return tiles.answers(index, targets(queries, piv, far), tiles.over(pts))
