"""Hierarchies of generators: each level's pivots own the nearest generators of the level below."""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellfleet.functions.geometry import dist2
from cellfleet.operators import pivots, tiles


def build(pts: DataFrame, fanout: int, mult: int = 10, seed: int = pivots.SEED, bottom: int | None = None) -> list[DataFrame]:
    """Levels from the bottom: (gid, x, y, n, f2, parent), f2 the squared distance of the furthest object below.

    A level of at most ``fanout`` generators is the last, its parent null; each level is a fan-out smaller than the one below.
    ``bottom``: generators of the lowest level."""
    levels: list[DataFrame] = []
    below, n = pts.select("oid", "x", "y"), pts.count()
    own = None
    wanted = bottom or min(pivots.MOST_PIVOTS, max(1, -(-n // fanout))) if n > fanout * fanout else min(fanout, n)
    while True:
        piv = pivots.choose(below, max(1, wanted), mult, seed)
        at = pivots.assign(below, piv)
        gen = pts.sparkSession.createDataFrame(piv, "gid long, x long, y long")
        size = at.groupBy("pid").agg(F.count("*").alias("n"), F.max("d2").alias("f2")).withColumnRenamed("pid", "gid")
        if own is not None:
            levels[-1] = own.join(at.select(F.col("oid").alias("gid"), F.col("pid").alias("parent")), "gid")
        own = gen.join(size, "gid")
        levels.append(own.withColumn("parent", F.lit(None).cast("long")))
        if len(piv) <= fanout:
            return levels
        below, wanted = gen.withColumnRenamed("gid", "oid"), -(-len(piv) // fanout)


def cost(n: int, fanout: int) -> float:
    """Generators visited by a search: the square root of the fan-out at each level."""
    return math.sqrt(fanout) * max(1, math.ceil(math.log(max(2, n), fanout)))


def reaches(levels: Sequence[DataFrame]) -> list[list[tuple[int, int, int, int | None, float]]]:
    """Each level on the driver, from the bottom: (gid, x, y, parent, reach), the reach covering all objects below. Generators are
    at most ``MOST_PIVOTS``, whatever the objects are."""
    out: list[list[tuple[int, int, int, int | None, float]]] = []
    for level in levels:
        rows = level.select("gid", "x", "y", "f2", "parent").collect()
        if not out:
            out.append([(r["gid"], r["x"], r["y"], r["parent"], math.sqrt(r["f2"])) for r in rows])
            continue
        at = {r["gid"]: (r["x"], r["y"]) for r in rows}
        reach = dict.fromkeys(at, 0.0)
        for _, x, y, parent, far in out[-1]:
            if parent in at:
                reach[parent] = max(reach[parent], math.dist(at[parent], (x, y)) + far)
        out.append([(r["gid"], r["x"], r["y"], r["parent"], reach[r["gid"]]) for r in rows])
    return out


def descend(levels: Sequence[Sequence[tuple[int, int, int, int | None, float]]], queries: DataFrame) -> DataFrame:
    """(qid, x, y, r, gid, visited): the lowest generators that may hold answers, found from the top down, and how many generators
    were looked at on the way. Of the children of a generator those stay whose objects can be within r: by the furthest one below,
    and among siblings by their borders, where a child's objects are nearest to it of all (the lowest level)."""
    tables, children = [], []
    for depth, level in enumerate(levels):
        tables.append((np.array([g for g, *_ in level]), np.array([(x, y) for _, x, y, *_ in level], dtype=np.float64).reshape(-1, 2), np.array([f for *_, f in level])))
        if depth + 1 < len(levels):
            place = {g: i for i, (g, *_) in enumerate(levels[depth + 1])}
            parent = np.array([place[p] for _, _, _, p, _ in level])
            order = np.argsort(parent, kind="stable")
            children.append((order, np.searchsorted(parent[order], np.arange(len(place) + 1))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x, y, r = (b.column(i).to_numpy(zero_copy_only=False).astype(np.float64) for i in (1, 2, 3))
            n = len(x)
            q, g = np.repeat(np.arange(n), len(tables[-1][0])), np.tile(np.arange(len(tables[-1][0])), n)
            visited = np.zeros(n, dtype=np.int64)
            for depth in range(len(tables) - 1, -1, -1):
                _, at, far = tables[depth]
                np.add.at(visited, q, 1)
                d2 = (at[g, 0] - x[q]) ** 2 + (at[g, 1] - y[q]) ** 2
                near = np.sqrt(d2) <= far[g] + r[q] + 1e-6
                if depth == 0 and len(q):  # objects are in the cells of their nearest generators: borders with the nearest one found
                    least = np.full(n, np.inf)
                    np.minimum.at(least, q, d2)
                    first = np.full(n, -1, dtype=np.int64)
                    own = d2 == least[q]
                    first[q[own][::-1]] = g[own][::-1]
                    gap = np.hypot(*(at[first[q]] - at[g]).T)
                    with np.errstate(divide="ignore", invalid="ignore"):
                        near &= (gap == 0) | ((d2 - least[q]) / (2 * gap) <= r[q] + 1e-6)
                q, g = q[near], g[near]
                if depth:
                    order, start = children[depth - 1]
                    size = start[g + 1] - start[g]
                    q = np.repeat(q, size)
                    g = order[np.arange(int(size.sum())) - np.repeat(size.cumsum() - size, size) + np.repeat(start[g], size)]
            taken = b.take(pa.array(q))
            yield pa.RecordBatch.from_arrays([*taken.columns, pa.array(tables[0][0][g], pa.int64()), pa.array(visited[q], pa.int64())], names=["qid", "x", "y", "r", "gid", "visited"])

    kind = queries.schema["qid"].dataType.simpleString()
    typed = queries.select("qid", F.col("x").cast("long").alias("x"), F.col("y").cast("long").alias("y"), F.col("r").cast("double").alias("r"))
    return typed.mapInArrow(run, f"qid {kind}, x bigint, y bigint, r double, gid bigint, visited bigint")


def answers(levels: Sequence[Sequence[tuple[int, int, int, int | None, float]]], index: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, oid, d2) within r, from an ``index(oid, x, y, pid)`` by the lowest level's generators."""
    return tiles.answers(index, descend(levels, queries).withColumnRenamed("gid", "pid"), tiles.over(index))


def search(top: Sequence[tuple[int, int, int, int]], pts: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, oid, d2) below the top generators (gid, x, y, f2) that may hold objects within a query's r."""
    boxes = pts.sparkSession.createDataFrame(list(top), "gid long, gx long, gy long, f2 long")
    at = pivots.assign(pts, [(g, x, y) for g, x, y, _ in top]).withColumnRenamed("pid", "gid").drop("d2")
    d = F.sqrt(dist2(F.col("qx"), F.col("qy"), F.col("gx"), F.col("gy")).cast("double"))
    q = queries.select("qid", F.col("x").alias("qx"), F.col("y").alias("qy"), "r")
    near = q.join(F.broadcast(boxes), d <= F.sqrt(F.col("f2").cast("double")) + F.col("r")).select("qid", "qx", "qy", "r", "gid")
    d2 = dist2(F.col("x"), F.col("y"), F.col("qx"), F.col("qy"))
    return at.join(near, "gid").withColumn("d2", d2).where(F.col("d2") <= F.col("r") * F.col("r")).select("qid", "oid", "d2")
