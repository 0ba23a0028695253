"""Tiles of pieces: squares of a grid over an index, so that a query is compared with the objects of the tiles that its circle
meets and not with whole pieces."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cellfleet.functions.geometry import dist2
from cellfleet.lineage import cut
from cellfleet.operators import pivots
from cellfleet.operators.pivot_grid import PAIRS, PivotGrid
from cellfleet.operators.pivots import Pivot

#: Objects that a tile has on average, and most tiles to a side of the grid.
OBJECTS, MOST_SIDE = 16_384, 256
#: Queries that a kernel looks up at once.
QUERIES = 1 << 13


class Tiles:
    """``side * side`` tiles over a box; what lies beyond it is in the outer ones."""

    def __init__(self, x0: float, y0: float, x1: float, y1: float, n: int, per: float = OBJECTS, most: int = MOST_SIDE):
        self.side = int(min(most, max(1, (n / per) ** 0.5)))
        self.x0, self.y0 = float(x0), float(y0)
        self.w, self.h = (x1 - x0 + 1) / self.side, (y1 - y0 + 1) / self.side

    def of(self, x: Column, y: Column) -> Column:
        at = lambda c, low, size: F.least(F.lit(self.side - 1), F.greatest(F.lit(0), F.floor((c - low) / size)))
        return (at(x, self.x0, self.w) * self.side + at(y, self.y0, self.h)).cast("long")

    def met(self, x: np.ndarray, y: np.ndarray, r: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(query, tile) of all tiles whose objects may be within r, some queries at a time. Outer tiles reach to any distance."""
        last, far = self.side - 1, r * (1 + 1e-9) + 1
        at = lambda v, low, size: np.clip(np.floor((v - low) / size), 0, last).astype(np.int64)
        c0, c1, r0, r1 = at(x - far, self.x0, self.w), at(x + far, self.x0, self.w), at(y - far, self.y0, self.h), at(y + far, self.y0, self.h)
        size = (c1 - c0 + 1) * (r1 - r0 + 1)
        ends, s = size.cumsum(), 0
        while s < len(x):
            e = max(s + 1, int(np.searchsorted(ends, (ends[s - 1] if s else 0) + PAIRS, side="right")))
            i = np.repeat(np.arange(s, e), size[s:e])
            j = np.arange(len(i)) - np.repeat(size[s:e].cumsum() - size[s:e], size[s:e])
            rows = r1[i] - r0[i] + 1
            c, w = c0[i] + j // rows, r0[i] + j % rows
            gap = lambda v, k, low, step: np.maximum(0.0, np.maximum(np.where(k > 0, low + k * step - v, 0.0), np.where(k < last, v - (low + (k + 1) * step), 0.0)))
            dx, dy = gap(x[i], c, self.x0, self.w), gap(y[i], w, self.y0, self.h)
            near = dx * dx + dy * dy <= far[i] * far[i]
            yield i[near], (c * self.side + w)[near]
            s = e


def extent(pts: DataFrame) -> tuple[int, int, int, int, int]:
    """(x0, y0, x1, y1, n): the box of all objects and their number, in one pass; zeros without any."""
    return tuple(v or 0 for v in pts.agg(F.min("x"), F.min("y"), F.max("x"), F.max("y"), F.count("*")).first())


def over(index: DataFrame, per: float = OBJECTS, most: int = MOST_SIDE) -> Tiles:
    """Tiles over the objects of an index: one pass."""
    return Tiles(*extent(index), per=per, most=most)


def targets(targeted: DataFrame, tiles: Tiles) -> DataFrame:
    """(qid, qx, qy, r, pid, tile): the tiles that a query's circle meets in the pieces of its targets."""
    kind = targeted.schema["qid"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x, y, r = (b.column(i).to_numpy(zero_copy_only=False).astype(np.float64) for i in (1, 2, 3))
            for i, tile in tiles.met(x, y, r):
                yield pa.RecordBatch.from_arrays([*b.take(pa.array(i)).columns, pa.array(tile, pa.int64())], names=["qid", "qx", "qy", "r", "pid", "tile"])

    typed = targeted.select("qid", F.col("x").cast("long").alias("qx"), F.col("y").cast("long").alias("qy"), F.col("r").cast("double").alias("r"), "pid")
    return typed.mapInArrow(run, f"qid {kind}, qx bigint, qy bigint, r double, pid bigint, tile bigint")


def tiled(index: DataFrame, tiles: Tiles) -> DataFrame:
    return index.select("oid", "x", "y", "pid", tiles.of(F.col("x"), F.col("y")).alias("tile"))


def answers(index: DataFrame, targeted: DataFrame, tiles: Tiles) -> DataFrame:
    """(qid, oid, d2) within r, inclusive. The targets of a tile are held in a hash table that its objects stream by, so that answers
    are neither kept nor sorted."""
    d2 = dist2(F.col("x"), F.col("y"), F.col("qx"), F.col("qy"))
    met = tiled(index, tiles).join(targets(targeted, tiles).hint("shuffle_hash"), ["pid", "tile"])
    return met.withColumn("d2", d2).where(F.col("d2") <= F.col("r") * F.col("r")).select("qid", "oid", "d2")


def best(index: DataFrame, targeted: DataFrame, tiles: Tiles, k: int, piv: Sequence[Pivot] | None = None) -> DataFrame:
    """(qid, oid, d2): of each tile that a query meets the k objects of least (d2, oid) within r, which hold the k best of all. The
    objects of a tile are looked up in a grid of their own; tiles that no query meets aren't sent. ``piv``: ``index`` has no pieces
    yet, and only the objects of tiles that are met are assigned to theirs."""
    t = cut(targets(targeted, tiles))
    kind, own = t.schema["qid"].dataType, index.schema["oid"].dataType.simpleString()

    def run(there: pa.Table, asked: pa.Table) -> pa.Table:
        out = []
        if there.num_rows and asked.num_rows:
            oid, x, y = (there.column(c).to_numpy() for c in ("oid", "x", "y"))
            qx, qy, r = (asked.column(c).to_numpy() for c in ("qx", "qy", "r"))
            grid, qid = PivotGrid(oid, x, y), asked.column("qid").combine_chunks()
            for s in range(0, len(qx), QUERIES):
                part = slice(s, s + QUERIES)
                for i, j, d2 in grid.within(qx[part], qy[part], r[part]):
                    ok = d2 <= r[part][i] * r[part][i]
                    i, j, d2 = i[ok] + s, j[ok], d2[ok]
                    o = np.lexsort((oid[j], d2, i))
                    i, j, d2 = i[o], j[o], d2[o]
                    first = np.arange(len(i)) - np.searchsorted(i, i) < k
                    out.append(pa.table({"qid": qid.take(pa.array(i[first])), "oid": pa.array(oid[j[first]]), "d2": pa.array(d2[first], pa.int64())}))
        return pa.concat_tables(out) if out else pa.table({"qid": asked.column("qid").slice(0, 0), "oid": there.column("oid").slice(0, 0), "d2": pa.array([], pa.int64())})

    if piv is None:
        held = tiled(index, tiles).join(F.broadcast(t.select("pid", "tile").distinct()), ["pid", "tile"], "left_semi")
    else:
        placed = index.select("oid", "x", "y", tiles.of(F.col("x"), F.col("y")).alias("tile"))
        held = pivots.assign(placed.join(F.broadcast(t.select("tile").distinct()), "tile", "left_semi"), piv).drop("d2")
    return held.groupBy("pid", "tile").cogroup(t.groupBy("pid", "tile")).applyInArrow(run, f"qid {kind.simpleString()}, oid {own}, d2 bigint")
