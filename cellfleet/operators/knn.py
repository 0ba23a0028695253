"""Batches of k-nearest-neighbour queries."""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cellfleet.functions.geometry import dist2
from cellfleet.lineage import cut
from cellfleet.operators import pivots, range_query, tiles
from cellfleet.operators.pivots import Pivot


def step_radius(k: int, n: int, side: float, const: str = "printed") -> float:
    """The radius a growing range query starts with and grows by: the expected distance of the k-th neighbour over k.
    ``printed`` takes 1 / sqrt(pi), ``unit_disk`` twice that, which fits uniform points."""
    c = (1.0 if const == "printed" else 2.0) / math.sqrt(math.pi)
    return c * (1 - math.sqrt(1 - math.sqrt(min(1.0, k / max(1, n))))) * side / k


def nearest(found: DataFrame, k: int | Column) -> DataFrame:
    """(qid, rank, oid, d2): the k rows of least (d2, oid) of each query."""
    rank = F.row_number().over(Window.partitionBy("qid").orderBy("d2", "oid"))
    return found.withColumn("rank", rank.cast("long")).where(F.col("rank") <= k).select("qid", "rank", "oid", "d2")


def bounds(queries: DataFrame, piv: Sequence[Pivot], stats: Sequence[tuple[int, int, int]], k: int) -> DataFrame:
    """``queries`` with r: pieces in order of their furthest possible object from the query, up to the first that makes k
    objects; all k answers lie within that distance."""
    known = {p: (n, math.sqrt(f2)) for p, n, f2 in stats}
    rows = [(p, x, y, *known[p]) for p, x, y in piv if p in known]
    far = F.array_sort(F.array(*[
        F.struct((F.sqrt(dist2(F.col("x"), F.col("y"), F.lit(x), F.lit(y)).cast("double")) + f).alias("far"), F.lit(n).cast("long").alias("n")) for _, x, y, n, f in rows
    ]))
    start = F.struct(F.lit(0).cast("long").alias("n"), F.lit(0.0).alias("r"))
    r = F.aggregate(far, start, lambda a, p: F.when(a["n"] >= k, a).otherwise(F.struct((a["n"] + p["n"]).alias("n"), p["far"].alias("r"))), lambda a: a["r"])
    return queries.withColumn("r", r * (1 + 1e-12) + 1e-6)


#: Squares to a side of the grid of counts that bounds a query's radius: at most its square of them come to the driver. Beyond the
#: least grid a square has ``SQUARE`` objects on average, up to the most.
GRID, MOST_GRID, SQUARE = 128, 1024, 32


class Counts:
    """How many objects are in each square of a grid, as running sums along both axes: a block of squares is counted by four of them."""

    def __init__(self, x0: float, y0: float, sx: float, sy: float, counts: np.ndarray):
        self.x0, self.y0, self.sx, self.sy, self.side = x0, y0, sx, sy, len(counts)
        self.sums = np.zeros((self.side + 1, self.side + 1), dtype=np.int64)
        self.sums[1:, 1:] = counts.cumsum(axis=0).cumsum(axis=1)

    def bound(self, x: np.ndarray, y: np.ndarray, k: int) -> np.ndarray:
        """A radius within which every point has k objects, or all there are: that of the furthest corner of the smallest block of
        squares around it that holds as many. The block's width is found by halving."""
        last = self.side - 1
        cx, cy = np.clip((x - self.x0) // self.sx, 0, last).astype(np.int64), np.clip((y - self.y0) // self.sy, 0, last).astype(np.int64)
        k = min(k, int(self.sums[-1, -1]))

        def block(m: np.ndarray) -> tuple[np.ndarray, ...]:
            return np.maximum(cx - m, 0), np.maximum(cy - m, 0), np.minimum(cx + m, last) + 1, np.minimum(cy + m, last) + 1

        low, high = np.zeros(len(x), dtype=np.int64), np.full(len(x), last)
        while (low < high).any():
            middle = (low + high) // 2
            a, b, c, e = block(middle)
            enough = self.sums[c, e] - self.sums[a, e] - self.sums[c, b] + self.sums[a, b] >= k
            low, high = np.where(enough, low, np.minimum(middle + 1, high)), np.where(enough, middle, high)
        a, b, c, e = block(low)
        dx = np.maximum(np.abs(x - (self.x0 + a * self.sx)), np.abs(x - (self.x0 + c * self.sx)))
        dy = np.maximum(np.abs(y - (self.y0 + b * self.sy)), np.abs(y - (self.y0 + e * self.sy)))
        return np.hypot(dx, dy) * (1 + 1e-12) + 1e-6


def count_grid(pts: DataFrame, side: int | None = None, extent: tuple[int, ...] | None = None) -> Counts:
    """Counts that serve all batches of a snapshot: two aggregations of the points, or one where ``extent`` is known."""
    x0, y0, x1, y1, n = extent or tiles.extent(pts)
    side = side or min(MOST_GRID, max(GRID, int(math.sqrt(n / SQUARE))))
    sx, sy = (x1 - x0 + 1) / side, (y1 - y0 + 1) / side
    square = lambda c, low, size: F.least(F.lit(side - 1), F.floor((F.col(c) - low) / size)).cast("int")
    counts = np.zeros((side, side), dtype=np.int64)
    t = pts.groupBy(square("x", x0, sx).alias("gx"), square("y", y0, sy).alias("gy")).agg(F.count("*").alias("n")).toArrow()
    counts[t.column("gx").to_numpy(), t.column("gy").to_numpy()] = t.column("n").to_numpy()
    return Counts(float(x0), float(y0), sx, sy, counts)


def grid_bounds(queries: DataFrame, grid: Counts, k: int) -> DataFrame:
    """(qid, x, y, r) from counts of a grid."""
    kind = queries.schema["qid"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x, y = (b.column(i).to_numpy(zero_copy_only=False).astype(np.float64) for i in (1, 2))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(grid.bound(x, y, k))], names=["qid", "x", "y", "r"])

    typed = queries.select("qid", F.col("x").cast("long").alias("x"), F.col("y").cast("long").alias("y"))
    return typed.mapInArrow(run, f"qid {kind}, x bigint, y bigint, r double")


def run(pts: DataFrame, queries: DataFrame, piv: Sequence[Pivot], k: int, bound: str = "grid") -> DataFrame:
    """Bound (by a grid of counts, or by the pieces' own counts), one range join of the pieces' tiles, rank: no rounds. A grid needs no
    statistics of pieces, so that objects are assigned once."""
    q, extent = queries.select("qid", "x", "y"), tiles.extent(pts)
    if bound == "grid":
        asked = range_query.targets(grid_bounds(q, count_grid(pts, extent=extent), k), piv)
    else:
        stats = [(r["pid"], r["n"], r["f2"]) for r in pivots.stats(pivots.assign(pts, piv)).collect()]
        asked = range_query.targets(bounds(q, piv, stats, k), piv, [(p, f2) for p, _, f2 in stats])
    return nearest(tiles.best(pts, asked, tiles.Tiles(*extent), k, piv), k)


def rounds(found: DataFrame, k: int, step: float) -> DataFrame:
    """(qid, rounds): how often a range query that grows by ``step`` has to be asked until it finds k objects."""
    last = found.groupBy("qid").agg(F.max("d2").alias("d2"))
    return last.select("qid", F.greatest(F.lit(1), F.ceil(F.sqrt(F.col("d2").cast("double")) / step)).cast("long").alias("rounds"))


def incremental(pts: DataFrame, queries: DataFrame, piv: Sequence[Pivot], k: int, step: float, most_rounds: int = 64) -> DataFrame:
    """The growing range query as such: (qid, rank, oid, d2). Each round asks the queries that haven't k objects yet, with a radius of
    twice as many steps, and is written once; so queries far outside of the objects end too. Objects aren't written: a round reads
    ``pts`` anew and assigns those of the tiles that its queries meet."""
    extent = tiles.extent(pts)
    over, wanted = tiles.Tiles(*extent), min(k, extent[-1])
    q, done = cut(queries.select("qid", "x", "y")), None
    for i in range(most_rounds):
        found = cut(nearest(tiles.best(pts, range_query.targets(q.withColumn("r", F.lit(float(2**i * step))), piv), over, k, piv), k))
        full = found.where(F.col("rank") == wanted).select("qid")
        best = found.join(full, "qid", "left_semi")
        done = best if done is None else done.unionByName(best)
        q = cut(q.join(full, "qid", "left_anti"))
        if q.isEmpty():
            return done
    raise RuntimeError(f"fewer than {k} objects after {most_rounds} rounds")
