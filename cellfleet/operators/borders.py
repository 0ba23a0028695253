"""Borders between pieces: distances, replicas of objects near them, neighbours of pivots."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cellfleet.functions.geometry import dist2, hp_distance
from cellfleet.operators import pivots
from cellfleet.operators.pivot_grid import PivotGrid
from cellfleet.operators.pivots import Pivot, literal


def to_others(piv: Sequence[Pivot]) -> Column:
    """Of a row with x, y, pid and d2: (pid, hp) for every other pivot."""
    home = F.get(literal(piv), F.col("pid").cast("int"))
    each = F.transform(
        F.filter(literal(piv), lambda p: p["pid"] != F.col("pid")),
        lambda p: F.struct(p["pid"].alias("pid"), hp_distance(F.col("d2"), dist2(F.col("x"), F.col("y"), p["x"], p["y"]), dist2(home["x"], home["y"], p["x"], p["y"])).alias("hp")),
    )
    return each


def nearest_border(assigned: DataFrame, piv: Sequence[Pivot]) -> DataFrame:
    """``assigned`` with hp: the distance to the nearest border line with any other pivot. Many pivots are looked up in a grid: the
    border with the next nearest pivot bounds how far the pivot of a nearer one may be."""
    if len(piv) <= pivots.LITERAL_PIVOTS:
        return assigned.withColumn("hp", F.array_min(F.transform(to_others(piv), lambda o: o["hp"])))
    at = table(piv)
    xi, yi, pi, di = (assigned.columns.index(c) for c in ("x", "y", "pid", "d2"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grid = PivotGrid(np.arange(len(at)), at[:, 0], at[:, 1])
        for b in batches:
            x, y, pid, d2 = (b.column(i).to_numpy(zero_copy_only=False) for i in (xi, yi, pi, di))
            next_, e2 = grid.nearest(x, y, but=pid)
            gap = lambda i, j: np.hypot(*(at[i] - at[j]).T.astype(np.float64))
            hp = (e2 - d2) / (2.0 * gap(pid, next_))
            for i, j, f2 in grid.within(x, y, np.sqrt(d2.astype(np.float64)) + 2 * hp):
                other = j != pid[i]
                i, j, f2 = i[other], j[other], f2[other]
                np.minimum.at(hp, i, (f2 - d2[i]) / (2.0 * np.sqrt(((at[pid[i]] - at[j]) ** 2).sum(axis=1).astype(np.float64))))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(hp, pa.float64())], names=[*b.schema.names, "hp"])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in assigned.schema)
    return assigned.mapInArrow(run, f"{kinds}, hp double")


def table(piv: Sequence[Pivot]) -> np.ndarray:
    """Places of pivots that are numbered from 0 on."""
    if [i for i, *_ in piv] != list(range(len(piv))):
        raise ValueError("pivots are numbered from 0 on")
    return np.array([(x, y) for _, x, y in piv], dtype=np.int64).reshape(-1, 2)


def crossing(grid: PivotGrid, at: np.ndarray, x: np.ndarray, y: np.ndarray, home: np.ndarray, d2: np.ndarray, reach: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(point, pid, d2) of other pieces whose border is within ``reach`` of a point, inclusive, some points at a time.

    With the home pivot at distance a, another one at b and a gap of at most a + b between them, the border is within r only if
    b * b - a * a <= 2 * r * (a + b), that is, b <= a + 2 * r: only those pivots are looked up."""
    for i, j, f2 in grid.within(x, y, np.sqrt(d2.astype(np.float64)) + 2 * np.maximum(reach, 0.0)):
        gap = np.sqrt(((at[home[i]] - at[j]) ** 2).sum(axis=1).astype(np.float64))
        near = (j != home[i]) & (np.divide(f2 - d2[i], 2.0 * gap, out=np.full(len(gap), np.inf), where=gap > 0) <= reach[i])
        yield i[near], j[near], f2[near]


def replicate(assigned: DataFrame, piv: Sequence[Pivot], lam: float, pairs: set[tuple[int, int]] | None = None) -> DataFrame:
    """(oid, x, y, pid, is_replica): home rows, and a copy for each other piece whose border is within ``lam``, inclusive.
    ``pairs``: only pieces that are neighbours; by default all that are near enough, which is complete."""
    if len(piv) > pivots.LITERAL_PIVOTS and pairs is None:
        return _replicate_by_kernel(assigned, piv, lam)
    near = F.filter(to_others(piv), lambda o: o["hp"] <= lam)
    if pairs is not None:
        codes = F.array(*[F.lit(a * len(piv) + b).cast("long") for a, b in sorted(pairs)])
        near = F.filter(near, lambda o: F.array_contains(codes, F.col("pid") * len(piv) + o["pid"]))
    home = F.array(F.struct(F.col("pid").alias("pid"), F.lit(False).alias("is_replica")))
    all_ = F.concat(home, F.transform(near, lambda o: F.struct(o["pid"].alias("pid"), F.lit(True).alias("is_replica"))))
    return assigned.select("oid", "x", "y", F.inline(all_))


def _replicate_by_kernel(assigned: DataFrame, piv: Sequence[Pivot], lam: float) -> DataFrame:
    at = table(piv)
    kind = assigned.schema["oid"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grid = PivotGrid(np.arange(len(at)), at[:, 0], at[:, 1])
        for b in batches:
            x, y, pid, d2 = (b.column(i).to_numpy(zero_copy_only=False) for i in (1, 2, 3, 4))
            yield pa.RecordBatch.from_arrays([*b.columns[:4], pa.array(np.zeros(len(x), dtype=bool))], names=NAMES)
            for i, j, _ in crossing(grid, at, x, y, pid, d2, np.full(len(x), float(lam))):
                taken = b.take(pa.array(i))
                yield pa.RecordBatch.from_arrays([*taken.columns[:3], pa.array(j, pa.int64()), pa.array(np.ones(len(i), dtype=bool))], names=NAMES)

    return assigned.select("oid", "x", "y", "pid", "d2").mapInArrow(run, f"oid {kind}, x bigint, y bigint, pid bigint, is_replica boolean")


NAMES = ["oid", "x", "y", "pid", "is_replica"]


def lambda_for(assigned: DataFrame, piv: Sequence[Pivot], ratio: float) -> float:
    """A margin by which about ``ratio`` of the objects get a copy."""
    return nearest_border(assigned, piv).select(F.percentile_approx("hp", ratio, 10_000).alias("v")).first()["v"]
