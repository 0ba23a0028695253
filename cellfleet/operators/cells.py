"""Voronoi cells: seeds from Z-order neighbours, refinement within a piece, an exactness test, repair across pieces.

Cells belong to distinct locations, named by the least oid there. A cell is a convex polygon with the neighbour on each edge,
clipped to the data's box grown by a hundredth. Within a piece every cell is made on its own; what only other pieces can
change is found by the influence region (the circles around the vertices through the generator) and repaired by one round of
messages: clipping only shrinks a cell, so the first region holds all that can ever matter."""

from __future__ import annotations

import math
from collections.abc import Iterable, Sequence
from itertools import islice
from typing import Any

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellfleet.functions import zorder
from cellfleet.functions.geometry import dist2
from cellfleet.lineage import cut
from cellfleet.operators import borders, pivots
from cellfleet.operators.pivot_grid import PivotGrid
from cellfleet.operators.pivots import Pivot

#: Neighbours in Z-order on each side that make a first cell; more of them where the rest is scanned by codes.
SEEDS, CODE_SEEDS = 3, 8
#: Home points that a cell meets before the replicas.
NEAREST = 24
CELL = "oid long, x long, y long, pid long, xs array<double>, ys array<double>, nbrs array<long>, area double, exact boolean"
Polygon = tuple[list[float], list[float], list[int]]
#: The owner of an edge on the box.
NOBODY = -1


def square(box: Sequence[float]) -> Polygon:
    x0, y0, x1, y1 = map(float, box)
    return [x0, x1, x1, x0], [y0, y0, y1, y1], [NOBODY] * 4


def clip(cell: Polygon, ox: float, oy: float, px: float, py: float, owner: int) -> Polygon:
    """The part of a cell nearer to o than to p; edge i runs from vertex i to the next one."""
    xs, ys, own = cell
    nx, ny = px - ox, py - oy
    c = (px * px - ox * ox + py * py - oy * oy) / 2
    side = [x * nx + y * ny - c for x, y in zip(xs, ys, strict=True)]
    if max(side) <= 0:
        return cell
    rx, ry, ro = [], [], []
    n = len(xs)
    for i in range(n):
        j = (i + 1) % n
        a, b = side[i], side[j]
        if a <= 0:
            rx.append(xs[i])
            ry.append(ys[i])
            ro.append(own[i] if b <= 0 or a < 0 else owner)
        if (a < 0 < b) or (b < 0 < a):
            t = a / (a - b)
            rx.append(xs[i] + t * (xs[j] - xs[i]))
            ry.append(ys[i] + t * (ys[j] - ys[i]))
            ro.append(owner if b > 0 else own[i])
    return rx, ry, ro


def reach(cell: Polygon, ox: float, oy: float) -> float:
    """Twice the distance to the furthest vertex: no point beyond it changes the cell."""
    return 2 * math.sqrt(max(((x - ox) ** 2 + (y - oy) ** 2 for x, y in zip(cell[0], cell[1], strict=True)), default=0.0))


def area(cell: Polygon) -> float:
    xs, ys, _ = cell
    return abs(sum(xs[i - 1] * ys[i] - xs[i] * ys[i - 1] for i in range(len(xs)))) / 2


def neighbours(cell: Polygon, least: float) -> list[int]:
    xs, ys, own = cell
    n = len(xs)
    return sorted({own[i] for i in range(n) if own[i] != NOBODY and math.hypot(xs[(i + 1) % n] - xs[i], ys[(i + 1) % n] - ys[i]) > least})


def influence(cell: Polygon, ox: float, oy: float) -> list[tuple[float, float, float]]:
    return [(x, y, math.hypot(x - ox, y - oy)) for x, y in zip(cell[0], cell[1], strict=True)]


def refine(cell: Polygon, ox: float, oy: float, near: Iterable[tuple[float, float, float, int]]) -> Polygon:
    """Clips by ``near`` points (distance, x, y, id) in growing distance until they are out of reach."""
    far = reach(cell, ox, oy)
    for d, x, y, i in near:
        if d > far:
            break
        if d > 0:
            new = clip(cell, ox, oy, x, y, i)
            if new is not cell:
                cell, far = new, reach(new, ox, oy)
    return cell


class Grid:
    """Points in square buckets; rings around a point come in growing distance."""

    def __init__(self, x: np.ndarray, y: np.ndarray, ids: np.ndarray):
        self.x, self.y, self.ids = x.tolist(), y.tolist(), ids.tolist()
        n = max(1, len(x))
        self.x0, self.y0 = float(x.min()), float(y.min())
        w, h = float(x.max()) - self.x0 + 1, float(y.max()) - self.y0 + 1
        self.side = max(math.sqrt(w * h * 2 / n), max(w, h) / 4096, 1.0)
        self.nx, self.ny = int(w / self.side) + 1, int(h / self.side) + 1
        self.of: dict[tuple[int, int], list[int]] = {}
        for i, k in enumerate(zip(((x - self.x0) / self.side).astype(int).tolist(), ((y - self.y0) / self.side).astype(int).tolist(), strict=True)):
            self.of.setdefault(k, []).append(i)

    def around(self, ox: float, oy: float) -> Iterable[tuple[float, float, float, int]]:
        gx, gy = int((ox - self.x0) // self.side), int((oy - self.y0) // self.side)
        waiting: list[tuple[float, float, float, int]] = []
        last = max(abs(gx), abs(gy), abs(self.nx - gx), abs(self.ny - gy)) + 1
        for ring in range(last + 1):
            if ring == 0:
                keys = [(gx, gy)]
            else:
                keys = [(i, j) for i in range(gx - ring, gx + ring + 1) for j in (gy - ring, gy + ring)] + [(i, j) for j in range(gy - ring + 1, gy + ring) for i in (gx - ring, gx + ring)]
            for k in keys:
                for i in self.of.get(k, ()):
                    waiting.append((math.hypot(self.x[i] - ox, self.y[i] - oy), self.x[i], self.y[i], self.ids[i]))
            waiting.sort(reverse=True)
            sure = ring * self.side  # nothing outside these rings is nearer
            while waiting and waiting[-1][0] <= sure:
                yield waiting.pop()
        while waiting:
            yield waiting.pop()


def all_exact(made: Sequence[Polygon], ox: Sequence[float], oy: Sequence[float], pids: Sequence[int], piv: Sequence[Pivot], margin: float) -> np.ndarray:
    """Of each cell whether no circle of its influence region reaches further than ``margin`` behind a border; needs the pivots alone."""
    out = np.ones(len(made), dtype=bool)
    if not made:
        return out
    at = borders.table(piv)
    grid = PivotGrid(np.arange(len(at)), at[:, 0], at[:, 1])
    of = np.repeat(np.arange(len(made)), [len(c[0]) for c in made])
    vx, vy = (np.concatenate([np.asarray(c[k], dtype=np.float64) for c in made]) for k in (0, 1))
    x, y, home = np.asarray(ox, dtype=np.float64)[of], np.asarray(oy, dtype=np.float64)[of], np.asarray(pids, dtype=np.int64)[of]
    r = np.hypot(vx - x, vy - y)
    d2 = (vx - at[home, 0]) ** 2 + (vy - at[home, 1]) ** 2
    for i, _, _ in borders.crossing(grid, at, vx, vy, home, d2, r - margin - 1e-9):
        out[of[i]] = False
    return out


#: Squares to a side of a scanned box, as a power of two.
BOX_BITS = 5


class CodeScan:
    """Points in Z-order; the points of a region are read by the code ranges of its box, which jump over what lies outside."""

    def __init__(self, x: np.ndarray, y: np.ndarray, ids: np.ndarray, most: int = 8):
        self.x0, self.y0, self.most = int(x.min()), int(y.min()), most
        # as many bits as the piece's extent needs, up to the codes' width; coarser codes let more points in, never fewer
        self.shift = max(0, max(int(x.max()) - self.x0, int(y.max()) - self.y0).bit_length() - zorder.BITS)
        code = self._code(x, y)
        order = np.argsort(code, kind="stable")
        self.code, self.x, self.y, self.ids = code[order], x[order], y[order], ids[order]
        self.read = 0

    def _code(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        return spread_bits((x - self.x0) >> self.shift) | (spread_bits((y - self.y0) >> self.shift) << np.uint64(1))

    def inside(self, circles: Sequence[tuple[float, float, float]]) -> np.ndarray:
        """Places of the points in any of the circles."""
        top = (1 << zorder.BITS) - 1
        cell = lambda v, low: min(top, max(0, int(math.floor(v) - low) >> self.shift))
        x0, y0 = cell(min(x - r for x, _, r in circles), self.x0), cell(min(y - r for _, y, r in circles), self.y0)
        x1, y1 = cell(max(x + r for x, _, r in circles) + 1, self.x0), cell(max(y + r for _, y, r in circles) + 1, self.y0)
        # the box is covered by squares of a size that puts at most some 32 on its side: finer ones would cost more than they leave out
        s = max(0, max(x1 - x0, y1 - y0).bit_length() - BOX_BITS)
        found = zorder.ranges(x0 >> s, y0 >> s, x1 >> s, y1 >> s, self.most, zorder.BITS - s)
        parts = [np.arange(*np.searchsorted(self.code, np.array([a << 2 * s, (b + 1) << 2 * s], dtype=np.uint64))) for a, b in found]
        at = np.concatenate(parts) if parts else np.zeros(0, dtype=np.int64)
        self.read += len(at)
        near = np.zeros(len(at), dtype=bool)
        for x, y, r in circles:
            near |= (self.x[at] - x) ** 2 + (self.y[at] - y) ** 2 <= r * r * (1 + 1e-9) + 1e-6
        return at[near]

    def refine(self, cell: Polygon, ox: float, oy: float) -> Polygon:
        """Clips by the points of the influence region; the region only shrinks, so one scan holds all that can matter."""
        at = self.inside(influence(cell, ox, oy))
        d = np.hypot(self.x[at] - ox, self.y[at] - oy)
        near = at[np.argsort(d, kind="stable")]
        return refine(cell, ox, oy, ((math.hypot(self.x[j] - ox, self.y[j] - oy), float(self.x[j]), float(self.y[j]), int(self.ids[j])) for j in near))


def spread_bits(v: np.ndarray) -> np.ndarray:
    v = v.astype(np.uint64)
    for s, m in zorder.SPREAD:
        v = (v | (v << np.uint64(s))) & np.uint64(m)
    return v


def places(pts: DataFrame) -> DataFrame:
    return pts.groupBy("x", "y").agg(F.min("oid").alias("oid")).select("oid", "x", "y")


def box_of(pts: DataFrame, whole: bool = False) -> tuple[float, float, float, float]:
    """The data's box grown by a hundredth; ``whole``: by so much that edges between far cells stay in it."""
    r = pts.agg(F.min("x").alias("x0"), F.min("y").alias("y0"), F.max("x").alias("x1"), F.max("y").alias("y1")).first()
    if r["x0"] is None:
        return 0.0, 0.0, 1.0, 1.0
    w = max(r["x1"] - r["x0"], r["y1"] - r["y0"], 1) * (1e4 if whole else 0.01)
    return r["x0"] - w, r["y0"] - w, r["x1"] + w, r["y1"] + w


#: Partitions that pieces are dealt to, at least.
TASKS = 64


def apart(placed: DataFrame, piv: Sequence[Pivot] | None = None) -> DataFrame:
    """``placed`` by pieces, in a number of partitions that is kept: pieces are small in bytes and long in work, and partitions that are
    small in bytes are put together by adaptive execution until one task makes all cells."""
    return placed.repartition(max(TASKS, 4 * len(piv or ())), "pid")


def local(placed: DataFrame, piv: Sequence[Pivot] | None, box: Sequence[float], margin: float = 0.0, seeds: int = SEEDS, by_codes: bool = False) -> DataFrame:
    """Cells of the home points of ``placed(oid, x, y, pid, is_replica)``, each piece in a task, from what the piece holds: refined by
    square buckets in rings, or ``by_codes``, by Z-order scans of the influence region. A piece is one task's work: elect as many
    pivots as make pieces of some ten thousand points, and group them on nodes."""
    least = 1e-9 * max(box[2] - box[0], box[3] - box[1]) if max(box[2] - box[0], box[3] - box[1]) < 1e9 else 1e-3

    def one(p: pd.DataFrame) -> pd.DataFrame:
        x, y, ids = p["x"].to_numpy(), p["y"].to_numpy(), p["oid"].to_numpy()
        order = np.argsort(spread_bits(x - x.min()) | (spread_bits(y - y.min()) << np.uint64(1)), kind="stable")
        replica, pids = p["is_replica"].to_numpy(), p["pid"].to_numpy()
        if by_codes:
            scan = CodeScan(x, y, ids)
        else:  # replicas are far fewer to the square than home points
            homes, others = (Grid(x[of].astype(float), y[of].astype(float), ids[of]) if of.any() else None for of in (~replica, replica))
        around = max(seeds, CODE_SEEDS) if by_codes else seeds
        rows, made = [], []
        for at, i in enumerate(order.tolist()):
            if replica[i]:
                continue
            ox, oy = float(x[i]), float(y[i])
            cell = square(box)
            for j in order[max(0, at - around) : at + around + 1].tolist():
                if j != i:
                    cell = clip(cell, ox, oy, float(x[j]), float(y[j]), int(ids[j]))
            if by_codes:
                cell = scan.refine(cell, ox, oy)
            else:
                near = homes.around(ox, oy)
                if others is not None:  # the nearest first, then replicas: they hold the cells of the border in
                    cell = refine(cell, ox, oy, islice(near, NEAREST))
                    cell = refine(cell, ox, oy, others.around(ox, oy))
                cell = refine(cell, ox, oy, near)
            made.append(cell)
            rows.append((int(ids[i]), int(x[i]), int(y[i]), int(pids[i]), cell[0], cell[1], neighbours(cell, least), area(cell)))
        out = pd.DataFrame(rows, columns=["oid", "x", "y", "pid", "xs", "ys", "nbrs", "area"])
        exact = np.zeros(len(made), dtype=bool) if piv is None else all_exact(made, out["x"], out["y"], out["pid"], piv, margin)
        return out.assign(exact=exact)

    return apart(placed, piv).groupBy("pid").applyInPandas(one, CELL)


def requests(inexact: DataFrame, piv: Sequence[Pivot]) -> DataFrame:
    """(oid, pid, circles): which pieces an inexact cell asks, and the circles it asks for. Pivots are looked up around the circles."""
    at = borders.table(piv)
    circles = F.zip_with("xs", "ys", lambda a, b: F.struct(a.alias("cx"), b.alias("cy"), F.sqrt((a - F.col("x")) * (a - F.col("x")) + (b - F.col("y")) * (b - F.col("y"))).alias("r")))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterable[pa.RecordBatch]:
        grid = PivotGrid(np.arange(len(at)), at[:, 0], at[:, 1])
        for b in batches:
            lists = b.column(2)
            of = np.repeat(np.arange(b.num_rows), lists.value_lengths().to_numpy(zero_copy_only=False))
            flat = lists.flatten()
            vx, vy, r = (flat.field(k).to_numpy(zero_copy_only=False) for k in range(3))
            home = b.column(1).to_numpy(zero_copy_only=False)[of]
            d2 = (vx - at[home, 0]) ** 2 + (vy - at[home, 1]) ** 2
            asked = [np.stack([of[i], j]) for i, j, _ in borders.crossing(grid, at, vx, vy, home, d2, r)]
            i, pid = np.unique(np.concatenate(asked, axis=1), axis=1) if asked else np.zeros((2, 0), dtype=np.int64)
            taken = b.take(pa.array(i))
            yield pa.RecordBatch.from_arrays([taken.column(0), pa.array(pid, pa.int64()), taken.column(2)], names=["oid", "pid", "circles"])

    return inexact.select("oid", "pid", circles.alias("circles")).mapInArrow(run, "oid bigint, pid bigint, circles array<struct<cx:double,cy:double,r:double>>")


#: Circles that a kernel looks up at once.
CIRCLES = 1 << 13


def inside_circles(asked: DataFrame, points: DataFrame, piv: Sequence[Pivot] | None = None) -> DataFrame:
    """(oid, other, x, y): the points of ``points(oid, x, y, pid)`` that lie in any of the circles that a cell of ``asked(oid, pid,
    circles)`` asks that piece for, each once. A piece's points are looked up in a grid and not compared with every cell."""

    def one(there: pa.Table, cells_: pa.Table) -> pa.Table:
        out = []
        if there.num_rows and cells_.num_rows:
            oid, x, y = (there.column(c).to_numpy() for c in ("oid", "x", "y"))
            grid, lists = PivotGrid(oid, x, y), cells_.column("circles").combine_chunks()
            names, flat = cells_.column("oid").to_numpy(), lists.flatten()
            of = np.repeat(np.arange(len(names)), lists.value_lengths().to_numpy(zero_copy_only=False))
            cx, cy, r = (flat.field(k).to_numpy(zero_copy_only=False) for k in range(3))
            s = 0
            while s < len(of):  # whole cells at a time, so that no point is named twice
                e = max(int(np.searchsorted(of, of[s], side="right")), int(np.searchsorted(of, of[min(len(of) - 1, s + CIRCLES)], side="left")))
                pairs = []
                for i, j, _ in grid.within(cx[s:e], cy[s:e], r[s:e]):
                    d2, r2 = (cx[s:e][i] - x[j]) ** 2 + (cy[s:e][i] - y[j]) ** 2, r[s:e][i] * r[s:e][i]
                    ok = d2 <= r2 * (1 + 1e-9) + 1e-6
                    pairs.append(np.unique(of[s:e][i[ok]] * len(x) + j[ok]))
                if pairs:
                    found = np.unique(np.concatenate(pairs))
                    i, j = found // len(x), found % len(x)
                    out.append(pa.table({"oid": pa.array(names[i]), "other": pa.array(oid[j]), "x": pa.array(x[j]), "y": pa.array(y[j])}))
                s = e
        return pa.concat_tables(out) if out else pa.table({c: pa.array([], pa.int64()) for c in ("oid", "other", "x", "y")})

    there = apart(points.select("oid", "x", "y", "pid"), piv)
    return there.groupBy("pid").cogroup(apart(asked.select("oid", "circles", "pid"), piv).groupBy("pid")).applyInArrow(one, "oid bigint, other bigint, x bigint, y bigint")


def repair(made: DataFrame, points: DataFrame, piv: Sequence[Pivot], box: Sequence[float], single: bool = False) -> DataFrame:
    """``made`` cells with the inexact ones clipped by what other pieces answer. ``single``: in one task, as a baseline."""
    least = 1e-9 * max(box[2] - box[0], box[3] - box[1]) if max(box[2] - box[0], box[3] - box[1]) < 1e9 else 1e-3
    inexact = made.where("not exact")
    asked = requests(inexact, piv)
    answers = inside_circles(asked, points, piv)
    lists = answers.groupBy("oid").agg(F.collect_list(F.struct(F.col("x").alias("x"), F.col("y").alias("y"), F.col("other").alias("o"))).alias("near"))
    todo = inexact.join(lists, "oid", "left")
    if single:
        todo = todo.coalesce(1)

    def run(batches: Iterable[pd.DataFrame]) -> Iterable[pd.DataFrame]:
        for b in batches:
            rows = []
            for r in b.itertuples():
                # edges keep their owners by clipping anew: neighbours within the piece are part of the cell already
                ox, oy = float(r.x), float(r.y)
                near = r.near if r.near is not None else []
                cell = (list(r.xs), list(r.ys), list(r.owners))
                cell = refine(cell, ox, oy, sorted((math.hypot(n["x"] - ox, n["y"] - oy), float(n["x"]), float(n["y"]), int(n["o"])) for n in near))
                rows.append((r.oid, r.x, r.y, r.pid, cell[0], cell[1], neighbours(cell, least), area(cell), True))
            yield pd.DataFrame(rows, columns=["oid", "x", "y", "pid", "xs", "ys", "nbrs", "area", "exact"])

    x0, y0, x1, y1 = map(float, box)

    def on_box(r: Any, i: int, j: int) -> bool:
        return r.xs[i] == r.xs[j] in (x0, x1) or r.ys[i] == r.ys[j] in (y0, y1)

    # the owner of each edge: the neighbour that is as far as the generator from the edge's middle, or nobody on the box, which is so far
    # away that all neighbours seem as far from it
    known = points.select(F.col("oid").alias("n_id"), F.col("x").alias("n_x"), F.col("y").alias("n_y"))
    near_at = inexact.select("oid", F.explode("nbrs").alias("n_id")).join(known, "n_id").groupBy("oid").agg(F.collect_list(F.struct("n_id", "n_x", "n_y")).alias("around"))
    todo = todo.join(near_at, "oid", "left")

    def owners(batches: Iterable[pd.DataFrame]) -> Iterable[pd.DataFrame]:
        for b in batches:
            found = []
            for r in b.itertuples():
                n, own = len(r.xs), []
                around = r.around if r.around is not None else []
                for i in range(n):
                    mx, my = (r.xs[i] + r.xs[(i + 1) % n]) / 2, (r.ys[i] + r.ys[(i + 1) % n]) / 2
                    d = math.hypot(mx - r.x, my - r.y)
                    best = min(((abs(math.hypot(mx - a["n_x"], my - a["n_y"]) - d), int(a["n_id"])) for a in around), default=(math.inf, NOBODY))
                    own.append(best[1] if best[0] <= 1e-6 * (d + 1) and not on_box(r, i, (i + 1) % n) else NOBODY)
                found.append(own)
            yield from run([b.assign(owners=found)])

    fixed = todo.select("oid", "x", "y", "pid", "xs", "ys", "near", "around").mapInPandas(owners, CELL)
    return made.where("exact").unionByName(fixed)


#: Scouts are at most so many places, and at most one of so many.
SCOUTS, SCOUT_OF = 1 << 14, 16


def with_scouts(placed: DataFrame, at: DataFrame, piv: Sequence[Pivot]) -> DataFrame:
    """``placed`` with scouts, some places ``at(oid, x, y, pid)`` from everywhere, as replicas in all other pieces. A cell at the border of
    its piece would reach to the box without them, and its influence region would ask for nearly all objects of all pieces."""
    k = max(SCOUT_OF, -(-at.count() // SCOUTS))
    others = F.broadcast(at.sparkSession.createDataFrame([(i,) for i, *_ in piv], "to long"))
    few = at.where(F.pmod(F.xxhash64("x", "y"), F.lit(k)) == 0).join(others, F.col("pid") != F.col("to"))
    return placed.unionByName(few.select("oid", "x", "y", F.col("to").alias("pid"), F.lit(True).alias("is_replica")))


def diagram(pts: DataFrame, piv: Sequence[Pivot], margin: float = 0.0, seeds: int = SEEDS, whole: bool = False, around: DataFrame | None = None, by_codes: bool = False) -> DataFrame:
    """All cells, exact: pieces of nearest pivots, replicas within ``margin`` of a border, scouts, local cells, one round of repair.
    ``around``: more points (x, y) that the box holds."""
    box = box_of(pts if around is None else pts.select("x", "y").unionByName(around.select("x", "y")), whole)
    at = pivots.assign(places(pts), piv)
    placed = borders.replicate(at, piv, margin) if margin > 0 else at.select("oid", "x", "y", "pid", F.lit(False).alias("is_replica"))
    placed = with_scouts(placed.select("oid", "x", "y", "pid", "is_replica"), at, piv)
    return repair(cut(local(placed, piv, box, margin, seeds, by_codes)), at, piv, box)  # read four times


def single_thread(pts: DataFrame, whole: bool = False) -> DataFrame:
    """The whole diagram in one task: a baseline, and the reference for tests."""
    placed = places(pts).withColumn("pid", F.lit(0).cast("long")).withColumn("is_replica", F.lit(False))
    r = placed.agg(F.min("x").alias("x"), F.min("y").alias("y")).first()
    return local(placed, [(0, r["x"], r["y"])], box_of(pts, whole))


def traffic(placed: DataFrame, points: DataFrame, piv: Sequence[Pivot] | None, box: Sequence[float], margin: float = 0.0) -> DataFrame:
    """(cells, inexact, asked, answers, sent): what a repair sends. Inexact cells ask the pieces that their influence region meets, or all of
    them where pieces are no regions (``piv`` is None), and get the objects of the region from elsewhere; ``sent`` counts an object once
    for each piece that needs it, however many of its cells do."""
    made = cut(local(placed, piv, box, margin))  # read four times
    inexact = made.where("not exact")
    if piv is None:
        circles = F.zip_with("xs", "ys", lambda a, b: F.struct(a.alias("cx"), b.alias("cy"), F.sqrt((a - F.col("x")) * (a - F.col("x")) + (b - F.col("y")) * (b - F.col("y"))).alias("r")))
        others = points.select("pid").distinct().withColumnRenamed("pid", "to")
        asked = inexact.select("oid", "pid", circles.alias("circles")).join(F.broadcast(others), F.col("pid") != F.col("to")).select("oid", F.col("to").alias("pid"), "circles")
    else:
        asked = requests(inexact, piv)
    home = made.select("oid", F.col("pid").alias("home"))
    answers = inside_circles(asked, points, piv).join(home, "oid").agg(F.count("*").alias("answers"), F.countDistinct("home", "other").alias("sent"))
    cells_ = made.agg(F.count("*").alias("cells"), F.count_if(~F.col("exact")).alias("inexact"))
    return cells_.join(asked.agg(F.count("*").alias("asked"))).join(answers)


def inaccuracy(pts: DataFrame, piv: Sequence[Pivot], margins: Sequence[float], whole: bool = False) -> DataFrame:
    """(method, margin, cells, replicas, inexact, wrong): cells whose neighbours are wrong before repair, and those flagged."""
    from cellfleet.baselines import indexes

    box = box_of(pts, whole)
    truth = single_thread(pts, whole).select("oid", F.col("nbrs").alias("true_nbrs"))
    at = pivots.assign(places(pts), piv)
    tried = [("random", 0.0, indexes.random_distribution(places(pts), len(piv), 7).withColumn("is_replica", F.lit(False)), None)]
    tried += [("pivots", m, borders.replicate(at, piv, m) if m > 0 else at.select("oid", "x", "y", "pid", F.lit(False).alias("is_replica")), piv) for m in margins]
    out = None
    for method, margin, placed, p in tried:
        made = local(placed.select("oid", "x", "y", "pid", "is_replica"), p, box, margin)
        copies = placed.where("is_replica").count()
        row = made.join(truth, "oid").agg(
            F.lit(method).alias("method"), F.lit(margin).alias("margin"), F.count("*").alias("cells"), F.lit(copies).cast("long").alias("replicas"),
            F.count_if(~F.col("exact")).alias("inexact"), F.count_if(F.col("nbrs") != F.col("true_nbrs")).alias("wrong"),
        )
        out = row if out is None else out.unionByName(row)
    return out


def locate(made: DataFrame, queries: DataFrame, buckets: int = 16) -> DataFrame:
    """(qid, oid, d2): the generators whose closed cells contain a query, found by buckets of the cells' boxes; several on an edge."""
    r = made.agg(F.min(F.array_min("xs")).alias("x0"), F.min(F.array_min("ys")).alias("y0"), F.max(F.array_max("xs")).alias("x1"), F.max(F.array_max("ys")).alias("y1")).first()
    sx, sy = (r["x1"] - r["x0"]) / buckets, (r["y1"] - r["y0"]) / buckets
    cap = lambda c: F.least(F.lit(buckets - 1), F.greatest(F.lit(0), F.floor(c))).cast("int")
    bx = lambda c: cap((c - r["x0"]) / sx)
    by = lambda c: cap((c - r["y0"]) / sy)
    gx = made.select("oid", F.col("x").alias("gx"), F.col("y").alias("gy"), "xs", "ys", F.explode(F.sequence(bx(F.array_min("xs")), bx(F.array_max("xs")))).alias("bx"))
    g = gx.select("*", F.explode(F.sequence(by(F.array_min("ys")), by(F.array_max("ys")))).alias("by"))
    qx, qy = F.least(F.greatest(F.col("x"), F.lit(r["x0"])), F.lit(r["x1"])), F.least(F.greatest(F.col("y"), F.lit(r["y0"])), F.lit(r["y1"]))
    q = queries.select("qid", "x", "y", qx.alias("px"), qy.alias("py")).withColumn("bx", bx(F.col("px"))).withColumn("by", by(F.col("py")))
    n = F.size("xs")

    def left_of(i):
        j = (i + 1) % n
        ax, ay, cx, cy = F.get("xs", i), F.get("ys", i), F.get("xs", j), F.get("ys", j)
        length = F.sqrt((cx - ax) * (cx - ax) + (cy - ay) * (cy - ay))
        return (cx - ax) * (F.col("py") - ay) - (cy - ay) * (F.col("px") - ax) >= -1e-6 * (length + 1)

    inside = F.forall(F.sequence(F.lit(0), n - 1), left_of)
    return q.join(g, ["bx", "by"]).where(inside).select("qid", "oid", dist2(F.col("x"), F.col("y"), F.col("gx"), F.col("gy")).alias("d2"))
