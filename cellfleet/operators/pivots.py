"""Pivots: candidates, election, assignment of points, partition statistics and grouping of pieces on nodes."""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator, Mapping, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cellfleet.functions.geometry import dist2
from cellfleet.lineage import cut
from cellfleet.operators.pivot_grid import PivotGrid

SEED = 42
#: Pivots that are compared within the plan; beyond it a kernel looks them up in a grid of pivots. In a plan that joins by the piece
#: the comparison is written out once for each use, until the generated code is too long to be compiled: 600,000 points in 8 pieces
#: took 3.1 s to answer 50 ranges, and 0.7 s by the kernel. So only a single pivot stays in the plan.
LITERAL_PIVOTS, MOST_PIVOTS = 1, 100_000
#: Candidates that an election may have: they are a top-k of samples that is merged on the driver.
MOST_CANDIDATES = 2_000_000
Pivot = tuple[int, int, int]


def draw(seed: int, oid: str = "oid") -> Column:
    """A sampling key that any engine can compute: rows are drawn in its order."""
    return F.md5(F.concat(F.lit(f"{seed}:"), F.col(oid).cast("string")))


def candidates(pts: DataFrame, n_cand: int, seed: int = SEED) -> DataFrame:
    """(rk, oid, x, y): the first ``n_cand`` points by sampling key, kept as a top-k per partition and merged."""
    top = pts.select("oid", "x", "y", draw(seed).alias("key")).orderBy("key", "oid").limit(n_cand)
    return top.select(F.row_number().over(Window.orderBy("key", "oid")).cast("long").alias("rk"), "oid", "x", "y")


def node_candidates(pts: DataFrame, nodes: int, per_node: int, seed: int = SEED) -> DataFrame:
    """(node, rk, oid, x, y): each node draws from its own points."""
    own = pts.withColumn("node", F.pmod(F.col("oid"), F.lit(nodes)))
    by = Window.partitionBy("node").orderBy("key", "oid")
    return own.withColumn("key", draw(seed)).withColumn("rk", F.row_number().over(by).cast("long")).where(F.col("rk") <= per_node).select("node", "rk", "oid", "x", "y")


def scores(cand: DataFrame, p: int, objective: str = "sum_dist") -> DataFrame:
    """(set, score) of the full sets of ``p`` candidates. ``sum_dist``: sum of pair distances; ``sum_sq``: of squared ones, by
    sums alone; ``first``: no election."""
    sets = cand.withColumn("set", F.floor((F.col("rk") - 1) / p).cast("long"))
    sets = sets.drop("node")
    full = sets.groupBy("set").agg(F.count("*").alias("n"), F.sum(F.col("x").cast("double")).alias("sx"), F.sum(F.col("y").cast("double")).alias("sy"), F.sum((F.col("x") * F.col("x") + F.col("y") * F.col("y")).cast("double")).alias("sq")).where(F.col("n") == p)
    if objective == "first":
        return full.select("set", F.lit(0.0).alias("score"))
    if objective == "sum_sq":
        return full.select("set", (p * F.col("sq") - F.col("sx") * F.col("sx") - F.col("sy") * F.col("sy")).alias("score"))
    if objective != "sum_dist":
        raise ValueError("objective is sum_dist, sum_sq or first")

    def pair_distances(t: pa.Table) -> pa.Table:
        """The sum for a set, a block of rows against all later ones at a time."""
        x, y = (t.column(c).to_numpy().astype(np.float64) for c in ("x", "y"))
        total, step = 0.0, max(1, (1 << 22) // max(1, len(x)))
        for s in range(0, len(x), step):
            dx, dy = x[s : s + step, None] - x[None, s:], y[s : s + step, None] - y[None, s:]
            total += float(np.triu(np.sqrt(dx * dx + dy * dy), 1).sum())
        return pa.table({"set": t.column("set").slice(0, 1), "score": pa.array([total])})

    return sets.join(full.select("set"), "set", "left_semi").groupBy("set").applyInArrow(pair_distances, "set bigint, score double")


def elect(cand: DataFrame, p: int, objective: str = "sum_dist") -> DataFrame:
    """(pid, x, y): the candidates of the set with the largest score, the first of equals; all if there is no full set."""
    best = scores(cand, p, objective).orderBy(F.desc("score"), "set").limit(1).select(F.col("set").alias("best"))
    sets = cand.withColumn("set", F.floor((F.col("rk") - 1) / p).cast("long"))
    joined = sets.join(F.broadcast(best), F.lit(True), "left").where(F.col("set") == F.coalesce("best", F.lit(0)))
    return joined.select(((F.col("rk") - 1) % p).alias("pid"), "x", "y")


def choose(pts: DataFrame, p: int, mult: int = 10, seed: int = SEED, objective: str = "sum_dist") -> list[Pivot]:
    """The elected pivots on the driver, in order of pid; at most ``MOST_PIVOTS``. Of pivots at one place the first stays, as
    no border lies between them."""
    if p > MOST_PIVOTS or p * mult > MOST_CANDIDATES:
        raise ValueError(f"at most {MOST_PIVOTS} pivots and {MOST_CANDIDATES} candidates")
    cand = cut(candidates(pts, p * mult, seed))  # an election reads them three times, and they take a pass over all points
    found = sorted((r["pid"], r["x"], r["y"]) for r in elect(cand, p, objective).collect())
    places = dict.fromkeys((x, y) for _, x, y in found)
    return [(i, x, y) for i, (x, y) in enumerate(places)]


def literal(piv: Sequence[Pivot]) -> Column:
    """Pivots as an array of structs in the plan: folded once, no join."""
    return F.array(*[F.struct(F.lit(i).cast("long").alias("pid"), F.lit(x).cast("long").alias("x"), F.lit(y).cast("long").alias("y")) for i, x, y in piv])


def assign(pts: DataFrame, piv: Sequence[Pivot], method: str | None = None) -> DataFrame:
    """``pts`` with pid and d2 of the nearest pivot, ties to the least pid. No shuffle: ``literal`` compares in generated code,
    ``kernel`` looks pivots up in a grid, in Arrow batches. Coordinates whose squared distances don't fit a long raise an error."""
    n = len(piv)
    if (method or ("literal" if n <= LITERAL_PIVOTS else "kernel")) == "literal":
        each = [dist2(F.col("x"), F.col("y"), F.lit(x), F.lit(y)) for _, x, y in piv]
        # near the pivots there is room for distance and place in one long; further out the two are compared one after the other
        _, cx, cy = piv[0]
        spread = max(max(abs(x - cx), abs(y - cy)) for _, x, y in piv)
        room = math.isqrt((2**62) // (2 * n)) - spread
        close = (F.abs(F.col("x") - cx) < room) & (F.abs(F.col("y") - cy) < room)
        packed = [e * n + i for i, e in enumerate(each)]
        pairs = [F.struct(e.alias("d2"), F.lit(i).cast("long").alias("i")) for i, e in enumerate(each)]
        least = lambda c: F.least(*c) if n > 1 else c[0]
        d = pts.withColumn("a_near", F.when(close, least(packed))).withColumn("a_far", F.when(~close, least(pairs)))
        at = F.coalesce(F.col("a_near") % n, F.col("a_far.i"))
        pid = at if [i for i, *_ in piv] == list(range(n)) else F.get(F.array(*[F.lit(i).cast("long") for i, *_ in piv]), at.cast("int"))
        return d.select(*pts.columns, pid.alias("pid"), F.coalesce(F.expr(f"a_near div {n}"), F.col("a_far.d2")).alias("d2"))
    ids, px, py = ([p[i] for p in piv] for i in range(3))
    xi, yi = pts.columns.index("x"), pts.columns.index("y")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grid = PivotGrid(ids, px, py)
        for b in batches:
            pid, d2 = grid.nearest(b.column(xi).to_numpy(zero_copy_only=False), b.column(yi).to_numpy(zero_copy_only=False))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(pid, pa.int64()), pa.array(d2, pa.int64())], names=[*b.schema.names, "pid", "d2"])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pts.schema)
    return pts.mapInArrow(run, f"{kinds}, pid bigint, d2 bigint")


def stats(assigned: DataFrame) -> DataFrame:
    """(pid, n, f2): objects of each piece and the squared distance of the furthest one."""
    return assigned.groupBy("pid").agg(F.count("*").alias("n"), F.max("d2").alias("f2"))


def balance(assigned: DataFrame, pieces: int) -> DataFrame:
    """(pieces, avg_n, min_n, max_n, std_n) over ``pieces`` pieces, empty ones counted."""
    n = assigned.groupBy("pid").agg(F.count("*").alias("n"))
    return n.agg(
        F.lit(pieces).cast("long").alias("pieces"), (F.sum("n") / pieces).alias("avg_n"),
        F.when(F.count("*") < pieces, 0).otherwise(F.min("n")).cast("long").alias("min_n"), F.max("n").alias("max_n"),
        F.sqrt(F.sum(F.col("n") * F.col("n")) / pieces - F.pow(F.sum("n") / pieces, F.lit(2.0))).alias("std_n"),
    )


def group_spatial(counts: DataFrame, nodes: int) -> DataFrame:
    """(pid, node): pieces in Z-order (or any column ``z``) cut into runs of nearly equal objects."""
    run = F.sum("n").over(Window.orderBy("z", "pid").rowsBetween(Window.unboundedPreceding, -1))
    total = F.sum("n").over(Window.partitionBy())
    return counts.select("pid", F.least(F.lit(nodes - 1), F.floor(F.coalesce(run, F.lit(0)) * nodes / total)).cast("long").alias("node"))


def group_balanced(counts: Sequence[tuple[int, int]], nodes: int) -> dict[int, int]:
    """Node of each piece: the largest piece first, always to the node with the fewest objects."""
    heap = [(0, k) for k in range(nodes)]
    out = {}
    for pid, n in sorted(counts, key=lambda c: (-c[1], c[0])):
        load, k = heapq.heappop(heap)
        out[pid] = k
        heapq.heappush(heap, (load + n, k))
    return out


def distribute(assigned: DataFrame, n: int, nodes: Mapping[int, int] | None = None) -> DataFrame:
    """The one large shuffle: each piece to the partition of its node, by default pid modulo ``n``; no two pieces meet by a hash."""
    to = F.col("pid") if nodes is None else F.get(F.array(*[F.lit(nodes.get(i, i)) for i in range(max(nodes, default=-1) + 1)]), F.col("pid").cast("int"))
    return assigned.repartitionById(n, F.pmod(to.cast("long"), F.lit(n)).cast("int"))
