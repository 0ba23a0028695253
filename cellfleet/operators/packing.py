"""Packing pieces on servers by their access patterns: agglomerative merging, then tabu search.

The input is a matrix of pieces by intervals on the driver, 288 numbers a piece. The work grows somewhat less than with the square of
the pieces: from ``MOST_PIECES`` on they are better packed region by region, each by one task (``pack_regions``)."""

from __future__ import annotations

import heapq
import random
from collections import deque
from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellfleet.functions.geometry import box_disk_d2
from cellfleet.lineage import cut
from cellfleet.operators import access, kdpart, pivots

MOST_PIECES = 5000
#: The weight of peaks beside idle time, and the least improvement that keeps a search going.
LEVEL, LEAST = 0.05, 1e-5
#: Patterns of signs, and intervals, by which pairs of clusters are bounded.
SIGNS, SEEN = 16, 24
#: Partners that a cluster keeps.
KEPT = 16
Tier = tuple[int, float, int, float]


def variation(loads: np.ndarray) -> np.ndarray:
    return np.abs(np.diff(loads, axis=-1)).sum(axis=-1)


def _tier(peak: float, rows: int, tiers: Sequence[Tier]) -> Tier | None:
    return min((t for t in tiers if peak < t[1] and rows <= t[2]), key=lambda t: t[3], default=None)


def cost_idle(load: np.ndarray, rows: int, tiers: Sequence[Tier]) -> float:
    """Idle capacity of a server's tier over the day; a closed server has none, one that no tier carries infinitely much."""
    if rows == 0 and not load.any():
        return 0.0
    t = _tier(float(load.max()), rows, tiers)
    return float("inf") if t is None else t[1] * load.size - float(load.sum())


def total_idle(plan: np.ndarray, a: np.ndarray, rows: np.ndarray, tiers: Sequence[Tier]) -> float:
    return sum(cost_idle(a[plan == s].sum(axis=0), int(rows[plan == s].sum()), tiers) for s in np.unique(plan))


def agglomerate(a: np.ndarray, rows: np.ndarray, servers: int, tiers: Sequence[Tier]) -> np.ndarray:
    """The server of each piece: the feasible pair of clusters that is flattest together is merged until ``servers`` are left
    or no pair is feasible. Each cluster keeps its ``KEPT`` best partners and looks for others when all of them are gone; a merged
    cluster is added to those that it is among the best of. To look for them reads two columns of numbers; only pairs that
    those can't rule out are bounded by the others, and few are compared in full."""
    p = len(a)
    load, size = a.astype(np.float64).copy(), rows.astype(np.int64).copy()
    plan = np.arange(p)
    capacity, storage = max(t[1] for t in tiers), max(t[2] for t in tiers)
    # the least flatness of a cluster's partners, the flatness up to which it knows all of them, and a cluster's version, -1 if it is gone
    best, known, version = np.full(p, np.inf), np.full(p, np.inf), np.zeros(p, dtype=np.int64)
    partners: list[list[tuple[float, int, int]]] = [[] for _ in range(p)]
    # sums of steps under signs bound the variation of a pair from below, some intervals its peak: most pairs are not compared in full
    t, width = np.arange(max(0, a.shape[1] - 1)), a.shape[1]
    signs = np.where(np.sin(2 * np.pi * (t[:, None] / max(1, width) + np.arange(SIGNS) / (2 * SIGNS))) >= 0, 1.0, -1.0)
    seen = np.unique(np.linspace(0, width - 1, min(width, SEEN)).astype(int))
    sums, steps, some = np.diff(load) @ signs, variation(load), load[:, seen]
    first, second = sums[:, 0].copy(), sums[:, SIGNS // 2].copy()  # infinite for clusters that are gone
    slack = 1e-9 * float(steps.max(initial=0.0))

    def flat(i: int, j: np.ndarray) -> np.ndarray:
        """How flat i is with each j; infinite if they don't fit one server."""
        both = load[i] + load[j]
        return np.where((both.max(axis=1) < capacity) & (size[j] + size[i] <= storage), variation(both), np.inf)

    def pairs(i: int, start: int, end: int, most: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(j, d), j from start to end: flatness of the feasible pairs of i and j that can be the ``KEPT`` flattest, or flatter than ``most`` of j."""
        rough = np.maximum(np.abs(first[start:end] + first[i]), np.abs(second[start:end] + second[i]))
        least = np.inf
        if most is None and len(rough) > 8 * KEPT:
            near = np.argpartition(rough, 2 * KEPT)[: 2 * KEPT]
            least = float(np.sort(np.where(rough[near] < np.inf, flat(i, start + near), np.inf))[KEPT - 1])
        j = np.flatnonzero((rough < np.inf) & (rough - 2 * slack <= (least if most is None else most)))
        limit = None if most is None else most[j]
        j = j + start
        if not len(j):
            return j, np.zeros(0)
        low = np.maximum(np.abs(sums[j] + sums[i]).max(axis=1), np.abs(steps[j] - steps[i])) - 1e-9 * (steps[j] + steps[i])
        can = (size[j] + size[i] <= storage) & ((some[j] + some[i]).max(axis=1) < capacity) & (low <= (least if limit is None else limit))
        j, low = j[can], low[can]
        order, d, s, step = np.argsort(low, kind="stable"), np.full(len(j), np.inf), 0, 2 * KEPT
        while s < len(j) and (most is not None or low[order[s]] <= least):
            at = order[s : s + step]
            d[at] = flat(i, j[at])
            s, step = s + step, min(1 << 10, 2 * step)
            if most is None and s >= KEPT:
                least = min(least, float(np.partition(d[order[:s]], KEPT - 1)[KEPT - 1]) if len(j) >= KEPT else np.inf)
        return j, d

    def refresh(i: int) -> None:
        j, d = pairs(i, i + 1, p)
        known[i] = np.partition(d, KEPT - 1)[KEPT - 1] if len(d) >= KEPT else np.inf
        kept = np.flatnonzero(d <= known[i]) if known[i] < np.inf else np.flatnonzero(d < np.inf)
        partners[i] = sorted(zip(d[kept].tolist(), j[kept].tolist(), version[j[kept]].tolist(), strict=True))
        best[i] = partners[i][0][0] if partners[i] else np.inf

    for i in range(p):
        refresh(i)
    left = p
    while left > servers:
        i = int(best.argmin())
        if not np.isfinite(best[i]):
            break
        d, j, v = partners[i][0]
        if version[j] != v:
            heapq.heappop(partners[i])
            if partners[i]:
                best[i] = partners[i][0][0]
            elif known[i] < np.inf:
                refresh(i)
            else:
                best[i] = np.inf
            continue
        load[i] += load[j]
        size[i] += size[j]
        sums[i], steps[i], some[i] = np.diff(load[i]) @ signs, variation(load[i]), load[i, seen]
        first[i], second[i], slack = sums[i, 0], sums[i, SIGNS // 2], max(slack, 1e-9 * float(steps[i]))
        version[i] += 1
        version[j], best[j], known[j], first[j], second[j], partners[j] = -1, np.inf, -np.inf, np.inf, np.inf, []
        plan[plan == j] = i
        left -= 1
        refresh(i)
        # the merged cluster may be a better partner for those before it
        before, d = pairs(i, 0, i, known[:i])
        for b, x in zip(before.tolist(), d.tolist(), strict=True):
            if x <= known[b]:
                heapq.heappush(partners[b], (x, i, int(version[i])))
                best[b] = min(best[b], x)
    return np.unique(plan, return_inverse=True)[1]


def tabu(plan: np.ndarray, a: np.ndarray, rows: np.ndarray, tiers: Sequence[Tier], eta: float = 50.0, list_size: int = 20, patience: int | None = None, seed: int = 1, fragments: int = 24, neighbourhood: str = "move", apart: Sequence[Sequence[int]] = ()) -> np.ndarray:
    """A plan with no more idle time. Idle time changes by steps, from tier to tier, so that plans are also compared by the sum of
    their servers' peaks, with the small weight ``LEVEL``: it leads over plateaus towards a tier less. Each iteration draws fragments and for each a random other server (``swap``: and one of
    its fragments, to change places); moves that change both servers' flatness by less than ``eta`` percent and fit some tier are
    admissible. The best one is taken even if it is worse; what it undoes is tabu while listed, unless it beats the best plan
    so far. Stops after ``patience`` iterations (200, or as many as there are pieces) without an improvement by ``LEAST`` of the whole. ``apart``: groups of pieces that never share a server."""
    rng = random.Random(seed)
    plan = plan.copy()
    k = int(plan.max()) + 1 if len(plan) else 0
    if k < 2:
        return plan
    load = np.array([a[plan == s].sum(axis=0) for s in range(k)])
    size = np.array([int(rows[plan == s].sum()) for s in range(k)])
    group = {p: i for i, g in enumerate(apart) for p in g}
    idle = [cost_idle(load[s], size[s], tiers) for s in range(k)]
    level = [LEVEL * a.shape[1] * float(x.max()) for x in load]
    now = sum(idle) + sum(level)
    patience = max(200, len(plan)) if patience is None else patience
    best, mark, least, kept = now, now, sum(idle), plan.copy()
    listed: deque[tuple[int, int]] = deque(maxlen=list_size)
    waited = 0
    while waited < patience:
        options = []
        for _ in range(fragments):
            p, t = rng.randrange(len(plan)), rng.randrange(k)
            s = int(plan[p])
            if s == t:
                continue
            q = None
            if neighbourhood == "swap":
                there = np.flatnonzero(plan == t)
                if not len(there):
                    continue
                q = int(there[rng.randrange(len(there))])
            moved, count = (a[p], int(rows[p])) if q is None else (a[p] - a[q], int(rows[p]) - int(rows[q]))
            if p in group and any(plan[x] == t and group.get(x) == group[p] and x != q for x in apart[group[p]]):
                continue
            if q is not None and q in group and any(plan[x] == s and group.get(x) == group[q] and x != p for x in apart[group[q]]):
                continue
            ls, lt = load[s] - moved, load[t] + moved
            d0, d1 = variation(np.array([load[s], load[t]])), variation(np.array([ls, lt]))
            if (np.abs(d1 - d0) > eta / 100 * np.maximum(d0, 1e-12)).any():
                continue
            a0, a1 = cost_idle(np.maximum(ls, 0.0), size[s] - count, tiers), cost_idle(lt, size[t] + count, tiers)
            p0, p1 = LEVEL * a.shape[1] * float(ls.max()), LEVEL * a.shape[1] * float(lt.max())
            then = now - idle[s] - idle[t] - level[s] - level[t] + a0 + a1 + p0 + p1
            tabu_move = (p, t) in listed or q is not None and (q, s) in listed
            if np.isfinite(then) and (not tabu_move or then < best - 1e-9):
                options.append((then, p, q, s, t, ls, lt, a0, a1, p0, p1, count))
        waited += 1
        if not options:
            continue
        then, p, q, s, t, ls, lt, a0, a1, p0, p1, count = min(options, key=lambda o: o[0])
        plan[p], now = t, then
        listed.append((p, s))
        if q is not None:
            plan[q] = s
            listed.append((q, t))
        load[s], load[t], idle[s], idle[t], level[s], level[t] = ls, lt, a0, a1, p0, p1
        size[s] -= count
        size[t] += count
        best = min(best, now)
        if now < mark - LEAST * abs(mark):
            mark, waited = now, 0
        if (total := sum(idle)) < least - 1e-9 or total <= least + 1e-9 and now <= best:
            least, kept = min(least, total), plan.copy()
    return kept


def pack(a: np.ndarray, rows: np.ndarray, servers: int, tiers: Sequence[Tier], search: bool = True, seeds: Sequence[int] = (1, 2, 3)) -> np.ndarray:
    start = agglomerate(a, rows, servers, tiers)
    if not search:
        return start
    tried = [tabu(start, a, rows, tiers, seed=s) for s in seeds] + [start]
    return min(tried, key=lambda plan: total_idle(plan, a, rows, tiers))


def matrix(vecs: DataFrame, rows: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(pids, patterns, rows) on the driver, of ``vecs(pid, v)`` and ``rows(pid, n)``: 2.3 KB a piece."""
    got = rows.join(vecs, "pid", "left").select("pid", "n", "v").orderBy("pid").toArrow()
    v = got.column("v").combine_chunks()
    known, flat = v.is_valid().to_numpy(zero_copy_only=False), v.flatten().to_numpy(zero_copy_only=False)
    a = np.zeros((got.num_rows, len(flat) // max(1, int(known.sum())) or 288))
    a[known] = flat.reshape(-1, a.shape[1])
    return got.column("pid").to_numpy(), a, got.column("n").to_numpy()


def pack_regions(pieces: DataFrame, servers: int, tiers: Sequence[Tier], search: bool = True) -> DataFrame:
    """(region, pid, server): each region of ``pieces(region, pid, n, v)`` packed by a task of its own."""

    def one(p: pd.DataFrame) -> pd.DataFrame:
        plan = pack(np.array(p["v"].tolist()), p["n"].to_numpy(), servers, tiers, search)
        return pd.DataFrame({"region": p["region"], "pid": p["pid"], "server": plan.astype("int64")})

    return pieces.groupBy("region").applyInPandas(one, "region long, pid long, server long")


def with_replicas(plan: DataFrame, copies: int, servers: int) -> DataFrame:
    """(pid, copy, server): whole-piece copies on the next servers, so that no server holds a piece twice."""
    if copies >= servers:
        raise ValueError("fewer copies than servers")
    c = F.explode(F.sequence(F.lit(0), F.lit(copies))).alias("copy")
    return plan.select("pid", "server", c).select("pid", "copy", ((F.col("server") + F.col("copy")) % servers).alias("server"))


def with_borders(at: DataFrame, boxed: DataFrame, lam: float, least: float = 1.0) -> DataFrame:
    """(oid, x, y, pid, is_replica): objects in their piece, and copies of those within ``lam`` of another piece's box in that piece;
    interiors aren't copied. Objects and boxes grown by ``lam`` meet in squares, a little wider than ``lam``."""
    side = max(float(lam), least) * 8
    square_of = lambda c: F.floor(c / side)
    b = boxed.select(F.col("pid").alias("to"), "x0", "y0", "x1", "y1")
    b = b.withColumn("sx", F.explode(F.sequence(square_of(F.col("x0") - lam), square_of(F.col("x1") + lam)))).withColumn("sy", F.explode(F.sequence(square_of(F.col("y0") - lam), square_of(F.col("y1") + lam))))
    own = at.select("oid", "x", "y", "pid")
    met = own.withColumn("sx", square_of(F.col("x"))).withColumn("sy", square_of(F.col("y"))).join(b, ["sx", "sy"])
    near = met.where((F.col("to") != F.col("pid")) & (box_disk_d2(F.col("x"), F.col("y"), F.col("x0"), F.col("y0"), F.col("x1"), F.col("y1")) <= lam * lam))
    return own.withColumn("is_replica", F.lit(False)).unionByName(near.select("oid", "x", "y", F.col("to").alias("pid"), F.lit(True).alias("is_replica")))


def run(pts: DataFrame, accesses: DataFrame, tiers: Sequence[Tier], servers: int, pieces: str = "kd", cap: int = 5000, count: int = 128, search: bool = True, bits: int = kdpart.DEPTH, levels: int = 30) -> DataFrame:
    """(pid, n, server): the whole packer. Points ``(oid, x, y)`` become pieces, ``kd`` leaves of at most ``cap`` points or ``voronoi``
    pieces of ``count`` elected pivots; ``accesses(oid, ts)`` their patterns; and the patterns a plan. Many more than
    ``MOST_PIECES`` pieces take long: they are better packed region by region (``pack_regions``)."""
    if pieces == "kd":
        coded = kdpart.coded(pts)
        boxed = kdpart.with_boxes(kdpart.build(coded, cap, bits, levels), bits)
        at = kdpart.assign(coded, boxed, bits).select("oid", "pid")
    elif pieces == "voronoi":
        at = pivots.assign(pts, pivots.choose(pts, count)).select("oid", "pid")
    else:
        raise ValueError("pieces are kd or voronoi")
    at = cut(at)
    pids, a, rows = matrix(access.vectors(access.patterns(at.join(accesses, "oid").select("pid", "ts"))), at.groupBy("pid").agg(F.count("*").alias("n")))
    plan = pack(a, rows, servers, tiers, search) if len(a) else np.zeros(0, dtype=np.int64)
    return pts.sparkSession.createDataFrame([(int(p), int(n), int(s)) for p, n, s in zip(pids, rows, plan, strict=True)], "pid long, n long, server long")
