"""Competing fleets: static grid, scattered grid, grid with an auto-scaler."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellfleet.operators import kdpart
from cellfleet.operators.packing import Tier, _tier

DOWN, WAIT = 0.5, 6


def grid_cells(pts: DataFrame, cap: int, bits: int = kdpart.DEPTH, levels: int = 30) -> DataFrame:
    """(depth, prefix, n): square cells of one size, halved on both axes until none has more than ``cap`` points."""
    deep = pts.groupBy(F.expr(f"shiftright(z, {bits - levels})").alias("code")).agg(F.count("*").alias("n"))
    each = deep.select("n", "code", F.explode(F.sequence(F.lit(0), F.lit(levels), F.lit(2))).alias("depth"))
    cells = each.groupBy("depth", F.expr(f"shiftright(code, {levels} - depth)").alias("prefix")).agg(F.sum("n").alias("n"))
    fits = cells.groupBy("depth").agg(F.max("n").alias("most")).agg(F.coalesce(F.min(F.when(F.col("most") <= cap, F.col("depth"))), F.lit(levels)).alias("depth"))
    return cells.join(F.broadcast(fits), "depth").select("depth", "prefix", "n")


def scattered(cells: DataFrame, servers: int, seed: int = 7) -> DataFrame:
    """``cells(depth, prefix, n)`` with a server by digest."""
    h = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("prefix").cast("string"))), 1, 7), 16, 10).cast("long")
    return cells.withColumn("server", h % servers)


class Reactive:
    """Grid servers under an auto-scaler. Every interval: a server at or above capacity splits its pieces by half of its rows
    and, alone with one piece, moves up a tier; one under half of its capacity for six intervals moves down a tier if its rows
    still fit; two that would have fitted into one for six intervals merge. A new server is of the lowest tier that stores its rows."""

    def __init__(self, a: np.ndarray, rows: np.ndarray, tiers: Sequence[Tier], start: Sequence[Sequence[int]]):
        self.a, self.rows, self.tiers = a, rows, sorted(tiers)
        self.capacity, self.storage = np.array([t[1] for t in self.tiers]), np.array([t[2] for t in self.tiers])
        self.servers = [self._server(list(g)) for g in start]  # pieces, tier, intervals since it last changed, load, rows
        self.events: list[tuple[int, str]] = []
        self.idle, self.by_hours = 0.0, 0.0

    def _server(self, pieces: list[int], tier: int | None = None, since: int = 0) -> list:
        n = int(self.rows[pieces].sum())
        return [pieces, self._storage_tier(n) if tier is None else tier, 0, self.a[pieces].sum(axis=0), n, since]

    def _bill(self, s: list, t: int) -> None:
        """A machine that is given back at ``t`` is paid by started hours."""
        self.by_hours += -(-(t - s[5]) // 12) * self.tiers[s[1]][3]

    def _storage_tier(self, n: int) -> int:
        return min(int(np.searchsorted(self.storage, n, side="left")), len(self.tiers) - 1)

    def _split(self, t: int) -> None:
        for at, s in enumerate(list(self.servers)):
            pieces, tier, _, load, _, since = s
            if load[t] < self.capacity[tier]:
                continue
            if len(pieces) == 1:
                if tier + 1 < len(self.tiers):
                    self._bill(s, t)
                    s[1], s[2], s[5] = tier + 1, 0, t
                    self.events.append((t, "up"))
                continue
            run = np.cumsum(self.rows[pieces])
            cut = min(len(pieces) - 1, max(1, int(np.searchsorted(run, run[-1] / 2, side="left")) + 1))
            self.servers[at] = self._server(pieces[:cut], tier, since)
            self.servers.append(self._server(pieces[cut:], since=t))
            self.events.append((t, "split"))

    def _down(self, t: int) -> None:
        for s in self.servers:
            tier, age, load, n = s[1:5]
            if tier and age >= WAIT and self._storage_tier(n) < tier and (load[max(0, t - WAIT + 1) : t + 1] < DOWN * self.capacity[tier]).all():
                self._bill(s, t)
                s[1], s[2], s[5] = tier - 1, 0, t
                self.events.append((t, "down"))

    def _merge(self, t: int) -> None:
        window = np.array([s[3][max(0, t - WAIT + 1) : t + 1] for s in self.servers])
        tier, age, n = (np.array([s[k] for s in self.servers]) for k in (1, 2, 4))
        alive = np.ones(len(self.servers), dtype=bool)
        for i in range(len(self.servers)):
            if not alive[i] or age[i] < WAIT:
                continue
            k = np.maximum(tier, tier[i])
            fits = alive & (age >= WAIT) & (np.arange(len(alive)) > i) & (n + n[i] <= self.storage[k]) & ((window + window[i]).max(axis=1) < self.capacity[k])
            if fits.any():
                j = int(fits.argmax())
                # the machine whose tier the two need stays
                stays, goes = (i, j) if tier[i] >= tier[j] else (j, i)
                self._bill(self.servers[goes], t)
                self.servers[i] = self._server(sorted(self.servers[i][0] + self.servers[j][0]), int(k[j]), self.servers[stays][5])
                alive[j], age[i] = False, 0
                self.events.append((t, "merge"))
        self.servers = [s for s, kept in zip(self.servers, alive.tolist(), strict=True) if kept]

    def run(self) -> float:
        """The cost of a day: prices of all servers by the interval. ``by_hours``: the same by started hours of each machine;
        ``idle``: capacity that wasn't used."""
        cost = 0.0
        for t in range(self.a.shape[1]):
            self._split(t)
            self._down(t)
            self._merge(t)
            for s in self.servers:
                s[2] += 1
            cost += sum(self.tiers[s[1]][3] for s in self.servers) / 12
            self.idle += sum(max(0.0, float(self.capacity[s[1]] - s[3][t])) for s in self.servers)
        for s in self.servers:
            self._bill(s, self.a.shape[1])
        return cost


def static(a: np.ndarray, rows: np.ndarray, plan: np.ndarray, tiers: Sequence[Tier]) -> tuple[int, float, float]:
    """(servers, idle capacity, cost) of a day of servers of fixed tiers, each the cheapest that carries its peak and rows; above
    all tiers, several of the highest."""
    top = max(tiers)
    servers, idle, cost = 0, 0.0, 0.0
    for s in np.unique(plan):
        load, n = a[plan == s].sum(axis=0), int(rows[plan == s].sum())
        t = _tier(float(load.max()), n, tiers)
        many = 1 if t else max(int(load.max() // top[1]) + 1, -(-n // top[2]))
        servers += many
        idle += many * (t or top)[1] * load.size - float(load.sum())
        cost += many * (t or top)[3] * 24
    return servers, idle, cost


def static_cost(a: np.ndarray, rows: np.ndarray, plan: np.ndarray, tiers: Sequence[Tier]) -> float:
    return static(a, rows, plan, tiers)[2]
