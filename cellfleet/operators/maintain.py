"""Keeping a fleet plan up to date: changed leaves, and servers found by free capacity."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cellfleet.functions import zorder
from cellfleet.lineage import cut
from cellfleet.operators import kdpart


def apply_changes(counts: DataFrame, changes: DataFrame, cap: int, levels: int = 30, bits: int = kdpart.DEPTH) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(counts, gone leaves, new leaves) after ``changes(z, dn)`` of ``counts(z, n)``; unchanged leaves are in neither."""
    after = counts.join(changes.groupBy("z").agg(F.sum("dn").alias("dn")), "z", "full_outer")
    after = after.select("z", (F.coalesce("n", F.lit(0)) + F.coalesce("dn", F.lit(0))).alias("n")).where("n > 0")
    old, new = kdpart.leaves(counts, cap, bits, levels), kdpart.leaves(after, cap, bits, levels)
    return after, old.join(new, ["depth", "prefix"], "left_anti"), new.join(old, ["depth", "prefix"], "left_anti")


def spread(total: int, room: np.ndarray, skew: float) -> np.ndarray:
    """How many of ``total`` changes fall into each piece: by rank ** -skew, the ranks mixed, and at most ``room``, the rest
    going to the pieces that have some."""
    weight = np.empty(len(room))
    weight[np.argsort(np.arange(len(room)) * 7919 % 104729)] = np.arange(1, len(room) + 1, dtype=float) ** -skew
    out = np.zeros(len(room), dtype=np.int64)
    while (left := min(total, int(room.sum())) - int(out.sum())) > 0:
        free = np.where(out < room, weight, 0.0)
        more = np.minimum((left * free / free.sum()).astype(np.int64), room - out)
        if not more.any():
            more[np.argsort(-free, kind="stable")[: min(left, np.count_nonzero(free))]] = 1
        out += more
    return out


def _share(tag: str, *keys: str) -> Column:
    """A number in [0, 1) by digest."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(tag), *[F.col(k).cast("string") for k in keys])), 1, 7), 16, 10).cast("double") / 16.0**7


def inserted(boxed: DataFrame, wanted: DataFrame) -> DataFrame:
    """(pid, z) of new objects, ``wanted(pid, k)`` of each leaf's ``boxed(pid, z0, z1)``, anywhere in it."""
    each = boxed.select("pid", "z0", "z1").join(F.broadcast(wanted.where("k > 0")), "pid").withColumn("j", F.explode(F.sequence(F.lit(1), F.col("k"))))
    return each.select("pid", (F.col("z0") + F.floor(_share("i", "pid", "j") * (F.col("z1") - F.col("z0") + 1))).cast("long").alias("z"))


def moved(at: DataFrame, wanted: DataFrame, most: float, side: int) -> DataFrame:
    """``at(oid, x, y, z, pid)`` with ``to``, the code of the new place of ``wanted(pid, k)`` objects of each leaf and null for the
    others: a step of up to ``most`` in one of eight directions, held within the square of ``side``."""
    turn = F.floor(_share("d", "oid") * 8) * (np.pi / 4)
    held = lambda v: F.least(F.lit(side - 1), F.greatest(F.lit(0), F.floor(v + 0.5))).cast("long")
    rank = F.row_number().over(Window.partitionBy("pid").orderBy(F.md5(F.concat(F.lit("m:"), F.col("oid").cast("string"))), "oid"))
    step = _share("s", "oid") * most
    go = at.withColumn("rank", rank).join(F.broadcast(wanted), "pid").withColumn("tx", held(F.col("x") + step * F.cos(turn))).withColumn("ty", held(F.col("y") + step * F.sin(turn)))
    go = cut(go)  # the code repeats its arguments by the bit: with the steps in it, it can't be compiled
    return go.withColumn("to", F.when(F.col("rank") <= F.col("k"), zorder.encode(F.col("tx"), F.col("ty")))).drop("rank", "k", "tx", "ty")


class Fleet:
    """Servers of equal capacity with their summed loads, found by groups of free capacity.

    A server is in group floor(free / capacity * groups); a piece asks first the group that its peak just fits in, then
    larger ones, and gets the server there that it is flattest with, or a new one."""

    def __init__(self, capacity: float, groups: int = 4, width: int = 288):
        self.capacity, self.groups, self.width = capacity, groups, width
        self.loads: list[np.ndarray] = []
        self.where: dict[int, int] = {}
        self.pieces: dict[int, np.ndarray] = {}

    def adopt(self, plan: np.ndarray, loads: np.ndarray) -> None:
        """Starts from a plan: the server of each piece, and the pieces' loads."""
        self.loads = [loads[plan == s].sum(axis=0) for s in range(int(plan.max()) + 1)] if len(plan) else []
        self.where = {i: int(s) for i, s in enumerate(plan)}
        self.pieces = dict(enumerate(loads))

    def group(self, share: float) -> int:
        return max(0, min(self.groups - 1, int(share / self.capacity * self.groups)))

    def place(self, pid: int, load: np.ndarray) -> int:
        if self.loads:
            at = np.stack(self.loads)
            groups = [self.group(self.capacity - peak) for peak in at.max(axis=1).tolist()]
            both = at + load
            flat, fits = np.abs(np.diff(both)).sum(axis=1).tolist(), (both.max(axis=1) < self.capacity).tolist()
            for g in range(self.group(float(load.max())), self.groups):
                found = [(flat[s], s) for s, own in enumerate(groups) if own == g and fits[s]]
                if found:
                    return self._put(pid, load, min(found)[1])
        self.loads.append(np.zeros(self.width))
        return self._put(pid, load, len(self.loads) - 1)

    def _put(self, pid: int, load: np.ndarray, s: int) -> int:
        self.loads[s] = self.loads[s] + load
        self.where[pid], self.pieces[pid] = s, load
        return s

    def remove(self, pid: int) -> None:
        s = self.where.pop(pid)
        self.loads[s] = np.maximum(0.0, self.loads[s] - self.pieces.pop(pid))

    def update(self, pid: int, load: np.ndarray) -> int:
        self.remove(pid)
        return self.place(pid, load)

    def place_all(self, pieces: dict[int, np.ndarray]) -> dict[int, int]:
        """Bulk changes: the piece of the highest peak first, ties by pid."""
        return {p: self.place(p, pieces[p]) for p in sorted(pieces, key=lambda p: (-float(pieces[p].max()), p))}
