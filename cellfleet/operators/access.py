"""Access patterns of pieces by 5-minute interval, and how flat they are."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

INTERVALS = 288


def interval(ts: Column) -> Column:
    """5-minute interval of the day, 0 to 287."""
    return (F.hour(ts) * 12 + F.floor(F.minute(ts) / 5)).cast("int")


def patterns(accesses: DataFrame, multiplier: float = 1.0) -> DataFrame:
    """(pid, t, a) of ``accesses(pid, ts)``; intervals without any aren't rows."""
    return accesses.groupBy("pid", interval(F.col("ts")).alias("t")).agg((F.count("*") * F.lit(multiplier)).cast("double").alias("a"))


def vectors(long: DataFrame) -> DataFrame:
    """(pid, v): the pattern as an array of 288 numbers, missing intervals 0."""
    known = long.groupBy("pid").agg(F.map_from_entries(F.collect_list(F.struct("t", "a"))).alias("m"))
    return known.select("pid", F.transform(F.sequence(F.lit(0), F.lit(INTERVALS - 1)), lambda t: F.coalesce(F.element_at("m", t), F.lit(0.0))).alias("v"))


def flatness(v: Column, mode: str = "variation") -> Column:
    """Sum of the absolute steps of a load; ``net`` is the absolute sum of its steps, which is 0 for any periodic load."""
    if mode == "net":
        return F.abs(F.element_at(v, -1) - F.element_at(v, 1))
    steps = F.zip_with(F.slice(v, 1, F.size(v) - 1), F.slice(v, 2, F.size(v) - 1), lambda a, b: F.abs(b - a))
    return F.aggregate(steps, F.lit(0.0), lambda acc, x: acc + x)


#: Pieces of a block of pairs, and of the strip of it that is compared at once.
PAIR_BLOCK, PAIR_STRIP = 512, 8


def pair_flatness(vecs: DataFrame) -> DataFrame:
    """(a, b, delta) of all pairs of pieces: how flat two patterns are together. Pieces are dealt to blocks, each pair of blocks is
    compared by a kernel on the steps of the patterns."""
    n = max(1, -(-vecs.count() // PAIR_BLOCK))
    at = vecs.select("pid", "v", F.pmod(F.col("pid"), F.lit(n)).cast("int").alias("k"))
    every = F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    l = at.withColumn("o", every).where("k <= o").select("pid", "v", F.col("k").alias("i"), F.col("o").alias("j"))
    r = at.withColumn("o", every).where("o <= k").select(F.col("pid").alias("q"), F.col("v").alias("w"), F.col("o").alias("i"), F.col("k").alias("j"))

    def one(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows or not right.num_rows:
            return pa.table({"a": pa.array([], pa.int64()), "b": pa.array([], pa.int64()), "delta": pa.array([], pa.float64())})
        (p, v), (q, w) = ((t.column(0).to_numpy(), np.stack(t.column(1).to_numpy())) for t in (left, right))
        same, out = left.column("i")[0].as_py() == left.column("j")[0].as_py(), []
        for s in range(0, len(p), PAIR_STRIP):
            both = v[s : s + PAIR_STRIP, None, :] + w[None, :, :]
            delta = np.abs(np.diff(both, axis=2)).sum(axis=2)
            x, y = np.broadcast_arrays(p[s : s + PAIR_STRIP, None], q[None, :])
            kept = x < y if same else np.ones(x.shape, dtype=bool)
            out.append(pa.table({"a": np.minimum(x, y)[kept], "b": np.maximum(x, y)[kept], "delta": delta[kept]}))
        return pa.concat_tables(out)

    return l.groupBy("i", "j").cogroup(r.groupBy("i", "j")).applyInArrow(one, "a bigint, b bigint, delta double")


def server_load(long: DataFrame, plan: DataFrame) -> DataFrame:
    """(server, t, load)."""
    return long.join(plan.select("pid", "server"), "pid").groupBy("server", "t").agg(F.sum("a").alias("load"))


def cosine_load(pieces: DataFrame, extent: float) -> DataFrame:
    """(pid, t, a) for ``pieces(pid, n, cx)``: one wave a day, its phase by place as if by time zone."""
    t = F.explode(F.sequence(F.lit(0), F.lit(INTERVALS - 1))).alias("t")
    wave = (1 + F.cos(2 * math.pi * (F.col("t") / INTERVALS - F.col("cx") / extent))) / 2
    return pieces.select("pid", "n", "cx", t).select("pid", "t", (F.col("n") * wave).alias("a"))


def zipf_load(pieces: DataFrame, skew: float) -> DataFrame:
    """(pid, t, a): intervals ranked by digest get rank ** -skew, scaled so that a piece's largest load is n."""
    e = pieces.select("pid", "n", F.explode(F.sequence(F.lit(0), F.lit(INTERVALS - 1))).alias("t"))
    rank = F.row_number().over(Window.partitionBy("pid").orderBy(F.md5(F.concat_ws(":", F.col("pid").cast("string"), F.col("t").cast("string")))))
    return e.withColumn("rank", rank).select("pid", "t", (F.col("n") * F.pow(F.col("rank").cast("double"), F.lit(-skew))).alias("a"))
