"""Competing indexes: random distribution, packed leaves, messages of an overlay and of a ring, a router tree. Searches of the
hashed snapshot are in ``hashed``, those of the tree overlay in ``trees``."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cellfleet.functions.geometry import box_disk_d2


def random_distribution(pts: DataFrame, n: int, seed: int) -> DataFrame:
    """Objects to pieces by digest, whatever their place."""
    h = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("oid").cast("string"))), 1, 7), 16, 10).cast("long")
    return pts.withColumn("pid", h % n)


#: Strips of x in which rows are ranked; a strip is what one task sorts.
STRIPS = 4096


def slices_by_x(pts: DataFrame, slices: int, strips: int = STRIPS) -> DataFrame:
    """``pts`` with slice: equal counts in the order of (x, oid), as ntile gives, but ranked strip by strip: counts of strips
    are prefix-summed, and no task sorts more than a strip."""
    e = pts.agg(F.min("x").alias("x0"), F.max("x").alias("x1"), F.count("*").alias("n")).first()
    n, width = e["n"], max(1, -(-((e["x1"] or 0) - (e["x0"] or 0) + 1) // strips))
    at = pts.withColumn("strip", F.floor((F.col("x") - (e["x0"] or 0)) / width))
    counts = at.groupBy("strip").agg(F.count("*").alias("c"))
    before = F.coalesce(F.sum("c").over(Window.orderBy("strip").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    placed = at.join(F.broadcast(counts.select("strip", before.alias("before"))), "strip")
    rank = F.col("before") + F.row_number().over(Window.partitionBy("strip").orderBy("x", "oid")) - 1
    q, r = divmod(n, slices)
    cut = r * (q + 1)
    tile = F.when(rank < cut, F.floor(rank / (q + 1))).otherwise(r + F.floor((rank - cut) / max(1, q)))
    return placed.withColumn("slice", (tile + 1).cast("int")).drop("strip", "before")


def packed_leaves(pts: DataFrame, slices: int, per_slice: int) -> DataFrame:
    """Sort-tile leaves: (slice, tile, n, x0, y0, x1, y1): equal slices by x, equal tiles by y within each."""
    s = slices_by_x(pts, slices)
    t = s.withColumn("tile", F.ntile(per_slice).over(Window.partitionBy("slice").orderBy("y", "oid")))
    return t.groupBy("slice", "tile").agg(F.count("*").alias("n"), F.min("x").alias("x0"), F.min("y").alias("y0"), F.max("x").alias("x1"), F.max("y").alias("y1"))


def leaves_touched(leaves: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, leaves): packed leaves whose boxes a query's disk meets."""
    q = queries.select("qid", "x", "y", "r")
    meets = box_disk_d2(F.col("x"), F.col("y"), F.col("x0"), F.col("y0"), F.col("x1"), F.col("y1")) <= F.col("r") * F.col("r")
    return leaves.join(F.broadcast(q), meets).groupBy("qid").agg(F.count("*").alias("leaves"))


def overlay_update_messages(nodes: int) -> float:
    """Messages of one in-place update: routing, and telling the levels above."""
    return math.log2(nodes) + 3 * math.log2(nodes / 4)


def ring_messages(nodes: int) -> float:
    return math.log2(nodes)


def break_even(nodes: int, beta: float, alpha: float) -> float:
    """Share of updated objects from which on a rebuild sends fewer messages than updates in place."""
    return (beta + alpha) / overlay_update_messages(nodes)


def router_load(queries: DataFrame, fanout: int, levels: int) -> DataFrame:
    """(level, node, n): queries at each node of a tree in which all start at the root; the leaf is the query's id modulo the leaves."""
    leaf = F.pmod(F.col("qid"), F.lit(fanout**levels))
    path = queries.select(leaf.alias("leaf"), F.explode(F.sequence(F.lit(0), F.lit(levels))).alias("level"))
    node = F.floor(F.col("leaf") / F.pow(F.lit(float(fanout)), F.lit(levels) - F.col("level"))).cast("long")
    return path.select("level", node.alias("node")).groupBy("level", "node").agg(F.count("*").alias("n"))
