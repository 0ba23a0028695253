"""The life of a snapshot: latest positions, rebuild, publication, and when to elect pivots anew."""

from __future__ import annotations

import json
import time
from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellfleet.operators import pivots
from cellfleet.operators.pivots import Pivot


def latest(reports: DataFrame, until: str | None = None) -> DataFrame:
    """(oid, x, y, ts): the last report of each object, ties by event."""
    r = reports if until is None else reports.where(F.col("ts") <= F.lit(until).cast("timestamp"))
    best = r.groupBy("obj").agg(F.max(F.struct("ts", "event_id", "x", "y")).alias("b"))
    return best.select(F.col("obj").alias("oid"), F.col("b.x").alias("x"), F.col("b.y").alias("y"), F.col("b.ts").alias("ts"))


def trajectories(reports: DataFrame, slot: str = "25 minutes") -> DataFrame:
    """(obj, slot, n, x, y): tracks cut by time; each cut is an object at its last place."""
    cut = reports.groupBy("obj", F.window("ts", slot).alias("w")).agg(F.count("*").alias("n"), F.max(F.struct("ts", "event_id", "x", "y")).alias("b"))
    return cut.select("obj", F.col("w.start").alias("slot"), "n", F.col("b.x").alias("x"), F.col("b.y").alias("y"))


def repartition_due(sizes: Sequence[int], policy: str, max_cv: float = 0.5) -> bool:
    """``always``, ``never``, or ``auto``: once the sizes of pieces deviate by more than ``max_cv`` of their mean."""
    if policy in ("always", "never"):
        return policy == "always"
    n = max(1, len(sizes))
    mean = sum(sizes) / n
    return mean > 0 and (sum((s - mean) ** 2 for s in sizes) / n) ** 0.5 / mean > max_cv


def cycle(pts: DataFrame, before: Sequence[Pivot] | None, p: int, policy: str = "always", max_cv: float = 0.5) -> tuple[DataFrame, list[Pivot], bool]:
    """(assigned points, pivots, whether they are new) of the next snapshot."""
    if before:
        kept = pivots.assign(pts, before)
        if policy == "never" or policy == "auto" and not repartition_due([r["n"] for r in pivots.stats(kept).collect()], policy, max_cv):
            return kept, list(before), False
    piv = pivots.choose(pts, p)
    return pivots.assign(pts, piv), piv, True


def publish(assigned: DataFrame, path: str, version: int, began: float | None = None) -> None:
    """Writes a version, then names it as the current one; readers of older versions aren't disturbed. ``began``: when its objects
    were read, in seconds."""
    assigned.write.mode("overwrite").partitionBy("pid").parquet(f"{path}/version={version}")
    spark = assigned.sparkSession
    told = json.dumps({"version": version, "began": began or time.time(), "published": time.time()})
    spark.createDataFrame([(told,)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest-{version}")


def current(spark: SparkSession, path: str) -> tuple[int, DataFrame]:
    """(version, index) of the last version with a manifest, that is, completely written."""
    row = spark.read.text(f"{path}/manifest-*").select(F.max(F.get_json_object("value", "$.version").cast("long")).alias("v")).first()
    return row["v"], spark.read.parquet(f"{path}/version={row['v']}")


def staleness(spark: SparkSession, path: str) -> DataFrame:
    """(version, cycle, age): seconds from reading a version's objects to publishing it, and how old they are when the next version
    takes over, null for the current one."""
    m = spark.read.text(f"{path}/manifest-*").select(F.from_json("value", "version long, began double, published double").alias("m")).select("m.*")
    after = F.lead("published").over(Window.orderBy("version"))
    return m.select("version", (F.col("published") - F.col("began")).alias("cycle"), (after - F.col("began")).alias("age"))
