"""Position reports as a stream: windows, latest places, continuous range queries, rebuild and swap."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellfleet.operators import pivots, range_query, snapshot, tiles
from cellfleet.operators.pivots import Pivot
from cellfleet.sources.views import fixed

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"

#: Tiles to a side over standing queries.
SIDE = 64


def read(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """(obj, event_id, ts, x, y, event_type) from a folder of event files."""
    raw = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files).parquet(path)
    return raw.selectExpr("user_id as obj", "event_id", "ts", f"{fixed('value')} as x", "cast(get_json_object(props, '$.k') as bigint)*500 as y", "event_type")


def accesses(stream: DataFrame, late: str = "10 minutes", window: str = "5 minutes", slide: str | None = None) -> DataFrame:
    """Accesses by window of time; rows later than the watermark are left out."""
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    return stream.withWatermark("ts", late).groupBy(w.alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(stream: DataFrame, gap: str = "6 hours", late: str = "1 day") -> DataFrame:
    """Runs of reports of an object without a longer gap."""
    return stream.withWatermark("ts", late).groupBy("obj", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("obj", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def distinct(stream: DataFrame, late: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def latest(stream: DataFrame) -> DataFrame:
    """The last report of each object so far, in update mode."""
    best = stream.groupBy("obj").agg(F.max(F.struct("ts", "event_id", "x", "y")).alias("b"))
    return best.select(F.col("obj").alias("oid"), F.col("b.x").alias("x"), F.col("b.y").alias("y"), F.col("b.ts").alias("ts"))


def inside(stream: DataFrame, queries: DataFrame, piv: Sequence[Pivot]) -> DataFrame:
    """(qid, oid, d2): reports that fall into standing range queries, by a join with their targets in tiles over the queries."""
    at = pivots.assign(stream.withColumnRenamed("event_id", "oid"), piv)
    box = queries.agg(F.min("x"), F.min("y"), F.max("x"), F.max("y")).first()
    over = tiles.Tiles(*(v or 0 for v in box), n=SIDE * SIDE, per=1.0, most=SIDE)
    return tiles.answers(at.select("oid", "x", "y", "pid"), range_query.targets(queries, piv), over)


def rebuild(path: str, p: int, policy: str = "auto"):
    """A ``foreachBatch`` function: each batch of latest positions becomes a published snapshot, on kept pivots if they do."""
    state: dict[str, list[Pivot] | None] = {"pivots": None}

    def one(batch: DataFrame, version: int) -> None:
        if batch.isEmpty():
            return
        at, state["pivots"], _ = snapshot.cycle(batch.select("oid", "x", "y"), state["pivots"], p, policy)
        snapshot.publish(at, path, version)

    return one
