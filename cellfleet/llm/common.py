"""Pieces that several operators share: words, tables, lineage cuts, joins of hot keys and connected components."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The white space that separates words: space and \t \n \v \f \r.
SPACES = " \t\n\x0b\x0c\r"
SPACE_RUN = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def words(text: Column) -> Column:
    """Runs of other than ``SPACES``; a null text has none."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), SPACE_RUN), "")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``, or the checkpoint folder that the session was given. Without
    either nothing is written anywhere, as a folder of one machine is none for the others."""
    there = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if there is None and spark.sparkContext.master.startswith("local"):  # one machine: its own folder is shared by all
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="cellfleet-"))
        there = spark.sparkContext.getCheckpointDir()
    if there is None:
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    return there


#: Rows of narrow tables that one task writes: a table of known size is written in as many files as it needs.
ROWS = 200_000


def gathered(df: DataFrame, rows: int | None) -> DataFrame:
    """``df`` in no more partitions than ``rows`` ask for: many tiny files cost a store more than they hold."""
    return df if rows is None else df.coalesce(max(1, -(-rows // ROWS)))


def cut(df: DataFrame, rows: int | None = None) -> DataFrame:
    """The same rows, written once to the shared folder, so that later steps neither recompute nor lose them."""
    shared_dir(df.sparkSession)
    return gathered(df, rows).checkpoint(eager=True)


def scratch(spark: SparkSession, kind: str) -> str:
    """A new path in the shared folder."""
    return f"{shared_dir(spark).rstrip('/')}/{kind}-{uuid.uuid4().hex}"


def stored(df: DataFrame, kind: str, rows: int | None = None) -> DataFrame:
    """The same rows, written once as a compressed table in the shared folder: for wide or long ones that are read again."""
    path = scratch(df.sparkSession, kind)
    gathered(df, rows).write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: Rows of one key from which on it is joined by itself: of n rows, at most n / HEAVY keys have as many.
HEAVY = 1_000_000


def onto(many: DataFrame, one: DataFrame, key: str | list[str], hot: DataFrame | None, how: str = "inner") -> DataFrame:
    """``many`` joined with ``one``, which has one row per key. ``hot``: the keys with more than ``HEAVY`` rows, few by their
    definition; their rows stay where they are and meet a broadcast, all others are shuffled. None: there are no such keys."""
    key = [key] if isinstance(key, str) else key
    if hot is None:
        return many.join(one, key, how)
    hot = F.broadcast(hot.select(*key))
    few = F.broadcast(one.join(hot, key, "left_semi"))
    return many.join(hot, key, "left_anti").join(one, key, how).unionByName(many.join(hot, key, "left_semi").join(few, key, how))


def heavy(many: DataFrame, key: str | list[str], rows: int, least: int = HEAVY) -> DataFrame | None:
    """The keys that ``many``, of about ``rows`` rows, has more than ``least`` times; None if it can have none."""
    if rows <= least:
        return None
    key = [key] if isinstance(key, str) else key
    found = cut(many.groupBy(*key).agg(F.count("*").alias("h_n")).where(F.col("h_n") > least).select(*key), 1)
    return None if found.isEmpty() else found


def components(links: DataFrame, rows: int | None = None, least: int = HEAVY) -> DataFrame:
    """Connected components of ``links(a, b)``: one row (node, component) per node, component = smallest node.

    Each round a node takes the smallest label among its neighbours (partial aggregation before the shuffle keeps
    hubs cheap) and then the label of its label. Hubs and labels of giant components are joined apart from the rest. Rounds
    are cut to the shared folder. A round that moves no label ends the loop, and as labels only fall, one does. ``rows``:
    about how many links there are, if known. Nodes may be of any ordered type. No links: no rows.
    """
    links = links.where("a <> b").select("a", "b")
    both = cut(links.union(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), rows)
    n = both.count()
    hubs = heavy(both, "b", n, least)
    labels = cut(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("m")).select("node", F.least("node", "m").alias("component")), n)
    while True:
        near = onto(both, labels.withColumnRenamed("node", "b"), "b", hubs).groupBy(F.col("a").alias("node")).agg(F.min("component").alias("m"))
        stepped = labels.join(near, "node").select("node", F.col("component").alias("old"), F.least("component", "m").alias("mid"))
        if n > least:
            stepped = cut(stepped, n)
        jump = labels.select(F.col("node").alias("mid"), F.col("component").alias("top"))
        known = onto(stepped, jump, "mid", heavy(stepped, "mid", n, least), "left")
        moved = cut(known.select("node", "old", F.least("mid", F.coalesce("top", "mid")).alias("component")), n)
        changed = not moved.where("component <> old").isEmpty()
        labels = moved.select("node", "component")
        if not changed:
            return labels
