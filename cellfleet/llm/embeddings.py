"""Near-duplicate embeddings by an exact metric range join.

On unit vectors a cosine of at least t is a distance of at most eps = sqrt(2 - 2 t). Pivots (vectors chosen by a hash of
their ids) partition the vectors; a vector that may have a partner in another cell is copied there. Two bounds of the
triangle inequality decide: the vector's distance to the cell's pivot is at most the cell's radius plus eps, and its
distance to the plane halfway between the two pivots is at most eps. Linked vectors pass both bounds both ways, so cells
(cut to blocks of ``BLOCK`` vectors where larger) join pair by pair, each independent of all others, and no pair is met twice.

Equal vectors enter once, with their number. A joined pair of blocks emits, for each vector, how many it links with and
one row to the smallest id it is connected to there: never all pairs of a group. Products are found in single precision
with a margin, and every pair within it is decided in double precision.

The number of pivots grows with the vectors up to ``MOST_PIVOTS``, which bounds what each task is sent. In many dimensions
without clusters most vectors are near all boundaries; the join is then as large as all pairs of blocks and stays exact.

Vectors that are null, empty, zero, or hold null or non-finite components link with nothing, equal ones included; vectors of
different lengths don't link. Null ids don't take part. Repeated rows count as vectors of their own. An empty table gives
an empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cellfleet.llm.common import HEAVY, components, cut, onto, table

COSINE, BLOCK, MOST_PIVOTS, TILE, MARGIN, SLACK = 0.95, 4096, 1024, 512, 1e-4, 1e-9
SHIFT = 1 << 24  # blocks are numbered cell * SHIFT + block within the cell


def valid(v: Column) -> Column:
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.coalesce(v.isNotNull() & (F.size(v) > 0) & ~bad & F.exists(v, lambda x: x != 0), F.lit(False))


def matrix(column: pa.Array) -> np.ndarray:
    """Rows of an Arrow list column as a float64 matrix."""
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1)


def unit(m: np.ndarray) -> np.ndarray:
    m = m / np.abs(m).max(axis=1, keepdims=True)  # so that squares neither overflow nor vanish
    return m / np.sqrt((m * m).sum(axis=1, keepdims=True))


def distances(u: np.ndarray, pivots: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum(0.0, 2.0 - 2.0 * (u @ pivots.T)))


def homes(vectors: DataFrame, pivots: np.ndarray) -> DataFrame:
    """``vectors(rep, w, v)`` with their cell and their distance to its pivot."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                d = distances(unit(matrix(b.column(2))), pivots)
                cell = d.argmin(axis=1)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(cell, pa.int32()), pa.array(d[np.arange(len(d)), cell])], names=["rep", "cell", "d"])

    return vectors.select("rep", "w", "v").mapInArrow(run, "rep bigint, cell int, d double")


def reach(vectors: DataFrame, pivots: np.ndarray, radii: np.ndarray, eps: float) -> DataFrame:
    """``vectors`` with their cell and the list of cells, their own included, that may hold a partner."""
    between, kind = distances(pivots, pivots), vectors.schema["v"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            d = distances(unit(matrix(b.column(2))), pivots)
            cell = d.argmin(axis=1)
            own = d[np.arange(len(d)), cell][:, None]
            apart = np.maximum(between[cell], 1e-300)
            near = (d <= radii[None, :] + eps + SLACK) & ((d * d - own * own) <= 2 * (eps + SLACK) * apart + SLACK)
            near[np.arange(len(d)), cell] = True
            cells = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], near.sum(axis=1).cumsum()]), pa.int32()), pa.array(near.nonzero()[1], pa.int32()))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(cell, pa.int32()), cells], names=["rep", "w", "v", "cell", "cells"])

    return vectors.select("rep", "w", "v").mapInArrow(run, f"rep bigint, w bigint, v {kind}, cell int, cells array<int>")


def linked(a: np.ndarray, b: np.ndarray, cosine: float, same: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs of linked unit vectors, tile by tile; within one block each pair once."""
    b32 = b.astype(np.float32).T.copy()
    for s in range(0, len(a), TILE):
        first = s + 1 if same else 0
        if first >= len(b):
            return
        near = a[s : s + TILE].astype(np.float32) @ b32[:, first:] >= cosine - MARGIN
        i, j = near.nonzero()
        i, j = i + s, j + first
        if same:
            i, j = i[i < j], j[i < j]
        for c in range(0, len(i), 1 << 16):
            x, y = i[c : c + (1 << 16)], j[c : c + (1 << 16)]
            ok = np.einsum("ij,ij->i", a[x], b[y]) >= cosine
            if ok.any():
                yield x[ok], y[ok]


def roots(n: int, i: np.ndarray, j: np.ndarray, label: np.ndarray) -> np.ndarray:
    """Labels of n nodes after joining i and j: the smallest index reachable."""
    while True:
        x, y = label[i], label[j]
        low, high = np.minimum(x, y), np.maximum(x, y)
        if (low == high).all():
            return label
        np.minimum.at(label, high, low)
        while (label[label] != label).any():
            label = label[label]


def joined(cosine: float):
    """Joins a pair of blocks: rows (a, n, b): a links n more vectors there and is connected to b."""

    def run(t: pa.Table) -> pa.Table:
        t = t.combine_chunks()
        x, y = t.column("x")[0].as_py(), t.column("y")[0].as_py()
        block = t.column("block").to_numpy()
        order = np.lexsort((t.column("rep").to_numpy(), block != x))
        ids, w = t.column("rep").to_numpy()[order], t.column("w").to_numpy()[order]
        u = unit(matrix(t.column("v").combine_chunks() if isinstance(t.column("v"), pa.ChunkedArray) else t.column("v")))[order]
        m = int((block == x).sum())
        same = x == y
        a, b, shift = (u, u, 0) if same else (u[:m], u[m:], m)
        n, label = np.zeros(len(u), dtype=np.int64), np.arange(len(u))
        if len(a) and len(b):
            for i, j in linked(a, b, cosine, same):
                j = j + shift
                np.add.at(n, i, w[j])
                np.add.at(n, j, w[i])
                label = roots(len(u), i, j, label)
        at = np.flatnonzero(n)
        return pa.table({"a": pa.array(ids[at], pa.int64()), "n": pa.array(n[at], pa.int64()), "b": pa.array(ids[label[at]], pa.int64())})

    return run


def join_cells(vectors: DataFrame, cosine: float = COSINE, block: int = BLOCK, most_pivots: int = MOST_PIVOTS) -> DataFrame:
    """(a, n, b) rows of all pairs of blocks, for distinct ``vectors(rep, w, v)`` of one length; read more than once."""
    eps = math.sqrt(2 - 2 * cosine)
    count = vectors.count()
    wanted = max(1, min(most_pivots, -(-count // block)))
    chosen = vectors.orderBy(F.xxhash64(F.lit(11), "rep"), "rep").select("v").limit(wanted).collect()
    if not chosen:
        return vectors.sparkSession.createDataFrame([], "a long, n long, b long")
    pivots = unit(np.array([r["v"] for r in chosen], dtype=np.float64))
    radii, sizes = np.zeros(len(pivots)), np.zeros(len(pivots), dtype=np.int64)
    for r in homes(vectors, pivots).groupBy("cell").agg(F.max("d").alias("r"), F.count("*").alias("n")).collect():
        radii[r["cell"]], sizes[r["cell"]] = r["r"], r["n"]
    blocks = F.array(*[F.lit(int(-(-n // block))) for n in sizes])
    near = reach(vectors, pivots, radii, eps)
    number = lambda cell, i: cell.cast("long") * SHIFT + i
    own = number(F.col("cell"), F.pmod(F.xxhash64(F.lit(13), "rep"), F.greatest(F.lit(1), F.get(blocks, F.col("cell")))))
    met = F.flatten(F.transform("cells", lambda c: F.when(F.get(blocks, c) > 0, F.transform(F.sequence(F.lit(0), F.get(blocks, c) - 1), lambda i: number(c, i))).otherwise(F.array().cast("array<bigint>"))))
    rows = near.withColumn("block", own).withColumn("other", F.explode(met))
    keyed = rows.select(F.least("block", "other").alias("x"), F.greatest("block", "other").alias("y"), "block", "rep", "w", "v")
    return keyed.groupBy("x", "y").applyInArrow(joined(cosine), "a bigint, n bigint, b bigint")


def classes(vectors: DataFrame, key: str = "vec_id", vector: str = "embedding", cosine: float = COSINE, block: int = BLOCK, most_pivots: int = MOST_PIVOTS, least: int = HEAVY) -> DataFrame:
    """(key, n_links, component_id, kept) of every vector."""
    spark = vectors.sparkSession
    kind = "array<double>" if "double" in vectors.schema[vector].dataType.simpleString() else "array<float>"
    all_ = vectors.select(F.col(key).alias("id"), F.col(vector).cast(kind).alias("v")).withColumn("ok", valid(F.col("v")) & F.col("id").isNotNull())
    distinct = cut(all_.where("ok").groupBy("v").agg(F.min("id").alias("rep"), F.count("*").alias("w")))
    found = spark.createDataFrame([], "a long, n long, b long")
    for r in distinct.groupBy(F.size("v").alias("k")).count().orderBy("k").collect():
        found = found.unionByName(join_cells(distinct.where(F.size("v") == r["k"]), cosine, block, most_pivots))
    found = cut(found)
    counts = found.groupBy(F.col("a").alias("rep")).agg(F.sum("n").alias("n"))
    tops = components(found.select("a", "b")).withColumnRenamed("node", "rep")
    known = distinct.join(counts, "rep", "left").join(tops, "rep", "left")
    known = known.select("v", (F.coalesce("n", F.lit(0)) + F.col("w") - 1).alias("n_links"), F.coalesce("component", "rep").alias("top"))
    # a vector that very many rows have is joined back apart from the rest
    hot = cut(distinct.where(F.col("w") > least).select("v"), 1)
    out = onto(all_.where("ok"), known, "v", None if hot.isEmpty() else hot).select("id", "n_links", "top")
    alone = all_.where("not ok").select("id", F.lit(0).cast("long").alias("n_links"), F.col("id").alias("top"))
    return out.unionByName(alone).select(F.col("id").alias(key), "n_links", F.col("top").alias("component_id"), (F.col("id") == F.col("top")).alias("kept"))


def op5_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(table(spark, sf_dir, "embeddings"))


ORACLE_SQL = f"""
with recursive v as (select vec_id, case when embedding is null or len(embedding) = 0 or len(list_filter(embedding, lambda x: x is null or isnan(x) or isinf(x))) > 0
   or len(list_filter(embedding, lambda x: x <> 0)) = 0 then null else embedding::double[] end as e from embeddings),
l as (select a.vec_id as a, b.vec_id as b from v a join v b on a.vec_id <> b.vec_id and len(a.e) = len(b.e) and list_cosine_similarity(a.e, b.e) >= {COSINE}),
r as (select vec_id as a, vec_id as b from v union select r.a, l.b from r join l on r.b = l.a),
c as (select a as vec_id, min(b) as component_id from r group by a), n as (select a as vec_id, count(*) as n from l group by a)
select c.vec_id, coalesce(n.n, 0)::bigint as n_links, c.component_id, c.vec_id = c.component_id as kept from c left join n using (vec_id)
"""
