"""The hashed snapshot: objects on nodes by id, each node's in Z-order; every query goes to every node, which searches its sorted
codes. A range reads the code ranges that cover its box; the nearest neighbours of a query are bounded by its neighbours in
the order of codes and then read from the blocks of the sorted array whose boxes are near enough.

The batch of queries is sent to all nodes: that is the method. It is checked to have at most ``MOST_QUERIES`` of them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellfleet.functions import zorder
from cellfleet.operators import knn

MOST_QUERIES, CODE_RANGES, BLOCK, PAIRS = 200_000, 16, 64, 1 << 19


def snapshot(pts: DataFrame, n: int) -> DataFrame:
    """Objects to nodes by id, each node's in Z-order."""
    return pts.withColumn("node", F.pmod(F.xxhash64("oid"), F.lit(n)).cast("int")).withColumn("z", zorder.encode(F.col("x"), F.col("y"))).repartitionById(n, "node").sortWithinPartitions("node", "z")


def sent(queries: DataFrame, *columns: str, each: int = 1) -> pa.Table:
    """The batch on the driver, from where it goes to all nodes; a query has up to ``each`` rows."""
    got = queries.select(*columns).limit(MOST_QUERIES * each + 1).toArrow()
    if got.num_rows > MOST_QUERIES * each or each > 1 and len(got.column("qid").unique()) > MOST_QUERIES:
        raise ValueError(f"at most {MOST_QUERIES} queries go to all nodes at once")
    return got


#: Squares to a side of a covered box, as a power of two.
BOX_BITS = 5


def cover(x0: int, y0: int, x1: int, y1: int, most: int = CODE_RANGES) -> list[tuple[int, int]]:
    """Code ranges, at most ``most``, that cover a box by squares of a size that puts some 32 on its side: finer ones would be joined again."""
    s = max(0, max(x1 - x0, y1 - y0).bit_length() - BOX_BITS)
    found = zorder.ranges(x0 >> s, y0 >> s, x1 >> s, y1 >> s, 1 << 2 * BOX_BITS, zorder.BITS - s)
    return [(a << 2 * s, ((b + 1) << 2 * s) - 1) for a, b in zorder.bridged(found, most)]


def code_ranges(queries: DataFrame, most: int = CODE_RANGES) -> DataFrame:
    """(qid, x, y, r, lo, hi): the code ranges that cover the box of each query's circle; none if it lies outside of all codes."""
    top = (1 << zorder.BITS) - 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at, lo, hi = [], [], []
            for i, (x, y, r) in enumerate(zip(*(c.to_pylist() for c in b.columns[1:]), strict=True)):
                x0, y0, x1, y1 = max(0, int(x - r)), max(0, int(y - r)), min(top, int(x + r) + 1), min(top, int(y + r) + 1)
                for a, e in cover(x0, y0, x1, y1, most) if x0 <= x1 and y0 <= y1 else ():
                    at.append(i)
                    lo.append(a)
                    hi.append(e)
            taken = b.take(pa.array(at, pa.int64()))
            yield pa.RecordBatch.from_arrays([*taken.columns, pa.array(lo, pa.int64()), pa.array(hi, pa.int64())], names=["qid", "x", "y", "r", "lo", "hi"])

    kind = queries.schema["qid"].dataType.simpleString()
    typed = queries.select("qid", F.col("x").cast("long").alias("x"), F.col("y").cast("long").alias("y"), F.col("r").cast("double").alias("r"))
    return typed.mapInArrow(run, f"qid {kind}, x bigint, y bigint, r double, lo bigint, hi bigint")


def slices(lo: np.ndarray, hi: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(slice, place) pairs of the half-open slices lo to hi, some slices at a time."""
    size = np.maximum(hi - lo, 0)
    ends = size.cumsum()
    s = 0
    while s < len(lo):
        e = max(s + 1, int(np.searchsorted(ends, (ends[s - 1] if s else 0) + PAIRS, side="right")))
        n = size[s:e]
        yield np.repeat(np.arange(s, e), n), np.arange(int(n.sum())) - np.repeat(n.cumsum() - n, n) + np.repeat(lo[s:e], n)
        s = e


def packed(asked: pa.Table) -> tuple[pa.Array, ...]:
    """(qid, x, y, r) of each query, and (query, lo, hi) of each of its code ranges: every task holds the whole batch, so that it is kept small."""
    x, y, r, lo, hi = (asked.column(c).to_numpy() for c in ("x", "y", "r", "lo", "hi"))
    qid = asked.column("qid").combine_chunks()
    codes = qid.dictionary_encode().indices.to_numpy(zero_copy_only=False)
    new = np.ones(len(x), dtype=bool)
    new[1:] = (np.diff(codes) != 0) | (np.diff(x) != 0) | (np.diff(y) != 0) | (np.diff(r) != 0)
    first = np.flatnonzero(new)
    return qid.take(pa.array(first)), x[first], y[first], r[first], (np.cumsum(new) - 1).astype(np.int32), lo, hi


def range_(held: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, oid, d2) within r, from each node's sorted codes."""
    kind = queries.schema["qid"].dataType.simpleString()
    whole = held.sparkSession.sparkContext.broadcast(packed(sent(code_ranges(queries), "qid", "x", "y", "r", "lo", "hi", each=CODE_RANGES)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qid, x, y, r, of, lo, hi = whole.value
        for b in batches:  # consecutive codes of a node
            oid, px, py, z = b.column(0), *(b.column(i).to_numpy(zero_copy_only=False) for i in (1, 2, 3))
            if not len(z) or (np.diff(z) < 0).any():
                order = np.argsort(z, kind="stable")
                oid, px, py, z = oid.take(pa.array(order)), px[order], py[order], z[order]
            near = np.flatnonzero((hi >= z[0]) & (lo <= z[-1])) if len(z) else np.zeros(0, dtype=np.int64)
            for i, j in slices(np.searchsorted(z, lo[near]), np.searchsorted(z, hi[near], side="right")):
                i = of[near[i]]
                d2 = (px[j] - x[i]) ** 2 + (py[j] - y[i]) ** 2
                ok = d2 <= r[i] * r[i]
                yield pa.RecordBatch.from_arrays([qid.take(pa.array(i[ok])), oid.take(pa.array(j[ok])), pa.array(d2[ok], pa.int64())], names=["qid", "oid", "d2"])

    return held.select("oid", "x", "y", "z").mapInArrow(run, f"qid {kind}, oid bigint, d2 bigint")


def interleaved(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    def spread(v: np.ndarray) -> np.ndarray:
        v = np.clip(v, 0, (1 << zorder.BITS) - 1).astype(np.uint64)
        for shift, mask in zorder.SPREAD:
            v = (v | (v << np.uint64(shift))) & np.uint64(mask)
        return v

    return (spread(x) | (spread(y) << np.uint64(1))).astype(np.int64)


def nearest(held: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """(qid, rank, oid, d2): each node's k best by a bound from the neighbouring codes, then the k best of those. A grid of counts of
    the whole snapshot bounds every query once: codes too far from it are passed over."""
    asked = sent(knn.grid_bounds(queries.select("qid", "x", "y"), knn.count_grid(held), k), "qid", "x", "y", "r")
    kind = queries.schema["qid"].dataType.simpleString()
    whole = held.sparkSession.sparkContext.broadcast(asked)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = whole.value
        whole_x, whole_y, whole_r, whole_ids = (*(t.column(c).to_numpy() for c in ("x", "y", "r")), t.column("qid").combine_chunks())
        for b in batches:
            if not b.num_rows:
                continue
            oid, px, py, z = (b.column(i).to_numpy(zero_copy_only=False) for i in range(4))
            order = np.argsort(z, kind="stable")
            oid, px, py, z = oid[order], px[order], py[order], z[order]
            first = np.arange(0, len(z), BLOCK)
            x0, y0, x1, y1 = (f.reduceat(v, first) for f, v in ((np.minimum, px), (np.minimum, py), (np.maximum, px), (np.maximum, py)))
            last = np.append(first[1:], len(z))
            away_x, away_y = (np.maximum(np.maximum(low.min() - v, v - high.max()), 0).astype(np.float64) for v, low, high in ((whole_x, x0, x1), (whole_y, y0, y1)))
            near = np.flatnonzero(away_x * away_x + away_y * away_y <= whole_r * whole_r)
            all_x, all_y, most, ids = whole_x[near], whole_y[near], np.ceil(whole_r[near] ** 2).astype(np.int64), whole_ids.take(pa.array(near))
            for s in range(0, len(all_x), max(1, PAIRS // max(len(first), 2 * k))):
                part = slice(s, s + max(1, PAIRS // max(len(first), 2 * k)))
                x, y = all_x[part], all_y[part]
                # the k-th best of the 2 k objects around the query's code bounds the k-th best of all here
                around = np.searchsorted(z, interleaved(x, y))[:, None] + np.arange(-k, k)[None, :]
                inside = (around >= 0) & (around < len(z))
                j = np.clip(around, 0, len(z) - 1)
                d2 = np.where(inside, (px[j] - x[:, None]) ** 2 + (py[j] - y[:, None]) ** 2, np.iinfo(np.int64).max)
                bound = np.minimum(np.partition(d2, min(k, 2 * k) - 1, axis=1)[:, k - 1], most[part])
                dx = np.maximum(np.maximum(x0[None, :] - x[:, None], x[:, None] - x1[None, :]), 0)
                dy = np.maximum(np.maximum(y0[None, :] - y[:, None], y[:, None] - y1[None, :]), 0)
                q, block = (dx * dx + dy * dy <= bound[:, None]).nonzero()
                for i, j in slices(first[block], last[block]):
                    i = q[i]
                    d2 = (px[j] - x[i]) ** 2 + (py[j] - y[i]) ** 2
                    ok = d2 <= bound[i]
                    i, j, d2 = i[ok], j[ok], d2[ok]
                    best = np.lexsort((oid[j], d2, i))
                    i, j, d2 = i[best], j[best], d2[best]
                    own = np.arange(len(i)) - np.searchsorted(i, i)
                    ok = own < k
                    yield pa.RecordBatch.from_arrays([ids.take(pa.array(i[ok] + s)), pa.array(oid[j[ok]]), pa.array(d2[ok])], names=["qid", "oid", "d2"])

    return knn.nearest(held.select("oid", "x", "y", "z").mapInArrow(run, f"qid {kind}, oid bigint, d2 bigint"), k)
