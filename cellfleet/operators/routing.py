"""Graph searches: walks over neighbouring pivots, targets of a range by exhaustion, nearest neighbours by neighbouring cells."""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator, Mapping, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellfleet.operators import cells
from cellfleet.operators.pivots import Pivot

#: Bytes of a pivot in a routing table: its place and its node's address.
PIVOT_BYTES = 40
MOST_GRAPH = 100_000


def neighbours(piv: Sequence[Pivot]) -> dict[int, list[int]]:
    """Pivots whose cells share an edge, by the cell kernel on the driver."""
    x, y, ids = (np.array([p[i] for p in piv], dtype=np.int64) for i in (1, 2, 0))
    w = max(int(x.max() - x.min()), int(y.max() - y.min()), 1) * 1e4
    box = (x.min() - w, y.min() - w, x.max() + w, y.max() + w)
    grid = cells.Grid(x.astype(float), y.astype(float), ids)
    return {i: cells.neighbours(cells.refine(cells.square(box), float(a), float(b), grid.around(float(a), float(b))), 1e-3) for i, a, b in piv}


def walk(queries: DataFrame, piv: Sequence[Pivot], near: Mapping[int, Sequence[int]]) -> DataFrame:
    """(qid, pid, hops): from the first pivot always to the neighbour that is nearest to the query, until none is nearer."""
    ids = sorted(i for i, *_ in piv)
    place = {i: k for k, i in enumerate(ids)}
    at = np.zeros((len(ids), 2), dtype=np.int64)
    for i, x, y in piv:
        at[place[i]] = x, y
    # neighbours in rows of one width, filled up with the pivot itself
    width = max(1, max((len(near[i]) for i in ids), default=1))
    around = np.array([[*(place[j] for j in near[i]), *[place[i]] * (width - len(near[i]))] for i in ids], dtype=np.int64)
    first = place[piv[0][0]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = np.array(ids, dtype=np.int64)
        for b in batches:
            xy = np.stack([b.column(i).to_numpy(zero_copy_only=False) for i in (1, 2)], axis=1)
            here, hops = np.full(len(xy), first), np.zeros(len(xy), dtype=np.int64)
            d2 = ((at[here] - xy) ** 2).sum(axis=1)
            todo = np.arange(len(xy))
            while len(todo):
                options = np.sort(around[here[todo]], axis=1)  # ties go to the least pivot
                d = ((at[options] - xy[todo, None, :]) ** 2).sum(axis=2)
                best = d.argmin(axis=1)
                rows = np.arange(len(todo))
                to, least = options[rows, best], d[rows, best]
                goes = (least < d2[todo]) | (least == d2[todo]) & (to < here[todo])
                todo, to, least = todo[goes], to[goes], least[goes]
                here[todo], d2[todo] = to, least
                hops[todo] += 1
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(names[here]), pa.array(hops)], names=["qid", "pid", "hops"])

    return queries.select("qid", "x", "y").mapInArrow(run, "qid bigint, pid bigint, hops bigint")


def targets_by_walk(queries: DataFrame, piv: Sequence[Pivot], near: Mapping[int, Sequence[int]]) -> DataFrame:
    """(qid, home, pid): pieces within r of a query, found from its own piece by its neighbours, theirs, and so on."""
    at = {i: (x, y) for i, x, y in piv}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows: list[tuple[int, int, int]] = []
            for q, x, y, r in zip(*(c.to_pylist() for c in b.columns), strict=True):
                d = {i: (px - x) ** 2 + (py - y) ** 2 for i, (px, py) in at.items()}
                home = min(d, key=lambda i: (d[i], i))
                seen, queue = {home}, [home]
                while queue:
                    i = queue.pop()
                    for j in near[i]:
                        if j not in seen and (d[j] - d[home]) / (2 * math.dist(at[home], at[j])) <= r:
                            seen.add(j)
                            queue.append(j)
                rows += [(q, home, j) for j in sorted(seen)]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (list(zip(*rows, strict=True)) or ([], [], []))], names=["qid", "home", "pid"])

    return queries.select("qid", "x", "y", F.col("r").cast("double").alias("r")).mapInArrow(run, "qid bigint, home bigint, pid bigint")


def sequential_knn(made: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """(qid, rank, oid, d2): walk to the cell that holds the query, then take the nearest of all neighbours of what is taken.

    A baseline for one node's cells: their graph, of at most ``MOST_GRAPH`` cells, goes to every task."""
    rows = made.select("oid", "x", "y", "nbrs").limit(MOST_GRAPH + 1).collect()
    if len(rows) > MOST_GRAPH:
        raise ValueError(f"at most {MOST_GRAPH} cells")
    graph = {r["oid"]: (r["x"], r["y"], r["nbrs"]) for r in rows}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[tuple[int, int, int, int]] = []
            for q, x, y in zip(*(c.to_pylist() for c in b.columns), strict=True):
                d = lambda i: ((graph[i][0] - x) ** 2 + (graph[i][1] - y) ** 2, i)
                here = d(next(iter(graph)))
                while (best := min((d(j) for j in graph[here[1]][2]), default=here)) < here:
                    here = best
                heap, seen, rank = [here], {here[1]}, 0
                while heap and rank < k:
                    d2, i = heapq.heappop(heap)
                    rank += 1
                    out.append((q, rank, i, d2))
                    for j in graph[i][2]:
                        if j not in seen:
                            seen.add(j)
                            heapq.heappush(heap, d(j))
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (list(zip(*out, strict=True)) or ([], [], [], []))], names=["qid", "rank", "oid", "d2"])

    return queries.select("qid", "x", "y").mapInArrow(run, "qid bigint, rank bigint, oid bigint, d2 bigint")
