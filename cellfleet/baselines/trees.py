"""The tree overlay: every node owns a tile of space with a packed tree of its objects; the tiles' boxes are known to all.

A tree is packed by sorting and tiling: strips of equal counts by x, tiles of equal counts by y within them; the node's tiles
are packed once more into leaves. A search goes from the tiles' boxes to the leaves' and to the objects, by joins. Updates
are made in place: an object is looked up, its leaf's box may grow, and what grew is told on."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cellfleet.baselines import indexes
from cellfleet.functions.geometry import box_disk_d2, dist2
from cellfleet.lineage import cut
from cellfleet.operators import knn

LEAF = 64
#: Boxes or targets that may be broadcast.
FEW = 200_000


def numbered(oid: np.ndarray, x: np.ndarray, y: np.ndarray, leaf: int = LEAF) -> np.ndarray:
    """The leaf of each object of a node."""
    leaves = -(-len(x) // leaf)
    per = leaf * max(1, math.ceil(math.sqrt(leaves)))  # objects of a strip
    by_x = np.lexsort((oid, x))
    strip = np.empty(len(x), dtype=np.int64)
    strip[by_x] = np.arange(len(x)) // per
    by_y = np.lexsort((oid, y, strip))
    starts = np.searchsorted(strip[by_y], strip[by_y])
    number = np.empty(len(x), dtype=np.int64)
    number[by_y] = strip[by_y] * (per // leaf) + (np.arange(len(x)) - starts) // leaf
    return number


def build(pts: DataFrame, strips: int, tiles: int, leaf: int = LEAF) -> DataFrame:
    """(oid, x, y, node, leaf): ``strips * tiles`` nodes, their objects in leaves of at most ``leaf``."""
    s = indexes.slices_by_x(pts, strips)
    t = s.withColumn("tile", F.ntile(tiles).over(Window.partitionBy("slice").orderBy("y", "oid")))
    at = t.select("oid", "x", "y", ((F.col("slice") - 1) * tiles + F.col("tile") - 1).cast("long").alias("node"))

    def packed(t: pa.Table) -> pa.Table:
        return t.append_column("leaf", pa.array(numbered(*(t.column(c).to_numpy() for c in ("oid", "x", "y")), leaf)))

    return at.groupBy("node").applyInArrow(packed, "oid bigint, x bigint, y bigint, node bigint, leaf bigint")


def boxes(index: DataFrame, *by: str) -> DataFrame:
    """(…, n, x0, y0, x1, y1) of the index's nodes or leaves."""
    return index.groupBy(*by).agg(F.count("*").alias("n"), F.min("x").alias("x0"), F.min("y").alias("y0"), F.max("x").alias("x1"), F.max("y").alias("y1"))


def _near() -> Column:
    return box_disk_d2(F.col("qx"), F.col("qy"), F.col("x0"), F.col("y0"), F.col("x1"), F.col("y1")) <= F.col("r") * F.col("r")


def search(index: DataFrame, queries: DataFrame, nodes: DataFrame | None = None, leaves: DataFrame | None = None) -> DataFrame:
    """(qid, oid, d2) within r, inclusive. ``nodes`` and ``leaves``: boxes that were made before."""
    nodes = boxes(index, "node") if nodes is None else nodes
    leaves = boxes(index, "node", "leaf") if leaves is None else leaves
    q = queries.select("qid", F.col("x").alias("qx"), F.col("y").alias("qy"), "r")
    tiles = nodes.select("node", "x0", "y0", "x1", "y1")
    routed = q.join(F.broadcast(tiles.limit(FEW)), _near()).select("qid", "qx", "qy", "r", "node")
    met = routed.join(leaves.select("node", "leaf", "x0", "y0", "x1", "y1"), "node").where(_near()).select("qid", "qx", "qy", "r", "node", "leaf")
    d2 = dist2(F.col("x"), F.col("y"), F.col("qx"), F.col("qy"))
    return index.join(met, ["node", "leaf"]).withColumn("d2", d2).where(F.col("d2") <= F.col("r") * F.col("r")).select("qid", "oid", "d2")


def _cuts(pts: DataFrame, groups: int, axis: str, within: str, bins: int = indexes.STRIPS) -> dict[int, list[tuple[int, int]]]:
    """Of each value of ``within``, where its rows in the order of (axis, oid) are cut into ``groups`` of equal counts: the first
    (axis, oid) of all groups but the first. Counts of bins come to the driver, and only the bins with a cut are sorted."""
    e = pts.agg(F.min(axis).alias("low"), F.max(axis).alias("high")).first()
    low, width = e["low"] or 0, max(1, -(-((e["high"] or 0) - (e["low"] or 0) + 1) // bins))
    at = pts.withColumn("bin", F.floor((F.col(axis) - low) / width))
    counts = sorted((r[within], r["bin"], r["n"]) for r in at.groupBy(within, "bin").agg(F.count("*").alias("n")).collect())
    wanted = []
    for key in sorted({k for k, _, _ in counts}):
        own = [(b, n) for k, b, n in counts if k == key]
        ends = np.cumsum([n for _, n in own])
        q, r = divmod(int(ends[-1]), groups)
        for g in range(1, groups):
            if (rank := g * q + min(g, r)) < ends[-1]:
                i = int(np.searchsorted(ends, rank, side="right"))
                wanted.append((key, own[i][0], rank - int(ends[i] - own[i][1]) + 1))
    out: dict[int, list[tuple[int, int]]] = {k: [] for k, _, _ in counts}
    if wanted:
        need = F.broadcast(pts.sparkSession.createDataFrame(wanted, f"{within} long, bin long, rank long"))
        rank = F.row_number().over(Window.partitionBy(within, "bin").orderBy(axis, "oid")).cast("long")
        rows = at.join(F.broadcast(need.select(within, "bin").distinct()), [within, "bin"], "left_semi").withColumn("rank", rank)
        for r in rows.join(need, [within, "bin", "rank"]).select(within, axis, "oid").collect():
            out[r[within]].append((r[axis], r["oid"]))
    return {k: sorted(c) for k, c in out.items()}


def _after(cuts: list[tuple[int, int]], axis: str) -> Column:
    """How many of the cuts a row is not before."""
    if not cuts:
        return F.lit(0)
    each = F.array(*[F.struct(F.lit(v).cast("long").alias("v"), F.lit(o).cast("long").alias("o")) for v, o in cuts])
    mine = F.struct(F.col(axis).cast("long").alias("v"), F.col("oid").cast("long").alias("o"))
    return F.size(F.filter(each, lambda c: c <= mine))


def placed(pts: DataFrame, strips: int, tiles: int) -> DataFrame:
    """(oid, x, y, node) as in ``build``, without a shuffle of the objects: nodes are told by the cuts between them. Rows alike, of one
    place and oid, are in one node. The leaves are packed where the node is read."""
    p = pts.select("oid", "x", "y").withColumn("slice", F.lit(0).cast("long"))
    p = p.withColumn("slice", _after(_cuts(p, strips, "x", "slice").get(0, []), "x").cast("long"))
    tile = F.lit(0)
    for k, c in _cuts(p, tiles, "y", "slice").items():
        tile = F.when(F.col("slice") == k, _after(c, "y")).otherwise(tile)
    return p.select("oid", "x", "y", (F.col("slice") * tiles + tile).cast("long").alias("node"))


#: Pairs of queries and boxes, or of queries and objects, that a kernel looks at at once.
PAIRS = 1 << 20


def _ragged(start: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, place) of all places of runs that begin at ``start`` and have ``n`` places."""
    row = np.repeat(np.arange(len(n)), n)
    return row, np.arange(len(row)) - np.repeat(n.cumsum() - n, n) + np.repeat(start, n)


def _box_d2(x: np.ndarray, y: np.ndarray, box: np.ndarray) -> np.ndarray:
    """Squared distances of points to boxes (x0, y0, x1, y1)."""
    dx = np.maximum(np.maximum(box[0] - x, x - box[2]), 0)
    dy = np.maximum(np.maximum(box[1] - y, y - box[3]), 0)
    return dx * dx + dy * dy


class Tree:
    """A node's objects in leaves, and runs of leaves above them: three levels, searched for blocks of queries."""

    def __init__(self, oid: np.ndarray, x: np.ndarray, y: np.ndarray, leaf: np.ndarray):
        order = np.argsort(leaf, kind="stable")
        self.oid, self.x, self.y = oid[order], x[order], y[order]
        self.start = np.flatnonzero(np.concatenate([[True], np.diff(leaf[order]) != 0]))
        self.n = np.diff(np.append(self.start, len(x)))
        over = lambda a, at: (np.minimum.reduceat(a[0], at), np.minimum.reduceat(a[1], at), np.maximum.reduceat(a[2], at), np.maximum.reduceat(a[3], at))
        self.boxes = np.stack(over((self.x, self.y, self.x, self.y), self.start))
        self.first = np.arange(0, len(self.start), max(1, math.ceil(math.sqrt(len(self.start)))))
        self.leaves = np.diff(np.append(self.first, len(self.start)))
        self.runs = np.stack(over(self.boxes, self.first))

    def _best(self, of: np.ndarray, leaf: np.ndarray, x: np.ndarray, y: np.ndarray, r2: np.ndarray, k: int) -> tuple[np.ndarray, ...]:
        """(query, place, d2) of the k objects of least (d2, oid) within r2 of each query, among its leaves; ``of`` ascends."""
        i, at = _ragged(self.start[leaf], self.n[leaf])
        i = of[i]
        d2 = (self.x[at] - x[i]) ** 2 + (self.y[at] - y[i]) ** 2
        ok = d2 <= r2[i]
        i, at, d2 = i[ok], at[ok], d2[ok]
        o = np.lexsort((self.oid[at], d2, i))
        i, at, d2 = i[o], at[o], d2[o]
        kept = np.arange(len(i)) - np.searchsorted(i, i) < k
        return i[kept], at[kept], d2[kept]

    def nearest(self, x: np.ndarray, y: np.ndarray, r2: np.ndarray, k: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(query, oid, d2) of the k best within r2. The best of the nearest leaf draw the circle closer, if they are k."""
        block = max(1, PAIRS // (len(self.first) + 16 * LEAF))
        for s in range(0, len(x), block):
            px, py, far = x[s : s + block], y[s : s + block], r2[s : s + block].copy()
            to_runs = _box_d2(px[:, None], py[:, None], self.runs[:, None, :])
            run = to_runs.argmin(axis=1)
            i, leaf = _ragged(self.first[run], self.leaves[run])
            d = _box_d2(px[i], py[i], self.boxes[:, leaf])
            o = np.lexsort((leaf, d, i))
            near = leaf[o[np.searchsorted(i, np.arange(len(px)))]]
            i, _, d2 = self._best(np.arange(len(px)), near, px, py, far, k)
            full = np.bincount(i, minlength=len(px)) == k
            last = np.searchsorted(i, np.arange(len(px)), side="right") - 1
            far[full] = d2[last[full]]
            i, run = np.nonzero(to_runs <= far[:, None])
            j, leaf = _ragged(self.first[run], self.leaves[run])
            i = i[j]
            met = _box_d2(px[i], py[i], self.boxes[:, leaf]) <= far[i]
            i, leaf = i[met], leaf[met]
            # circles that nothing has drawn closer meet many leaves: some queries at a time
            ends, a = np.cumsum(np.bincount(i, weights=self.n[leaf], minlength=len(px))), 0
            while a < len(px):
                b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + PAIRS, side="right")))
                lo, hi = np.searchsorted(i, (a, b))
                q, at, d2 = self._best(i[lo:hi], leaf[lo:hi], px, py, far, k)
                yield q + s, self.oid[at], d2
                a = b


def _in_nodes(index: DataFrame, asked: DataFrame, k: int) -> DataFrame:
    """(qid, qx, qy, node, r2, oid, d2): of each node that ``asked(qid, qx, qy, node, r2)`` meets the k best objects within r2."""
    kind, own = asked.schema["qid"].dataType.simpleString(), index.schema["oid"].dataType.simpleString()
    names = [c for c in ("oid", "x", "y", "node", "leaf") if c in index.columns]

    def run(there: pa.Table, q: pa.Table) -> pa.Table:
        out = []
        if there.num_rows and q.num_rows:
            oid, x, y = (there.column(c).to_numpy() for c in ("oid", "x", "y"))
            tree = Tree(oid, x, y, there.column("leaf").to_numpy() if "leaf" in names else numbered(oid, x, y))
            q = q.combine_chunks()
            for i, o, d2 in tree.nearest(*(q.column(c).to_numpy() for c in ("qx", "qy", "r2")), k):
                out.append(q.take(pa.array(i)).append_column("oid", pa.array(o)).append_column("d2", pa.array(d2, pa.int64())))
        return pa.concat_tables(out) if out else q.slice(0, 0).append_column("oid", there.column("oid").slice(0, 0)).append_column("d2", pa.array([], pa.int64()))

    held = index.select(*names).join(F.broadcast(asked.select("node").distinct()), "node", "left_semi").select(*names)
    return held.groupBy("node").cogroup(asked.groupBy("node")).applyInArrow(run, f"qid {kind}, qx bigint, qy bigint, node bigint, r2 bigint, oid {own}, d2 bigint")


def _routed(q: DataFrame, at: np.ndarray, k: int, home: bool) -> DataFrame:
    """(qid, qx, qy, node, r2) by the nodes' boxes ``at`` (node, n, x0, y0, x1, y1). ``home``: the nearest node of each query, r2 from its
    furthest corner and those of the boxes that make k objects. Else ``q`` has (home, r2), and all other nodes that its circle meets are taken."""
    kind, boxed = q.schema["qid"].dataType.simpleString(), at[2:]
    block = max(1, PAIRS // max(1, at.shape[1]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (c for whole in batches for c in (whole.slice(s, block) for s in range(0, whole.num_rows, block))):
            x, y = (b.column(i).to_numpy(zero_copy_only=False)[:, None] for i in (1, 2))
            d2 = _box_d2(x, y, boxed[:, None, :])
            if home:
                dx, dy = (np.maximum(np.abs(v - boxed[c]), np.abs(v - boxed[c + 2])) for v, c in ((x, 0), (y, 1)))
                far = dx * dx + dy * dy
                order = far.argsort(axis=1, kind="stable")
                enough = np.minimum((at[1][order].cumsum(axis=1) < k).sum(axis=1), at.shape[1] - 1)
                i = np.arange(b.num_rows)
                j = d2.argmin(axis=1)
                r2 = np.maximum(far[i, order[i, enough]], far[i, j])  # the nearest node has objects within it, whatever k
            else:
                r2 = b.column(4).to_numpy(zero_copy_only=False)
                i, j = np.nonzero((d2 <= r2[:, None]) & (at[0] != b.column(3).to_numpy(zero_copy_only=False)[:, None]))
                r2 = r2[i]
            taken = b.take(pa.array(i))
            yield pa.RecordBatch.from_arrays([*taken.columns[:3], pa.array(at[0][j]), pa.array(r2, pa.int64())], names=["qid", "qx", "qy", "node", "r2"])

    return q.mapInArrow(run, f"qid {kind}, qx bigint, qy bigint, node bigint, r2 bigint")


def nearest(index: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """(qid, rank, oid, d2): the best of the node that is nearest to the query, then of the other nodes that their distance reaches. Only
    queries and answers are kept between the two; pairs of queries and leaves are made and dropped within a node's task."""
    found = boxes(index, "node").select("node", "n", "x0", "y0", "x1", "y1").toArrow()
    at = np.stack([found.column(c).to_numpy().astype(np.int64) for c in found.column_names])
    at = at[:, np.argsort(at[0])]
    q = queries.select("qid", F.col("x").cast("long").alias("qx"), F.col("y").cast("long").alias("qy"))
    if not at.shape[1]:
        return knn.nearest(q.join(index.select("oid"), F.lit(False)).select("qid", "oid", F.lit(0).cast("long").alias("d2")), k)
    first = cut(_in_nodes(index, _routed(q, at, k, True), k))
    drawn = F.when(F.count("*") == k, F.max("d2")).otherwise(F.first("r2"))
    rest = first.groupBy("qid", "qx", "qy", F.col("node").alias("home")).agg(drawn.alias("r2"))
    others = _in_nodes(index, cut(_routed(rest, at, k, False)), k)
    return knn.nearest(first.select("qid", "oid", "d2").unionByName(others.select("qid", "oid", "d2")), k)


def update(index: DataFrame, moves: DataFrame) -> DataFrame:
    """``index`` with the objects of ``moves(oid, x, y)`` at their new places: in their own leaf while it is in their node's tile,
    else in the last leaf of the tile that takes them in with the least growth."""
    tiles = F.broadcast(boxes(index, "node").limit(FEW).select(F.col("node").alias("to"), "x0", "y0", "x1", "y1"))
    there = moves.select("oid", F.col("x").alias("nx"), F.col("y").alias("ny"))
    far = box_disk_d2(F.col("nx"), F.col("ny"), F.col("x0"), F.col("y0"), F.col("x1"), F.col("y1"))
    best = there.join(tiles).groupBy("oid", "nx", "ny").agg(F.min(F.struct(far.alias("d"), "to")).alias("b")).select("oid", "nx", "ny", F.col("b.to").alias("to"))
    at = index.join(best, "oid", "left")
    stays = F.col("to").isNull() | (F.col("to") == F.col("node"))
    return at.select("oid", F.coalesce("nx", "x").alias("x"), F.coalesce("ny", "y").alias("y"), F.coalesce("to", "node").alias("node"), F.when(stays, F.col("leaf")).otherwise(-1).alias("leaf"))


def update_cost(before: DataFrame, after: DataFrame, nodes: int) -> DataFrame:
    """(updates, left, leaves_grown, messages): objects that moved, those that left their node, leaves whose box changed, and the
    messages: routing for each update, and telling on what changed."""
    a = before.select("oid", F.col("x").alias("x0"), F.col("y").alias("y0"), F.col("node").alias("n0"))
    moved = after.join(a, "oid").where("x <> x0 or y <> y0").agg(F.count("*").alias("updates"), F.count_if(F.col("node") != F.col("n0")).alias("left"))
    old, new = boxes(before, "node", "leaf"), boxes(after, "node", "leaf")
    grown = new.join(old.select("node", "leaf", *[F.col(c).alias(f"o{c}") for c in ("x0", "y0", "x1", "y1")]), ["node", "leaf"], "left")
    changed = ~F.coalesce((F.col("x0") == F.col("ox0")) & (F.col("y0") == F.col("oy0")) & (F.col("x1") == F.col("ox1")) & (F.col("y1") == F.col("oy1")), F.lit(False))
    grown = grown.where(changed).agg(F.count("*").alias("leaves_grown"))
    told = F.col("updates") * math.log2(nodes) + F.col("leaves_grown") * 3 * math.log2(max(1.0, nodes / 4))
    return moved.join(grown).withColumn("messages", told)
