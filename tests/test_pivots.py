"""Grids of pivots against all pairs, wide coordinates, and pieces on partitions."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from cellfleet.operators import borders, pivots, range_query
from cellfleet.operators.pivot_grid import PivotGrid


@pytest.mark.parametrize("n,m,spread", [(1, 50, 100), (2, 50, 100), (7, 500, 1000), (100, 1000, 10**9), (900, 1500, 10**6), (300, 1000, 50)])
def test_grid(n, m, spread):
    rng = np.random.default_rng(n)
    px, py = rng.integers(0, spread, n), rng.integers(0, spread // 3 + 1, n)
    x, y = (rng.integers(-spread // 2, spread * 3 // 2, m) for _ in range(2))
    grid = PivotGrid(np.arange(n) * 3 + 1, px, py)
    all_ = (x[:, None] - px) ** 2 + (y[:, None] - py) ** 2
    pid, d2 = grid.nearest(x, y)
    assert (all_.min(axis=1) == d2).all() and (all_.argmin(axis=1) * 3 + 1 == pid).all()
    if n > 1:
        rest = all_.copy()
        rest[np.arange(m), all_.argmin(axis=1)] = 2**62
        pid, d2 = grid.nearest(x, y, but=pid)
        assert (rest.min(axis=1) == d2).all() and (rest.argmin(axis=1) * 3 + 1 == pid).all()
    r = rng.random(m) * spread / 3
    got = set()
    for i, j, f2 in grid.within(x, y, r):
        assert (all_[i, j] == f2).all()
        got |= set(zip(i.tolist(), j.tolist(), strict=True))
    assert {(int(i), int(j)) for i, j in zip(*np.nonzero(all_ <= (r * r)[:, None]), strict=True)} <= got


def test_no_pivots():
    assert PivotGrid([], [], []).nearest(np.array([1]), np.array([2]))[0].tolist() == [-1]


@pytest.mark.parametrize("method", ["literal", "kernel"])
def test_wide_coordinates(spark, method):
    """The range of the uniform set of the experiments, and beyond it: exact, or an error, never a wrong piece."""
    piv = [(i, i * 120_000_000, i * 90_000_000) for i in range(8)]
    rows = [(1, 10**9, 10**9), (2, 0, 0), (3, 10**9, 0), (4, 350_000_000, 300_000_000), (5, -(10**9), 10**9)]
    got = {r["oid"]: (r["pid"], r["d2"]) for r in pivots.assign(spark.createDataFrame(rows, "oid long, x long, y long"), piv, method).collect()}
    for i, x, y in rows:
        d2, pid = min(((x - a) ** 2 + (y - b) ** 2, p) for p, a, b in piv)
        assert got[i] == (pid, d2)
    with pytest.raises(Exception, match="OVERFLOW|verflow"):
        pivots.assign(spark.createDataFrame([(1, 6 * 10**9, 5)], "oid long, x long, y long"), piv, method).collect()


def test_kernels_equal_all_pairs(spark, monkeypatch):
    rng = np.random.default_rng(2)
    xy = rng.integers(0, 10_000, (700, 2)).tolist()
    pts = spark.createDataFrame([(i, x, y) for i, (x, y) in enumerate(xy)], "oid long, x long, y long")
    piv = [(i, x, y) for i, (x, y) in enumerate(dict.fromkeys((int(a), int(b)) for a, b in rng.integers(0, 10_000, (40, 2))))]
    at = pivots.assign(pts, piv)
    q = pts.select(F.col("oid").alias("qid"), "x", "y", (F.col("oid") * 3.0).alias("r"))
    rows = lambda df: sorted(map(tuple, df.collect()))
    border = lambda: [(a, round(h, 6)) for a, h in rows(borders.nearest_border(at, piv).select("oid", "hp"))]
    kernel = rows(borders.replicate(at, piv, 300.0)), rows(range_query.targets(q, piv)), border()
    monkeypatch.setattr(pivots, "LITERAL_PIVOTS", 100)
    assert kernel == (rows(borders.replicate(at, piv, 300.0)), rows(range_query.targets(q, piv)), border())


def test_election_by_distances(spark):
    rng = np.random.default_rng(3)
    pts = spark.createDataFrame([(i, int(a), int(b)) for i, (a, b) in enumerate(rng.integers(0, 1000, (90, 2)))], "oid long, x long, y long")
    cand = pivots.candidates(pts, 35)
    want = {}
    for r in cand.collect():
        want.setdefault((r["rk"] - 1) // 10, []).append((r["x"], r["y"]))
    want = {s: sum(np.hypot(a[0] - b[0], a[1] - b[1]) for i, a in enumerate(v) for b in v[i + 1 :]) for s, v in want.items() if len(v) == 10}
    got = {r["set"]: r["score"] for r in pivots.scores(cand, 10).collect()}
    assert got.keys() == want.keys() and all(got[s] == pytest.approx(want[s]) for s in want)


def test_pieces_on_partitions(spark):
    """Each piece is on its node's partition, none by chance on that of another."""
    pts = spark.range(2000).select(F.col("id").alias("oid"), F.pmod("id", F.lit(12)).alias("pid"))
    got = pivots.distribute(pts, 6).select("pid", F.spark_partition_id().alias("p")).distinct().collect()
    assert {(r["pid"], r["p"]) for r in got} == {(i, i % 6) for i in range(12)}
    nodes = pivots.group_balanced([(i, 10 + i) for i in range(12)], 4)
    got = pivots.distribute(pts, 4, nodes).select("pid", F.spark_partition_id().alias("p")).distinct().collect()
    assert {(r["pid"], r["p"]) for r in got} == set(nodes.items())


def test_leaves_by_ranges_and_by_join(spark):
    from cellfleet.operators import kdpart

    rng = np.random.default_rng(5)
    pts = kdpart.coded(spark.createDataFrame([(i, int(a), int(b)) for i, (a, b) in enumerate(rng.integers(0, 4000, (500, 2)))], "oid long, x long, y long"))
    boxed = kdpart.with_boxes(kdpart.build(pts.where("x < 2000"), 20))
    rows = lambda df: sorted((r["oid"], r["pid"]) for r in df.collect())
    by_range = rows(kdpart.assign(pts, boxed))
    assert by_range == rows(kdpart.assign(pts, boxed, most=0)) and len(by_range) < 500
