"""What grows with the tables: the driver's memory, and work that would grow with the square of a piece."""

import tracemalloc

import numpy as np

from pyspark.sql import functions as F

from cellfleet.functions import zorder
from cellfleet.operators import access, cells
from cellfleet.plans import fleet_queries


def test_counts_become_loads_without_wide_rows():
    rng = np.random.default_rng(3)
    key, by, n = rng.integers(0, 50, 100_000), rng.integers(0, access.INTERVALS + 1, 100_000), rng.integers(1, 9, 100_000)
    wide = np.eye(access.INTERVALS)
    tracemalloc.start()
    names, a, rows = fleet_queries.summed_loads(key, by, n)
    _, b, _ = fleet_queries.summed_loads(key, np.minimum(by, access.INTERVALS - 1), n, wide)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 100_000 * access.INTERVALS  # a byte for each row and interval
    for k in (0, 7, 49):
        mine = (key == names[k]) & (by < access.INTERVALS)
        assert (a[k] == np.bincount(by[mine], weights=n[mine], minlength=access.INTERVALS)).all()
        assert rows[k] == n[key == names[k]].sum() == b[k].sum()


def test_circles_are_looked_up(spark):
    rng = np.random.default_rng(4)
    p = [(i, int(x), int(y), i % 3) for i, (x, y) in enumerate(rng.integers(0, 1_000, (300, 2)))]
    c = [(1_000 + i, i % 3, [(float(a), float(b), float(r)) for a, b, r in rng.integers(0, 1_000, (4, 3)) * (1, 1, 0.2 if i else 9)]) for i in range(20)]
    pts = spark.createDataFrame(p, "oid long, x long, y long, pid long")
    asked = spark.createDataFrame(c, "oid long, pid long, circles array<struct<cx:double,cy:double,r:double>>")
    got = [tuple(r) for r in cells.inside_circles(asked, pts).collect()]
    assert sorted(got) == sorted((o, i, x, y) for o, pid, around in c for i, x, y, at in p if at == pid and any((a - x) ** 2 + (b - y) ** 2 <= r * r * (1 + 1e-9) + 1e-6 for a, b, r in around))


def test_pieces_of_cells_are_not_put_in_one_task(spark):
    placed = spark.range(600).select(F.col("id").alias("oid"), (F.col("id") * 37 % 1_000).alias("x"), (F.col("id") * 91 % 997).alias("y"), (F.col("id") % 6).alias("pid"), F.lit(False).alias("is_replica"))
    made = cells.local(placed, None, (-10.0, -10.0, 1_010.0, 1_010.0)).withColumn("task", F.spark_partition_id())
    assert made.select("task").distinct().count() > 3


def test_standing_ranges_are_joined_by_tiles(spark, d):
    from cellfleet.plans.operator_queries import event_stream
    from cellfleet.streaming import positions

    q = spark.createDataFrame([(1, 500, 500, 2_000.0), (2, 40_000, 9_000, 90_000.0)], "qid long, x long, y long, r double")
    plan = positions.inside(event_stream(spark, d), q, [(0, 0, 0), (1, 9_000, 9_000)])._jdf.queryExecution().analyzed().toString()
    assert "tile" in plan


def test_pairs_of_patterns_are_compared_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(access, "PAIR_BLOCK", 7)
    rng = np.random.default_rng(6)
    v = {i * 3 + 1: rng.integers(0, 9, access.INTERVALS).astype(float) for i in range(40)}
    vecs = spark.createDataFrame([(i, x.tolist()) for i, x in v.items()], "pid long, v array<double>")
    got = access.pair_flatness(vecs)
    assert "NestedLoop" not in got._jdf.queryExecution().executedPlan().toString()
    assert {tuple(r) for r in got.collect()} == {(a, b, float(np.abs(np.diff(v[a] + v[b])).sum())) for a in v for b in v if a < b}


def test_ranges_are_joined_at_their_least_gaps():
    def one_by_one(r, most):
        while len(r) > most:
            i = min(range(len(r) - 1), key=lambda k: r[k + 1][0] - r[k][1])
            r[i : i + 2] = [(r[i][0], r[i + 1][1])]
        return r

    rng = np.random.default_rng(9)
    for _ in range(100):
        ends = rng.integers(1, 6, 80).cumsum()
        found = [(int(a), int(b)) for a, b in zip(ends[::2], ends[1::2], strict=True)]
        for most in (1, 2, 7, 20, 39, 40, 50):
            assert zorder.bridged(list(found), most) == one_by_one(list(found), most)
    x = np.arange(4_000)
    assert zorder.bridged([(int(a), int(a)) for a in 3 * x], 1) == [(0, 3 * 3_999)]


def test_large_boxes_are_scanned_by_few_squares(monkeypatch):
    rng, asked, ranges = np.random.default_rng(10), [], zorder.ranges
    x, y = rng.integers(0, 2_000_000, (2, 800))
    scan = cells.CodeScan(x, y, np.arange(800))
    monkeypatch.setattr(zorder, "ranges", lambda *a: asked.append(max(a[2] - a[0], a[3] - a[1])) or ranges(*a))
    for cx, cy, r in [(900_000, 300_000, 700_000.0), (-4e9, 1e6, 4.0005e9), (x[3], y[3], 0.0), (1_999_000, 5_000, 90_000.0)]:
        at = scan.inside([(cx, cy, r)])
        assert sorted(scan.ids[at].tolist()) == np.flatnonzero((x - cx) ** 2.0 + (y - cy) ** 2.0 <= r * r * (1 + 1e-9) + 1e-6).tolist()
    assert max(asked) <= 1 << cells.BOX_BITS


def test_cells_are_made_once_for_their_repair(spark, monkeypatch):
    made, cut = [], cells.cut
    monkeypatch.setattr(cells, "cut", lambda df: made.append(df) or cut(df))
    pts = spark.range(300).select(F.col("id").alias("oid"), (F.col("id") * 37 % 1_000).alias("x"), (F.col("id") * 91 % 997).alias("y"))
    out = cells.diagram(pts, [(0, 100, 100), (1, 800, 700)], whole=True, by_codes=True)
    assert len(made) == 1 and "FlatMapGroupsInPandas" not in out._jdf.queryExecution().executedPlan().toString()


def test_nobody_owns_the_edges_on_the_box(spark):
    """0 and 1 meet in their piece until 2, of the other piece, comes between them; the far box is as far from 1 as from 0."""
    pts = spark.createDataFrame([(0, 1_000, 0), (1, 998, 1_000), (2, 1_004, 500), (3, 500, 500), (4, 0, 100)], "oid long, x long, y long")
    true_ = {r["oid"]: list(r["nbrs"]) for r in cells.single_thread(pts, whole=True).collect()}
    assert true_[0] == [2, 3, 4]
    for by_codes in (False, True):
        made = cells.diagram(pts, [(0, 999, 500), (1, 1_005, 500)], whole=True, by_codes=by_codes)
        assert {r["oid"]: list(r["nbrs"]) for r in made.collect()} == true_
