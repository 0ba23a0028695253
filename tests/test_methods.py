"""Kernels, worked examples and invariants of the methods."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from cellfleet.baselines import fleets, indexes
from cellfleet.functions import zorder
from cellfleet.operators import access, borders, cells, costs, hierarchy, kdpart, knn, maintain, packing, pivots, range_query, snapshot

TIERS = [(0, 10.0, 1000, 1.0), (1, 20.0, 2000, 2.0), (2, 40.0, 4000, 4.0)]


def points(spark, rows):
    return spark.createDataFrame([(i, int(x), int(y)) for i, (x, y) in enumerate(rows)], "oid long, x long, y long")


@pytest.fixture(scope="module")
def cloud():
    rng = np.random.default_rng(1)
    xy = np.concatenate([rng.integers(0, 10_000, (150, 2)), rng.normal(3000, 200, (150, 2)).astype(int)])
    return [tuple(map(int, p)) for p in xy]


def test_printed_rule_is_unsound(spark):
    """The nearest piece's object is within reach, though the rule measured from the query's pivot leaves its piece out."""
    piv = [(0, 0, 0), (1, 10, 0)]
    q = spark.createDataFrame([(1, 4, 0, 2.0)], "qid long, x long, y long, r double")
    index = pivots.assign(points(spark, [(6, 0)]), piv)
    far = [(r["pid"], r["f2"]) for r in pivots.stats(index).collect()]
    sound = range_query.answers(index, range_query.targets(q, piv, far))
    printed = range_query.answers(index, range_query.targets(q, piv, far, "far_as_printed"))
    assert sound.count() == 1 and printed.count() == 0


def test_replicas_at_a_corner(spark):
    piv = [(0, 0, 0), (1, 100, 0), (2, 0, 100), (3, 100, 100)]
    at = pivots.assign(points(spark, [(10, 10), (45, 10), (45, 45), (40, 40), (39, 39)]), piv)
    n = {r["oid"]: r["n"] for r in borders.replicate(at, piv, 10.0).groupBy("oid").agg(F.count("*").alias("n")).collect()}
    assert n == {0: 1, 1: 2, 2: 4, 3: 3, 4: 1}


@pytest.mark.parametrize("rows", [[(0, 0)], [(0, 0), (0, 0)], [(i, 0) for i in range(4)], [(i * 10, j * 10) for i in range(3) for j in range(3)]])
def test_degenerate_cells(spark, rows):
    pts = points(spark, rows)
    piv = pivots.choose(pts, 2, 2)
    x0, y0, x1, y1 = cells.box_of(pts)
    made = cells.diagram(pts, piv).collect()
    assert len(made) == len(set(rows)) and sum(r["area"] for r in made) == pytest.approx((x1 - x0) * (y1 - y0))


@pytest.mark.parametrize("p,margin,seeds", [(2, 0.0, 3), (5, 0.0, 1), (5, 300.0, 3), (9, 100.0, 6)])
def test_cells_are_the_same_however_made(spark, cloud, p, margin, seeds):
    pts = points(spark, cloud)
    truth = {r["oid"]: (r["area"], r["nbrs"]) for r in cells.single_thread(pts).collect()}
    piv = pivots.choose(pts, p, 4)
    made = cells.diagram(pts, piv, margin, seeds).collect()
    assert len(made) == len(truth)
    for r in made:
        assert r["area"] == pytest.approx(truth[r["oid"]][0], rel=1e-9, abs=1e-3) and r["nbrs"] == truth[r["oid"]][1]
    assert np.mean([len(r["nbrs"]) for r in made]) <= 6


def test_flagged_exact_cells_are_right(spark, cloud):
    pts = points(spark, cloud)
    truth = {r["oid"]: r["nbrs"] for r in cells.single_thread(pts).collect()}
    piv = pivots.choose(pts, 6, 4)
    at = pivots.assign(cells.places(pts), piv)
    for margin in (0.0, 200.0):
        placed = borders.replicate(at, piv, margin) if margin else at.withColumn("is_replica", F.lit(False))
        made = cells.local(placed.select("oid", "x", "y", "pid", "is_replica"), piv, cells.box_of(pts), margin).collect()
        assert all(r["nbrs"] == truth[r["oid"]] for r in made if r["exact"]) and any(not r["exact"] for r in made)


def test_repair_in_one_task_is_the_same(spark, cloud):
    pts = points(spark, cloud)
    piv = pivots.choose(pts, 5, 4)
    at = pivots.assign(cells.places(pts), piv)
    box = cells.box_of(pts)
    made = cells.local(at.select("oid", "x", "y", "pid", F.lit(False).alias("is_replica")), piv, box)
    rows = lambda df: sorted((r["oid"], tuple(r["nbrs"])) for r in df.collect())
    assert rows(cells.repair(made, at, piv, box)) == rows(cells.repair(made, at, piv, box, single=True))


def test_random_pieces_make_more_wrong_cells(spark, cloud):
    pts = points(spark, cloud)
    got = {(r["method"], r["margin"]): r for r in cells.inaccuracy(pts, pivots.choose(pts, 6, 4), (0.0, 400.0)).collect()}
    assert got[("random", 0.0)]["wrong"] > 2 * got[("pivots", 0.0)]["wrong"] > 2 * got[("pivots", 400.0)]["wrong"]


def test_clip():
    assert cells.area(cells.clip(cells.square((0, 0, 10, 10)), 2, 5, 8, 5, 7)) == pytest.approx(50)
    half = cells.clip(cells.square((0, 0, 10, 10)), 2, 5, 8, 5, 7)
    assert cells.neighbours(half, 1e-9) == [7] and cells.clip(half, 2, 5, 30, 5, 9) is half


def test_zorder():
    rng = np.random.default_rng(3)
    code = lambda x, y: sum((x >> i & 1) << 2 * i | (y >> i & 1) << 2 * i + 1 for i in range(26))
    for _ in range(20):
        x0, y0 = rng.integers(0, 60, 2)
        x1, y1 = x0 + rng.integers(0, 20), y0 + rng.integers(0, 20)
        exact = zorder.ranges(int(x0), int(y0), int(x1), int(y1), 1 << 30)
        inside = {code(x, y) for x in range(x0, x1 + 1) for y in range(y0, y1 + 1)}
        assert {z for a, b in exact for z in range(a, b + 1)} == inside
        few = zorder.ranges(int(x0), int(y0), int(x1), int(y1), 4)
        assert len(few) <= 4 and all(any(a <= z <= b for a, b in few) for z in inside)
        z = int(rng.integers(0, max(inside) + 1))
        assert zorder.next_in_box(z, int(x0), int(y0), int(x1), int(y1)) == min(v for v in inside if v >= z)


@pytest.mark.parametrize("k", [1, 5, 400])
def test_knn_beyond_all(spark, cloud, k):
    pts = points(spark, cloud)
    piv = pivots.choose(pts, 5, 4)
    q = spark.createDataFrame([(1, 3000, 3000), (2, -50_000, 90_000)], "qid long, x long, y long")
    got, again = ([(r["qid"], r["rank"], r["oid"]) for r in knn.run(pts, q, piv, k, bound).orderBy("qid", "rank").collect()] for bound in ("grid", "pieces"))
    assert got == again
    want = []
    for i, x, y in ((1, 3000, 3000), (2, -50_000, 90_000)):
        best = sorted((((x - a) ** 2 + (y - b) ** 2), o) for o, (a, b) in enumerate(cloud))[:k]
        want += [(i, n + 1, o) for n, (_, o) in enumerate(best)]
    assert got == want


def test_step_radius():
    assert knn.step_radius(1, 10_000, 1.0, "unit_disk") == pytest.approx(2 * knn.step_radius(1, 10_000, 1.0))
    assert knn.step_radius(50, 10, 1.0) == pytest.approx(1 / math.sqrt(math.pi) / 50)


def test_hierarchy_answers(spark, cloud):
    pts = points(spark, cloud)
    levels = hierarchy.build(pts, 5, 3)
    assert len(levels) >= 2 and levels[0].agg(F.sum("n")).first()[0] == len(cloud)
    low = levels[0].collect()
    top = {r["gid"] for r in levels[1].collect()}
    assert {r["parent"] for r in low} <= top
    q = spark.createDataFrame([(1, 3000, 3000, 150.0)], "qid long, x long, y long, r double")
    got = {r["oid"] for r in hierarchy.search([(r["gid"], r["x"], r["y"], r["f2"]) for r in low], pts, q).collect()}
    assert got == {i for i, (x, y) in enumerate(cloud) if (x - 3000) ** 2 + (y - 3000) ** 2 <= 150**2}


def test_complementary_patterns_are_flat(spark):
    t = np.arange(288)
    sine = 10 + 5 * np.sin(2 * np.pi * t / 288)
    v = spark.createDataFrame([(0, sine.tolist()), (1, (20 - sine).tolist())], "pid long, v array<double>")
    assert access.pair_flatness(v).first()["delta"] == pytest.approx(0, abs=1e-9)
    assert all(r["f"] > 15 for r in v.select(access.flatness(F.col("v")).alias("f")).collect())


def six_pieces():
    """A, B, C add up to a flat load, and so do D, E, F."""
    a = np.zeros((6, 288))
    for i in range(6):
        a[i, i % 3 * 96 : (i % 3 + 1) * 96] = 6.0
    a += 0.5
    return a, np.full(6, 100)


def test_worked_example_of_six_pieces():
    a, rows = six_pieces()
    plan = packing.agglomerate(a, rows, 2, [(0, 10.0, 1000, 1.0)])
    assert len(np.unique(plan)) == 2
    assert all(packing.variation(a[plan == s].sum(axis=0)) == 0 for s in (0, 1))
    bad = np.array([0, 0, 0, 1, 1, 1])[[0, 3, 1, 4, 2, 5]]
    for how in ("move", "swap"):
        for seed in range(3):
            better = packing.tabu(bad, a, rows, TIERS, eta=1000.0, seed=seed, neighbourhood=how, patience=200)
            assert packing.total_idle(better, a, rows, TIERS) <= packing.total_idle(bad, a, rows, TIERS)
    assert packing.total_idle(packing.pack(a, rows, 2, TIERS), a, rows, TIERS) <= packing.total_idle(packing.agglomerate(a, rows, 2, TIERS), a, rows, TIERS)


def test_merging_stops_where_nothing_fits():
    a = np.full((4, 288), 8.0)
    assert len(np.unique(packing.agglomerate(a, np.full(4, 10), 1, [(0, 10.0, 1000, 1.0)]))) == 4


def test_agglomerate_equals_naive():
    rng = np.random.default_rng(6)
    a = rng.random((14, 24)) * 3
    rows = np.full(14, 10)
    tiers = [(0, 12.0, 1000, 1.0)]
    groups = [[i] for i in range(14)]
    while len(groups) > 4:
        best = None
        for i in range(len(groups)):
            for j in range(i + 1, len(groups)):
                both = a[groups[i] + groups[j]].sum(axis=0)
                if both.max() < 12 and (best is None or packing.variation(both) < best[0] - 1e-12):
                    best = (packing.variation(both), i, j)
        if best is None:
            break
        groups[best[1]] += groups.pop(best[2])
    plan = packing.agglomerate(a, rows, 4, tiers)
    assert sorted(map(sorted, groups)) == sorted(np.flatnonzero(plan == s).tolist() for s in np.unique(plan))


def test_copies_stay_apart(spark):
    a, rows = six_pieces()
    twice, n = np.concatenate([a, a]), np.concatenate([rows, rows])
    start = np.array([0, 1, 2, 3, 4, 5, 1, 2, 3, 4, 5, 0])
    plan = packing.tabu(start, twice, n, TIERS, eta=1000.0, apart=[(i, i + 6) for i in range(6)], patience=100)
    assert all(plan[i] != plan[i + 6] for i in range(6))
    p = spark.createDataFrame([(i, i % 4) for i in range(8)], "pid long, server long")
    copies = packing.with_replicas(p, 2, 4)
    assert copies.count() == 24 and copies.select("pid", "server").distinct().count() == 24


def test_maintainer_groups():
    f = maintain.Fleet(100.0, 4, 4)
    f.loads = [np.full(4, 100.0), np.full(4, 70.0), np.full(4, 40.0), np.zeros(4)]
    assert [f.group(100.0 - l.max()) for l in f.loads] == [0, 1, 2, 3]
    assert f.place(1, np.full(4, 25.0)) == 1  # the group it just fits in
    assert f.place(2, np.full(4, 80.0)) == 3
    assert f.place(3, np.full(4, 90.0)) == 4  # a new server
    f.remove(3)
    assert f.loads[4].max() == 0 and f.update(2, np.full(4, 10.0)) in range(5)


def test_auto_scaler():
    t = np.arange(288)
    low = np.where(t < 100, 15.0, np.where(t < 200, 4.0, 15.0))
    r = fleets.Reactive(np.array([low]), np.array([100]), TIERS, [[0]])
    r.run()
    kinds = [k for _, k in r.events]
    assert kinds[:2] == ["up", "down"] and (r.events[1][0] >= 105)
    two = fleets.Reactive(np.full((2, 288), 3.0), np.array([100, 100]), TIERS, [[0], [1]])
    two.run()
    assert [k for _, k in two.events] == ["merge"] and len(two.servers) == 1
    hot = np.full((2, 288), 2.0)
    hot[:, 50] = 8.0
    one = fleets.Reactive(hot, np.array([100, 100]), TIERS, [[0, 1]])
    one.run()
    assert one.events[0] == (50, "split")


def test_grid_and_leaves(spark):
    pts = kdpart.coded(points(spark, [(0, 0)] * 50 + [(i, i) for i in range(1, 50)]))
    leaf = kdpart.with_boxes(kdpart.build(pts, 10, 12, 12), 12).collect()
    assert sum(r["n"] for r in leaf) == 99 and all(r["n"] <= 10 or r["depth"] == 12 for r in leaf)
    grid = fleets.grid_cells(pts, 60, 12, 12).collect()
    assert sum(r["n"] for r in grid) == 99 and len({r["depth"] for r in grid}) == 1


def test_regions_are_packed_alike(spark):
    a, rows = six_pieces()
    data = [(g, i, int(rows[i]), a[i].tolist()) for g in (1, 2) for i in range(6)]
    got = packing.pack_regions(spark.createDataFrame(data, "region long, pid long, n long, v array<double>"), 2, TIERS, search=False).collect()
    plan = packing.agglomerate(a, rows, 2, TIERS)
    assert {(r["region"], r["pid"], r["server"]) for r in got} == {(g, i, int(plan[i])) for g in (1, 2) for i in range(6)}


def test_tier_over_all(spark):
    loads = spark.createDataFrame([(1, 5.0, 10), (2, 15.0, 10), (3, 5.0, 3000), (4, 99.0, 1)], "server long, peak double, rows long")
    got = {r["server"]: (r["tier"], r["over"]) for r in costs.choose_tier(loads, costs.frame(spark, TIERS)).collect()}
    assert got == {1: (0, False), 2: (1, False), 3: (2, False), 4: (2, True)}


def test_snapshot_versions(spark, tmp_path, cloud):
    pts = points(spark, cloud)
    at, piv, new = snapshot.cycle(pts, None, 4)
    assert new
    snapshot.publish(at, str(tmp_path), 1)
    assert snapshot.cycle(pts, piv, 4, "never")[1] == piv and snapshot.cycle(pts, piv, 4, "auto", 99.0)[2] is False
    snapshot.publish(at.limit(3), str(tmp_path), 2)
    v, index = snapshot.current(spark, str(tmp_path))
    assert v == 2 and index.count() == 3


def test_message_formulas():
    assert indexes.overlay_update_messages(128) == 7 + 15 and indexes.ring_messages(128) == 7
    assert indexes.break_even(128, 1.0, 0.1) == pytest.approx(1.1 / 22)
    assert pivots.group_balanced([(0, 5), (1, 4), (2, 3), (3, 3)], 2) == {0: 0, 1: 1, 2: 1, 3: 0}


@pytest.mark.parametrize("rule", [None, "far", "far_as_printed"])
def test_kernel_finds_the_same_targets(spark, cloud, rule, monkeypatch):
    pts = points(spark, cloud)
    piv = pivots.choose(pts, 9, 4)
    far = [(r["pid"], r["f2"]) for r in pivots.stats(pivots.assign(pts, piv)).collect()] if rule else None
    q = pts.select(F.col("oid").alias("qid"), "x", "y", (F.col("oid") * 10.0).alias("r"))
    rows = lambda: sorted(map(tuple, range_query.targets(q, piv, far, rule or "far").collect()))
    in_plan = rows()
    monkeypatch.setattr(pivots, "LITERAL_PIVOTS", 4)
    assert rows() == in_plan


def test_cells_at_a_border_ask_for_few(spark, monkeypatch):
    """Without scouts a cell at the border of its piece reaches to the box and asks for nearly all objects of the others."""
    asked, plain = [], cells.inside_circles
    monkeypatch.setattr(cells, "inside_circles", lambda *a: asked.append(plain(*a)) or asked[-1])
    pts = spark.range(3000).selectExpr("id as oid", "cast(conv(substring(md5(cast(id as string)), 1, 5), 16, 10) as bigint) as x", "cast(conv(substring(md5(cast(id as string)), 6, 5), 16, 10) as bigint) as y")
    piv = pivots.choose(pts, 8)
    got = {r["oid"]: (r["nbrs"], round(r["area"])) for r in cells.diagram(pts, piv).collect()}
    assert got == {r["oid"]: (r["nbrs"], round(r["area"])) for r in cells.single_thread(pts).collect()}
    assert asked[0].count() < 20 * 3000
