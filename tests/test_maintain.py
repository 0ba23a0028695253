"""Inserted and moved objects, and the leaves that they change."""

import numpy as np
from pyspark.sql import functions as F

from cellfleet import catalogue
from cellfleet.operators import kdpart, maintain
from cellfleet.plans import fleet_queries as fq


def test_spread():
    assert maintain.spread(10, np.full(5, 10), 0.0).tolist() == [2] * 5
    skewed = maintain.spread(100, np.full(20, 100), 1.0)
    assert skewed.sum() == 100 and skewed.max() > 20
    assert maintain.spread(30, np.array([1, 2, 40]), 1.0).sum() == 30
    assert maintain.spread(30, np.array([1, 2, 3]), 1.0).tolist() == [1, 2, 3]
    assert fq.rows_kept(np.array([0, 0, 1]), np.array([7, 7, 3]), np.array([5, 5, 2])) == 12


def test_changes_are_rows(spark, d):
    pts, boxed = fq.leaves(spark, d, 100)
    at = kdpart.assign(pts, boxed, fq.BITS)
    n = boxed.count()
    wanted = spark.createDataFrame([(i, 3) for i in range(n)], "pid long, k long")
    new = maintain.inserted(boxed, wanted)
    assert new.count() == 3 * n and kdpart.assign(new.withColumnRenamed("pid", "src"), boxed, fq.BITS).where("src = pid").count() == 3 * n
    moved = maintain.moved(at, wanted, 500.0, 65_536)
    assert moved.count() == at.count() and moved.where("to is not null").count() == 3 * n
    counts = at.groupBy("z").agg(F.count("*").alias("n"))
    after, gone, made = maintain.apply_changes(counts, new.select("z", F.lit(1).alias("dn")), 100, fq.BITS, fq.BITS)
    want = kdpart.leaves(pts.select("z").unionByName(new.select("z")).groupBy("z").agg(F.count("*").alias("n")), 100, fq.BITS, fq.BITS)
    had = {tuple(r) for r in kdpart.leaves(counts, 100, fq.BITS, fq.BITS).select("depth", "prefix").collect()}
    want = {tuple(r) for r in want.select("depth", "prefix").collect()}
    assert {tuple(r) for r in gone.select("depth", "prefix").collect()} == had - want
    assert {tuple(r) for r in made.select("depth", "prefix").collect()} == want - had
    assert after.agg(F.sum("n")).first()[0] == at.count() + 3 * n


def test_incremental_transfer(spark, d):
    rows = catalogue.queries()["incremental_transfer"](spark, d).collect()
    assert {(r["change"], r["skew"], r["share"]) for r in rows} == {(c, s, h) for c in ("insert", "move") for s in (0.0, 1.0) for h in (0.01, 0.05, 0.10)}
    assert all(0 <= r["incremental"] <= 1 and 0 <= r["repacked"] <= 1 for r in rows)


def test_relabelled_plan_moves_nothing():
    plan = np.array([0, 0, 1, 2, 2, 2, 1])
    rows = np.array([4, 1, 7, 2, 2, 9, 1])
    renamed = np.array([5, 9, 1])[plan]
    assert fq.rows_kept(plan, renamed, rows) == rows.sum()
    assert fq.rows_kept(plan, np.zeros(7, dtype=int), rows) == 13  # only the largest common share keeps its name
    fleet = maintain.Fleet(100.0, width=3)
    loads = np.ones((7, 3))
    fleet.adopt(plan, loads)
    assert [load.tolist() for load in fleet.loads] == [[2.0] * 3, [2.0] * 3, [3.0] * 3] and fleet.where == dict(enumerate(plan.tolist()))
    fleet.remove(5)
    assert fleet.loads[2].tolist() == [2.0] * 3


def test_grid_fleets(spark, d):
    """The same objects and loads on the grid's servers, scattered ones and pieces."""
    units, tiers = fq.fleet_units(spark, d, "cosine", 50)
    n = fq.views.skewed(spark, d).count()
    assert units["rows"].sum() == units["cells_rows"].sum() == n and np.allclose(units["a"].sum(axis=0), units["cells_a"].sum(axis=0))
    assert units["cells_rows"].max() <= max(1, n // 50) and len(np.unique(units["grid"])) < len(units["prefix"])
    cells = np.bincount(units["grid"], weights=units["cells_rows"])
    assert cells.max() <= fq.GRID_CAP * (n // 50)
    got = {r["method"]: r for r in fq.fleet_costs(spark, d, "cosine", 50).collect()}
    assert set(got) == {"grid", "grid_scattered", "grid_reactive", "grid_reactive_by_hours", "packer", "packer_search"}
    assert got["packer_search"]["idle"] <= got["packer"]["idle"] and got["grid_reactive"]["cost"] <= got["grid_reactive_by_hours"]["cost"] + 1e-6


def test_few_pairs_are_compared(monkeypatch):
    """Merging looks at few pairs in full and makes the plan that all pairs make."""
    from cellfleet.operators import costs, packing

    rng = np.random.default_rng(3)
    p, t = 80, np.arange(288)
    rows = rng.integers(20, 500, p)
    a = rows[:, None] * (1 + np.cos(2 * np.pi * (t / 288 - rng.integers(0, 64, p)[:, None] / 64))) / 2
    tiers = costs.tiers(max(float(a.max()) * 1.01, float(a.sum(axis=0).max()) / 24), max(1, int(rows.sum()) // 24), 0.1)
    capacity, storage = max(x[1] for x in tiers), max(x[2] for x in tiers)
    load, size, want, alive = a.copy(), rows.copy(), np.arange(p), list(range(p))
    while len(alive) > 4:
        pairs = [(float(packing.variation(load[i] + load[j])), i, j) for n, i in enumerate(alive) for j in alive[n + 1 :] if (load[i] + load[j]).max() < capacity and size[i] + size[j] <= storage]
        if not pairs:
            break
        _, i, j = min(pairs)
        load[i] += load[j]
        size[i] += size[j]
        want[want == j] = i
        alive.remove(j)
    looked, plain = [], packing.variation
    monkeypatch.setattr(packing, "variation", lambda x: looked.append(len(x) if x.ndim > 1 else 1) or plain(x))
    assert packing.agglomerate(a, rows, 4, tiers).tolist() == np.unique(want, return_inverse=True)[1].tolist()
    new = sum(looked)
    assert new < p * p


def test_more_pieces_than_a_region_has(spark):
    """A plan, and the loads it is made of, have no limit of pieces (before, 5,000)."""
    from cellfleet.operators import packing

    n = 5_002
    a = np.random.default_rng(5).random((n, 3))
    assert len(np.unique(packing.agglomerate(a, np.ones(n, dtype=np.int64), n - 3, [(0, 100.0, 100, 1.0)]))) == n - 3
    rows = spark.range(n).select(F.col("id").alias("pid"), F.lit(2).cast("long").alias("n"))
    vecs = rows.where("pid % 2 = 1").select("pid", F.array(F.col("pid").cast("double"), F.lit(1.0)).alias("v"))
    pids, v, held = packing.matrix(vecs, rows)
    assert pids.tolist() == list(range(n)) and held.sum() == 2 * n and v[:4].tolist() == [[0.0, 0.0], [1.0, 1.0], [0.0, 0.0], [3.0, 1.0]]


def test_loads_that_are_carried(monkeypatch):
    monkeypatch.setattr(fq, "FLOWS", 7)
    rng = np.random.default_rng(2)
    a, rows, src, dst, n = rng.random((5, 4)), np.array([3, 4, 5, 6, 7]), rng.integers(0, 5, 40), rng.integers(0, 9, 40), rng.integers(1, 4, 40)
    load, size = np.zeros((9, 4)), np.zeros(9, dtype=np.int64)
    np.add.at(load, dst, a[src] * (n / rows[src])[:, None])
    np.add.at(size, dst, n)
    got = fq.carried(a, rows, src, dst, n, 9)
    assert np.allclose(got[0], load) and got[1].tolist() == size.tolist()
