"""Searches and updates of the competing indexes."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from cellfleet.baselines import hashed, trees


@pytest.fixture(scope="module")
def cloud(spark):
    rng = np.random.default_rng(4)
    xy = np.concatenate([rng.integers(0, 10_000, (400, 2)), rng.normal(3000, 100, (400, 2)).astype(int), [[5000, 5000]] * 30])
    return xy, spark.createDataFrame([(i, int(x), int(y)) for i, (x, y) in enumerate(xy)], "oid long, x long, y long")


def asked(spark):
    rows = [(1, 3000, 3000, 120.0), (2, -500, 200, 900.0), (3, 5000, 5000, 0.0), (4, 9000, 1000, 2500.0), (5, 50_000, 50_000, 10.0)]
    return rows, spark.createDataFrame(rows, "qid long, x long, y long, r double")


@pytest.mark.parametrize("kind", ["hashed", "tree"])
def test_searches(spark, cloud, kind):
    xy, pts = cloud
    rows, q = asked(spark)
    index = hashed.snapshot(pts, 3) if kind == "hashed" else trees.build(pts, 2, 3, 16)
    found = (hashed.range_ if kind == "hashed" else trees.search)(index, q)
    want = {(i, o) for i, x, y, r in rows for o, (a, b) in enumerate(xy.tolist()) if (a - x) ** 2 + (b - y) ** 2 <= r * r}
    assert {(r["qid"], r["oid"]) for r in found.collect()} == want and found.count() == len(want)
    for k in (1, 7, 40, 900):
        got = [(r["qid"], r["rank"], r["oid"]) for r in (hashed if kind == "hashed" else trees).nearest(index, q, k).orderBy("qid", "rank").collect()]
        best = [(i, n + 1, o) for i, x, y, _ in rows for n, (_, o) in enumerate(sorted(((a - x) ** 2 + (b - y) ** 2, o) for o, (a, b) in enumerate(xy.tolist()))[:k])]
        assert got == best


def test_leaves_are_full(cloud):
    xy, pts = cloud
    index = trees.build(pts, 2, 3, 16)
    sizes = [r["n"] for r in trees.boxes(index, "node", "leaf").collect()]
    assert sum(sizes) == len(xy) and max(sizes) <= 16 and len(sizes) <= 1.3 * len(xy) / 16 + 6


def test_updates_in_place(spark, cloud):
    xy, pts = cloud
    index = trees.build(pts, 2, 3, 16)
    moves = pts.where("oid % 10 = 0").withColumn("x", F.col("x") + F.when(F.col("oid") % 20 == 0, 4000).otherwise(3))
    after = trees.update(index, moves)
    at = {r["oid"]: (r["x"], r["y"], r["node"]) for r in after.collect()}
    assert len(at) == len(xy) and all(at[i][:2] == (x + (0 if i % 10 else 4000 if i % 20 == 0 else 3), y) for i, (x, y) in enumerate(xy.tolist()))
    cost = trees.update_cost(index, after, 6).first()
    assert cost["updates"] == 83 and 0 < cost["left"] < 83 and cost["leaves_grown"] > 0 and cost["messages"] > cost["updates"] * 2
    _, q = asked(spark)
    places = {i: at[i][:2] for i in at}
    want = {(i, o) for i, x, y, r in asked(spark)[0] for o, (a, b) in places.items() if (a - x) ** 2 + (b - y) ** 2 <= r * r}
    assert {(r["qid"], r["oid"]) for r in trees.search(after, q).collect()} == want


def test_neighbours_of_placed_nodes(spark, cloud):
    """Nodes told by cuts are those of the built trees, and neighbours are found without pairs of queries and leaves in the plan."""
    xy, pts = cloud
    at = trees.placed(pts, 2, 3)
    assert {tuple(r) for r in at.select("oid", "node").collect()} == {tuple(r) for r in trees.build(pts, 2, 3).select("oid", "node").collect()}
    assert "Exchange" not in at._jdf.queryExecution().executedPlan().toString()
    rows, q = asked(spark)
    for k in (1, 40, 900):
        got = [(r["qid"], r["rank"], r["oid"]) for r in trees.nearest(at, q, k).orderBy("qid", "rank").collect()]
        assert got == [(i, n + 1, o) for i, x, y, _ in rows for n, (_, o) in enumerate(sorted(((a - x) ** 2 + (b - y) ** 2, o) for o, (a, b) in enumerate(xy.tolist()))[:k])]
