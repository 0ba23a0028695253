"""Tiles of pieces: searches by tiles against brute force, many tiles and queries far outside of them included."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from cellfleet import catalogue
from cellfleet.operators import knn, pivot_grid, pivots, range_query, tiles


@pytest.fixture(scope="module")
def points(spark):
    rng = random.Random(5)
    p = [(i, rng.randrange(10_000), rng.randrange(5_000)) for i in range(1_500)] + [(1_500 + i, 77, 78) for i in range(40)]
    q = [(i, rng.randrange(-2_000, 12_000), rng.randrange(-1_000, 6_000), float(rng.choice((0, 60, 700)))) for i in range(60)] + [(90, 9_000_000, -40_000, 9_000_000.0), (91, 77, 78, 0.0)]
    return p, q, spark.createDataFrame(p, "oid long, x long, y long"), spark.createDataFrame(q, "qid long, x long, y long, r double")


def brute(p, q):
    return {(i, o, (x - a) ** 2 + (y - b) ** 2) for i, a, b, r in q for o, x, y in p if (x - a) ** 2 + (y - b) ** 2 <= r * r}


def test_tiles_hold_all_answers(spark, points):
    p, q, pts, asked = points
    piv = pivots.choose(pts, 5)
    index, over = pivots.assign(pts, piv), tiles.over(pts, per=20)
    assert over.side > 5
    t = range_query.targets(asked, piv)
    assert {tuple(r) for r in tiles.answers(index, t, over).collect()} == brute(p, q)
    mine = {(r["qid"], r["rank"], r["oid"]) for r in knn.nearest(tiles.best(index, t, over, 7), 7).collect()}
    best = {}
    for i, o, d in brute(p, q):
        best.setdefault(i, []).append((d, o))
    assert mine == {(i, n + 1, o) for i, found in best.items() for n, (_, o) in enumerate(sorted(found)[:7])}


def test_neighbours_are_not_joined_by_pieces(spark, d):
    for name in ("knn_8_batch", "knn_rounds_4_batch"):
        p = catalogue.queries()[name](spark, d)._jdf.queryExecution().executedPlan().toString()
        assert "FlatMapCoGroupsInArrow" in p and "SortMergeJoin" not in p


def test_growing_ranges_reach_far_queries(spark, points):
    p, q, pts, asked = points
    got = knn.incremental(pts, asked.select("qid", "x", "y"), pivots.choose(pts, 5), 3, 1.0).collect()
    assert len(got) == 3 * len(q)
    for i, a, b, _ in q:
        assert [r["oid"] for r in sorted((r for r in got if r["qid"] == i), key=lambda r: r["rank"])] == [o for _, o in sorted(((x - a) ** 2 + (y - b) ** 2, o) for o, x, y in p)[:3]]


def test_ranges_of_codes_are_not_counted_as_queries(spark, points, monkeypatch):
    from cellfleet.baselines import hashed

    p, q, pts, asked = points
    monkeypatch.setattr(hashed, "MOST_QUERIES", len(q))
    assert hashed.code_ranges(asked).count() > len(q)
    assert {tuple(r) for r in hashed.range_(hashed.snapshot(pts, 2), asked).collect()} == brute(p, q)
    monkeypatch.setattr(hashed, "MOST_QUERIES", len(q) // 2)
    with pytest.raises(ValueError):
        hashed.range_(hashed.snapshot(pts, 2), asked)


def test_ranges_are_joined_by_tiles(spark, d):
    for name in ("range_query_batch", "hierarchy_range_batch", "sql_surface_batch"):
        p = catalogue.queries()[name](spark, d)._jdf.queryExecution().executedPlan().toString()
        assert "ShuffledHashJoin" in p and "tile" in p and "SortMergeJoin" not in p


def test_objects_are_assigned_once(spark, points, monkeypatch):
    p, q, pts, asked = points
    monkeypatch.setattr(pivots, "stats", lambda index: pytest.fail("a pass over all objects for what a grid bounds"))
    got = {(r["qid"], r["rank"], r["oid"]) for r in knn.run(pts, asked, pivots.choose(pts, 5), 6).collect()}
    assert got == {(i, n + 1, o) for i, a, b, _ in q for n, (_, o) in enumerate(sorted(((x - a) ** 2 + (y - b) ** 2, o) for o, x, y in p)[:6])}


def test_growing_ranges_write_no_copy_of_the_objects(spark, points, monkeypatch):
    p, q, pts, asked = points
    written, cut = [], knn.cut
    monkeypatch.setattr(knn, "cut", lambda df: written.append(n := cut(df)) or n)
    knn.incremental(pts, asked.where("qid < 5").select("qid", "x", "y"), pivots.choose(pts, 5), 3, 100.0)
    assert written and max(df.count() for df in written) < len(p)


def test_candidates_are_drawn_once(spark, points, monkeypatch):
    p, q, pts, asked = points
    drawn = spark.sparkContext.accumulator(0)

    def count(batches):
        for b in batches:
            drawn.add(b.num_rows)
            yield b

    assert len(pivots.choose(pts.mapInArrow(count, pts.schema), 5)) == 5
    assert drawn.value == len(p)


def test_few_pivots_are_compared_without_a_grid():
    rng = np.random.default_rng(8)
    few, x, y = rng.integers(0, 60, (pivot_grid.FEW, 3)), rng.integers(-50, 110, 3_000), rng.integers(-50, 110, 3_000)
    ids = rng.permutation(1_000)[: len(few)]
    grid, but = pivot_grid.PivotGrid(ids, few[:, 1], few[:, 2]), rng.choice(ids, len(x))
    places = {j: (int(a), int(b)) for j, (_, a, b) in zip(ids.tolist(), few.tolist(), strict=True)}
    for without in (None, but):
        pid, d2 = grid.nearest(x, y, without)
        want = [min(((a - int(u)) ** 2 + (b - int(v)) ** 2, j) for j, (a, b) in places.items() if without is None or j != without[n]) for n, (u, v) in enumerate(zip(x, y, strict=True))]
        assert [(int(d), int(j)) for d, j in zip(d2, pid, strict=True)] == want
    pid, d2 = pivot_grid.PivotGrid([7], [3], [4]).nearest(x[:2], y[:2], np.array([7, 7]))
    assert pid.tolist() == [-1, -1] and (d2 == np.iinfo(np.int64).max).all()


def test_boxes_are_covered_by_few_squares():
    """A box's cover looks at squares of a thirty-second of its side, not at finer ones that are joined again."""
    import sys

    from cellfleet.baselines import hashed
    from cellfleet.functions import zorder

    rng, looked = random.Random(4), 0
    for side in (0, 1, 700, 90_000, 800_000):
        for _ in range(20):
            x0, y0 = rng.randrange(9_000_000), rng.randrange(9_000_000)
            found = hashed.cover(x0, y0, x0 + side, y0 + side)
            assert 1 <= len(found) <= hashed.CODE_RANGES and all(a <= b for a, b in found) and all(b < c for (_, b), (c, _) in zip(found, found[1:], strict=False))
            for x, y in [(x0, y0), (x0 + side, y0 + side), *((x0 + rng.randint(0, side), y0 + rng.randint(0, side)) for _ in range(50))]:
                z = sum((x >> i & 1) << 2 * i | (y >> i & 1) << 2 * i + 1 for i in range(zorder.BITS))
                assert any(a <= z <= b for a, b in found)
    lines = [0]
    sys.settrace(lambda frame, event, arg: (lambda f, e, a: lines.__setitem__(0, lines[0] + (e == "line"))) if frame.f_code is zorder.ranges.__code__ else None)
    try:
        hashed.cover(2_345_678, 3_456_789, 2_345_678 + 800_001, 3_456_789 + 800_001)
    finally:
        sys.settrace(None)
    assert 0 < lines[0] < 4_000


def test_a_batch_is_sent_once_for_its_ranges():
    import pyarrow as pa

    from cellfleet.baselines import hashed

    t = pa.table({"qid": [7, 7, 7, 3, 3, 9], "x": [1, 1, 1, 2, 2, 1], "y": [5] * 6, "r": [2.0] * 6, "lo": [0, 4, 8, 1, 5, 2], "hi": [1, 5, 9, 2, 6, 3]})
    qid, x, y, r, of, lo, hi = hashed.packed(pa.concat_tables([t.slice(0, 2), t.slice(2)]))
    assert qid.to_pylist() == [7, 3, 9] and x.tolist() == [1, 2, 1] and y.tolist() == [5] * 3 and r.tolist() == [2.0] * 3
    assert of.tolist() == [0, 0, 0, 1, 1, 2] and lo.tolist() == t.column("lo").to_pylist() and hi.tolist() == t.column("hi").to_pylist()
