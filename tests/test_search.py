import math
import random

import numpy as np
import pyarrow as pa
import pytest
from gridknn.functions.metrics import metric
from gridknn.operators import brute as brute_force
from gridknn.operators import joins, local, merge, probe
from gridknn.operators.density import cell_counts
from gridknn.operators.grid import GridSpec, bounds, suggest
from gridknn.plans import cost, pipeline
from pyspark.sql import functions as F

CELL1 = [(0.9, 0.8), (0.7, 0.4), (0.3, 0.3), (0.2, 0.7), (0.5, 0.1)]
CELL2 = [(1.3, 0.3), (1.7, 0.6)]
CELL3 = [(0.38, 1.5), (0.6, 1.5), (0.5, 1.65), (0.2, 1.8)]
CELL4 = [(1.2, 1.15), (1.6, 1.3), (1.8, 1.8), (1.4, 1.7)]
FOUR = CELL1 + CELL2 + CELL3 + CELL4


def train_of(spark, rows):
    d = len(rows[0][0]) if rows else 2
    return spark.createDataFrame([(i, *map(float, x), c) for i, (x, c) in enumerate(rows)], "tid long, " + ", ".join(f"t{i} double" for i in range(d)) + ", cls string")


def query_of(spark, rows, d=None):
    d = d or len(rows[0])
    return spark.createDataFrame([(i, *map(float, x)) for i, x in enumerate(rows)], "pid long, " + ", ".join(f"q{i} double" for i in range(d)))


def brute(queries, train, k, dist=math.dist, skip_self=False):
    return {i: [(t, d) for d, t in sorted((dist(q, x), t) for t, (x, _) in enumerate(train) if not (skip_self and t == i))][:k] for i, q in enumerate(queries)}


def lists(df):
    return {r.pid: [(x.tid, x.dist) for x in r.nn] for r in df.collect()}


def same(got, want):
    assert got.keys() == want.keys()
    for i, w in want.items():
        assert [t for t, _ in got[i]] == [t for t, _ in w], i
        assert [d for _, d in got[i]] == pytest.approx([d for _, d in w])


def test_four_cells_merging_costs_a_complete_point_more(spark):
    """One query is complete in its cell, the other short: merging makes both pay."""
    train, query = train_of(spark, [(x, "A") for x in FOUR]), query_of(spark, [(0.5, 1.5), (1.2, 0.8)])
    grid = GridSpec.pow2(2, 1, [0, 0], [2, 2])
    grow = pipeline.search(query, train, 3, grid)
    own = {r.pid: len(r.nn) for r in grow.own.collect()}
    assert own == {0: 3, 1: 2}
    same(lists(grow.final), brute([(0.5, 1.5), (1.2, 0.8)], [(x, "A") for x in FOUR], 3))
    assert cost.primitive_pairs(grid.assign(query, "q").filter("pid = 0"), grow.train).first().pairs == 4
    assert grow.probes.filter("pid = 0").count() == 0
    merged = pipeline.search(query, train, 3, grid, strategy="merge")
    q, t = cost.placed(merged)
    assert cost.primitive_pairs(q.filter("pid = 0"), t).first().pairs == 15
    same(lists(merged.final), brute([(0.5, 1.5), (1.2, 0.8)], [(x, "A") for x in FOUR], 3))


def test_touch_trap(spark):
    train = train_of(spark, [((0.999,), "A"), ((1.8,), "A"), ((2.99,), "B")])
    query, grid = query_of(spark, [(1.95,)]), GridSpec.equal([3], [0], [3])
    run = lambda **o: [t for t, _ in lists(pipeline.search(query, train, 2, grid, **o).final)[0]]
    assert run(growth="touch") == [1, 2]
    assert run() == run(growth="contain") == run(growth="points") == [1, 0]


def cloud(seed, n, d, skew):
    rng = random.Random(seed)
    return [tuple(rng.random() ** skew for _ in range(d)) for _ in range(n)]


@pytest.mark.parametrize(
    "d,grid,options",
    [
        (2, GridSpec.pow2(2, 3), {}),
        (2, GridSpec.pow2(2, 6), {"growth": "contain"}),
        (3, GridSpec.equal([3, 5, 2]), {"step": "continuous"}),
        (1, GridSpec.pow2(1, 5), {"growth": "points"}),
        (2, GridSpec.pow2(2, 3), {"strategy": "merge"}),
        (2, GridSpec.pow2(2, 0), {"physical": "pairs"}),
        (4, GridSpec.pow2(4, 1), {"physical": "arrow"}),
        (2, GridSpec.pow2(2, 4), {"growth_scope": "cell"}),
    ],
)
def test_exact_variants(spark, d, grid, options):
    train = [(x, "ABC"[i % 3]) for i, x in enumerate(cloud(1, 90, d, 3))]
    train += [(train[0][0], "B"), (train[0][0], "C")]  # repeated points
    queries = cloud(2, 60, d, 2) + [train[5][0], (0.0,) * d, (1.0,) * d, (1.7,) * d, (-0.4,) * d]
    k = 1 if not options else 7
    same(lists(pipeline.search(query_of(spark, queries), train_of(spark, train), k, grid, **options).final), brute(queries, train, k))


def test_lattice_ties_other_metrics_and_quantile_grid(spark):
    train = [((x, y), "A") for x in range(5) for y in range(5)]
    queries = [(1.5, 1.5), (2.0, 2.0), (0.0, 4.5)]
    q, t = query_of(spark, queries), train_of(spark, train)
    grid = GridSpec.quantile(t, [3, 3])
    norms = {"euclidean": math.dist, "manhattan": lambda a, b: sum(abs(x - y) for x, y in zip(a, b, strict=True)), "chebyshev": lambda a, b: max(abs(x - y) for x, y in zip(a, b, strict=True))}
    for name, norm in norms.items():
        same(lists(pipeline.search(q, t, 4, grid, metric=name).final), brute(queries, train, 4, norm))


def test_few_or_no_training_points(spark):
    grid, queries = GridSpec.pow2(2, 2), [(0.1, 0.1), (0.9, 0.9)]
    for n in (0, 1, 3):
        train = [(x, "A") for x in cloud(3, n, 2, 1)]
        out = pipeline.classify(query_of(spark, queries), train_of(spark, train), 3, grid, keep_neighbours=True).collect()
        assert {r.pid: len(r.nn) for r in out} == {0: n, 1: n}
        assert {r.cls_pred for r in out} == ({"A"} if n else {None})
    assert pipeline.classify(query_of(spark, [], 2), train_of(spark, [((0.5, 0.5), "A")]), 3, grid).collect() == []


def test_self_search_and_cloak(spark):
    pts = cloud(4, 50, 2, 1) + [(0.5, 0.5)] * 3
    frame = spark.createDataFrame([(i, *x, "A") for i, x in enumerate(pts)], "pid long, x0 double, x1 double, cls string")
    got = {}
    for r in joins.all_knn_self(frame, 2, 4, GridSpec.pow2(2, 3)).orderBy("pid", "rank").collect():
        got.setdefault(r.pid, []).append((r.tid, r.dist))
    want = brute(pts, [(x, "A") for x in pts], 4, skip_self=True)
    same(got, want)
    for r in joins.cloak(frame, 2, 4, GridSpec.pow2(2, 3)).collect():
        xs = [pts[t][0] for t, _ in want[r.pid]] + [pts[r.pid][0]]
        assert (r.lo0, r.hi0) == (min(xs), max(xs))


def test_radius_bounds_hold(spark):
    train, queries = [(x, "A") for x in cloud(5, 80, 2, 3)], cloud(6, 40, 2, 1)
    grid, k = GridSpec.pow2(2, 4), 5
    t = train_of(spark, train)
    counts = cell_counts(t, grid)
    assert counts.agg({"n": "sum"}).first()[0] == len(train)
    far = probe.safe_radius(grid.assign(query_of(spark, queries), "q"), counts, grid, k)
    low = {r.pid: r.need for r in probe.reach(far, counts, grid, k).collect()}
    high = {r.pid: r.need for r in probe.reach(far, counts, grid, k, contain=True).collect()}
    for i, nn in brute(queries, train, k).items():
        assert low[i] <= nn[-1][1] * (1 + 1e-9) and nn[-1][1] <= high[i] * (1 + 1e-9)


def test_merge_regions_by_level(spark):
    """A lone sparse cell, a chain of two levels, a sparse cell without queries, and nothing."""
    grid = GridSpec.pow2(2, 4)
    place = lambda c: ((c[0] + 0.5) / 16, (c[1] + 0.5) / 16)
    train, queries = [], []
    for x in range(16):
        for y in range(16):
            sparse = (x, y) == (0, 0) or (12 <= x and y < 2 and x < 14) or (x, y) == (0, 12)
            train += [(place((x, y)), "A")] * (0 if sparse else 3)
    queries += [place((0, 0)), place((12, 0)), place((13, 1))]
    t, q = grid.assign(train_of(spark, train), "t"), grid.assign(query_of(spark, queries), "q")
    found = merge.regions(t, q, grid, 3)
    out = merge.stats(found, grid).first()
    assert (out.merged_cells, out.largest_merged, out.merged_regions) == (20, 16, 2)
    assert out.pct_of_cells == pytest.approx(7.8125)


def test_small_helpers_and_invalid_settings(spark):
    t, q = train_of(spark, [((0.0, 3.0), "A"), ((2.0, -1.0), "A")]), query_of(spark, [(5.0, 0.0)])
    assert bounds(t, q, 2) == ((0.0, -1.0), (5.0, 3.0))
    assert suggest(1_900_000, 2, 7.2).splits == (512, 512) and suggest(100, 9) is None
    near = joins.within(q, t, 4.0, GridSpec.pow2(2, 2, [0, -1], [5, 3])).collect()
    assert [(r.pid, r.tid) for r in near] == [(0, 1)]
    for bad in ({"k": 0}, {"strategy": "merge", "growth": "touch"}, {"growth": "none"}, {"strategy": "merge", "grid": GridSpec.equal([3, 3])}, {"grid": GridSpec.pow2(3, 1)}):
        with pytest.raises(ValueError):
            pipeline.search(q, t, **({"k": 1, "grid": GridSpec.pow2(2, 1)} | bad))
    line = joins.nearest_1d(query_of(spark, [(0.1,), (2.6,), (9.0,)]), train_of(spark, [((0.0,), "A"), ((1.0,), "A"), ((4.0,), "A")]), 2)
    assert {r.pid: (r.tid, r.dist) for r in line.collect()} == {0: (0, pytest.approx(0.1)), 1: (2, pytest.approx(1.4)), 2: (2, 5.0)}


def test_nearest_on_a_line_reads_each_slice_once_in_either_direction(spark):
    """Repeated places and ties; no frame runs to the end of its slice, which costs the square of its rows."""
    points, queries = [0.0, 0.0, 1.0, 1.0, 1.0, 3.0, 7.0, 7.0], [-1.0, 0.0, 0.5, 1.0, 2.0, 2.0, 5.0, 7.0, 9.0]
    train = [((x,), "A") for x in points]
    for slices in (1, 3):
        line = joins.nearest_1d(query_of(spark, [(x,) for x in queries]), train_of(spark, train), slices)
        got = {r.pid: [(r.tid, r.dist)] for r in line.collect()}
        same(got, brute([(x,) for x in queries], train, 1))
        plan = line._jdf.queryExecution().optimizedPlan().toString()
        assert "currentrow$(), unboundedfollowing$()" not in plan


def test_within_pairs_points_of_one_place_only_as_rows_leave(spark):
    """Copies on both sides, more than an array holds: every pair is there, and the cell join sees places."""
    queries, points = [(0.1, 0.1)] * 1100 + [(0.5, 0.5), (0.9, 0.1)], [(0.1, 0.12)] * 3 + [(0.5, 0.5), (0.52, 0.5), (0.7, 0.9)]
    t = train_of(spark, [(x, "AB"[i % 2]) for i, x in enumerate(points)])
    near = joins.within(query_of(spark, queries), t, 0.03, GridSpec.pow2(2, 3))
    want = {(i, j, "AB"[j % 2]) for i, q in enumerate(queries) for j, x in enumerate(points) if math.dist(q, x) <= 0.03}
    rows = near.collect()
    assert {(r.pid, r.tid, r.cls) for r in rows} == want and len(rows) == len(want) == 3302
    assert "Generate" in near._jdf.queryExecution().optimizedPlan().toString().split("Join")[0]


def test_brute_force_neither_fans_queries_out_nor_shuffles_lists(spark):
    """Several blocks on both sides, copies, classes without a name, and no points at all."""
    queries = cloud(7, 1500, 2, 1) + [(0.5, 0.5)] * 3
    train = [(x, "AB"[i % 2] if i % 5 else None) for i, x in enumerate(cloud(8, 5000, 2, 3) + [(0.5, 0.5)] * 9)]
    q, t = query_of(spark, queries), train_of(spark, train)
    found = pipeline.search(q, t, 4, strategy="brute").final
    same(lists(found), brute(queries, train, 4))
    assert {x.cls == train[x.tid][1] for r in found.collect() for x in r.nn} == {True}
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert "Generate" not in plan and "Aggregate" not in plan
    assert lists(pipeline.search(q.filter("pid < 2"), t.filter("false"), 4, strategy="brute").final) == {0: [], 1: []}
    own = [(i, *x) for i, (x, _) in enumerate(train[-40:])]
    frame = spark.createDataFrame([(*r, None) for r in own], "pid long, x0 double, x1 double, cls string")
    got = lists(joins.all_knn_self(frame, 2, 10, None, strategy="brute").groupBy("pid").agg(F.array_sort(F.collect_list(F.struct("dist", "tid"))).alias("nn")))
    same(got, brute([x for x, _ in train[-40:]], train[-40:], 10, skip_self=True))


@pytest.mark.parametrize("options", [{}, {"strategy": "brute"}, {"strategy": "merge"}, {"growth": "points"}])
def test_queries_at_one_place_are_searched_once_and_all_answered(spark, monkeypatch, options):
    train = [(x, "ABC"[i % 3]) for i, x in enumerate(cloud(9, 60, 2, 2))]
    queries = (cloud(10, 12, 2, 1) + [(0.0, 0.3)]) * 3 + [(-0.0, 0.3)]
    asked, search = [], pipeline.search
    monkeypatch.setattr(pipeline, "search", lambda query, *a, **o: asked.append(query.count()) or search(query, *a, **o))
    q, t, grid = query_of(spark, queries), train_of(spark, train), GridSpec.pow2(2, 2)
    rows = pipeline.all_knn(q, t, 5, grid, **options).collect()
    got = {}
    for r in sorted(rows, key=lambda r: (r.pid, r["rank"])):
        got.setdefault(r.pid, []).append((r.tid, r.dist))
    same(got, brute(queries, train, 5))
    assert len(rows) == 5 * len(queries)
    votes = {r.pid: r.cls_pred for r in pipeline.classify(q, t, 5, grid, **options).collect()}
    assert len(votes) == len(queries) and len({votes[i] for i in range(0, 39, 13)}) == 1
    assert asked == [13, 13]


def test_large_blocks_meet_only_near_tiles(monkeypatch):
    """Queries of a cell with many points don't go through all of them; ties and repeated places stay as they are."""
    rng = np.random.default_rng(4)
    t = [np.round(rng.random(6000), 2), np.round(rng.random(6000), 3)]
    q = [np.append(rng.random(700), t[0][:50]), np.append(rng.random(700), t[1][:50])]
    tid, pid = np.arange(6000), np.append(np.arange(700) + 10_000, np.arange(50))
    asked, dist = [], local._numpy_dist
    monkeypatch.setattr(local, "_numpy_dist", lambda m, a, b: asked.append(len(a[0]) * len(b[0])) or dist(m, a, b))
    for m in (metric("euclidean"), metric("chebyshev")):
        whole = dist(m, q, t)
        for r, skip in ((None, False), (None, True), (np.full(750, 0.03), False)):
            asked.clear()
            got = {}
            for at, sizes, dists, take in local._block_lists(q, pid, r, t, tid, local._tiles_of(t, tid, q, []), 7, m, skip):
                for i, ds, js in zip(at, np.split(dists, np.cumsum(sizes)[:-1]), np.split(take, np.cumsum(sizes)[:-1]), strict=True):
                    got[i] = list(zip(ds, js, strict=True))
            assert sum(asked) < whole.size / 2
            for i in range(0, 750, 10):
                ok = [(d, j) for j, d in enumerate(whole[i]) if not (skip and j == pid[i]) and (r is None or d <= 0.03 * (1 + 1e-9) + 1e-12)]
                assert got[i] == sorted(ok)[:7], i


def test_brute_force_takes_exact_distances_of_few_pairs_only(monkeypatch):
    """All pairs are met in single precision; only those it can't rule out are in double, far from the origin too."""
    rng = np.random.default_rng(5)
    for shift in (0.0, 1e6):
        t, q = ([np.round(rng.random(n), 3) + shift for _ in range(2)] for n in (4096, 300))
        qs = pa.StructArray.from_arrays([pa.array(np.arange(300)), *map(pa.array, q)], names=["pid", "q0", "q1"])
        asked, dist = [], brute_force._numpy_dist
        monkeypatch.setattr(brute_force, "_numpy_dist", lambda m, a, b, dist=dist, asked=asked: asked.append(len(a[0]) * len(b[0])) or dist(m, a, b))
        best = brute_force._Nearest(qs, 2, 5, metric("euclidean"), False)
        for x in (0, 2048):
            best.meet([c[x : x + 2048] for c in t], np.arange(x, x + 2048), np.zeros(2048, int))
        assert sum(asked) <= 300 * 2048
        monkeypatch.undo()
        whole = dist(metric("euclidean"), q, t)
        for i in range(300):
            assert list(zip(best.dist[i], best.tid[i], strict=True)) == sorted(zip(whole[i], range(4096), strict=True))[:5]
