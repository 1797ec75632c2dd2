"""Hand fixtures, the definition by brute force on random pairs, and invariants."""

import itertools

import numpy as np
import pytest

from comovement import points
from comovement.engine import SubtrajectoryJoin
from comovement.operators.refine import components_of
from comovement.params import JoinParams
from comovement.plans import partitioning
from comovement.sources.scratch import written


def pts(spark, r, s):
    rows = [(1, t, float(x), float(y), k) for k, (t, x, y) in enumerate(r)] + [(2, t, float(x), float(y), 100 + k) for k, (t, x, y) in enumerate(s)]
    return spark.createDataFrame(rows, "traj long, t long, x double, y double, pid long")


LINE = [(t, t, 0) for t in range(8)]
BESIDE = [(t, t, 0.5 if t != 4 else 100) for t in range(8)]
BREAKS = [(t, t, 50 if t in (0, 5) else 0) for t in range(9)]
CASES = {
    "H1a": (LINE, BESIDE, (1, 0, 0), {(0, 3, 0, 3), (5, 7, 5, 7)}),
    "H1b": (LINE, BESIDE, (1.5, 1, 0), {(0, 4, 0, 3), (4, 7, 5, 7)}),
    "H1c": (LINE, BESIDE, (1.5, 1, 5), {(0, 4, 0, 3)}),
    "H1d": (LINE, BESIDE, (1.5, 1, 4), {(0, 4, 0, 3), (4, 7, 5, 7)}),
    "H1e": (LINE, BESIDE, (1.5, 1, 6), set()),
    "H2": (BREAKS, [(t, t, 0) for t in range(9)], (0.5, 0, 0), {(1, 4, 1, 4), (6, 8, 6, 8)}),
    "H2b": (BREAKS, [(t, t, 0) for t in range(9)], (0.5, 0, 3), {(1, 4, 1, 4)}),
    "H3": ([(0, 0, 0), (1, 9, 9), (2, 0, 0)], [(0, 0, 0), (1, 5, 5), (2, 0, 0)], (1, 0, 0), set()),
    "H4": ([(0, 0, 0), (10, 0, 0)], [(2, 3, 4), (12, 3, 4)], (5, 2, 12), {(0, 1, 0, 1)}),
    "H4b": ([(0, 0, 0), (10, 0, 0)], [(2, 3, 4), (12, 3, 4)], (5, 2, 13), set()),
    "H4c": ([(0, 0, 0), (10, 0, 0)], [(2, 3, 4), (12, 3, 4)], (4.999, 2, 0), set()),
    "H5": ([(t, 0, 0) for t in range(0, 13, 2)], [(t, 0, 0) for t in range(0, 13, 3)], (1, 1, 0), {(0, 6, 0, 4)}),
    "H6": ([(t, 0, 0) for t in range(6)], [(t, 0, 0) if t != 3 else (3, 9, 9) for t in range(6)], (1, 1, 3), {(0, 3, 0, 2), (3, 5, 4, 5)}),
}


@pytest.mark.parametrize("case", CASES)
@pytest.mark.parametrize("method", ["basic", "indexed"])
def test_hand_fixtures(spark, case, method):
    r, s, p, expected = CASES[case]
    found = SubtrajectoryJoin(JoinParams(*p), method, n_slabs=5).run(pts(spark, r, s)).collect()
    assert {(m.r_from - 1, m.r_to - 1, m.s_from - 1, m.s_to - 1) for m in found} == expected


def brute(edges):
    """Maximal mutually covering pieces of at least two points a side, by enumeration."""
    covers = []
    rs, ss = sorted({r for r, _ in edges}), sorted({s for _, s in edges})
    for a, b in itertools.combinations(rs, 2):
        for c, d in itertools.combinations(ss, 2):
            own = [(r, s) for r, s in edges if a <= r <= b and c <= s <= d]
            if {r for r, _ in own} == set(range(a, b + 1)) and {s for _, s in own} == set(range(c, d + 1)):
                covers.append((a, b, c, d))
    inside = lambda x, y: x != y and y[0] <= x[0] and y[1] >= x[1] and y[2] <= x[2] and y[3] >= x[3]
    return {x for x in covers if not any(inside(x, y) for y in covers)}


def test_components_are_maximal_covers():
    rng = np.random.default_rng(1)
    for _ in range(500):
        n = int(rng.integers(3, 8))
        edges = sorted({(int(r), int(s)) for r, s in rng.integers(0, n, (int(rng.integers(2, 3 * n)), 2))})
        e = np.array(edges)
        comp = components_of(e[:, 0], e[:, 1])
        found = set()
        for c in np.unique(comp):
            own = e[comp == c]
            piece = (*map(int, (own[:, 0].min(), own[:, 0].max(), own[:, 1].min(), own[:, 1].max())),)
            if piece[1] > piece[0] and piece[3] > piece[2]:
                found.add(piece)
        assert found == brute(edges)


def test_methods_agree_whatever_the_slabs(spark, sf_dir):
    from comovement.operators.pointjoin import joining_pairs
    from comovement.sources.tables import table

    numbered = points.with_sequence(points.companions(points.from_events(table(spark, sf_dir, "events")))).cache()
    params = JoinParams(20.0, 6 * 3_600_000_000)
    rows = None
    for method, n in (("basic", 1), ("basic", 64), ("prepart", 7), ("indexed", 16), ("sweep", 9), ("gridtile", 0), ("slab_nested_loop", 5)):
        found = sorted(map(tuple, joining_pairs(numbered, None, params, method, n_slabs=n).collect()))
        assert len(found) == len(set(found))
        rows = rows or found
        assert found == rows
    assert {(s, j, r, i) for r, i, _, s, j, _ in rows} == {(r, i, s, j) for r, i, _, s, j, _ in rows}


def test_narrow_slabs_warn(spark):
    line = spark.createDataFrame([(1, t, 0.0, 0.0, t) for t in (0, 10, 90)], "traj long, t long, x double, y double, pid long")
    gap = points.summary(line).first().max_gap
    with pytest.warns(UserWarning, match="narrower"):
        partitioning.uniform(line, 9, gap)
    assert partitioning.uniform(line, 1, gap).count == 1


def test_no_nested_loops(spark, sf_dir):
    from comovement.operators.pointjoin import joining_pairs
    from comovement.sources.tables import table

    numbered = points.with_sequence(points.from_events(table(spark, sf_dir, "events")))
    for method in ("slab_nested_loop", "basic", "prepart", "indexed", "gridtile"):
        plan = joining_pairs(numbered, None, JoinParams(10.0, 7_200_000_000), method)._jdf.queryExecution().executedPlan().toString()
        assert "NestedLoop" not in plan and "Cartesian" not in plan


def test_empty_single_and_bad_points(spark):
    rows = [(1, 0, 0.0, 0.0, 1), (1, 1, None, 0.0, 2), (1, 1, float("nan"), 0.0, 3), (None, 1, 0.0, 0.0, 4)]
    df = spark.createDataFrame(rows, "traj long, t long, x double, y double, pid long")
    good = points.from_columns(df, "traj", "t", "x", "y", "pid")
    assert good.count() == 1
    for p in (good, good.where("false")):
        for method in ("basic", "prepart", "indexed", "gridtile"):
            assert SubtrajectoryJoin(JoinParams(1.0, 1), method).run(p).count() == 0


def test_slab_lookup_matches_bisect(spark):
    import bisect

    bounds = (3, 4, 10, 11, 500, 501, 502, 10_000)
    slabs = partitioning.Slabs(bounds)
    df = spark.range(-5, 10_050).selectExpr("id t")
    assert all(r.slab == bisect.bisect_right(bounds, r.t) for r in df.withColumn("slab", slabs.of(df.t)).collect())


def points_of(spark, sf_dir, companions=True):
    from comovement.sources.tables import table

    pts_ = points.from_events(table(spark, sf_dir, "events"))
    return points.companions(pts_) if companions else pts_


@pytest.mark.parametrize("eps_t", [0, 7_200_000_000, 200 * 3_600_000_000])
def test_prepared_store_reads_own_rows_and_what_its_tolerance_meets(spark, sf_dir, tmp_path, eps_t):
    from comovement.sources import store

    pts_ = points_of(spark, sf_dir, False)
    store.prepare(pts_, str(tmp_path / "s"), 9)
    back, params = store.load(spark, str(tmp_path / "s")), JoinParams(10.0, eps_t)
    assert back.slabs.count == 9 and back.points(spark).count() == pts_.count()
    rows = store.halo(spark, back, params)
    wide = partitioning.expand(pts_.select("traj", "t", "pid"), back.slabs, eps_t).select("pid", "slab", "is_home")
    found = sorted(map(tuple, rows.select("pid", "slab", "is_home").collect()))
    assert found == sorted(map(tuple, wide.collect()))
    times = rows.select("slab", "t").collect()
    assert all(x.slab != y.slab or x.t <= y.t for x, y in zip(times, times[1:]))


def test_slabs_follow_the_size_of_the_points(spark, sf_dir, tmp_path, monkeypatch):
    from comovement.sources import store

    pts_ = points_of(spark, sf_dir, False)
    assert store.prepare(pts_, str(tmp_path / "a")).slabs.count == store.LEAST_SLABS
    monkeypatch.setattr(store, "BLOCK_BYTES", 20 * store.ROW_BYTES)
    many = store.prepare(pts_, str(tmp_path / "b"))
    assert 45 <= many.slabs.count <= 51
    assert SubtrajectoryJoin(JoinParams(20.0, 6 * 3_600_000_000, 13 * 3_600_000_000), "indexed").run(many.points(spark), None, many).count() == SubtrajectoryJoin(JoinParams(20.0, 6 * 3_600_000_000, 13 * 3_600_000_000), "basic").run(pts_).count()


def plan_of(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("options", [{}, {"spatial_index": False}, {"traj_index": False}])
def test_join_on_a_store_with_ties(spark, tmp_path, options):
    """Equal times, repeated points and several trajectories at one place: numbering decides by pid."""
    rng = np.random.default_rng(5)
    rows = [(int(rng.integers(0, 8)), int(rng.integers(0, 60)), float(rng.integers(0, 12)), float(rng.integers(0, 12)), i) for i in range(600)]
    pts_ = spark.createDataFrame(rows, "traj long, t long, x double, y double, pid long")
    for params in (JoinParams(2.0, 3), JoinParams(2.0, 0, metric="chebyshev"), JoinParams(0.0, 4, metric="manhattan")):
        path = str(tmp_path / f"{params.eps_sp}{params.eps_t_us}")
        engine = SubtrajectoryJoin(params, "indexed", n_slabs=7, cap_fraction=0.02, **options)
        prepared = engine.prepare(pts_, path)
        found = engine.pairs(prepared.points(spark), None, prepared)
        wanted = SubtrajectoryJoin(params, "basic").pairs(points.with_sequence(pts_))
        assert sorted(map(tuple, found.collect())) == sorted(map(tuple, wanted.collect())) and wanted.count() > 0
        if not options:
            assert "Exchange" not in plan_of(found) and "Join" not in plan_of(found)


def test_exact_refine_is_one_shuffle_and_one_sort(spark, sf_dir):
    from comovement.operators import pointjoin, refine

    params = JoinParams(20.0, 6 * 3_600_000_000, 13 * 3_600_000_000)
    jp = written(pointjoin.joining_pairs(points.with_sequence(points_of(spark, sf_dir)), None, params), "jp")
    plan = plan_of(refine.maximal_matches(jp, params))
    assert plan.count("Sort [") == 1 and plan.count("Exchange ") == 1 and "Window" not in plan
    plan = plan_of(refine.windowed(jp.withColumn("r_next_t", jp.r_t), spark.createDataFrame([], "traj long, seq long, t long"), spark.createDataFrame([], "r_traj long, s_traj long, s_seq long"), params))
    assert plan.count("Sort [") == 1 and plan.count("Exchange ") == 1 and "Window" not in plan


def test_kernels_do_not_depend_on_batches(spark, sf_dir):
    """Frames of three rows give what whole partitions give."""
    from comovement.operators import pointjoin

    params = JoinParams(20.0, 6 * 3_600_000_000, 13 * 3_600_000_000)
    numbered = written(points.with_sequence(points_of(spark, sf_dir)), "points")
    run = lambda form: sorted(map(tuple, SubtrajectoryJoin(params, "basic", refine=form).run(numbered).collect()))
    sweep = lambda: sorted(map(tuple, pointjoin.joining_pairs(numbered, None, params, "sweep").collect()))
    wanted = [run("exact"), run("windowed_span"), run("windowed_lifespan"), sweep()]
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, "3")
    try:
        assert [run("exact"), run("windowed_span"), run("windowed_lifespan"), sweep()] == wanted and all(wanted)
    finally:
        spark.conf.set(key, before)


def test_breaks_and_misses_decide(spark):
    """Without its misses, or with a break amid a run, the windowed refine gives other runs."""
    from comovement.operators import classify, refine

    params = JoinParams(1.0, 1, 0)
    line = [(1, t, float(t), 0.0, t) for t in range(8)] + [(2, t, float(t), 100.0 if t == 4 else 0.5, 100 + t) for t in range(8)]
    numbered = points.with_sequence(spark.createDataFrame(line, "traj long, t long, x double, y double, pid long"))
    jp = SubtrajectoryJoin(JoinParams(1.5, 1, 0), "basic").pairs(numbered, carry=("next_t",))
    misses, none = classify.miss_positions(numbered, jp), spark.createDataFrame([], "traj long, seq long, t long")
    bp = classify.breaking_points(numbered, jp)
    run = lambda b, m: sorted((r.r_traj, r.r_from, r.r_to, r.s_from, r.s_to) for r in refine.windowed(jp, b, m, params).collect() if r.r_traj == 1)
    assert run(bp, misses) == [(1, 1, 5, 1, 4), (1, 5, 8, 6, 8)]
    assert run(bp, misses.where("false")) == [(1, 1, 8, 1, 8)]
    more = bp.unionByName(spark.createDataFrame([(1, 3, 2)], "traj long, seq long, t long"))
    assert run(none, misses) == run(bp, misses) and run(more, misses) != run(bp, misses)
    candidates = classify.candidate_misses(numbered, jp.drop("r_next_t")).select("r_traj", "s_traj", "s_seq").distinct()
    assert sorted(map(tuple, candidates.collect())) == sorted(map(tuple, misses.collect()))


def test_cell_table_equals_columns(spark):
    from comovement.plans import quadtree
    from pyspark.sql import functions as F

    rng = np.random.default_rng(9)
    xy = np.concatenate([rng.normal(0, 1, (400, 2)), rng.normal(5, 0.1, (400, 2))])
    df = spark.createDataFrame([(i, float(x), float(y)) for i, (x, y) in enumerate(xy)], "id long, x double, y double")
    tree = quadtree.build(df, 0.02)
    table = quadtree.CellTable(tree)
    rows = df.select("id", tree.home_cell(F.col("x"), F.col("y")).alias("h"), tree.touched_cells(F.col("x"), F.col("y"), 0.3).alias("m")).orderBy("id").collect()
    keys = [quadtree._key(*leaf) for leaf in tree.leaves]
    assert [r.h for r in rows] == [keys[k] for k in table.home(*xy.T)]
    point, leaf = table.touched(*xy.T, 0.3)
    assert sorted((r.id, k) for r in rows for k in r.m) == sorted((int(p), keys[k]) for p, k in zip(point, leaf))
    with pytest.raises(ValueError):
        quadtree.build(df, 0.0001, most_leaves=20)
