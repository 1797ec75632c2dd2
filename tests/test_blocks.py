"""Whole trajectory pairs in blocks: the answers of the pairs' own operators, and no pair in a shuffle."""

import os
import time

import numpy as np
import pytest

from comovement import points, registry
from comovement.engine import SubtrajectoryJoin
from comovement.operators import apps, blocks, classify, pointjoin, refine, semantics
from comovement.params import HOUR, SET_A, SET_B, JoinParams
from comovement.plans import quadtree
from comovement.sources import store
from comovement.sources.scratch import scratch


def rows(df):
    return sorted(tuple(r) for r in df.select(*sorted(df.columns)).collect())


@pytest.fixture(scope="module")
def odd(spark):
    """Uneven trajectories with ties in time, copies, numbers that are not consecutive, and one that is far away."""
    rng = np.random.default_rng(5)
    n = 900
    traj = rng.choice([-3, 0, 1, 2, 7, 8, 40], n, p=[0.4, 0.2, 0.1, 0.1, 0.1, 0.05, 0.05])
    found = [(int(k), int(t), float(x), float(y), i) for i, (k, t, x, y) in enumerate(zip(traj, rng.integers(-500, 500, n), rng.integers(0, 9, n) / 2, rng.integers(0, 5, n)))]
    found += [(99, t, 1e9, 0.0, 10_000 + t) for t in range(3)] + [(k + 100, t, x, y, i + 20_000) for k, t, x, y, i in found]
    numbered = points.with_sequence(spark.createDataFrame(found, "traj long, t long, x double, y double, pid long"))
    return numbered.where("pmod(pid, 17) <> 3").persist()


PARAMS = [JoinParams(1.0, 5), JoinParams(1.5, 0), JoinParams(1.0, 6, 30), JoinParams(0.5, 9, 40, "manhattan", 1), JoinParams(2.0, 3, 6, "chebyshev", 3)]


@pytest.mark.parametrize("params", PARAMS)
@pytest.mark.parametrize("cells", [False, True])
def test_matches_as_from_pairs(spark, odd, params, cells, monkeypatch):
    monkeypatch.setattr(blocks, "CHUNK", 500)  # chunks of single trajectories, and turns
    tree = quadtree.build(odd, 0.05) if cells else None
    jp = pointjoin.joining_pairs(odd, None, params, "naive").where("r_traj < s_traj")
    expected = rows(refine.maximal_matches(jp, params))
    assert len(expected) > 50
    for groups in (1, 3):
        assert rows(blocks.matches(odd, params, tree, groups)) == expected


@pytest.mark.parametrize("bits", [None, 28])
def test_rounds_of_matches(spark, odd, bits, monkeypatch):
    """Only components that a side splits are sorted again; numbers that do not fit in a key are sorted as columns."""
    side, params = side_of(odd), JoinParams(1.0, 6, 30)
    r, s = (np.concatenate(f) for f in zip(*blocks.chunks(side, side, True, params, None)))
    expected = rows(refine.maximal_matches(pointjoin.joining_pairs(odd, None, params, "naive").where("r_traj < s_traj"), params))
    if bits:
        monkeypatch.setattr(blocks, "_bits", lambda n: bits)
    sizes, repeat = [], np.repeat
    monkeypatch.setattr(blocks.np, "repeat", lambda a, n, **k: sizes.append(len(out := repeat(a, n, **k))) or out)
    found = blocks.matches_of(side, side, r, s, params)
    monkeypatch.undo()
    assert sorted(map(tuple, found[sorted(found.columns)].to_numpy().tolist())) == expected
    assert sizes[-1] < found["n_r"].sum()  # of all pairs of the matches, some are in the last round


def test_lifespan_is_asked_in_the_rounds(spark, odd):
    """Matches of a least lifespan are those of all that last so long; shorter ones are not made."""
    params = JoinParams(1.0, 6, 30)
    m = blocks.matches(odd, params, None, 2).persist()
    for least in (0, 25, 60):
        found = rows(blocks.matches(odd, params, None, 2, least_us=least))
        assert found == rows(m.where(f"lifespan_us >= {least}")) != []
    assert len(found) < m.count()


def test_nothing(spark, odd):
    none = odd.where("false")
    assert blocks.matches(none, SET_A).count() == 0
    assert blocks.matches(odd.where("traj = 0"), SET_A).count() == 0


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name", ["match_exact_indexed", "match_exact_auto", "match_exact_prepart", "match_exact_stored", "match_directed", "app_rideshare", "app_suspicious", "app_topk_partners", "app_longest", "gap_definition_window"])
def test_no_pair_is_shuffled(spark, sf_dir, name):
    """The points are shuffled, by trajectory and by block; pairs are found and refined in one task, without a join."""
    found = plan(registry.QUERIES[name](spark, sf_dir))
    assert "Join" not in found and "mapInPandas" in found.replace("MapInPandas", "mapInPandas")


def test_radii_in_one_join(spark, sf_dir):
    """One join for all radii, with the counts of a join each."""
    from comovement import workloads

    pts = registry.events(spark, sf_dir)
    found = workloads.vary_eps_sp(pts)
    assert "Join" not in plan(found)
    assert rows(found) == sorted((pointjoin.joining_pairs(pts, None, JoinParams(e, 2 * HOUR), "basic").count(), e)[::-1] for e in workloads.EPS_SP)


def test_intermediate_counts(spark, odd):
    """Pairs, breaks and misses counted in blocks, as counted from the pairs; the pairs are not joined a second time."""
    from comovement import metrics

    params = JoinParams(1.0, 6)
    jp = pointjoin.joining_pairs(odd, None, params, "naive")
    expected = (odd.count(), jp.count(), classify.breaking_points(odd, jp).count(), classify.candidate_misses(odd, jp).count())
    found = metrics.intermediate(odd, params, quadtree.build(odd, 0.05))
    assert tuple(found.first())[:4] == expected
    assert "SortMergeJoin" not in plan(found)


def side_of(pts):
    own = pts.select("traj", "seq", "t", "x", "y").toPandas().sort_values(["traj", "seq"])
    return blocks.Side(*[own[c].to_numpy() for c in own.columns])


@pytest.mark.parametrize("bits", [None, 28])
def test_misses_are_counted(odd, monkeypatch, bits):
    """Misses are counted from sorted pairs, with no frame of them, and points that join as bits, 64 in a row."""
    params = JoinParams(1.0, 6)
    a, b = side_of(odd.where("traj < 50")), side_of(odd.where("traj >= 50"))
    if bits:
        monkeypatch.setattr(blocks, "_bits", lambda n: bits)  # pairs of trajectories do not fit beside the numbers
    for one, other in ((a, b), (b, a), (a, a)):
        r, s = (np.concatenate(f) for f in zip(*blocks.chunks(one, other, one is other, params, None)))
        frames = list(blocks.misses_of(one, other, r, s))
        near = {p: set(zip(r[one.code[r] == p].tolist(), s[one.code[r] == p].tolist())) for p in range(len(one.names))}
        expected = set()
        for p, pairs in near.items():
            for own, far, pairs in ((one, other, pairs), (other, one, {(v, q) for q, v in pairs})):
                hit = {(own.code[q], far.code[v], far.seq[v]) for q, v in pairs}
                expected |= {(own.names[own.code[q]], own.seq[q], far.names[far.code[v]], far.seq[v] + d) for q, v in pairs for d in (-1, 1) if 1 <= far.seq[v] + d <= far.last[far.code[v]] and (own.code[q], far.code[v], far.seq[v] + d) not in hit}
        found = [tuple(m) for f in frames for m in f.to_numpy()]
        assert len(found) == len(set(found)) == blocks.count_misses(one, other, r, s) > 100 and set(found) == expected
    monkeypatch.setattr(blocks, "misses_of", None)
    sent = list(blocks._tally(a, b, blocks.chunks(a, b, False, params, None)))
    assert sum(map(len, sent)) == 1 + sum(-(-len(side.t) // 64) for side in (a, b))
    assert sum(int(f["n_miss"].sum()) for f in sent) > 100


def test_candidate_misses_in_blocks(spark, odd, sf_dir):
    params = JoinParams(1.0, 6)
    expected = rows(classify.candidate_misses(odd, pointjoin.joining_pairs(odd, None, params, "naive")))
    for tree in (None, quadtree.build(odd, 0.05)):
        assert rows(blocks.candidate_misses(odd, params, tree, 2)) == expected
    assert "Join" not in plan(registry.QUERIES["miss_candidates"](spark, sf_dir))


def test_slab_plan_follows_the_table(spark, sf_dir):
    total = registry.raw(spark, sf_dir).count() * 48
    found = registry.QUERIES["slab_plan"](spark, sf_dir).collect()
    assert total and {r.total_bytes for r in found} == {total} and [r.slabs for r in found] == [max(1, -(-total // r.block_bytes)) for r in found]


def test_network_shuffles_no_steps(spark, sf_dir):
    """Exchanges: numbering and blocks, pieces by trajectory, counts by edge; none of (edge, trajectory, partner)."""
    found = registry.QUERIES["app_network"](spark, sf_dir)
    shuffled = [line for line in plan(found).splitlines() if "Exchange hashpartitioning" in line]
    assert shuffled and not any("partner" in line and "from_x" in line for line in shuffled)


@pytest.mark.parametrize("params", [JoinParams(1.0, 6, 30), JoinParams(0.5, 9, 40, "manhattan", 1)])
def test_network_in_blocks(spark, odd, sf_dir, params, monkeypatch):
    """The edges of the pairs in blocks as of all matches; no match leaves its block, so none is sent to the driver for a join."""
    monkeypatch.setattr(blocks, "CHUNK", 500)
    whole = odd.selectExpr("traj", "seq", "t", "x * 7 - 9 x", "y * 7 y", "lead(x) over (partition by traj order by seq) * 7 - 9 next_x", "lead(y) over (partition by traj order by seq) * 7 next_y")
    m = blocks.matches(odd, params, None, 1).persist()
    expected = rows(apps.shared_segments(m, whole, 20.0))
    each, schema = apps.shared_segments_each(20.0)

    def moved(frames, a, b):
        for side in {id(a): a, id(b): b}.values():
            side.x, side.y = side.x * 7 - 9, side.y * 7
        yield from each(frames, a, b)

    for groups in (1, 3):
        found = blocks.matches(odd, params, None, groups, lambda frames, a, b: moved(list(frames), a, b), schema, sides=True)
        assert rows(apps.segments_of_blocks(found)) == expected != []
    assert "Join" not in plan(registry.QUERIES["app_network"](spark, sf_dir))


def shuffled(df):
    return [line for line in plan(df).splitlines() if "Exchange hashpartitioning" in line]


@pytest.mark.parametrize("name", ["app_rideshare", "app_suspicious", "app_topk_partners"])
def test_no_pair_of_trajectories_is_shuffled(spark, sf_dir, name):
    """Matches of a pair of trajectories stand in one frame, so they are put together there."""
    found = shuffled(registry.QUERIES[name](spark, sf_dir))
    assert found and not any("s_traj" in line.split("ENSURE")[0] for line in found)


def test_uses_in_blocks(spark, odd, monkeypatch):
    """The uses of matches in blocks, parts of a block put together, as of all matches."""
    monkeypatch.setattr(blocks, "CHUNK", 500)
    monkeypatch.setattr(apps, "HELD", 3)
    params = JoinParams(1.0, 6, 30)
    m = blocks.matches(odd, params, None, 1).persist()
    in_blocks = lambda form: blocks.matches(odd, params, None, 2, *form)
    assert rows(apps.rideshare(m, 90)) == rows(in_blocks(apps.rideshare_each(90))) != []
    assert rows(apps.suspicious(m, 25, 3)) == rows(in_blocks(apps.suspicious_each(25, 3))) != []
    assert rows(apps.top_partners(refine.mirrored(m), 2)) == rows(apps.top_of_blocks(in_blocks(apps.top_partners_each(2)), 2)) != []
    best = in_blocks(apps.longest_each(4))
    assert best.count() <= 3 * 4 < m.count()
    assert [r.lifespan_us for r in apps.longest(best, 4).collect()] == [r.lifespan_us for r in apps.longest(m, 4).collect()]


def test_gap_is_counted_in_blocks(spark, sf_dir):
    """A block gives one row, not its matches."""
    from comovement import metrics

    expected = metrics.gap(registry.matched(spark, sf_dir, SET_B), SET_B)
    found = registry.QUERIES["gap_definition_window"](spark, sf_dir)
    assert "lifespan_us" not in plan(found) and rows(found) == rows(expected)


def test_decorated_by_trajectory(spark, sf_dir):
    """Matches are counted by trajectory before the customers are joined: no match is shuffled."""
    before_join = plan(registry.QUERIES["op_decorate"](spark, sf_dir)).split("Join", 1)[1]
    assert "partial_sum(lifespan_us" in before_join


def test_match_files_are_written_where_rows_are(spark, tmp_path):
    """Rows are not shuffled into one task for each bucket."""
    from comovement.sources.tables import MATCH_COLUMNS, write_matches

    m = spark.range(0, 96, 1, 3).selectExpr(*[f"id * 16 {c}" for c in MATCH_COLUMNS])
    write_matches(m, str(tmp_path / "m"))
    assert len(list((tmp_path / "m" / "r_bucket=0").glob("part-*.parquet"))) == 3
    assert sorted(r.r_traj for r in spark.read.parquet(str(tmp_path / "m")).collect()) == [16 * k for k in range(96)]


def test_definition_in_blocks(spark, odd, sf_dir, monkeypatch):
    """The tests of the definition on frames, as of the pairs' own, on matches of which some are cut, widened or repeated."""
    monkeypatch.setattr(semantics, "PIECE", 50)
    params = JoinParams(1.0, 6, 30)
    jp = pointjoin.joining_pairs(odd, None, params, "naive").where("r_traj < s_traj").persist()
    m = refine.maximal_matches(jp, params)
    m = m.unionByName(m.where("r_from % 3 = 0").withColumn("r_from", m.r_from + 1)).unionByName(m.where("s_to % 3 = 0").withColumn("s_to", m.s_to + 1)).unionByName(m.where("s_to % 5 = 0").withColumn("lifespan_us", m.lifespan_us - 20)).persist()
    key = ["r_traj", "s_traj", "r_from", "r_to", "s_from", "s_to", "lifespan_us"]
    frame = m.toPandas()
    for kept, expected in ((semantics.matching_rows(jp.toPandas(), frame, params), semantics.is_matching(jp, m, params).where("matching")), (semantics.maximal_rows(frame), semantics.is_maximal(m))):
        assert 0 < sum(kept) < len(frame)
        assert sorted(map(tuple, frame[kept][key].to_numpy().tolist())) == sorted(map(tuple, expected.select(*key).collect()))
    n = blocks.matches(odd, params).count()
    assert tuple(blocks.checked(odd, params, quadtree.build(odd, 0.05), 2).first()) == (n, n, n)
    assert tuple(blocks.checked(odd.where("false"), params).first()) == (0, 0, 0)
    assert "Join" not in plan(registry.QUERIES["check_matching"](spark, sf_dir))


def test_pairs_and_breaks_in_one_join(spark, odd, sf_dir):
    """An outer join of points gives what one of points and pairs gives; the query has that one join."""
    params = JoinParams(0.5, 2)
    expected = classify.pairs_and_breaks(odd, pointjoin.joining_pairs(odd, None, params, "naive"))
    assert expected.where("kind = 'BP'").count() > 3
    text = lambda df: sorted(str(tuple(r)) for r in df.select(*pointjoin.OUT, "kind").collect())
    assert text(pointjoin.pairs_and_breaks(odd, params)) == text(expected)
    found = registry.QUERIES["jp_bp_outer"](spark, sf_dir)
    assert plan(found).split("== Initial Plan ==")[0].count("Join") == 1


def test_breaks_in_blocks(spark, odd, sf_dir, monkeypatch):
    """Pairs do not follow a shuffle, points are not copied for one, and points that break are found without all of their candidates."""
    found = plan(registry.QUERIES["jp_bp_outer"](spark, sf_dir)).split("== Initial Plan ==")[0]
    assert "Generate" not in found and all("traj" in line for line in found.splitlines() if "Exchange hashpartitioning" in line)
    for params in (JoinParams(0.5, 2), JoinParams(0.5, 0), JoinParams(1.0, 6)):
        expected = classify.pairs_and_breaks(odd, pointjoin.joining_pairs(odd, None, params, "naive"))
        for groups in (1, 4):
            assert sorted(map(str, pointjoin.pairs_and_breaks(odd, params, 0.05, groups).select(*pointjoin.OUT, "kind").collect())) == sorted(map(str, expected.select(*pointjoin.OUT, "kind").collect()))
    none = pointjoin.pairs_and_breaks(odd.where("false"), SET_A)
    assert none.count() == 0
    one = pointjoin.pairs_and_breaks(odd.where("traj = 0"), SET_A)
    assert one.where("kind = 'BP'").count() == one.count() == odd.where("traj = 0").count()
    rng, n, tested = np.random.default_rng(3), 4000, []
    own = blocks.Side(np.repeat(np.arange(50), 80), np.tile(np.arange(1, 81), 50), rng.integers(0, 500, n), rng.random(n) * 50, rng.random(n) * 50)
    own.x[::1000] += 1e6
    params = JoinParams(6.0, 50)
    monkeypatch.setitem(blocks._NEAR, "euclid", lambda dx, dy, eps, f=blocks._NEAR["euclid"]: tested.append(len(dx)) or f(dx, dy, eps))
    alone = blocks._alone(own, iter([own]), params, None)
    near = [np.abs(np.subtract.outer(v, v)) for v in (own.t, own.x, own.y)]
    joins = (near[0] <= 50) & (near[1] ** 2 + near[2] ** 2 <= 36) & np.not_equal.outer(own.code, own.code)
    assert list(alone) == list(np.flatnonzero(~joins.any(axis=1))) and len(alone) >= 4
    assert sum(tested) < np.count_nonzero((near[0] <= 50) & (near[1] <= 6)) / 2


def test_numbers_are_joined_to_points(spark, sf_dir):
    """Without the trajectory index: the numbering is joined to the slabs' rows before the sweep, not to its pairs."""
    found = plan(registry.QUERIES["jp_indexed_no_traj_index"](spark, sf_dir))
    assert found.count("Join") == 1 and found.index("MapInPandas") < found.index("Join")


def test_rounds_of_open_edges(spark, odd, sf_dir):
    """Pairs that can be in no match do not leave their block; the rounds give the same matches of the rest."""
    params = JoinParams(1.0, 6, 30)
    jp = pointjoin.joining_pairs(odd, None, params, "naive").where("r_traj < s_traj")
    expected = rows(refine.maximal_matches(jp, params))
    for tree in (None, quadtree.build(odd, 0.05)):
        edges = blocks.open_edges(odd, params, tree, 2)
        assert edges.exceptAll(jp.select(*edges.columns)).count() == 0 and edges.count() < jp.count()
        assert rows(refine.by_rounds(edges, params)) == expected
    assert blocks.open_edges(odd.where("false"), params).count() == 0
    assert "Join" not in plan(registry.QUERIES["match_rounds"](spark, sf_dir))


def test_methods_compared_in_blocks(spark, odd, sf_dir, monkeypatch):
    """Pairs by time and by cells are compared where both are found; a pair lost or doubled by the cells is counted."""
    from comovement.plans.quadtree import CellTable

    monkeypatch.setattr(blocks, "CHUNK", 500)
    params, tree = JoinParams(1.0, 6), quadtree.build(odd, 0.05)
    n = pointjoin.joining_pairs(odd, None, params, "naive").count()
    assert tuple(blocks.compare_cells(odd, params, tree, 2).first()) == (0, 0, n, 0)
    assert "Join" not in plan(registry.QUERIES["compare_methods"](spark, sf_dir))
    assert list(blocks.bag_difference(np.array([1, 1, 2, 5]), np.array([1, 2, 2, 7]))) == [2, 2, 2, 1]
    own = odd.select("traj", "seq", "t", "x", "y").where("traj < 99").toPandas().sort_values(["traj", "seq"])
    side = blocks.Side(*[own[c].to_numpy() for c in own.columns])

    class Blind(CellTable):
        def touched(self, x, y, eps):
            return np.arange(len(x)), self.home(x, y)  # nothing across a cell's border

    found = sum(blocks.bag_difference(*[r.astype(np.int64) * len(side.t) + s for r, s in both]) for both in blocks.chunks_together(side, side, True, params, [None, Blind(tree.coarsened(params.eps_sp))]))
    assert found[0] > 0 and found[1] == found[3] == 0 and found[2] > 0


@pytest.mark.parametrize("cells", [False, True])
def test_non_joining_pairs_as_from_pairs(spark, odd, cells, monkeypatch):
    monkeypatch.setattr(blocks, "PIECE", 700)  # fewer than a block has points, or few rows of one
    few, params = odd.where("pmod(pid, 3) = 0 or traj = 99").persist(), JoinParams(1.0, 5)
    tree = quadtree.build(few, 0.05) if cells else None
    expected = rows(classify.non_joining(few, pointjoin.joining_pairs(few, None, params, "naive")))
    assert len(expected) > 1000
    for groups in (1, 3):
        assert rows(blocks.non_joining(few, params, tree, groups)) == expected
    assert blocks.non_joining(few.where("traj = 0"), params).count() == 0


def test_non_joining_pairs_are_not_shuffled(spark, sf_dir):
    """The pairs come from the last step, which nothing follows, and only points are joined."""
    found = plan(registry.QUERIES["njp_pairs"](spark, sf_dir)).split("== Initial Plan ==")[0]
    assert "CartesianProduct" not in found and "NestedLoop" not in found and "LeftAnti" not in found
    assert found.replace("AdaptiveSparkPlan isFinalPlan=false", "").lstrip(" \n+-").lower().startswith("mapinpandas")


@pytest.mark.parametrize("name", ["match_directed", "match_exact_auto", "match_exact_stored"])
def test_points_are_dealt_once(spark, sf_dir, name, monkeypatch):
    """However many groups there are, each point lies in one file of one group, and no point is sent to blocks."""
    monkeypatch.setattr(blocks, "LEAST_GROUPS", 9)
    paths, deal = [], blocks.dealt
    monkeypatch.setattr(blocks, "dealt", lambda pts, groups: paths.append(deal(pts, groups)) or paths[-1])
    found = registry.QUERIES[name](spark, sf_dir)
    assert "Exchange" not in plan(found) and len(paths) == 1
    dealt = spark.read.parquet(paths[0])
    files = dealt.selectExpr("g", "traj", "seq", "input_file_name() f")
    assert dealt.count() == points.companions(registry.raw(spark, sf_dir)).count() == dealt.select("traj", "seq").distinct().count()
    assert files.select("g").distinct().count() == files.select("g", "f").distinct().count() > 6
    assert files.select("traj").distinct().count() == files.select("traj", "g").distinct().count()
    expected = registry.QUERIES["match_exact_basic"](spark, sf_dir)
    assert rows(found) == rows(refine.mirrored(expected) if name == "match_directed" else expected)


def test_points_are_numbered_in_their_groups(spark, sf_dir):
    """One shuffle numbers and deals points; ties in time, negative and repeated ids are numbered as everywhere."""
    rows_ = [(k % 7 - 3, k * k % 11, float(k % 5), float(k % 3), k // 2) for k in range(400)]
    for pts in (spark.createDataFrame(rows_, "traj long, t long, x double, y double, pid long").dropDuplicates(["traj", "t", "pid"]).persist(), registry.raw(spark, sf_dir, True)):
        numbered = points.with_sequence(pts)
        found = blocks.in_groups(pts, 5)
        assert plan(found).count("Exchange ") - plan(pts).count("Exchange ") == 1
        assert rows(found) == rows(blocks.in_groups(numbered, 5))
        assert rows(found.select("traj", "seq", "t", "x", "y")) == rows(numbered.select("traj", "seq", "t", "x", "y"))
        back = blocks.points_of(spark, blocks.dealt(pts, 5))
        assert rows(back) == rows(found) and back.columns == found.columns
        at = [(r.g, r.traj, r.seq) for r in found.collect()]
        assert at == sorted(at)


def shuffle_files(spark):
    return {f.getName() for f in spark._jvm.scala.jdk.javaapi.CollectionConverters.asJava(spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()) if f.getName().startswith("shuffle_")}


def test_no_files_of_shuffles_stay_behind_dealing(spark, sf_dir):
    before, end = shuffle_files(spark), time.time() + 30
    blocks.dealt(registry.raw(spark, sf_dir, True), 5)
    while (left := shuffle_files(spark) - before) and time.time() < end:
        time.sleep(0.2)  # another thread deletes them
    assert not left


def test_auto_shuffles_its_points_once(spark, sf_dir, monkeypatch):
    """Points come to their groups without numbers, tree and method from what is dealt."""
    given, deal, build = [], blocks.dealt, quadtree.build
    monkeypatch.setattr(blocks, "dealt", lambda pts, groups: given.append(pts) or deal(pts, groups))
    monkeypatch.setattr(quadtree, "build", lambda pts, cap: given.append(pts) or build(pts, cap))
    found = registry.QUERIES["match_exact_auto"](spark, sf_dir)
    raw, own = given
    assert "seq" not in raw.columns and "Exchange" not in plan(raw) and "groups-" in own.inputFiles()[0]
    assert rows(found) == rows(registry.QUERIES["match_exact_basic"](spark, sf_dir))


def test_store_keeps_little_on_its_way(spark, sf_dir, odd, tmp_path, monkeypatch):
    """The store has what is asked of it and no samples twice; what it writes on its way and its shuffles are gone."""
    odd.count()  # persisted by now
    made, before, end = [], shuffle_files(spark), time.time() + 30
    monkeypatch.setattr(store, "scratch", lambda s, name: made.append(scratch(s, name)) or made[-1])
    plain = odd.select("traj", "t", "x", "y", "pid")
    prepared = store.prepare(plain, str(tmp_path / "s"), 5, 0.05)
    assert len(made) == 1 and not os.path.exists(made[0].removeprefix("file:"))
    while len(left := {f.split("_")[1] for f in shuffle_files(spark) - before}) > 3 and time.time() < end:
        time.sleep(0.2)
    assert len(left) <= 3  # those of slabs and tree, which are small
    assert sorted(spark.read.parquet(f"{tmp_path}/s/points").columns) == sorted(["traj", "t", "x", "y", "pid", "seq", "slab"])
    found, numbered = prepared.points(spark), points.with_sequence(plain)
    assert rows(found.drop("slab").select(*numbered.columns).na.fill(-1)) == rows(numbered.na.fill(-1))
    assert rows(found.select("slab", "t")) == rows(plain.select(prepared.slabs.of(plain.t).alias("slab"), "t"))
    assert prepared.tree == quadtree.build(plain, 0.05)
    assert "Exchange" not in plan(found.select("traj", "seq", "t", "x", "y"))
    assert store.prepare(plain.where("false"), str(tmp_path / "none")).points(spark).count() == 0


def test_engine_without_points(spark, odd):
    none = odd.select("traj", "t", "x", "y", "pid").where("false")
    for method in ("auto", "prepart", "indexed"):
        assert SubtrajectoryJoin(SET_A, method).run(none).count() == 0


@pytest.mark.parametrize("params", PARAMS)
def test_basic_sweeps_stretches(spark, odd, params):
    one, other = odd.where("pmod(traj, 2) = 0"), odd.where("pmod(traj, 2) = 1")
    for left, right in ((odd, None), (one, other)):
        expected = rows(pointjoin.joining_pairs(left, right, params, "naive"))
        assert len(expected) > 50
        for n in (1, 16, 300):  # slabs narrower than the tolerance, too
            assert rows(pointjoin.joining_pairs(left, right, params, "basic", n_slabs=n)) == expected


def test_basic_tests_few_pairs(spark, sf_dir, monkeypatch):
    """No join of all points of neighbouring buckets: what is tested is near along x, and each pair is tested once."""
    assert "Join" not in plan(registry.QUERIES["jp_basic"](spark, sf_dir))
    rng, n, tested = np.random.default_rng(2), 3000, []
    rows_ = {"t": np.sort(rng.integers(0, 600, n)), "x": rng.random(n) * 100, "y": rng.random(n) * 100, "traj": rng.integers(0, 50, n), "seq": np.arange(n), "home": np.ones(n, bool)}
    monkeypatch.setitem(pointjoin._NEAR, "euclid", lambda dx, dy, eps, f=pointjoin._NEAR["euclid"]: tested.append(len(dx)) or f(dx, dy, eps))
    found = sum(len(f) for f in pointjoin._strips(rows_, JoinParams(5.0, 100), True, 5000))
    dt, dx = (np.abs(np.subtract.outer(rows_[c], rows_[c])) for c in ("t", "x"))
    d2 = dx**2 + np.subtract.outer(rows_["y"], rows_["y"]) ** 2
    assert found == np.count_nonzero((dt <= 100) & (d2 <= 25) & np.not_equal.outer(rows_["traj"], rows_["traj"])) > 0
    assert sum(tested) < 0.7 * np.count_nonzero((dt <= 100) & (dx <= 5))
