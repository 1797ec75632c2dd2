"""File formats, SQL views and functions, ablations."""

import numpy as np
import pytest

from comovement import points, sqlapi, workloads
from comovement.engine import SubtrajectoryJoin
from comovement.operators import classify, general, pointjoin, refine
from comovement.operators.baselines import jp_only_runs, warping_distance
from comovement.params import SET_B, JoinParams
from comovement.sources import tables
from comovement.sources.tables import table


@pytest.mark.parametrize("fmt", ["parquet", "orc", "csv", "json"])
def test_formats_round_trip(spark, sf_dir, tmp_path, fmt):
    pts = points.from_events(table(spark, sf_dir, "events"))
    tables.write_points(pts, str(tmp_path / fmt), fmt)
    found = general.compare(pts, tables.read_points(spark, str(tmp_path / fmt), fmt)).first()
    assert (found.only_left, found.only_right) == (0, 0) and found.both == pts.count()


def test_sql_views_and_functions(spark, sf_dir):
    sqlapi.register(spark)
    pts = points.companions(points.from_events(table(spark, sf_dir, "events")))
    sqlapi.create_views(pts, SET_B)
    assert spark.sql("select count(*) from matches").first()[0] == 54
    assert spark.sql("select count(*) from (select r_traj from joining_pairs where r_traj < s_traj)").first()[0] == 1210
    native = {r.traj: r.p for r in general.speed(pts).groupBy("traj").agg({"step": "sum"}).withColumnRenamed("sum(step)", "p").collect()}
    for r in spark.sql("select traj, path_length(t, x, y) p from points group by traj").collect():
        assert r.p == pytest.approx(native[r.traj])
    assert spark.sql("select haversine_m(0D, 0D, 0D, 1D)").first()[0] == pytest.approx(111_195, rel=1e-4)


def test_leaving_out_breaks_gives_false_results(spark):
    line = [(1, t, float(t), 0.0, t) for t in range(8)] + [(2, t, float(t), 100.0 if t == 4 else 0.5, 100 + t) for t in range(8)]
    pts = points.with_sequence(spark.createDataFrame(line, "traj long, t long, x double, y double, pid long"))
    params = JoinParams(1.5, 1)
    jp = pointjoin.joining_pairs(pts, None, params, "basic").where("r_traj < s_traj")
    exact = refine.maximal_matches(jp, params).select("r_traj", "s_traj", "r_from", "r_to", "s_from", "s_to")
    found = general.compare(jp_only_runs(jp, params), exact).first()
    assert (found.only_left, found.only_right) == (1, 2)


def test_candidate_misses_suffice(spark, sf_dir):
    pts = points.with_sequence(points.companions(points.from_events(table(spark, sf_dir, "events"))))
    jp = pointjoin.joining_pairs(pts, None, SET_B)
    effective = classify.effective_misses(pts, jp)
    candidates = classify.candidate_misses(pts, jp).select("r_traj", "s_traj", "s_seq").distinct()
    assert effective.count() > 0 and effective.join(candidates, ["r_traj", "s_traj", "s_seq"], "left_anti").count() == 0


def test_kernel_equals_rounds_and_depth_is_no_limit(spark, sf_dir):
    pts = points.with_sequence(points.companions(points.from_events(table(spark, sf_dir, "events"))))
    jp = pointjoin.joining_pairs(pts, None, SET_B).where("r_traj < s_traj").cache()
    wanted = sorted(map(tuple, refine.maximal_matches(jp, SET_B).collect()))
    for rounds in (1, 2, 4):
        assert sorted(map(tuple, refine.by_rounds(jp, SET_B, rounds).collect())) == wanted


def test_tolerances_are_monotone(spark, sf_dir):
    pts = points.with_sequence(points.from_events(table(spark, sf_dir, "events")))
    counts = [pointjoin.joining_pairs(pts, None, JoinParams(e, 7_200_000_000)).count() for e in (5.0, 10.0, 20.0)]
    assert counts == sorted(counts)


def test_warping_distance():
    a = np.array([[0.0, 0.0], [1.0, 0.0], [2.0, 0.0]])
    assert warping_distance(a, a) == 0 and warping_distance(a, a[[0, 0, 1, 2, 2]]) == 0 and warping_distance(a, a + [0, 1]) == 3


def test_parameters_reject_negative_tolerances():
    with pytest.raises(ValueError):
        JoinParams(-1, 0)


def test_naive_engine_from_end_to_end(spark, sf_dir):
    pts = points.companions(points.from_events(table(spark, sf_dir, "events")))
    wanted = sorted(map(tuple, SubtrajectoryJoin(SET_B, "naive").run(pts).collect()))
    assert len(wanted) == 54 and wanted == sorted(map(tuple, SubtrajectoryJoin(SET_B, "indexed").run(pts).collect()))
    with pytest.raises(ValueError):
        SubtrajectoryJoin(SET_B, "gridtile").run(pts)


def test_timed_workloads_measure_every_query(spark, sf_dir, tmp_path):
    pts = points.companions(points.from_events(table(spark, sf_dir, "events")))
    rows = workloads.amortised(pts, [JoinParams(10.0, 7_200_000_000), JoinParams(20.0, 7_200_000_000)], str(tmp_path / "a"), ("basic", "indexed"))
    assert [(r["method"], r["queries"]) for r in rows] == [("basic", 1), ("basic", 2), ("indexed", 1), ("indexed", 2)]
    assert all(rows[k]["total_s"] < rows[k + 1]["total_s"] for k in (0, 2)) and rows[1]["n_jp"] == rows[3]["n_jp"] > rows[0]["n_jp"]
    rows = workloads.vary_timed(pts, "eps_sp", [5.0, None], str(tmp_path / "v"), JoinParams(10.0, 7_200_000_000))
    assert [r["method"] for r in rows] == ["prepart", "indexed"] * 2 and rows[0]["n_jp"] == rows[1]["n_jp"] < rows[2]["n_jp"] == rows[3]["n_jp"]
    rows = workloads.index_cost(pts, JoinParams(10.0, 7_200_000_000), str(tmp_path / "i"), (3, 5))
    assert all(r["spatial_bytes"] > 0 and r["trajectory_bytes"] > 0 and r["spatial_build_s"] > 0 and r["trajectory_build_s"] > 0 for r in rows)
