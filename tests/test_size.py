"""What keeps queries going on large tables: the same answers, with less work or held in less memory."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from phasewise.baselines import neighbours as bn
from phasewise.functions.draws import draws
from phasewise.operators import kernel as kn
from phasewise.operators import miner as mn
from phasewise.operators.engine import Settings


@pytest.mark.parametrize("rule", ["priced", "unpriced"])
@pytest.mark.parametrize("distance", ["euclidean", "sqeuclidean", "manhattan"])
@pytest.mark.parametrize("limits", [kn.StopLimits(), kn.StopLimits(cost_cap=900.0), kn.StopLimits(median_cap=40), kn.StopLimits(cost_cap=300.0, cost_basis="service")])
def test_a_line_is_scanned_as_a_plane(rule, distance, limits):
    rng = np.random.default_rng(3)
    x = np.concatenate([rng.integers(0, 200, 700), rng.integers(0, 200, 700)]).astype(float).reshape(-1, 1) / 4
    w, ids = rng.integers(1, 4, len(x)).astype(float), np.arange(len(x)) * 7
    u = draws("hash", 1, 0, 1, ids)
    line, plane = (of(1, 5.0, rule=rule, distance=distance, limits=limits, carried=100, keep=True) for of in (kn.scan, kn.FacilityScan))
    assert isinstance(line, kn.LineScan)
    for at in range(0, len(x), 333):
        part = slice(at, at + 333)
        line.feed(ids[part], x[part], w[part], u[part]), plane.feed(ids[part], x[part], w[part], u[part])
    for name in ("rows", "ids", "at", "weight", "gained", "gained_raw", "to", "dist"):
        assert np.array_equal(getattr(line, name), getattr(plane, name)), name
    for name in ("read", "service", "ssq", "max_dist", "stop_reason", "total"):
        assert getattr(line, name) == getattr(plane, name), name


def line_points(spark, values):
    rows = [("all", i + 1, i, [float(v)], 1.0) for i, v in enumerate(values)]
    return spark.createDataFrame(rows, "stream_key string, ordinal long, point_id long, vec array<double>, weight double")


def test_a_stream_writes_what_is_asked_for(spark):
    p = line_points(spark, [(i * 37) % 101 + (i % 13) * 0.5 for i in range(400)])
    s = Settings(k=3, num=50, runs=2, floor_growth="on_breach")
    whole = mn.mine_single_stream(p, s, stretch=150)
    some = mn.mine_single_stream(p, s, stretch=150, keep=("phase_log", "verdicts", mn.LAST_MEDIANS))
    key = lambda df: sorted(map(str, df.collect()))
    assert key(some.phase_log) == key(whole.phase_log) and key(some.verdicts) == key(whole.verdicts) and key(some.final()[0]) == key(whole.final()[0])
    assert some.run_log.count() == 0 and 0 < some.medians.count() < whole.medians.count()


def brute(values, k):
    """{id: its k nearest others as (distance, id)}"""
    return {i: sorted((float(np.sqrt(((a - b) ** 2).sum())), j) for j, b in enumerate(values) if i != j)[:k] for i, a in enumerate(values)}


@pytest.mark.parametrize("prune", [False, True])
def test_neighbours_among_copies_and_in_many_blocks(spark, monkeypatch, prune):
    monkeypatch.setattr(bn, "BLOCK", 16)
    rng = np.random.default_rng(5)
    some = rng.integers(0, 40, (90, 2)).astype(float)
    values = np.concatenate([some, some[:60], some[:30], some[:10], some[:10], rng.random((60, 2)) * 500])
    p = spark.createDataFrame([("all", i + 1, i, v.tolist(), 1.0) for i, v in enumerate(values)], "stream_key string, ordinal long, point_id long, vec array<double>, weight double")
    want = brute(values, 3)
    got = {r.point_id: [(x["dist"], x["id"]) for x in r.near] for r in bn.nearest_lists(p, 3, 2, prune=prune).collect()}
    assert got == want
    whole = sorted(((-near[-1][0], i) for i, near in want.items()))[:7]
    for rows in (bn.knn_rank(p, 3, 7, d=2), bn.knn_rank_cells(p, 3, 7, d=2, most_rows=5)):
        assert [(-r.dist, r.point_id) for r in rows.collect()] == whole
    model = bn.LofModel(np.arange(len(values)), values, 3).scores().set_index("point_id")["lof"]
    assert all(r.lof == pytest.approx(model[r.point_id]) for r in bn.lof(p, 3, d=2).collect())


def test_baselines_take_large_tables(spark):
    n = 60_000
    p = spark.range(n).selectExpr("'all' as stream_key", "id + 1 as ordinal", "id as point_id", "array(double(id % 97)) as vec", "1.0D as weight")
    assert [(r.point_id, r.dist) for r in bn.knn_rank(p, 3, 2, d=1, method="block").collect()] == [(0, 0.0), (1, 0.0)]
    assert [(r.point_id, r.dist) for r in bn.knn_rank_cells(p, 3, 2, d=1, most_rows=50).collect()] == [(0, 0.0), (1, 0.0)]
    assert bn.lof(p, 3, d=1).where("lof = 1").count() == n
    assert bn.db_outliers(p, 1.0, 0.99, d=1).count() == bn.db_outliers(p, 1.0, 0.99, d=1, method="grid").count() == 0


def test_the_lateral_join_meets_few_medians(spark):
    from phasewise.queries import core, relational

    sf = "/root/testdata/sf0.01"
    got = sorted(map(tuple, relational.lateral_nearest(spark, sf).collect()))
    assert got == sorted(map(tuple, mn.assign(core.events_points(spark, sf), core.fixed_medians(spark, sf), 1).select("point_id", "median_id").collect()))
    assert spark.sql("select max(size(ms)) from lateral_near").head()[0] < core.fixed_medians(spark, sf).count()


CELLS = [
    Settings(runs=1, k=k, outlier_phases=o, num=num, gamma=gamma, beta=beta, floor_growth=growth, **more)
    for num, o, growth in ((4, 3, "on_breach"), (9, 1, "every_phase"), (9, 2, "on_breach"), (4, 2, "every_phase")) for k, gamma, beta in ((1, 18.0, 3.0), (4, 18.0, 3.0), (4, 34.0, 3.0), (2, 34.0, 34.0))
    for more in ({}, {"median_cap": 7, "max_stalled_phases": 99}, {"include_first_phase": False, "warmup_phases": 2}, {"floor": 9.0}, {"cost_cap": 60.0}, {"candidate_rule": "stalled_light"})
]


@pytest.mark.parametrize("kind", ["few", "fine", "equal", "late", "heavy", "again", "plane"])
def test_cells_that_share_their_work_are_miners(kind):
    from phasewise.operators.engine import Miner, NoProgress
    from phasewise.operators.sweeping import sweep_stream

    rng = np.random.default_rng(8)
    x, w, ids = rng.integers(0, 12, (90, 1)) / 2, np.ones(90), rng.permutation(900)[:90]
    if kind in ("fine", "heavy"):
        x = np.concatenate([rng.random((45, 1)) * 9, rng.random((45, 1)) * 300])
    elif kind in ("equal", "late"):
        x[: 90 if kind == "equal" else 40] = 5.0
    elif kind == "plane":
        x = np.concatenate([x, x[::-1]], axis=1)
    w = rng.integers(1, 9, 90) / 2.0 if kind == "heavy" else w
    ids = ids // 9 if kind == "again" else ids  # ids that repeat
    want = {}
    for s in CELLS:
        try:
            log = Miner(s, x.shape[1]).run(ids, x, w)
        except NoProgress:
            with pytest.raises(NoProgress):
                sweep_stream([s], ids, x, w)
        else:
            want[s] = (len(log.phases), sum(v["verdict"] == "outlier" for v in log.verdicts), sum(float(p["total_cost"]) for p in log.phases), log.phases[-1]["medians_out"])
    assert len(want) > 0.8 * len(CELLS) and dict(zip(want, sweep_stream(list(want), ids, x, w), strict=True)) == want


def test_a_sweep_moves_points_once(spark, sf):
    """Before, every point went to every cell, and each cell was a run of its own."""
    from phasewise.plans import workloads as wl
    from phasewise.sources.tables import events_points

    p = events_points(spark, sf, stream_key="user_id").unionByName(line_points(spark, [3, 3, 9, 4, 4, 80]).withColumn("stream_key", F.lit(None).cast("string")))
    out = wl.sweep(p, Settings(runs=1, floor_growth="on_breach"), {"k": [1, 5], "outlier_phases": [1, 3], "num": [5, 20]})
    assert "Generate" not in out._jdf.queryExecution().executedPlan().toString()
    assert {r.streams for r in out.collect()} == {p.select("stream_key").distinct().count()}


def test_points_that_are_not_ranked_keep_their_order(spark, sf):
    from phasewise.sources.tables import events_points

    ranked, plain = ([(r.stream_key, r.point_id, r.vec) for r in events_points(spark, sf, stream_key="user_id", ranked=ranked).orderBy("stream_key", "ordinal").collect()] for ranked in (True, False))
    assert ranked == plain


@pytest.mark.parametrize("d", [1, 3])
def test_places_within_a_radius_are_counted_in_blocks(spark, monkeypatch, d):
    """Before, every place was copied into all the cells around it, and the copies could be broadcast."""
    rng = np.random.default_rng(6)
    x = np.concatenate([rng.integers(0, 30, (150, d)), rng.integers(0, 8, (100, d)), np.full((9, d), 4)]).astype(float)
    p = spark.createDataFrame([("all", i + 1, i, v, 1.0) for i, v in enumerate(x.tolist())], "stream_key string, ordinal long, point_id long, vec array<double>, weight double")
    near = (np.sqrt(((x[:, None] - x[None]) ** 2).sum(2)) <= 5.0).sum(1) - 1
    for places, leaf in ((4096, 64), (16, 4)):
        monkeypatch.setattr(bn, "PLACES", places, raising=False), monkeypatch.setattr(bn, "LEAF", leaf, raising=False)
        out = bn.db_outliers(p, 5.0, 0.8, d=d)
        plan = out._jdf.queryExecution().executedPlan().toString()
        assert "Generate" not in plan and "Broadcast" not in plan
        assert {r.point_id: r.near for r in out.collect()} == {i: c for i, c in enumerate(near) if c <= 0.2 * len(x)}


@pytest.mark.parametrize("full", [1, 64])
def test_cells_are_halved_before_points_are_measured(spark, monkeypatch, full):
    """Before, every point of a cell that was not dense enough by itself went to the 49 cells around."""
    monkeypatch.setattr(bn, "FULL", full, raising=False)
    rng = np.random.default_rng(7)
    x = np.concatenate([np.round(rng.random((900, 2)) * 9 - 4), rng.normal(0, 2, (300, 2)), [[40.0, -7.0]]])
    p = spark.createDataFrame([("all", i + 1, i, v, 1.0) for i, v in enumerate(x.tolist())], "stream_key string, ordinal long, point_id long, vec array<double>, weight double")
    near = (np.sqrt(((x[:, None] - x[None]) ** 2).sum(2)) <= 3.0).sum(1) - 1
    out = bn.db_outliers(p, 3.0, 0.95, d=2, method="grid")
    assert "Generate" not in out._jdf.queryExecution().executedPlan().toString()
    assert {r.point_id: r.near for r in out.collect()} == {i: c for i, c in enumerate(near) if c <= 60}


def test_lineitems_are_ranked_by_their_keys_alone(spark, sf):
    from phasewise.operators.points import to_points
    from phasewise.sources import tables as st

    df = st.table(spark, sf, "lineitem").select(*st.LINEITEM_KEYS).withColumn("l_shipdate", F.to_date("l_shipdate"))
    want, got = to_points(df, st.LINEITEM_KEYS, st.LINEITEM_FEATURES), st.lineitem_points(spark, sf)
    assert got.dtypes == want.dtypes and sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    assert not {"_k0", "l_partkey"} & set(spark.read.parquet(*got.inputFiles()).columns)  # what is written


@pytest.mark.parametrize("kind", ["mixed", "copies"])
def test_cells_rank_without_the_blocks_of_all_points(spark, monkeypatch, kind):
    """Before, many points alone in their cells, or copies everywhere, sent all points to the blocks."""
    rng = np.random.default_rng(4)
    x = {"mixed": np.concatenate([np.round(rng.random((500, 2)) * 6), rng.random((300, 2)) * 9]), "copies": np.repeat(rng.random((50, 2)) * 6, 5, 0)}[kind]
    p = spark.createDataFrame([("all", i + 1, i, v, 1.0) for i, v in enumerate(x.tolist())], "stream_key string, ordinal long, point_id long, vec array<double>, weight double")
    kth = {i: near[-1][0] for i, near in brute(x, 3).items()}
    monkeypatch.setattr(bn, "knn_rank", None)
    got = [(r.point_id, r.dist) for r in bn.knn_rank_cells(p, 3, 7, d=2, most_rows=20).collect()]
    assert got == sorted(kth.items(), key=lambda r: (-r[1], r[0]))[:7]
