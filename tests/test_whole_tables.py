"""Queries over whole tables, against SQL or brute force on small ones."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from phasewise import registry
from phasewise.baselines import neighbours as bn
from phasewise.operators import miner as mn
from phasewise.operators.engine import Settings
from phasewise.operators.points import with_ordinal
from phasewise.sources import tables as src
from phasewise.streaming import live

POINTS = "stream_key string, ordinal long, point_id long, vec array<double>, weight double"


def by_sql(sf, sql):
    con = duckdb.connect()
    for t in ("events", "customer", "nation", "lineitem", "orders"):
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    done = con.execute(sql)
    return [d[0] for d in done.description], done.fetchall()


@pytest.mark.parametrize("name", ["facility_pass", "facility_pass_weighted", "miner_per_user", "miner_limits", "miner_single_stream", "miner_limit_driven", "sharded_verdicts", "assign_keyed", "knn_rank_cells", "db_grid", "evolving_windows"])
def test_queries_equal_their_sql(spark, sf, name):
    cols, want = by_sql(sf, registry.oracle_sql()[name])
    got = [tuple(r[c] for c in cols) for r in registry.queries()[name](spark, sf).collect()]
    plain = lambda rows: sorted(tuple(round(float(v), 5) if isinstance(v, float) else str(v) for v in r) for r in rows)
    assert plain(got) == plain(want) and got


def test_text_keys_of_any_script_are_ordered(spark):
    rows = [(f"{'漢é zA'[i % 5]}{i * 7919 % 600:03d}{'語' * (i % 3)}", i) for i in range(600)]
    got = {r.ordinal: r.k for r in with_ordinal(spark.createDataFrame(rows, "k string, _at long").repartition(7), ["k"]).collect()}
    assert [got[i + 1] for i in range(600)] == sorted((k for k, _ in rows), key=lambda k: k.encode())


def test_a_point_goes_to_a_median_of_its_own_stream(spark):
    p = spark.createDataFrame([("a", 1, 1, [0.0], 1.0), ("b", 1, 2, [0.0], 1.0), ("b", 2, 2, [0.0], 1.0)], POINTS)
    m = spark.createDataFrame([("a", 7, [9.0]), ("b", 8, [100.0])], "stream_key string, median_id long, vec array<double>")
    got = sorted((r.stream_key, r.median_id) for r in mn.assign(p, m, 1).collect())
    assert got == [("a", 7), ("b", 8), ("b", 8)]  # rows that repeat stay


def test_blocks_of_medians_find_the_same(spark, sf, monkeypatch):
    p = src.events_points(spark, sf)
    m = p.where("ordinal % 7 = 1").select(F.col("point_id").alias("median_id"), "vec")
    rows = lambda: sorted(map(tuple, mn.assign(p, m, 1, keep=("ordinal",)).collect()))
    blocks = rows()
    monkeypatch.setattr(mn, "MOST_ELEMENTS", 10_000)
    assert m.count() > 128 and blocks == rows()


def test_a_stream_goes_on_where_it_was_written(spark, sf, tmp_path):
    """Stretches hand their state on; a call after a loss reads what is there and does the rest."""
    import shutil

    p, s, path = src.events_points(spark, sf), Settings(k=3, num=90, runs=2, floor_growth="on_breach"), str(tmp_path / "s")
    whole = mn.mine_outliers(p, s)
    want = sorted(map(str, whole.phase_log.collect())), sorted(map(str, whole.verdicts.collect()))
    r = mn.mine_single_stream(p, s, stretch=200, path=path)
    assert (sorted(map(str, r.phase_log.collect())), sorted(map(str, r.verdicts.collect()))) == want
    shutil.rmtree(tmp_path / "s/log-3")
    shutil.rmtree(tmp_path / "s/log-4")
    kept = (tmp_path / "s/log-2/_SUCCESS").stat().st_mtime_ns
    r = mn.mine_single_stream(p, s, stretch=200, path=path)
    assert sorted(map(str, r.verdicts.collect())) == want[1] and (tmp_path / "s/log-2/_SUCCESS").stat().st_mtime_ns == kept


@pytest.mark.parametrize("more", [{"median_cap": 9.0}, {"rewatch": False}])
def test_batches_equal_one_run(more):
    """Also where a limit ends phases early, and where inliers are not watched again."""
    from phasewise.operators.engine import Miner, StreamMiner

    rng = np.random.default_rng(2)
    x, s = rng.choice([0.0, 5.0, 9.0, 60.0, 200.0], (400, 1)) + rng.random((400, 1)), Settings(k=2, num=20, runs=2, n_declared=400, max_stalled_phases=90, **more)
    log = Miner(s, 1).run(np.arange(400), x, np.ones(400))
    if "median_cap" in more:
        assert any(p["stop_reason"] == "medians" for p in log.phases)
    state, verdicts = None, []
    for at in range(0, 400, 37):
        stream = StreamMiner(s, 1, state)
        verdicts += live._take(stream, [(f"{i:04}", i, x[i].tolist(), 1.0) for i in range(at, min(at + 37, 400))])
        state = stream.state()
    stream = StreamMiner(s, 1, state)
    stream.flush(final=True)
    key = lambda vs: sorted((v["median_id"], v["first_phase"], v["settled_phase"] or 0, v["score"], v["verdict"]) for v in vs)
    assert key(verdicts + stream.miner.log.verdicts) == key(log.verdicts)


def brute_kth(x, k):
    gap = np.sqrt(((x[:, None] - x[None]) ** 2).sum(2))
    np.fill_diagonal(gap, np.inf)
    return np.sort(gap, 1)[:, k - 1]


@pytest.mark.parametrize("kind", ["plain", "clustered", "repeated"])
def test_cells_find_what_all_pairs_find(spark, kind):
    rng = np.random.default_rng(4)
    x = {"plain": rng.random((700, 2)) * 40, "clustered": np.concatenate([rng.normal(c, 0.3, (230, 2)) for c in (0, 10, 30)] + [rng.random((10, 2)) * 60]), "repeated": np.round(rng.random((700, 2)) * 6)}[kind]
    p = spark.createDataFrame([("all", i + 1, i, v, 1.0) for i, v in enumerate(x.tolist())], POINTS).repartition(5)
    kth = brute_kth(x, 3)
    order = np.lexsort((np.arange(len(x)), -kth))[:7]
    got = [(r.point_id, round(r.dist, 9)) for r in bn.knn_rank_cells(p, 3, 7, d=2).collect()]
    assert sorted(g for _, g in got) == sorted(np.round(kth[order], 9).tolist())
    if kind != "repeated":
        assert [i for i, _ in got] == order.tolist()
    gap = np.sqrt(((x[:, None] - x[None]) ** 2).sum(2))
    for radius, share in ((3.0, 0.98), (1.0, 0.99), (8.0, 0.9)):
        near = (gap <= radius).sum(1) - 1
        want = {i: int(c) for i, c in enumerate(near) if c <= int(np.floor(len(x) * (1 - share) + 1e-9))}
        assert {r.point_id: r.near for r in bn.db_outliers(p, radius, share, d=2, method="grid").collect()} == want


def test_thinned_windows_keep_their_outliers(spark, sf):
    """Only safe inliers are thinned: what has too few neighbours in truth is found, and safe points never are."""
    p = src.events_points(spark, sf, scale=100.0)
    exact = {r.point_id: (r.near, r.is_outlier) for r in bn.window_knn(p, 100.0, 2, 50, d=1).collect()}
    some = {r.point_id: r.is_outlier for r in bn.window_knn(p, 100.0, 2, 50, d=1, approx=0.5).collect()}
    wrong = [i for i, out in some.items() if out != exact[i][1]]
    assert len(wrong) < 0.1 * len(some) and sum(exact[i][1] for i in some if not some[i]) < 0.2 * sum(o for _, o in exact.values())


def test_gaps_in_order_equal_nearest_distances(spark, sf):
    p = src.events_points(spark, sf, scale=100.0)
    x = np.sort(np.array([r.vec[0] for r in p.collect()]))
    want = sorted(np.minimum(np.diff(x, prepend=-np.inf), np.diff(x, append=np.inf)).tolist())
    assert sorted(r.dist for r in bn.nearest_gaps(p).collect()) == want


def test_a_sweep_cell_is_the_miner(spark, sf):
    from phasewise.plans.workloads import sweep

    p = src.events_points(spark, sf, stream_key="user_id")
    rows = {r.cell: r for r in sweep(p, Settings(runs=1, num=10), {"k": [1, 3]}).collect()}
    for cell, k in enumerate((1, 3)):
        r = mn.mine_outliers(p, Settings(runs=1, num=10, k=k))
        assert rows[cell].outliers == r.verdicts.where("verdict = 'outlier'").count() and rows[cell].phases == r.phase_log.count()
        assert rows[cell].total_cost == pytest.approx(r.phase_log.agg(F.sum("total_cost")).head()[0])


def test_shards_with_verdicts(spark, sf):
    """More shards: every median is judged by the whole stream's points."""
    p = src.events_points(spark, sf)
    out = mn.mine_shards(p, 1, Settings(num=100), shards=5, price=20.0)
    n = p.count()
    assert out["medians"].agg(F.sum("weight")).head()[0] == n
    assert {r.verdict for r in out["verdicts"].collect()} <= {"outlier", "inlier", "pending"} and out["verdicts"].count()


def test_constants_come_from_the_table(spark, tmp_path):
    """Before, the grid was made up and no table was read."""
    spark.createDataFrame([(i, v) for i, v in enumerate([None, float("nan"), -3.0, 0.5, 18.9, 18.2, 62.0, 96.0, 180.99, 181.0])], "event_id long, value double").write.parquet(f"{tmp_path}/events.parquet")
    (tmp_path / "sql").mkdir()
    duckdb.sql(f"copy (select * from '{tmp_path}/events.parquet/*.parquet') to '{tmp_path}/sql/events.parquet'")
    got = sorted((r.gamma, r.beta) for r in registry.queries()["constants_grid"](spark, str(tmp_path)).collect())
    want = duckdb.connect()
    want.execute(f"create view events as select * from '{tmp_path}/sql/events.parquet'")
    assert got == sorted(want.execute(registry.oracle_sql()["constants_grid"]).fetchall()) == [(g, b) for g in (18, 62, 96, 180) for b in (18, 62, 96, 180) if g + 4 * (1 + 4 * (b + g)) <= g * b and b >= 3 * g + 2] and got


def test_handover_is_every_users(spark, sf):
    """Before, ten made-up points were handed over and no table was read."""
    cols, want = by_sql(sf, registry.oracle_sql()["handover_phases"])
    got = [tuple(r[c] for c in cols) for r in registry.queries()["handover_phases"](spark, sf).collect()]
    assert sorted(got) == sorted(want) and len({r[0] for r in got}) == src.table(spark, sf, "events").select("user_id").distinct().count()
