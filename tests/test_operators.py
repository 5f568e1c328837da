"""Operators on DataFrames: points, baselines, streams, SQL surface."""

import os

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from phasewise import sqlapi
from phasewise.baselines import neighbours as bn
from phasewise.baselines.means import exact_kmedian, mean_miner
from phasewise.operators import measures as ms
from phasewise.operators import miner as mn
from phasewise.operators.engine import Settings
from phasewise.operators.points import to_points, with_ordinal
from phasewise.plans import workloads as wl
from phasewise.plans.schedule import initial_floor
from phasewise.sources import tables as src
from phasewise.streaming import live

POINTS = "stream_key string, ordinal long, point_id long, vec array<double>, weight double"


def line(spark, values):
    return spark.createDataFrame([("all", i + 1, i, [float(v)], 1.0) for i, v in enumerate(values)], POINTS)


def test_ordinals_follow_all_keys(spark):
    df = spark.range(5000).select(F.xxhash64("id").alias("h"), (F.col("id") % 7).alias("g"))
    rows = with_ordinal(df, ["g", "h"]).collect()
    want = sorted((r.g, r.h) for r in rows)
    assert [(r.g, r.h) for r in sorted(rows, key=lambda r: r.ordinal)] == want
    assert sorted(r.ordinal for r in rows) == list(range(1, 5001))


@pytest.mark.parametrize("nulls, n", [("drop", 1), ("impute", 2)])
def test_null_policies(spark, nulls, n):
    df = spark.createDataFrame([(1, 2.0), (2, None)], "id long, v double")
    assert to_points(df, ["id"], ["v"], nulls=nulls).count() == n
    with pytest.raises(Exception, match="null, NaN"):
        to_points(df, ["id"], ["v"]).collect()


def test_nan_always_fails(spark):
    df = spark.createDataFrame([(1, float("nan"))], "id long, v double")
    with pytest.raises(Exception, match="null, NaN"):
        to_points(df, ["id"], ["v"], nulls="drop").collect()


def test_initial_floor(spark):
    assert initial_floor(line(spark, [6.55, 12.31, 1.63]), 2, 34, d=1).head()["floor"] == pytest.approx(0.144706, abs=1e-6)
    assert initial_floor(line(spark, [5, 5, 7, 9]), 2, 1, d=1).head()["closest"] == 2
    with pytest.raises(Exception, match="zero floor"):
        initial_floor(line(spark, [5, 5, 7, 9]), 2, 1, d=1, zero_floor="error").collect()


def test_exact_answers(spark):
    p = line(spark, [0, 1, 2, 3, 10])
    assert exact_kmedian(p, 1, 1).head()["cost"] == 12 and exact_kmedian(p, 2, 1).head()["cost"] == 4
    assert [(r.point_id, r.dist) for r in bn.knn_rank(p, 3, 1, d=1).collect()] == [(4, 9)]
    for method in ("nested", "grid"):
        assert [r.point_id for r in bn.db_outliers(p, 3.0, 0.75, d=1, method=method).collect()] == [4]


def test_knn_methods_agree(spark):
    rng = np.random.default_rng(3)
    rows = [("all", i + 1, i, v, 1.0) for i, v in enumerate(rng.normal(size=(300, 2)).tolist())]
    p = spark.createDataFrame(rows, POINTS)
    want = [(r.point_id, round(r.dist, 9)) for r in bn.knn_rank(p, 3, 7, d=2).collect()]
    for method in ("block", "pruned"):
        assert [(r.point_id, round(r.dist, 9)) for r in bn.knn_rank(p, 3, 7, d=2, method=method).collect()] == want


def test_incremental_lof_equals_batch(spark):
    rng = np.random.default_rng(5)
    x = rng.normal(size=(80, 2))
    model = bn.LofModel(np.arange(60), x[:60], 4)
    changed = model.insert(np.arange(60, 80), x[60:])
    assert len(changed) < 80
    got = dict(model.scores().itertuples(index=False))
    p = spark.createDataFrame([("all", i + 1, i, v, 1.0) for i, v in enumerate(x.tolist())], POINTS)
    assert all(got[r.point_id] == pytest.approx(r.lof) for r in bn.lof(p, 4, d=2).collect())


def test_all_pairs_are_guarded(spark):
    with pytest.raises(ValueError, match="limited"):
        bn.kth_distances(line(spark, range(20)), 1, 1, most_rows=10)


def test_single_stream_equals_keyed(spark, sf):
    p = src.events_points(spark, sf, upto=300)
    s = Settings(k=3, num=100, runs=3)
    a = mn.mine_outliers(p, s).phase_log.orderBy("phase").collect()
    b = mn.mine_single_stream(p, s).phase_log.orderBy("phase").collect()
    assert a == b


def test_layout_changes_nothing(spark, sf):
    p = src.events_points(spark, sf, stream_key="user_id")
    s = Settings(k=2, num=10, runs=2)
    a = mn.mine_outliers(p, s).verdicts.orderBy("stream_key", "median_id").collect()
    b = mn.mine_outliers(p.repartition(7, "vec"), s).verdicts.orderBy("stream_key", "median_id").collect()
    assert a == b and a


def test_shards_conserve_weight(spark, sf):
    p = src.events_points(spark, sf)
    out = mn.sharded_medians(p, shards=9, price=30.0, fan_in=3)
    assert out.agg(F.sum("weight")).head()[0] == p.count()


def test_planted_points_are_found(spark, sf):
    p = wl.planted(src.events_points(spark, sf, upto=600), [151, 351], 1e6, 1)
    r = mn.mine_outliers(p, Settings(k=2, num=100, runs=3, outlier_phases=2))
    found = {x.median_id for x in r.verdicts.where("verdict = 'outlier'").collect()}
    assert 150 in found
    q = ms.detection_quality(r.verdicts.where("verdict = 'outlier'").select(F.col("median_id").alias("point_id"), "score"), spark.createDataFrame([(150,)], "point_id long")).head()
    assert q.recall == 1


def test_mean_miner_settles(spark):
    p = line(spark, [1, 2, 1, 2, 100, 1, 2, 1, 2, 1, 2, 1, 2, 1, 2, 1])
    v = {(r.point_id, r.verdict) for r in mean_miner(p, 2, 8, 2, rule="light", min_weight=2.0).collect()}
    assert (4, "outlier") in v


def _stream_source(spark, sf, folder, parts=4):
    e = src.table(spark, sf, "events").select("event_id", "user_id", "ts", "value").orderBy("event_id").toPandas()
    step = -(-len(e) // parts)
    for i in range(parts):
        e.iloc[i * step : (i + 1) * step].to_parquet(f"{folder}/part-{i}.parquet", coerce_timestamps="us")
    return "event_id long, user_id long, ts timestamp_ntz, value double"


def test_stream_equals_batch(spark, sf, tmp_path):
    source, out = tmp_path / "in", tmp_path / "out"
    source.mkdir()
    schema = _stream_source(spark, sf, source)
    s = Settings(k=2, num=10, runs=2, n_declared=64)
    v = wl.live_events(spark, str(source), schema, s)
    v.writeStream.format("parquet").option("path", str(out)).option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start().awaitTermination(240)
    key = ("stream_key", "median_id", "first_phase", "settled_phase", "verdict")
    got = {tuple(r[c] for c in key) for r in spark.read.schema(live.VERDICTS).parquet(str(out)).collect()}
    batch = mn.mine_outliers(src.events_points(spark, sf, stream_key="user_id"), s)
    full = {r.stream_key: r.n // 10 for r in src.table(spark, sf, "events").groupBy(F.col("user_id").cast("string").alias("stream_key")).agg(F.count("*").alias("n")).collect()}
    want = {tuple(r[c] for c in key) for r in batch.verdicts.where("verdict <> 'pending'").collect() if r.settled_phase <= full[r.stream_key]}
    assert got == want and got


def test_foreach_batch_restarts(spark, sf, tmp_path):
    source, path = tmp_path / "in", str(tmp_path / "out")
    source.mkdir()
    schema = _stream_source(spark, sf, source, 3)
    s = Settings(k=2, num=100, runs=2, n_declared=1024)
    points = live.live_points(src.read_stream(spark, str(source), schema), key=None)
    sink = live.batch_miner(path, s, 1)

    def twice(df, batch):
        sink(df, batch)
        sink(df, batch)  # the same batch again changes nothing

    points.writeStream.foreachBatch(twice).option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start().awaitTermination(240)
    got = {(r.median_id, r.verdict) for r in spark.read.schema(live.VERDICTS).parquet(f"{path}/verdicts/*").collect()}
    want = {(r.median_id, r.verdict) for r in mn.mine_outliers(src.events_points(spark, sf), s).verdicts.where("verdict <> 'pending'").collect()}
    assert got == want and got


def test_scores_and_windows_on_a_stream(spark, sf, tmp_path):
    schema = _stream_source(spark, sf, tmp_path, 2)
    medians = spark.createDataFrame([(1, [20.0]), (2, [200.0])], "median_id long, vec array<double>")
    scored = live.score_stream(live.live_points(src.read_stream(spark, str(tmp_path), schema)), medians, 1, 50.0)
    scored.writeStream.format("memory").queryName("scored").trigger(availableNow=True).start().awaitTermination(240)
    assert spark.table("scored").count() == src.table(spark, sf, "events").count()
    counts = live.windowed_counts(src.read_stream(spark, str(tmp_path), schema), "1 day", "1 hour")
    counts.writeStream.format("memory").queryName("counts").outputMode("append").trigger(availableNow=True).start().awaitTermination(240)
    assert spark.table("counts").count() == 29  # the last window stays open


def test_late_rows_are_counted(spark, tmp_path):
    source = tmp_path / "in"
    source.mkdir()
    schema, frame = "event_id long, user_id long, ts timestamp_ntz, value double", lambda rows: pd.DataFrame(rows, columns=["event_id", "user_id", "ts", "value"]).astype({"ts": "datetime64[us]"})
    for i, day in enumerate(("2024-01-01", "2024-01-09", "2024-01-10", "2024-01-02")):  # the last file is late
        frame([(i * 10 + j, 1, f"{day} 00:00:0{j}", 1.0) for j in range(3)]).to_parquet(source / f"{i}.parquet")
        os.utime(source / f"{i}.parquet", (1000 + i, 1000 + i))
    points = live.live_points(src.read_stream(spark, str(source), schema))
    q = points.writeStream.format("memory").queryName("late").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(240)
    assert live.late_rows(q) == 3


def test_sources_and_sinks(spark, tmp_path):
    df = spark.createDataFrame([(1, "a"), (2, "b")], "phase int, v string")
    src.write_phases(df, str(tmp_path / "p"))
    src.write_phases(df.where("phase = 2"), str(tmp_path / "p"))
    assert src.read(spark, str(tmp_path / "p")).count() == 2
    for kind in ("csv", "json", "orc"):
        df.write.format(kind).save(str(tmp_path / kind))
        assert src.read(spark, str(tmp_path / kind), kind, "phase int, v string").count() == 2
    with pytest.raises(ValueError, match="schema"):
        src.read(spark, str(tmp_path / "csv"), "csv")


def test_sql_surface(spark, sf):
    sqlapi.register(spark)
    p = src.events_points(spark, sf, stream_key="user_id")
    sqlapi.views(p)
    by_sql = spark.sql("select stream_key, median_id, weight from facility_scan(table(select * from stream_points), 50.0D, 1)")
    done = mn.pass_assignments(p, 50.0).groupBy("stream_key", "median_id").agg(F.sum("weight").alias("weight"))
    assert {tuple(r) for r in by_sql.collect()} == {tuple(r) for r in done.collect()}
    near = sqlapi.nearest_distance(np.array([[10.0], [90.0]]))
    got = p.select("point_id", F.round(near("vec"), 6).alias("d")).collect()
    want = {r.point_id: round(min(abs(r.vec[0] - 10), abs(r.vec[0] - 90)), 6) for r in p.collect()}
    assert all(want[r.point_id] == r.d for r in got)
