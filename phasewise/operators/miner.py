"""Outlier mining over DataFrames: many keyed streams, one long stream, one huge stream in shards.  (M10, M18-M22, M25-M27)"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.distance import block_distances, distance_expr, vector
from ..functions.draws import draws
from ..plans.schedule import plan_phase
from ..sources.shared import new_path, stored, written
from .engine import Miner, Settings, StreamMiner
from .kernel import facility_pass, scan as open_scan

TAGGED = (
    "stream_key string, kind string, phase int, median_id long, vec array<double>, weight_before double, weight_after double, born_phase int, is_candidate boolean, "
    "score int, age int, first_phase int, settled_phase int, weight double, verdict string, floor double, price double, runs int, winner_run int, points_in long, points_read long, "
    "unread long, medians_out int, new_medians int, service_cost double, facility_cost double, total_cost double, ssq double, max_dist double, stop_reason string, run int, medians int"
)
COLUMNS = [c.split()[0] for c in TAGGED.split(", ")]
KINDS = {
    "phase_log": "phase floor price runs winner_run points_in points_read unread medians_out new_medians service_cost facility_cost total_cost ssq max_dist stop_reason",
    "run_log": "phase run points_read medians total_cost stop_reason",
    "medians": "phase median_id vec weight_before weight_after born_phase is_candidate score age",
    "verdicts": "median_id first_phase settled_phase age score weight verdict",
}


@dataclass
class MinerResult:
    """Tables of a run; all are filters of one tagged table."""

    tagged: DataFrame

    def table(self, kind: str) -> DataFrame:
        return self.tagged.where(F.col("kind") == kind).select("stream_key", *KINDS[kind].split())

    phase_log = property(lambda self: self.table("phase_log"))
    run_log = property(lambda self: self.table("run_log"))
    medians = property(lambda self: self.table("medians"))
    verdicts = property(lambda self: self.table("verdicts"))

    @property
    def outliers(self) -> DataFrame:
        place = self.medians.groupBy("stream_key", "median_id").agg(F.first("vec").alias("vec"))
        return self.verdicts.where("verdict = 'outlier'").join(place, ["stream_key", "median_id"])

    def final(self, recent_only: bool = True) -> tuple[DataFrame, DataFrame]:
        """(medians, outliers); ``recent_only``: those of the last phase, medians without the outliers that it
        retired.  (M30)"""
        if not recent_only:
            return self.medians, self.outliers
        last = self.phase_log.groupBy("stream_key").agg(F.max("phase").alias("last"))
        held = self.medians.join(last, "stream_key").where("phase = last").drop("last")
        gone = self.verdicts.where("verdict = 'outlier'").select("stream_key", "median_id")
        return held.join(gone, ["stream_key", "median_id"], "left_anti"), self.outliers.join(last, "stream_key").where("settled_phase = last").drop("last")


ARROW = {"string": pa.string(), "int": pa.int32(), "long": pa.int64(), "double": pa.float64(), "boolean": pa.bool_(), "array<double>": pa.list_(pa.float64())}
SCHEMA = pa.schema([(f.split()[0], ARROW[f.split()[1]]) for f in TAGGED.split(", ")])


def rows_of(log, stream_key: str, keep: tuple[str, ...] = tuple(KINDS)) -> pa.Table:
    """The log of a stream as rows of the tagged table, of the kinds in ``keep``."""
    tables = [SCHEMA.empty_table()]
    for kind, rows in (("phase_log", log.phases), ("run_log", log.runs), ("medians", log.medians), ("verdicts", log.verdicts)):
        if rows and kind in keep:
            mine = {c: pa.array([r[c] for r in rows], SCHEMA.field(c).type) for c in KINDS[kind].split()}
            mine |= {"stream_key": pa.repeat(pa.scalar(stream_key, pa.string()), len(rows)), "kind": pa.repeat(kind, len(rows))}
            tables.append(pa.table([mine[f.name] if f.name in mine else pa.nulls(len(rows), f.type) for f in SCHEMA], schema=SCHEMA))
    return pa.concat_tables(tables)


def _columns(table: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(point ids, coordinates, weights) in stream order."""
    table = table.sort_by("ordinal")
    vec = table.column("vec").combine_chunks()
    x = vec.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(table), -1)
    return table.column("point_id").to_numpy(), x, table.column("weight").to_numpy()


def _arrays(pdf: pd.DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    pdf = pdf.sort_values("ordinal", kind="stable")
    return pdf["point_id"].to_numpy(np.int64), np.stack(pdf["vec"].to_numpy()).astype(float), pdf["weight"].to_numpy(float)


def mine_outliers(points: DataFrame, settings: Settings = Settings(), *, keep: tuple[str, ...] = tuple(KINDS)) -> MinerResult:
    """Many streams, each on its own: one exchange by stream key, then the phases in the stream's task, which
    holds the stream.  A single long stream goes through ``mine_single_stream``, a huge one through
    ``mine_shards``.  ``keep`` names the tables that are given away (all of them)."""

    def run(table: pa.Table) -> pa.Table:
        ids, x, w = _columns(table)
        miner = Miner(settings, x.shape[1])
        miner.log.holds_medians = "medians" in keep
        return rows_of(miner.run(ids, x, w), table.column("stream_key")[0].as_py(), keep)

    return MinerResult(points.select("stream_key", "ordinal", "point_id", "vec", "weight").groupBy("stream_key").applyInArrow(run, TAGGED))


STATE = "state"


LAST_MEDIANS = "last_medians"


def _stretch(settings: Settings, n: int, key: str, state: str | None, last: bool, keep: tuple[str, ...]):
    """Reads a stretch of one stream, batch by batch: log rows, given away as they come, and the state that the
    next one needs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        stream = None
        kinds = tuple("medians" if k == LAST_MEDIANS else k for k in keep)

        def given(ends: bool) -> Iterator[pa.RecordBatch]:
            log = stream.miner.log
            medians = log.medians if log.last_only and not ends else None
            if medians is not None:  # they may not be the last yet
                log.medians = []
            yield from rows_of(log, key, kinds).to_batches(max_chunksize=10_000)
            log.phases.clear(), log.runs.clear(), log.medians.clear(), log.verdicts.clear()
            log.medians = medians if medians is not None else log.medians

        for batch in batches:
            if batch.num_rows:
                ids, x, w = _columns(pa.Table.from_batches([batch]))
                if stream is None:
                    stream = StreamMiner(settings, x.shape[1], state, n=n)
                    stream.miner.log.holds_medians, stream.miner.log.last_only = "medians" in kinds, LAST_MEDIANS in keep
                stream.add(ids, x, w)
                yield from given(False)
        if stream is None:
            return
        if last:
            stream.flush(final=True)
        yield from given(True)
        if not last:
            yield from pa.Table.from_pylist([{"stream_key": key, "kind": STATE, "stop_reason": stream.state()}], schema=SCHEMA).to_batches()

    return run


def mine_single_stream(points: DataFrame, settings: Settings = Settings(), *, stretch: int = 1_000_000, path: str | None = None, keep: tuple[str, ...] = tuple(KINDS)) -> MinerResult:
    """One long stream, of any length: its ordered points are written once, then read in stretches of
    ``stretch`` ordinals.  A stretch is one task that takes its rows batch by batch, from the state that the
    stretch before left to its own, which is written with its log rows below ``path``.  No task or driver
    holds the stream: a task holds a batch, the points that are not read yet, the medians, and a batch's log.

    ``keep`` names the tables that are written (all of them); with "last_medians" the table of medians holds
    those of each stretch's last phase only.

    A call with the same ``path`` goes on after the last stretch that was written.  In limit-driven mode
    an open phase must not cross a border, so the rest of the stream is one stretch."""
    spark = points.sparkSession
    base = path or new_path(spark, "stream")
    held = points.select("stream_key", "ordinal", "point_id", "vec", "weight").repartitionByRange("ordinal").sortWithinPartitions("ordinal")
    held = spark.read.parquet(f"{base}/points") if _exists(spark, f"{base}/points/_SUCCESS") else written(held, f"{base}/points")
    n = held.agg(F.max("ordinal")).head()[0] or 0
    if not n:
        return MinerResult(spark.createDataFrame([], TAGGED))
    key = held.select("stream_key").head()[0]
    size = n if settings.mode == "limit_driven" else max(stretch, settings.num)
    state, tables = None, []
    for i, at in enumerate(range(0, n, size)):
        where = f"{base}/log-{i}"
        if not _exists(spark, f"{where}/_SUCCESS"):
            rows = held.where(F.col("ordinal").between(at + 1, at + size)).coalesce(1).sortWithinPartitions("ordinal")
            written(rows.mapInArrow(_stretch(settings, settings.n_declared or n, key, state, at + size >= n, keep), TAGGED), where)
        tables.append(where)
        state = spark.read.schema(TAGGED).parquet(where).where(F.col("kind") == STATE).select("stop_reason").head()
        state = state[0] if state else None
    return MinerResult(spark.read.schema(TAGGED).parquet(*tables))


def _exists(spark, path: str) -> bool:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()).exists(at)


def sharded_medians(points: DataFrame, *, shards: int, price: float, settings: Settings = Settings(), fan_in: int = 64) -> DataFrame:
    """One huge stream as (median_id, vec, weight): stretches of ordinals are condensed side
    by side at one shared price, then merged ``fan_in`` at a time; every round's medians are written.  An
    approximation: the order of points counts within a stretch only.  Weights add up to the stream's.  (M22)"""
    schema = "shard long, ordinal long, point_id long, vec array<double>, weight double"

    def condense(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("ordinal", kind="stable")
        ids, x, w = _arrays(pdf)
        p = facility_pass(x, w, draws(settings.draws, settings.seed, 0, 0, ids, settings.constant), price, rule=settings.opening_rule, distance=settings.distance)
        return pd.DataFrame({"shard": pdf["shard"].iloc[0], "ordinal": pdf["ordinal"].to_numpy()[p.rows], "point_id": ids[p.rows], "vec": list(x[p.rows]), "weight": p.weight})

    n = points.agg(F.max("ordinal")).head()[0] or 1
    out = points.withColumn("shard", F.floor((F.col("ordinal") - 1) * shards / F.lit(n)).cast("long")).select(*(f.split()[0] for f in schema.split(", ")))
    out = stored(out.groupBy("shard").applyInPandas(condense, schema), "shards")
    while shards > 1:
        shards = -(-shards // fan_in)
        out = stored(out.withColumn("shard", F.floor(F.col("shard") / fan_in).cast("long")).groupBy("shard").applyInPandas(condense, schema), "shards")
    return out.select(F.col("point_id").alias("median_id"), "vec", "weight")


def shared_price(points: DataFrame, settings: Settings, d: int, phase: int = 1) -> float:
    """The price of a phase of the whole stream: what ``sharded_medians`` should be given."""
    from ..plans.schedule import initial_floor

    row = initial_floor(points, settings.k, settings.beta, d=d, distance=settings.distance, zero_floor=settings.zero_floor).head()
    n = settings.n_declared or points.count()
    floor = settings.floor if settings.floor is not None else (row["floor"] if row else 0.0)
    return plan_phase(phase, floor * settings.beta ** (phase - 1), k=settings.k, n=n, gamma=settings.gamma, beta=settings.beta, log_base=settings.log_base).price


def mine_shards(points: DataFrame, d: int, settings: Settings = Settings(), *, shards: int, price: float | None = None) -> dict[str, DataFrame]:
    """A huge stream in shards, with verdicts.  Phases are ``num`` ordinals each, as in one stream.

    The shards' medians are found at one shared price.  A confirming scan then assigns every point to
    its nearest median (a broadcast of medians, behind a check of their number) and counts who gains
    weight in which phase; a median stalls in a phase that gives it no point but itself.  Ageing and settling
    follow the same rule as the miner's, over these counts.  (M22)

    Returns medians, stalls (median_id, phase, stalled) and verdicts."""
    price = shared_price(points, settings, d) if price is None else price
    medians = stored(sharded_medians(points, shards=shards, price=price, settings=settings), "medians")
    phase = F.floor((F.col("ordinal") - 1) / settings.num) + 1
    near = assign(points, medians, d, settings.distance, keep=("ordinal",))
    hits = near.where(F.col("point_id") != F.col("median_id")).groupBy("median_id", phase.cast("int").alias("phase")).agg(F.sum("weight").alias("gained"))
    born = points.select(F.col("point_id").alias("median_id"), phase.cast("int").alias("born")).join(F.broadcast(medians.select("median_id")), "median_id")
    last = points.agg(F.max(phase).cast("int").alias("last"))
    every = born.join(F.broadcast(last), F.lit(True)).select("median_id", F.explode(F.sequence("born", "last")).alias("phase"))  # one row
    stalls = stored(every.join(hits, ["median_id", "phase"], "left").select("median_id", "phase", F.col("gained").isNull().alias("stalled")), "stalls")
    return {"medians": medians, "stalls": stalls, "verdicts": settle(stalls, settings.outlier_phases)}


MOST_MEDIANS, MOST_ELEMENTS = 200_000, 128


def _assign_blocks(points: DataFrame, medians: DataFrame, distance: str, keep: tuple[str, ...]) -> DataFrame:
    rows = medians.select("median_id", "vec").orderBy("median_id").collect()  # MOST_MEDIANS at most
    held = points.sparkSession.sparkContext.broadcast((np.array([r.median_id for r in rows], np.int64), np.array([list(r.vec) for r in rows], float)))
    columns = ["stream_key", "point_id", "weight", *keep]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, at = held.value
        for batch in batches:
            for start in range(0, batch.num_rows, 1024):
                part = batch.slice(start, 1024)
                x = np.array(part.column(0).to_pylist(), float).reshape(part.num_rows, -1)
                gap = block_distances(distance, x, at)
                near = gap.argmin(1)  # ids are in order: ties go to the smaller one
                found = [pa.array(ids[near]), pa.array(gap[np.arange(len(near)), near])]
                yield pa.RecordBatch.from_arrays([*part.columns[1:4], *found, *part.columns[4:]], ["stream_key", "point_id", "weight", "median_id", "dist", *keep])

    kinds = {f.name: f.dataType.simpleString() for f in points.schema.fields}
    schema = ", ".join(f"`{c}` {kinds[c]}" for c in columns[:3]) + ", median_id bigint, dist double" + "".join(f", `{c}` {kinds[c]}" for c in keep)
    return points.select("vec", *columns).mapInArrow(run, schema)


def assign(points: DataFrame, medians: DataFrame, d: int, distance: str = "euclidean", keep: tuple[str, ...] = ()) -> DataFrame:
    """(stream_key, point_id, weight, median_id, dist, ``keep``): each row's nearest median; ties go to the
    smaller id.  Medians with a stream_key are for the points of that stream; without one they are for
    all.  (M25)

    A stream's medians are one array beside its points, and the nearest is its least element: points are
    neither multiplied nor moved while the medians can be broadcast (a check of their number).  Beyond
    that, keyed medians meet their points by an exchange.  More than MOST_ELEMENTS medians for all points
    meet them in matrices of blocks, with the same distances."""
    few = medians.count() <= MOST_MEDIANS
    one = F.sort_array(F.collect_list(F.struct("median_id", "vec"))).alias("_ms")
    if "stream_key" in medians.columns:
        held = medians.groupBy("stream_key").agg(one)
        both = points.join(F.broadcast(held) if few else held, "stream_key")
    elif few:
        if medians.count() > MOST_ELEMENTS:
            return _assign_blocks(points, medians, distance, keep)
        both = points.join(F.broadcast(medians.agg(one)), F.lit(True))
    else:
        raise ValueError(f"more than {MOST_MEDIANS} medians: condense them first (sharded_medians)")
    gap = lambda m: distance_expr(distance, vector("vec", d), [m["vec"].getItem(i) for i in range(d)])
    best = F.array_min(F.transform("_ms", lambda m: F.struct(gap(m).alias("dist"), m["median_id"].alias("median_id"))))
    out = both.select("stream_key", "point_id", "weight", *keep, best.alias("_m"))
    return out.select("stream_key", "point_id", "weight", "_m.median_id", "_m.dist", *keep)


def explain_outliers(outliers: DataFrame, medians: DataFrame, d: int) -> DataFrame:
    """(median_id, near_id, dist, share): the nearest other median and each dimension's part of the
    squared distance to it.  (M27)"""
    others = medians.select(F.col("median_id").alias("near_id"), F.col("vec").alias("mvec"))
    pairs = outliers.select("median_id", "vec").join(F.broadcast(others), F.col("median_id") != F.col("near_id"))
    pairs = pairs.withColumn("dist", distance_expr("euclidean", vector("vec", d), vector("mvec", d)))
    near = pairs.groupBy("median_id").agg(F.min(F.struct("dist", "near_id", "vec", "mvec")).alias("m"))
    part = lambda i: (F.col("m.vec")[i] - F.col("m.mvec")[i]) * (F.col("m.vec")[i] - F.col("m.mvec")[i])
    return near.select("median_id", "m.near_id", "m.dist", *((F.when(F.col("m.dist") > 0, part(i) / (F.col("m.dist") * F.col("m.dist"))).otherwise(0.0)).alias(f"share_{i}") for i in range(d)))


# steps over tables (the same rules as the engine's, for logs at rest) -------------------------


def mark_candidates(before: DataFrame, after: DataFrame, rule: str = "stalled", max_weight: float = 3.0) -> DataFrame:
    """(median_id, weight_before, weight_after, is_new, is_candidate) from (median_id, weight) tables; a
    new median stalls if it kept the weight it opened with (``own``).  (M14)"""
    b = before.select("median_id", F.col("weight").alias("weight_before"))
    a = after.select("median_id", F.col("weight").alias("weight_after"), "own")
    both = b.join(a, "median_id", "full_outer")
    stalled = F.col("weight_after").isNotNull() & (F.col("weight_after") == F.coalesce("weight_before", "own"))
    if rule == "stalled_light":
        stalled = stalled & (F.col("weight_after") <= max_weight)
    return both.select("median_id", "weight_before", "weight_after", F.col("weight_before").isNull().alias("is_new"), F.coalesce(stalled, F.lit(False)).alias("is_candidate"))


def settle(stalls: DataFrame, phases: int) -> DataFrame:
    """(median_id, first_phase, verdict) from (median_id, phase, stalled): outlier if all of ``phases``
    phases from the first stall on stalled, pending if the log ends before, else inlier.  (M15)"""
    first = stalls.where("stalled").groupBy("median_id").agg(F.min("phase").alias("first_phase"))
    seen = stalls.join(first, "median_id").where((F.col("phase") >= F.col("first_phase")) & (F.col("phase") < F.col("first_phase") + phases))
    score = seen.groupBy("median_id", "first_phase").agg(F.sum(F.col("stalled").cast("int")).alias("score"), F.count("*").alias("age"))
    verdict = F.when(F.col("age") < phases, "pending").when(F.col("score") == phases, "outlier").otherwise("inlier")
    return score.select("median_id", "first_phase", F.col("age").cast("long").alias("age"), F.col("score").cast("long").alias("score"), verdict.alias("verdict"))


def retire(medians: DataFrame, outliers: DataFrame) -> DataFrame:
    """Medians without the settled outliers.  (M16)"""
    return medians.join(outliers.select("median_id"), "median_id", "left_anti")


def next_input(medians: DataFrame, unread: DataFrame) -> DataFrame:
    """Carried medians first, then unread points, in order.  (M13)"""
    carried = medians.select(F.lit(0).alias("rank"), F.col("median_id").alias("point_id"), "vec", "weight")
    return carried.unionByName(unread.select(F.lit(1).alias("rank"), "point_id", "vec", "weight"))


def split_read(points: DataFrame, read: int, carried: int = 0) -> DataFrame:
    """``points`` with is_read; positions count the carried medians first.  (M12)"""
    return points.withColumn("is_read", F.col("ordinal") + carried <= read)


def stop_audit(assignments: DataFrame, price: float, cost_cap: float) -> DataFrame:
    """(stream_key, first_over): the first ordinal whose running cost passes the cap.  (M9)"""
    running = F.sum(F.when(F.col("opens"), F.lit(price)).otherwise(F.col("dist") * F.col("weight"))).over(W.partitionBy("stream_key").orderBy("ordinal").rowsBetween(W.unboundedPreceding, 0))
    return assignments.withColumn("cost", running).where(F.col("cost") > cost_cap).groupBy("stream_key").agg(F.min("ordinal").alias("first_over"))


def pass_assignments(points: DataFrame, price: float, settings: Settings = Settings(), run: int = 0, phase: int = 1) -> DataFrame:
    """(stream_key, ordinal, point_id, weight, median_id, dist, opens): one facility pass per stream."""

    def go(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("ordinal", kind="stable")
        ids, x, w = _arrays(pdf)
        p = facility_pass(x, w, draws(settings.draws, settings.seed, run, phase, ids, settings.constant), price, rule=settings.opening_rule, distance=settings.distance)
        opens = np.zeros(len(ids), bool)
        opens[p.rows] = True
        return pd.DataFrame({"stream_key": pdf["stream_key"].iloc[0], "ordinal": pdf["ordinal"].to_numpy(), "point_id": ids, "weight": w, "median_id": ids[p.rows][p.to], "dist": p.dist, "opens": opens})

    return points.groupBy("stream_key").applyInPandas(go, "stream_key string, ordinal long, point_id long, weight double, median_id long, dist double, opens boolean")


def pass_stream(points: DataFrame, price: float, settings: Settings = Settings(), run: int = 0, phase: int = 1) -> DataFrame:
    """``pass_assignments`` of one long stream: one task reads it in order, batch by batch, and holds a batch and
    the open medians only (a pass is sequential by definition; ``sharded_medians`` is its parallel form)."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scan = None
        for batch in batches:
            if not batch.num_rows:
                continue
            table = pa.Table.from_batches([batch])
            ids, x, w = _columns(table)
            scan = scan or open_scan(x.shape[1], price, rule=settings.opening_rule, distance=settings.distance, keep=True)
            m = len(scan.rows)
            scan.feed(ids, x, w, draws(settings.draws, settings.seed, run, phase, ids, settings.constant))
            opens = np.zeros(len(ids), bool)
            opens[scan.rows[m:] - (scan.read - len(ids))] = True
            to, dist = np.array(scan.ids, np.int64)[scan.to], scan.dist
            scan.kept.clear()
            yield pa.RecordBatch.from_arrays([table.column("stream_key").combine_chunks(), table.column("ordinal").combine_chunks(), pa.array(ids), pa.array(w), pa.array(to), pa.array(dist), pa.array(opens)], ["stream_key", "ordinal", "point_id", "weight", "median_id", "dist", "opens"])

    rows = points.select("stream_key", "ordinal", "point_id", "vec", "weight").coalesce(1).sortWithinPartitions("ordinal")
    return rows.mapInArrow(go, "stream_key string, ordinal long, point_id long, weight double, median_id long, dist double, opens boolean")
