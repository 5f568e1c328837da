"""Neighbour baselines: k-th neighbour ranking, distance-fraction outliers, windowed counts, local
density.  (B1, B2, B4, B5)

All pairs are quadratic by definition, so copies are not expanded into pairs, and blocks of neighbouring
points meet only the blocks that can hold a nearer one.  ``most_rows``, where it is given, fails a larger
table; without it tables of any size go through.  "cells" and "grid" have the same answers from counts
of grid cells: only the points in sparse cells are measured."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import product

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.distance import block_distances, distance_expr, distances, vector
from ..operators.points import with_ordinal
from ..sources.shared import stored

MOST_ROWS = 50_000  # more points than that do not meet as one theta join, or as one broadcast
BLOCK, SAMPLE = 1024, 100_000
HALVED, FULL = 2, 64  # how often cells are halved, while they hold so many points
PLACES, LEAF = 4096, 64  # places of a block that is counted within a radius, and of its parts
NEAR = "point_id long, near array<struct<dist:double,id:long>>"


def _guard(points: DataFrame, most_rows: int | None) -> None:
    if most_rows is not None:
        n = points.count()
        if n > most_rows:
            raise ValueError(f"{n} rows: an all-pairs baseline is limited to {most_rows} (raise most_rows to go on)")


def _kept(points: DataFrame, k: int) -> DataFrame:
    """(point_id, vec, place, copies), the first k + 1 ids of each place: nobody's k nearest hold a later one, and a
    place with more than k copies is its own neighbourhood."""
    of = W.partitionBy("vec")
    ranked = points.select("point_id", "vec").withColumn("place", F.row_number().over(of.orderBy("point_id")))
    sizes = points.groupBy("vec").agg(F.count("*").alias("copies"))
    return stored(ranked.where(F.col("place") <= k + 1).join(sizes, "vec").select("point_id", "vec", "place", "copies"), "places")


def _sides(points: DataFrame) -> tuple[DataFrame, DataFrame]:
    return points.select(F.col("point_id").alias("a_id"), F.col("vec").alias("a")), points.select(F.col("point_id").alias("b_id"), F.col("vec").alias("b"))


def _tree(x: np.ndarray, most: int) -> list[tuple[int, float, int, int]]:
    """Halving cuts of a sample down to ``most`` points a leaf: (dimension, value, below, from there on), or
    (-1, 0, leaf, 0)."""
    nodes: list = [None]
    todo, leaves = [(0, np.arange(len(x)))], 0
    while todo:
        at, rows = todo.pop()
        width = x[rows].max(0) - x[rows].min(0) if len(rows) > most else np.zeros(1)
        if not width.max(initial=0.0) > 0:
            nodes[at], leaves = (-1, 0.0, leaves, 0), leaves + 1
            continue
        i = int(width.argmax())
        v = x[rows, i]
        cut = np.partition(v, len(v) // 2)[len(v) // 2]
        cut = cut if cut > v.min() else v[v > cut].min()
        nodes[at] = (i, float(cut), len(nodes), len(nodes) + 1)
        todo += [(len(nodes), rows[v < cut]), (len(nodes) + 1, rows[v >= cut])]
        nodes += [None, None]
    return nodes


def _packed(kept: DataFrame, k: int, d: int) -> DataFrame:
    """(block, ids, x, asks): neighbouring points, BLOCK or so a row; ``asks`` marks those whose k nearest are wanted.
    The cuts are fitted on SAMPLE points or so, which bears on the work only."""
    n = kept.count()
    some = kept.where(F.pmod(F.xxhash64("point_id"), F.lit(max(1, n // SAMPLE))) == 0).select("vec").collect()
    x = np.array([list(r.vec) for r in some], float).reshape(-1, d)
    tree = _tree(x, max(8, BLOCK * len(x) // max(n, 1)))
    dim, cut, low, high = (np.array(c) for c in zip(*tree, strict=True))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(batch.num_rows, d)
            at, rows = np.zeros(len(x), np.int64), np.arange(len(x))
            while len(rows := rows[dim[at[rows]] >= 0]):
                here = at[rows]
                at[rows] = np.where(x[rows, dim[here]] < cut[here], low[here], high[here])
            yield pa.RecordBatch.from_arrays([pa.array(low[at].astype(np.int32)), *batch.columns], ["block", "point_id", "vec", "asks"])

    def pack(key: tuple, table: pa.Table) -> pa.Table:
        table = table.sort_by("point_id")
        x = table.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(float)
        asks = table.column("asks").to_numpy()
        return pa.table({"block": pa.array([key[0].as_py()], pa.int32()), "ids": pa.array([table.column("point_id").to_numpy().tobytes()], pa.binary()), "x": pa.array([x.tobytes()], pa.binary()), "asks": pa.array([asks.astype(bool).tobytes()], pa.binary())})

    rows = kept.where(F.col("place") <= k).select("point_id", "vec", F.col("asks") if "asks" in kept.columns else (F.col("copies") <= k).alias("asks"))
    return stored(rows.mapInArrow(place, "block int, point_id long, vec array<double>, asks boolean").groupBy("block").applyInArrow(pack, "block int, ids binary, x binary, asks binary"), "blocks")


def nearest_lists(points: DataFrame, k: int, d: int, *, distance: str = "euclidean", prune: bool = False, most_rows: int | None = None) -> DataFrame:
    """(point_id, near): the k nearest others of each point, nearest first (ties: smaller id).

    A point with k copies of its place has its nearest there.  Of the rest, neighbouring points make a block,
    each block is a matrix of distances, of which k columns a row go on; the k-th bounds what is left to
    look for, so a point meets only the other blocks whose box is not beyond it.  ``prune`` sorts a block by
    distance from a pivot and leaves out the columns that the triangle inequality puts beyond a row's k-th."""
    if prune and distance == "sqeuclidean":
        raise ValueError("pruning needs a metric")
    _guard(points, most_rows)
    return _nearest_lists(points, _kept(points, k), k, d, distance, prune)


def _nearest_lists(points: DataFrame, kept: DataFrame, k: int, d: int, distance: str, prune: bool) -> DataFrame:
    lists = _nearest_apart(kept, k, d, distance, prune)
    firsts = kept.where(F.col("copies") > k).groupBy("vec").agg(F.sort_array(F.collect_list("point_id")).alias("ids"))  # k + 1 a place
    here = F.slice(F.filter("ids", lambda i: i != F.col("point_id")), 1, k)
    dense = points.select("point_id", "vec").join(firsts, "vec", "left")
    near = F.when(F.col("ids").isNotNull(), F.transform(here, lambda i: F.struct(F.lit(0.0).alias("dist"), i.alias("id"))))
    return dense.select("point_id", near.alias("copies")).join(lists, "point_id", "left").select("point_id", F.coalesce("copies", "near").alias("near"))


def _nearest_apart(kept: DataFrame, k: int, d: int, distance: str, prune: bool) -> DataFrame:
    """(point_id, near) of the points with fewer than k copies of their place."""
    if not kept.where(F.col("copies") <= k).head(1):
        return kept.sparkSession.createDataFrame([], NEAR)
    packed = _packed(kept, k, d)

    def box(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                x = np.frombuffer(row["x"]).reshape(-1, d)
                yield pa.RecordBatch.from_arrays([pa.array([row["block"]], pa.int32()), pa.array([x.min(0).tolist()]), pa.array([x.max(0).tolist()])], ["block", "lo", "hi"])

    boxes = packed.mapInArrow(box, "block int, lo array<double>, hi array<double>").orderBy("block").collect()  # one a block
    number, lo, hi = np.array([r.block for r in boxes]), np.array([r.lo for r in boxes]), np.array([r.hi for r in boxes])

    def full(a_ids, a, ids, x) -> Iterator[tuple]:
        gap = block_distances(distance, a, x)
        gap[np.equal.outer(a_ids, ids)] = np.inf
        for i, row in enumerate(gap):
            few = min(k, int(np.isfinite(row).sum()))
            if few:
                some = np.flatnonzero(row <= np.partition(row, few - 1)[few - 1])
                yield i, some, row[some]

    def pruned(a_ids, a, ids, x) -> Iterator[tuple]:
        to_pivot = distances(distance, x, x[0])
        order = np.argsort(to_pivot, kind="stable")
        at, x, ids = to_pivot[order], x[order], ids[order]
        for i, v in enumerate(a):
            mine = float(distances(distance, x[:1], v)[0]) if len(x) else 0.0
            middle, reach = int(np.searchsorted(at, mine)), max(2 * k, 16)
            while True:  # a window around the point's own distance grows until all outside it is too far
                lo, hi = max(0, middle - reach), min(len(x), middle + reach)
                gap = distances(distance, x[lo:hi], v)
                gap[ids[lo:hi] == a_ids[i]] = np.inf
                few = min(k, int(np.isfinite(gap).sum()))
                bound = np.partition(gap, few - 1)[few - 1] if few == k else np.inf
                if (lo == 0 or mine - at[lo - 1] > bound) and (hi == len(x) or at[hi] - mine > bound):
                    break
                reach *= 2
            if few:
                some = np.flatnonzero(gap <= np.partition(gap, few - 1)[few - 1])
                yield i, order[lo + some], gap[some]

    def lists(a_ids, a, ids, x) -> dict[int, list]:
        found = (pruned if prune else full)(a_ids, a, ids, x)
        return {i: sorted(zip(g.tolist(), ids[j].tolist(), strict=True))[:k] for i, j, g in found}

    def own(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                asks = np.frombuffer(row["asks"], bool)
                if not asks.any():
                    continue
                ids, x = np.frombuffer(row["ids"], np.int64), np.frombuffer(row["x"]).reshape(-1, d)
                a_ids, a = ids[asks], x[asks]
                near = lists(a_ids, a, ids, x)
                near = [near.get(i, []) for i in range(len(a))]
                reach = np.array([g[-1][0] if len(g) == k else np.inf for g in near])
                out = [(row["block"], None, None, int(i), g) for i, g in zip(a_ids, near, strict=True)]
                gap = _box_gap(distance, a.min(0), a.max(0), lo, hi)
                for other in np.flatnonzero((gap <= reach.max()) & (number != row["block"])):
                    mine = _box_gap(distance, a, a, lo[other], hi[other]) <= reach
                    if mine.any():
                        out.append((int(number[other]), a_ids[mine].tobytes(), a[mine].tobytes(), None, None))
                yield from _rows(out)

    def others(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                a_ids, ids = np.frombuffer(row["a_ids"], np.int64), np.frombuffer(row["ids"], np.int64)
                near = lists(a_ids, np.frombuffer(row["a"]).reshape(-1, d), ids, np.frombuffer(row["x"]).reshape(-1, d))
                yield from _rows([(0, None, None, int(a_ids[i]), g) for i, g in near.items()])

    first = stored(packed.repartition(WIDE).mapInArrow(own, MET), "met")
    meet = first.where("a_ids is not null").select("block", "a_ids", "a").join(packed.select("block", "ids", "x"), "block").repartition(WIDE)
    every = first.where("point_id is not null").select("point_id", "near").unionByName(meet.mapInArrow(others, MET).select("point_id", "near"))
    near = every.groupBy("point_id").agg(F.slice(F.array_sort(F.flatten(F.collect_list("near"))), 1, k).alias("near"))  # k a block
    return near.where(F.size("near") > 0)


WIDE = 64
MET = "block int, a_ids binary, a binary, point_id long, near array<struct<dist:double,id:long>>"


def _rows(out: list[tuple]) -> Iterator[pa.RecordBatch]:
    if out:
        block, a_ids, a, ids, near = zip(*out, strict=True)
        near = [None if g is None else [{"dist": t, "id": j} for t, j in g] for g in near]
        yield pa.RecordBatch.from_arrays([pa.array(block, pa.int32()), pa.array(a_ids, pa.binary()), pa.array(a, pa.binary()), pa.array(ids, pa.int64()), pa.array(near, pa.list_(pa.struct([("dist", pa.float64()), ("id", pa.int64())])))], ["block", "a_ids", "a", "point_id", "near"])


def _box_gap(distance: str, low: np.ndarray, high: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """The least distance between points of two boxes, rounded as the points' own distances are."""
    return distances(distance, np.maximum(np.maximum(lo - high, low - hi), 0.0), np.zeros(lo.shape[-1]))


def kth_distances(points: DataFrame, k: int, d: int, *, method: str = "join", distance: str = "euclidean", most_rows: int | None = None) -> DataFrame:
    """(point_id, dist): distance to the k-th nearest other point.

    "join": pairs in the JVM, a ranking window per point (of MOST_ROWS points at most; more go through blocks);
    "block": NumPy matrices of blocks; "pruned": the same with columns left out by the triangle inequality.  A
    point with k copies of its place meets nobody: its distance is 0."""
    if method not in ("join", "block", "pruned"):
        raise ValueError(f"unknown method {method!r}")
    _guard(points, most_rows)
    kept = _kept(points, k)
    far = kept.where(F.col("copies") <= k)
    if method == "join" and far.count() <= MOST_ROWS:
        a, _ = _sides(far)
        _, b = _sides(kept.where(F.col("place") <= k))
        pairs = b.join(F.broadcast(a), F.col("a_id") != F.col("b_id")).select("a_id", distance_expr(distance, vector("a", d), vector("b", d)).alias("dist"))
        rank = F.row_number().over(W.partitionBy("a_id").orderBy("dist"))
        apart = pairs.withColumn("r", rank).where(F.col("r") <= k).groupBy("a_id").agg(F.max(F.when(F.col("r") == k, F.col("dist"))).alias("apart")).select(F.col("a_id").alias("point_id"), "apart")
    else:
        apart = _nearest_apart(kept, k, d, distance, method == "pruned").select("point_id", F.get("near", F.lit(k - 1))["dist"].alias("apart"))
    dense = kept.where((F.col("copies") > k) & (F.col("place") == 1)).select("vec", F.lit(0.0).alias("here"))
    both = points.select("point_id", "vec").join(dense, "vec", "left").join(apart, "point_id", "left")
    return both.select("point_id", F.coalesce("here", "apart").alias("dist"))


def kth_distances_of(some: DataFrame, points: DataFrame, k: int, d: int, distance: str = "euclidean") -> list[tuple[float, int]]:
    """(dist, point_id) of the points ``some`` (few: they are broadcast), each against all points."""
    rows = some.select("point_id", "vec").collect()
    ids, x = np.array([r.point_id for r in rows], np.int64), np.array([list(r.vec) for r in rows], float).reshape(-1, d)
    held = points.sparkSession.sparkContext.broadcast((ids, x))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, x = held.value
        best = np.full((len(ids), k), np.inf)
        for batch in batches:
            for at in range(0, batch.num_rows, BLOCK):
                part = batch.slice(at, BLOCK)
                others = part.column(1).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(-1, d)
                gap = block_distances(distance, x, others)
                gap[np.equal.outer(ids, part.column(0).to_numpy())] = np.inf
                best = np.partition(np.concatenate([best, gap], 1), k - 1, axis=1)[:, :k]
        near = [sorted(g for g in row if g < np.inf) for row in best.tolist()]
        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(near, pa.list_(pa.float64()))], ["point_id", "near"])

    near = points.select("point_id", "vec").mapInArrow(run, "point_id long, near array<double>")
    near = near.groupBy("point_id").agg(F.slice(F.array_sort(F.flatten(F.collect_list("near"))), 1, k).alias("near"))  # k a task
    return sorted(((r.near[k - 1], r.point_id) for r in near.collect() if len(r.near) == k), key=lambda r: (-r[0], r[1]))


def knn_rank_cells(points: DataFrame, k: int = 3, top_n: int = 7, *, d: int, most_rows: int = MOST_ROWS) -> DataFrame:
    """``knn_rank`` without all pairs.  A point in a grid cell with k others has its k-th neighbour within the box of the
    cell's points, whose diagonal is its bound; points in other cells have none.  Cells are made smaller until top_n points
    have no bound; some of these are measured against all, and what is bounded below the top_n-th of them cannot be among
    the first.  The rest are measured among the points of the cells around, as neighbouring blocks, and once more against
    all where that may miss a neighbour.  Where copies fill every cell the first ids are the answer; where more than
    ``most_rows`` points would be measured against all, the blocks of all points give it."""
    spark, keys = points.sparkSession, [f"k{i}" for i in range(d)]
    p, axes = points.select("point_id", "vec"), [F.col("vec")[i] for i in range(d)]
    span = p.agg(*(F.max(v).alias(f"hi{i}") for i, v in enumerate(axes)), *(F.min(v).alias(f"lo{i}") for i, v in enumerate(axes)), F.count("*").alias("n")).head()
    side = max((span[f"hi{i}"] - span[f"lo{i}"] for i in range(d)), default=0.0) if span["n"] else 0.0
    whole = lambda: knn_rank(points, k, top_n, d=d, method="block")
    if span["n"] <= k + top_n or not side > 0:
        return whole()
    loose = p.groupBy(*(v.alias(key) for key, v in zip(keys, axes, strict=True))).agg(F.count("*").alias("c")).where(F.col("c") <= k).agg(F.coalesce(F.sum("c"), F.lit(0))).head()[0]
    if not loose:  # k copies or more beside every point
        return p.orderBy("point_id").limit(top_n).select("point_id", F.lit(0.0).alias("dist"))
    if loose < top_n:
        return whole()
    boxes = [F.min(f"lo{i}").alias(f"lo{i}") for i in range(d)] + [F.max(f"hi{i}").alias(f"hi{i}") for i in range(d)]
    wide = F.sqrt(sum(((F.col(f"hi{i}") - F.col(f"lo{i}")) ** 2 for i in range(d)), F.lit(0.0))) * (1 + 1e-9)

    def halves(by: int) -> DataFrame:
        """The counted cells, joined to those of 2**by times their side, with the bound of their points."""
        joined = cells.groupBy(*(F.shiftright(key, by).alias(key) for key in keys)).agg(F.sum("c").alias("c"), *boxes) if by else cells
        return joined.withColumn("bound", F.when(F.col("c") > k, wide).otherwise(float("inf")))

    def of(held: DataFrame, by: float) -> DataFrame:
        at = p.withColumns(dict(zip(keys, _cells(side * by, d), strict=True)))
        return at.join(held.select(*keys), keys, "left_semi").select("point_id", "vec")

    least_side = side * 2.0**-40
    while True:
        cells = p.groupBy(*_cells(side, d)).agg(F.count("*").alias("c"), *(F.min(v).alias(f"lo{i}") for i, v in enumerate(axes)), *(F.max(v).alias(f"hi{i}") for i, v in enumerate(axes)))
        cells = stored(cells, "cells")
        if halves(0).where(F.col("c") <= k).agg(F.coalesce(F.sum("c"), F.lit(0))).head()[0] >= top_n:
            break
        if side < least_side:
            return whole()
        side /= 8
    few = next(by for by in (2, 1, 0) if by == 0 or halves(by).where(F.col("c") <= k).agg(F.coalesce(F.sum("c"), F.lit(0))).head()[0] >= top_n)
    first = stored(halves(few).where(F.col("c") <= k).orderBy(*keys).limit(4 * top_n), "first")
    known = kth_distances_of(of(first, 2**few), p, k, d)[:top_n]
    least = known[-1][0] if len(known) == top_n else 0.0
    if not least > 0:
        return whole()
    rest = {by: halves(by).where(F.col("bound") >= least).agg(F.coalesce(F.sum("c"), F.lit(0))).head()[0] for by in (0, 1, 2)}
    by = min(rest, key=rest.get)
    left = stored(halves(by).where(F.col("bound") >= least).select(*keys), "left")
    # cells of a side no less than ``least``: what is nearer than their side is in a cell around
    up = by
    while side * 2**up < least:
        up += 1
    reach = side * 2**up * (1 - 1e-9)
    steps = spark.createDataFrame(_shifts(1, d), ", ".join(f"s{i} long" for i in range(d)))
    around = left.select(*(F.shiftright(key, up - by).alias(key) for key in keys)).distinct().crossJoin(F.broadcast(steps))
    around = stored(around.select(*((F.col(f"k{i}") + F.col(f"s{i}")).alias(f"k{i}") for i in range(d))).distinct(), "around")
    kept = _kept(of(around, 2**up), k)
    asks = kept.withColumns(dict(zip(keys, _cells(side * 2**by, d), strict=True))).join(left.withColumn("left", F.lit(True)), keys, "left")
    asks = stored(asks.select("point_id", "vec", "place", "copies", ((F.col("copies") <= k) & F.col("left").isNotNull()).alias("asks")), "asks")
    near = _nearest_apart(asks, k, d, "euclidean", False).select("point_id", F.get("near", F.lit(k - 1))["dist"].alias("dist"))
    near = stored(asks.where("asks").select("point_id", "vec").join(near, "point_id", "left"), "near")
    missed = near.where(F.col("dist").isNull() | (F.col("dist") > reach)).select("point_id", "vec")
    if missed.count() > most_rows:
        return whole()
    sure = near.where(F.col("dist") <= reach).orderBy(F.desc("dist"), "point_id").limit(top_n).select("dist", "point_id").collect()
    out = sorted([*map(tuple, sure), *kth_distances_of(missed, p, k, d)], key=lambda r: (-r[0], r[1]))[:top_n]
    return spark.createDataFrame([(i, g) for g, i in out], "point_id long, dist double")


def knn_rank(points: DataFrame, k: int = 3, top_n: int = 7, *, d: int, **how) -> DataFrame:
    """The ``top_n`` points of largest distance to their k-th neighbour (ties: smaller id).  (B1)"""
    return kth_distances(points, k, d, **how).where("dist is not null").orderBy(F.desc("dist"), "point_id").limit(top_n)


def db_outliers(points: DataFrame, radius: float, share: float, *, d: int, method: str = "nested", most_rows: int | None = None) -> DataFrame:
    """(point_id, near): points with at most floor(n (1 - share)) others within ``radius``.  (B2)

    "nested": places meet in blocks; "grid": counts of cells, then the points of sparse cells only."""
    if method not in ("nested", "grid"):
        raise ValueError(f"unknown method {method!r}")
    if radius < 0:
        raise ValueError("the radius must not be negative")
    if method != "grid":
        _guard(points, most_rows)
    n = points.count()
    allowed = int(np.floor(n * (1 - share) + 1e-9))
    if method == "grid" and radius > 0:
        return _grid_outliers(points, radius, allowed, d)
    places = stored(points.groupBy("vec").agg(F.count("*").alias("c"), F.min("point_id").alias("point_id")), "places")
    out = _few_near(places.withColumn("asks", F.lit(True)), radius, allowed, d)
    # a stored table is small on disk, not in the driver's memory: it isn't broadcast
    out = places.select("point_id", "vec").join(out.hint("merge"), "point_id").select("vec", "near")
    return points.select("point_id", "vec").join(out.hint("merge"), "vec").select("point_id", "near")


def _leaves(x: np.ndarray, most: int) -> list[np.ndarray]:
    """Rows of ``x`` in neighbouring groups of ``most`` at most."""
    todo, out = [np.arange(len(x))], []
    while todo:
        rows = todo.pop()
        if len(rows) <= most:
            out.append(rows)
            continue
        i = int((x[rows].max(0) - x[rows].min(0)).argmax())
        rows = rows[np.argpartition(x[rows, i], len(rows) // 2)]
        todo += [rows[: len(rows) // 2], rows[len(rows) // 2 :]]
    return out


def _met(a: np.ndarray, lo: np.ndarray, hi: np.ndarray, radius: float) -> tuple[np.ndarray, np.ndarray]:
    """(whole, border), a row a point and a column a box: all of the box is within the radius, or some of it may be.
    A little inside and outside the radius: borders are decided on points."""
    far, near = 0.0, 0.0
    for i in range(a.shape[1]):
        below, above = lo[None, :, i] - a[:, i, None], a[:, i, None] - hi[None, :, i]
        far = far + np.maximum(-below, -above) ** 2
        near = near + np.maximum(np.maximum(below, above), 0.0) ** 2
    whole = np.sqrt(far) <= radius * (1 - 1e-9)
    return whole, ~whole & (np.sqrt(near) <= radius * (1 + 1e-9))


def _within(a: np.ndarray, x: np.ndarray, c: np.ndarray, radius: float) -> np.ndarray:
    """How many of the places ``x`` (``c`` points each) are within the radius of each row of ``a``."""
    leaves = _leaves(x, LEAF)
    lo, hi = np.array([x[rows].min(0) for rows in leaves]), np.array([x[rows].max(0) for rows in leaves])
    total, near = np.array([c[rows].sum() for rows in leaves]), np.zeros(len(a), np.int64)
    parts = [(x[rows], c[rows].astype(float)) for rows in leaves]
    for at in range(0, len(a), BLOCK):
        some = a[at : at + BLOCK]
        whole, border = _met(some, lo, hi, radius)
        count = whole @ total
        for j in np.flatnonzero(border.any(0)):
            rows = np.flatnonzero(border[:, j])
            close = block_distances("euclidean", some[rows], parts[j][0]) <= radius
            count[rows] += (close @ parts[j][1]).astype(np.int64)
        near[at : at + BLOCK] = count
    return near


def _few_near(places: DataFrame, radius: float, allowed: int, d: int) -> DataFrame:
    """(point_id, near) of the places (point_id, vec, c, asks) that ask and have at most ``allowed`` others within
    the radius.

    Neighbouring places make a block.  A block wholly within the radius is counted by its total; a place whose count
    passes ``allowed`` is out, and only the rest go on to the blocks on their border.  Inside a block the same holds of
    its leaves, so pairs are few; nothing is broadcast but a box a block."""
    n = places.count()
    if not n:
        return places.sparkSession.createDataFrame([], "point_id long, near long")
    some = places.where(F.pmod(F.xxhash64("point_id"), F.lit(max(1, n // SAMPLE))) == 0).select("vec").toArrow()
    x = some.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(float).reshape(-1, d)
    tree = _tree(x, max(8, PLACES * len(x) // n))
    dim, cut, low, high = (np.array(c) for c in zip(*tree, strict=True))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = batch.column("vec").flatten().to_numpy(zero_copy_only=False).astype(float).reshape(batch.num_rows, d)
            at, rows = np.zeros(len(x), np.int64), np.arange(len(x))
            while len(rows := rows[dim[at[rows]] >= 0]):
                here = at[rows]
                at[rows] = np.where(x[rows, dim[here]] < cut[here], low[here], high[here])
            yield pa.RecordBatch.from_arrays([pa.array(low[at].astype(np.int32)), *batch.columns], ["block", "point_id", "vec", "c", "asks"])

    def pack(key: tuple, table: pa.Table) -> pa.Table:
        ids, c, asks = (table.column(name).to_numpy() for name in ("point_id", "c", "asks"))
        x = table.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(float).reshape(-1, d)
        first = np.argsort(~asks.astype(bool), kind="stable")  # those that ask come first
        packs = [pa.array([b.tobytes()], pa.binary()) for b in (ids[first[: int(asks.sum())]], x[first], c[first].astype(np.int64))]
        boxes = [pa.array([v.tolist()], pa.list_(pa.float64())) for v in (x.min(0), x.max(0))]
        return pa.table([pa.array([key[0].as_py()], pa.int32()), *packs, *boxes, pa.array([int(c.sum())])], ["block", "ids", "x", "c", "lo", "hi", "total"])

    rows = places.select("point_id", "vec", "c", "asks").mapInArrow(place, "block int, point_id long, vec array<double>, c long, asks boolean")
    packed = stored(rows.groupBy("block").applyInArrow(pack, "block int, ids binary, x binary, c binary, lo array<double>, hi array<double>, total long"), "blocks")
    boxes = packed.select("block", "lo", "hi", "total").orderBy("block").collect()  # one a block
    number, total = np.array([r.block for r in boxes]), np.array([r.total for r in boxes])
    lo, hi = np.array([r.lo for r in boxes]).reshape(-1, d), np.array([r.hi for r in boxes]).reshape(-1, d)

    def own(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                ids, x, c = np.frombuffer(row["ids"], np.int64), np.frombuffer(row["x"]).reshape(-1, d), np.frombuffer(row["c"], np.int64)
                if not len(ids):
                    continue
                a = x[: len(ids)]
                near = _within(a, x, c, radius) - 1  # itself
                gap = _box_gap("euclidean", a.min(0), a.max(0), lo, hi)
                reached = np.flatnonzero((gap <= radius * (1 + 1e-9)) & (number != row["block"]))
                borders = []
                for at in range(0, len(reached), BLOCK):
                    part = reached[at : at + BLOCK]
                    whole, border = _met(a, lo[part], hi[part], radius)
                    near += whole @ total[part]
                    borders += [(int(number[part[j]]), np.flatnonzero(border[:, j])) for j in np.flatnonzero(border.any(0))]
                few = near <= allowed
                asked = [(block, rows[few[rows]]) for block, rows in borders]
                out = [(-1, ids[few].tobytes(), None, near[few].tobytes())]
                out += [(block, ids[rows].tobytes(), a[rows].tobytes(), None) for block, rows in asked if len(rows)]
                yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(zip(*out, strict=True), (pa.int32(), pa.binary(), pa.binary(), pa.binary()), strict=True)], ["block", "a_ids", "a", "near"])

    def others(asking: pa.Table, held: pa.Table) -> pa.Table:
        ids, near = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        if asking.num_rows and held.num_rows:
            x, c = np.frombuffer(held.column("x")[0].as_py()).reshape(-1, d), np.frombuffer(held.column("c")[0].as_py(), np.int64)
            ids = [np.frombuffer(v.as_py(), np.int64) for v in asking.column("a_ids")]
            near = [_within(np.frombuffer(b"".join(v.as_py() for v in asking.column("a"))).reshape(-1, d), x, c, radius)]
        return pa.table({"point_id": pa.array(np.concatenate(ids)), "near": pa.array(np.concatenate(near))})

    def opened(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, g in zip(batch.column("a_ids").to_pylist(), batch.column("near").to_pylist(), strict=True):
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(i, np.int64)), pa.array(np.frombuffer(g, np.int64))], ["point_id", "near"])

    first = stored(packed.repartition(WIDE).mapInArrow(own, "block int, a_ids binary, a binary, near binary"), "met")
    sure = first.where("block < 0").select("a_ids", "near").mapInArrow(opened, "point_id long, near long")
    asking = first.where("block >= 0").select("block", "a_ids", "a").groupBy("block")
    more = asking.cogroup(packed.select("block", "x", "c").groupBy("block")).applyInArrow(others, "point_id long, near long")
    return sure.unionByName(more).groupBy("point_id").agg(F.sum("near").alias("near")).where(F.col("near") <= allowed)


def _cells(side: float, d: int, halved: int = 0) -> list:
    """A row's cell of the grid whose cells of ``side`` are halved so many times: k0, k1, ..."""
    return [F.floor(F.col("vec")[i] / F.lit(side / 2**halved)).alias(f"k{i}") for i in range(d)]


def _shifts(reach: int, d: int, within: float = np.inf) -> list[list[int]]:
    """The steps to the cells around one, to those whose points all are less than ``within`` sides from all of its."""
    return [list(s) for s in product(range(-reach, reach + 1), repeat=d) if sum((abs(i) + 1) ** 2 for i in s) < within**2 * (1 - 1e-9)]


def _grid_outliers(points: DataFrame, radius: float, allowed: int, d: int) -> DataFrame:
    """Cells of side radius / (2 sqrt(d)).  A cell with more than ``allowed`` others in the cells that are wholly within
    the radius of all its points holds no outlier.  Cells that stay open are halved, HALVED times at most and only while
    they hold FULL points on average; the points of the last are counted among those of the cells around (``_few_near``)."""
    if d > 3:
        raise ValueError("the grid has too many neighbouring cells: three dimensions at most")
    spark, side, keys = points.sparkSession, radius / (2 * d**0.5), [f"k{i}" for i in range(d)]
    fine = stored(points.groupBy(*_cells(side, d, HALVED)).agg(F.count("*").alias("c")), "cells")

    def coarser(df: DataFrame, by: int) -> list:
        return [F.shiftright(k, by).alias(k) for k in keys]  # cells halved share their borders to the bit

    def around(cells: DataFrame, shifts: list[list[int]]) -> DataFrame:
        steps = spark.createDataFrame(shifts, ", ".join(f"s{i} long" for i in range(d)))
        return cells.crossJoin(F.broadcast(steps))

    left, at = None, 0
    for halved in range(HALVED + 1):
        counts = fine.groupBy(*coarser(fine, HALVED - halved)).agg(F.sum("c").alias("c")) if halved < HALVED else fine
        cells = counts if left is None else counts.join(left.select(*(F.col(k).alias(f"p{k}") for k in keys)), [F.shiftright(k, 1) == F.col(f"p{k}") for k in keys], "left_semi")
        most = 2 * d**0.5 * 2**halved
        met = around(cells.select(*(F.col(k).alias(f"o{k}") for k in keys), F.col("c").alias("own")), _shifts(int(most), d, most))
        met = met.select(*(f"o{k}" for k in keys), "own", *((F.col(f"ok{i}") + F.col(f"s{i}")).alias(f"k{i}") for i in range(d)))
        sure = met.join(counts, keys).groupBy(*(F.col(f"o{k}").alias(k) for k in keys), "own").agg(F.sum("c").alias("sure"))
        left, at = stored(sure.where(F.col("sure") - 1 <= allowed).select(*keys, "own"), "open"), halved
        held = left.agg(F.count("*").alias("n"), F.sum("own").alias("own")).head()
        if not held["n"] or held["own"] < FULL * held["n"]:
            break
    left = left.select(*keys)
    reach = int(np.ceil(2 * d**0.5)) + 1  # one more for what is rounded
    near = around(left.select(*coarser(left, at)).distinct(), _shifts(reach, d)).select(*((F.col(f"k{i}") + F.col(f"s{i}")).alias(f"k{i}") for i in range(d))).distinct()
    p = points.select("point_id", "vec")
    held = p.withColumns({k: c for k, c in zip(keys, _cells(side, d), strict=True)}).join(stored(near, "around"), keys, "left_semi")
    places = held.groupBy("vec").agg(F.count("*").alias("c"), F.min("point_id").alias("point_id"))
    asks = places.withColumns({k: c for k, c in zip(keys, _cells(side, d, at), strict=True)}).join(left.withColumn("open", F.lit(True)), keys, "left")
    places = stored(asks.select("point_id", "vec", "c", F.col("open").isNotNull().alias("asks")), "places")
    out = _few_near(places, radius, allowed, d)
    out = places.where("asks").select("point_id", "vec").join(out.hint("merge"), "point_id").select("vec", "near")
    some = p.withColumns({k: c for k, c in zip(keys, _cells(side, d, at), strict=True)}).join(left, keys, "left_semi").select("point_id", "vec")
    return some.join(out.hint("merge"), "vec").select("point_id", "near")


def window_knn(points: DataFrame, radius: float, k: int, width: int, *, d: int, approx: float | None = None) -> DataFrame:
    """(point_id, near, is_outlier): neighbours within ``radius`` among the ``width`` points before and
    after in stream order; outlier below k.  A bucketed range join: buckets of ``width`` ordinals.

    ``approx`` keeps that share (by hash) of the safe inliers as neighbours of others, and scales their
    count.  A safe inlier has k neighbours within the radius that come after it: it stays an inlier for
    as long as it is in the window.  All other points are kept.  (B4)"""
    p = points.select("point_id", "ordinal", "vec")
    a = p.select(F.col("point_id").alias("a_id"), F.col("ordinal").alias("i"), F.col("vec").alias("a"), F.floor(F.col("ordinal") / width).alias("bucket"))
    b = p.select(F.col("point_id").alias("b_id"), F.col("ordinal").alias("j"), F.col("vec").alias("b"), F.explode(F.array(*(F.floor(F.col("ordinal") / width) + s for s in (-1, 0, 1)))).alias("bucket"))
    close = distance_expr("euclidean", vector("a", d), vector("b", d)) <= radius
    pairs = a.join(b, "bucket").where((F.col("a_id") != F.col("b_id")) & (F.abs(F.col("i") - F.col("j")) <= width) & close)
    count = F.count("*")
    if approx is not None:
        safe = pairs.where("j > i").groupBy("a_id").agg(F.count("*").alias("after")).where(F.col("after") >= k).select(F.col("a_id").alias("b_id"), F.lit(True).alias("safe"))
        pairs = pairs.join(safe, "b_id", "left").where(F.col("safe").isNull() | (F.pmod(F.xxhash64("b_id"), F.lit(10_000)) < approx * 10_000))
        count = F.count(F.when(F.col("safe").isNull(), 1)) + F.round(F.count("safe") / approx).cast("long")
    near = pairs.groupBy(F.col("a_id").alias("point_id")).agg(count.alias("near"))
    out = points.select("point_id").join(near, "point_id", "left").select("point_id", F.coalesce("near", F.lit(0)).alias("near"))
    if approx is None:
        return out.withColumn("is_outlier", F.col("near") < k)
    known = out.join(safe.withColumnRenamed("b_id", "point_id"), "point_id", "left")
    return known.select("point_id", "near", ((F.col("near") < k) & F.col("safe").isNull()).alias("is_outlier"))


def lof(points: DataFrame, k: int, *, d: int, most_rows: int | None = None) -> DataFrame:
    """(point_id, lof): local outlier factor with exactly k neighbours (ties: smaller id).  (B5)

    It is computed for the first k + 2 ids of each place: later copies have the neighbours, and so the factor, of
    the last of them."""
    _guard(points, most_rows)
    kept = _kept(points, k + 1)
    lists = stored(_nearest_lists(kept, kept.where(F.col("place") <= k + 1), k, d, "euclidean", False).where("near is not null"), "near")
    near = lists.select(F.col("point_id").alias("a_id"), F.explode("near").alias("x")).select("a_id", F.col("x.id").alias("b_id"), "x.dist")
    kth = lists.select(F.col("point_id").alias("b_id"), F.array_max(F.transform("near", lambda x: x["dist"])).alias("b_kd"))
    reach = near.join(kth, "b_id").withColumn("reach", F.greatest("dist", "b_kd"))
    density = reach.groupBy("a_id").agg((F.lit(1.0) / F.greatest(F.avg("reach"), F.lit(1e-12))).alias("lrd"))
    both = near.join(density, "a_id").join(density.select(F.col("a_id").alias("b_id"), F.col("lrd").alias("b_lrd")), "b_id")
    out = both.groupBy(F.col("a_id").alias("point_id")).agg((F.avg("b_lrd") / F.first("lrd")).alias("lof"))
    last = kept.where(F.col("place") == k + 2).join(out, "point_id").select("vec", F.col("lof").alias("rest"))
    all_points = points.select("point_id", "vec").join(out, "point_id", "left").join(last, "vec", "left")
    return all_points.select("point_id", F.coalesce("lof", "rest").alias("lof")).where("lof is not null")


def nearest_gaps(points: DataFrame) -> DataFrame:
    """(point_id, dist) to the nearest other point, for one dimension and any number of points: the
    neighbours in the order of values."""
    placed = with_ordinal(points.select("point_id", F.col("vec")[0].alias("x")), ["x", "point_id"], name="o")
    sides = [placed.select((F.col("o") + s).alias("o"), F.col("x").alias(n)) for s, n in ((1, "below"), (-1, "above"))]
    both = placed.join(sides[0], "o", "left").join(sides[1], "o", "left")
    return both.select("point_id", F.least(F.col("x") - F.col("below"), F.col("above") - F.col("x")).alias("dist"))


class LofModel:
    """Local outlier factors that follow insertions: only neighbourhoods that a new point enters, and
    those that look at them, are computed again.  (B5a)"""

    def __init__(self, ids: np.ndarray, x: np.ndarray, k: int):
        self.k, self.ids, self.x = k, np.asarray(ids, np.int64), np.asarray(x, float)
        self.near = {int(i): self._neighbours(i) for i in self.ids}

    def _neighbours(self, i: int) -> list[tuple[float, int]]:
        at = int(np.flatnonzero(self.ids == i)[0])
        gap = distances("euclidean", self.x, self.x[at])
        order = np.lexsort((self.ids, gap))
        return [(float(gap[j]), int(self.ids[j])) for j in order if self.ids[j] != i][: self.k]

    def insert(self, ids: np.ndarray, x: np.ndarray) -> set[int]:
        """Adds points; returns the ids whose neighbourhood changed."""
        old = list(self.near)
        self.ids, self.x = np.concatenate([self.ids, ids]), np.concatenate([self.x, x])
        place = {int(i): v for i, v in zip(self.ids, self.x, strict=True)}
        changed = {int(i) for i in ids}
        for i in old:
            worst = self.near[i][-1]
            gaps = distances("euclidean", np.asarray(x, float), place[i])
            if len(self.near[i]) < self.k or any((float(g), int(j)) < worst for g, j in zip(gaps, ids, strict=True)):
                changed.add(i)
        for i in changed:
            self.near[i] = self._neighbours(i)
        return changed

    def scores(self) -> pd.DataFrame:
        kd = {i: n[-1][0] for i, n in self.near.items()}
        lrd = {i: 1.0 / max(np.mean([max(g, kd[j]) for g, j in n]), 1e-12) for i, n in self.near.items()}
        return pd.DataFrame({"point_id": list(self.near), "lof": [float(np.mean([lrd[j] for _, j in n]) / lrd[i]) for i, n in self.near.items()]})
