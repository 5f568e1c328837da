"""k-means and exact k-median baselines, the chunked mean miner, reduction to k medians.  (B3, B8, M24)"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.distance import distance_expr, pairwise, vector


def lloyd(points: DataFrame, k: int, iters: int, d: int) -> DataFrame:
    """(cluster, weight, c0..): Lloyd iterations from the first k points.  The k centres are literals of the
    plan, so an iteration is one scan with one aggregation of k groups.  (B3a)"""
    rows = points.where(F.col("ordinal") <= k).select((F.col("ordinal") - 1).cast("int").alias("cluster"), "vec").collect()  # k rows
    centres = {r.cluster: list(r.vec) for r in rows}
    schema = "cluster int, weight double, " + ", ".join(f"c{i} double" for i in range(d))
    found = [(c, 0.0, *v) for c, v in sorted(centres.items())]
    for _ in range(iters):
        gap = lambda v: distance_expr("sqeuclidean", vector("vec", d), [F.lit(float(x)) for x in v])
        near = F.array_min(F.array(*(F.struct(gap(v).alias("dist"), F.lit(c).alias("cluster")) for c, v in sorted(centres.items()))))["cluster"]
        total = F.sum("weight")
        means = points.groupBy(near.alias("cluster")).agg(total.alias("weight"), *((F.sum(F.col("vec")[i] * F.col("weight")) / total).alias(f"c{i}") for i in range(d)))
        found = [tuple(r) for r in means.collect()]  # k rows
        centres = {r[0]: r[2:] for r in found}
    return points.sparkSession.createDataFrame(found, schema)


def lloyd_kernel(x: np.ndarray, w: np.ndarray, k: int, iters: int) -> tuple[np.ndarray, np.ndarray]:
    """(centres, cluster of each row)."""
    _, first = np.unique(x, axis=0, return_index=True)
    centres = x[np.sort(first)[:k]].copy()
    near = np.zeros(len(x), np.int64)
    for _ in range(iters):
        near = pairwise("sqeuclidean", x, centres).argmin(1)
        for c in range(len(centres)):
            if w[near == c].sum() > 0:
                centres[c] = np.average(x[near == c], axis=0, weights=w[near == c])
    return centres, near


def mean_miner(points: DataFrame, k: int, num: int, outlier_phases: int, iters: int = 10, *, rule: str = "light", min_weight: float = 2.0, farthest: int = 5) -> DataFrame:
    """(stream_key, chunk, point_id, first_phase, settled_phase, score, verdict): the chunked mean miner.

    Every chunk, with the carried means and candidates, is put into exactly k means.  Candidates are
    members of means lighter than ``min_weight`` ("light") or the ``farthest`` members of each mean
    ("farthest"); a candidate stays with the next chunks and is settled after ``outlier_phases``.  (B3)"""
    schema = "stream_key string, point_id long, first_phase int, settled_phase int, age int, score int, verdict string"

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("ordinal", kind="stable")
        ids, x, w = pdf["point_id"].to_numpy(), np.stack(pdf["vec"].to_numpy()).astype(float), pdf["weight"].to_numpy(float)
        means, mass = np.zeros((0, x.shape[1])), np.zeros(0)
        watched: dict[int, list] = {}
        out = []
        for phase, at in enumerate(range(0, len(ids), num), 1):
            block = slice(at, at + num)
            old = list(watched)
            all_x = np.concatenate([means, np.array([watched[i][0] for i in old]).reshape(-1, x.shape[1]), x[block]])
            all_w = np.concatenate([mass, np.ones(len(old)), w[block]])
            names = np.concatenate([np.full(len(means), -1), np.array(old, np.int64), ids[block]]).astype(np.int64)
            centres, near = lloyd_kernel(all_x, all_w, k, iters)
            weight = np.array([all_w[near == c].sum() for c in range(len(centres))])
            gap = np.sqrt(((all_x - centres[near]) ** 2).sum(1))
            flagged = set()
            for c in range(len(centres)):
                rows = np.flatnonzero((near == c) & (names >= 0))
                if rule == "light":
                    flagged |= set(names[rows].tolist()) if weight[c] < min_weight else set()
                else:
                    flagged |= set(names[rows[np.argsort(-gap[rows], kind="stable")[:farthest]]].tolist())
            for i in old:
                watched[i][2] += 1
                watched[i][3] += i in flagged
            for i in flagged - set(old):
                row = int(np.flatnonzero(names == i)[0])
                watched[i] = [all_x[row], phase, 1, 1]
            for i in list(watched):
                place, first, age, score = watched[i]
                if age >= outlier_phases:
                    out.append((i, first, phase, age, score, "outlier" if score == outlier_phases else "inlier"))
                    del watched[i]
            keep = np.array([n < 0 or n not in watched for n in names.tolist()], bool) & ~np.isin(names, [o[0] for o in out if o[2] == phase and o[5] == "outlier"])
            mass = np.array([all_w[keep & (near == c)].sum() for c in range(len(centres))])
            means, mass = centres[mass > 0], mass[mass > 0]
        out += [(i, first, None, age, score, "pending") for i, (_, first, age, score) in watched.items()]
        found = pd.DataFrame(out, columns=["point_id", "first_phase", "settled_phase", "age", "score", "verdict"]).astype({"settled_phase": "Int32"})
        found.insert(0, "stream_key", pdf["stream_key"].iloc[0])
        return found

    return points.groupBy("stream_key").applyInPandas(run, schema)


MOST_EXACT = 400


def exact_kmedian(points: DataFrame, k: int, d: int, distance: str = "euclidean", most_rows: int = MOST_EXACT) -> DataFrame:
    """(cost, m1..mk): the best k medians among the points themselves, by trying all.  (B8)"""
    if points.count() > most_rows or k > 3:
        raise ValueError(f"exact search takes {most_rows} points and k = 3 at most")
    a = points.select(F.col("point_id").alias("p"), F.col("vec").alias("a"), F.col("weight").alias("w"))
    b = points.select(F.col("point_id").alias("m"), F.col("vec").alias("b"))
    gap = a.join(F.broadcast(b), F.lit(True)).select("p", "m", (F.col("w") * distance_expr(distance, vector("a", d), vector("b", d))).alias("g"))
    sets = gap.select("p", F.col("m").alias("m1"), F.col("g").alias("best"))
    for i in range(2, k + 1):
        more = gap.select("p", F.col("m").alias(f"m{i}"), F.col("g").alias("other"))
        sets = sets.join(more, "p").where(F.col(f"m{i - 1}") < F.col(f"m{i}")).withColumn("best", F.least("best", "other")).drop("other")
    names = [f"m{i}" for i in range(1, k + 1)]
    cost = sets.groupBy(*names).agg(F.sum("best").alias("cost"))
    return cost.orderBy("cost", *names).limit(1).select("cost", *names)


def reduce_to_k(x: np.ndarray, w: np.ndarray, k: int, method: str = "greedy", distance: str = "euclidean") -> tuple[np.ndarray, float]:
    """(rows of the k medians, cost) of weighted medians that fit in the driver.  (M24)"""
    gap = pairwise(distance, x, x).T * w[:, None]  # gap[i, j]: cost of point i at median j

    def cost(rows) -> float:
        return float(gap[:, list(rows)].min(1).sum())

    k = min(k, len(x))
    if method == "exhaustive":
        best = min(combinations(range(len(x)), k), key=cost)
        return np.array(best), cost(best)
    chosen: list[int] = []
    while len(chosen) < k:
        chosen.append(min((i for i in range(len(x)) if i not in chosen), key=lambda i: cost([*chosen, i])))
    if method == "local_swap":
        improved = True
        while improved:
            improved = False
            for out in list(chosen):
                rest = [c for c in chosen if c != out]
                swap = min((i for i in range(len(x)) if i not in rest), key=lambda i: cost([*rest, i]))
                if cost([*rest, swap]) < cost(chosen) - 1e-12:
                    chosen, improved = [*rest, swap], True
                    break
    elif method != "greedy":
        raise ValueError(f"unknown method {method!r}")
    return np.array(sorted(chosen)), cost(chosen)
