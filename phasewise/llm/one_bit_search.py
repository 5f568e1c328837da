"""Approximate nearest neighbours with randomly rotated one-bit codes.

Index: every vector, scaled to length 1 and rotated by a fixed random rotation, is kept as one
sign bit a dimension (packed) and a correction scalar a, the inner product of the vector with
its own code.  A query's inner product with the code, divided by a, estimates the cosine; the
error is at most ``width`` * sqrt((1 - a^2) / a^2 / (d - 1)) but for a chance that falls fast with
``width``.  Vectors whose upper bound reaches the k-th best cosine found so far are measured
exactly, so the answers are exact cosines and a true neighbour is missed only beyond the bound.

Rows are packed into blocks of bounded size, which are written once.  Queries are broadcast in
batches of bounded bytes; every task walks its blocks of rows and keeps the k best of each query,
which prune its further blocks.  The tasks' results meet in a window per query.

Defined results: null, zero or non-finite vectors and rows without an id take no part; rows
that repeat an id count once (the smallest vector); vectors of different lengths are not
compared; ties go to the smaller id; components of any finite size count (vectors are scaled by a
power of two, which changes no cosine); extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .store import stored

#: Rows of a block, and bytes of the query vectors that are broadcast at a time.
ROWS, BATCH_BYTES = 4096, 32 << 20


def scaled(x: np.ndarray) -> np.ndarray:
    """Rows divided by the power of two next to their largest component: squares cannot overflow."""
    return np.ldexp(x, -np.frexp(np.abs(x).max(1, initial=0.0))[1][:, None])


def rotation(d: int, seed: int = 20) -> np.ndarray:
    q, r = np.linalg.qr(np.random.default_rng(seed + d).standard_normal((d, d)))
    return q * np.sign(np.diag(r))


def encode(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(packed bits, correction scalars) of the rows of ``x``."""
    d = x.shape[1]
    unit = x / np.sqrt((x * x).sum(1, keepdims=True))
    turned = unit @ rotation(d)
    return np.packbits(turned > 0, axis=1), np.abs(turned).sum(1) / math.sqrt(d)


def exact_cosine(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Cosines row by row in double precision; sums run over the dimensions in order, so equal
    vectors have equal cosines wherever they lie."""
    dot, a, b = (np.zeros(len(x)) for _ in range(3))
    for i in range(x.shape[1]):
        u, v = x[:, i], y[:, i]
        dot += u * v
        a += u * u
        b += v * v
    return dot / (np.sqrt(a) * np.sqrt(b))


class Nearest:
    """The k best rows of each query among the coded blocks that it has met."""

    def __init__(self, query_ids: np.ndarray, q: np.ndarray, k: int, width: float):
        self.ids, self.q, self.k, self.width = query_ids, q, k, width
        self.turned = ((q / np.sqrt((q * q).sum(1, keepdims=True))) @ rotation(q.shape[1])).astype(np.float32)
        self.found = [(np.zeros(0, np.int64), np.zeros(0)) for _ in query_ids]

    def meet(self, ids: np.ndarray, x: np.ndarray, bits: np.ndarray, a: np.ndarray) -> None:
        d, k = x.shape[1], self.k
        signs = np.unpackbits(bits, axis=1, count=d).astype(np.float32) * np.float32(2 / math.sqrt(d)) - np.float32(1 / math.sqrt(d))
        a = a.astype(np.float32)
        slack = self.width * np.sqrt(np.maximum(1 - a * a, 0) / (a * a) / max(d - 1, 1)) + np.float32(1e-5)
        estimates = (self.turned @ signs.T) / a
        estimates[np.equal.outer(self.ids, ids)] = -np.inf
        for j, estimate in enumerate(estimates):
            held, best = self.found[j]
            upper = estimate + slack
            if len(best) == k and upper.max() < best[-1] - 1e-12:
                continue
            others = len(ids) - int(np.isneginf(estimate).sum())
            if not others:
                continue
            least = best[-1] if len(best) == k else -np.inf
            if others >= k:
                first = np.argpartition(-estimate, k - 1)[:k]
                least = max(least, exact_cosine(x[first], np.broadcast_to(self.q[j], (k, d))).min())
            chosen = np.flatnonzero((upper >= least - 1e-12) & ~np.isneginf(estimate))
            score = np.concatenate([best, exact_cosine(x[chosen], np.broadcast_to(self.q[j], (len(chosen), d)))])
            held = np.concatenate([held, ids[chosen]])
            order = np.lexsort((held, -score))[:k]
            self.found[j] = held[order], score[order]

    def table(self) -> pa.RecordBatch:
        n = [len(held) for held, _ in self.found]
        columns = np.repeat(self.ids, n), np.concatenate([h for h, _ in self.found]), np.concatenate([s for _, s in self.found])
        return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["query_id", "vec_id", "score"])


def _vectors(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """(ids in order, scaled vectors) of vectors of one length."""
    ids = table.column("vec_id").to_numpy()
    x = table.column("v").combine_chunks().flatten().to_numpy().reshape(len(ids), -1)
    order = np.argsort(ids)
    return ids[order], scaled(x[order])


def _pack(table: pa.Table) -> pa.Table:
    ids, x = _vectors(table)
    bits, a = encode(x)
    cells = [ids.tobytes()], [x.tobytes()], [bits.tobytes()], [a.tobytes()]
    return pa.table([pa.array([x.shape[1]], pa.int32())] + [pa.array(c, pa.binary()) for c in cells], names=["d", "ids", "x", "bits", "a"])


def _meet(queries, k: int, width: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        by_size: dict[int, Nearest] = {}
        for batch in batches:
            for i in range(batch.num_rows):
                d, ids, x, bits, a = (c[i].as_py() for c in batch.columns)
                if d not in queries.value:
                    continue
                if d not in by_size:
                    by_size[d] = Nearest(*queries.value[d], k, width)
                ids = np.frombuffer(ids, np.int64)
                by_size[d].meet(ids, np.frombuffer(x).reshape(-1, d), np.frombuffer(bits, np.uint8).reshape(len(ids), -1), np.frombuffer(a))
        for found in by_size.values():
            yield found.table()

    return run


def usable(vectors: DataFrame) -> DataFrame:
    """(vec_id, v): one finite, non-zero vector of doubles for each id."""
    v = F.col("embedding").cast("array<double>")
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    nonzero = F.exists(v, lambda x: x != 0)
    rows = vectors.where(F.col("vec_id").isNotNull() & F.coalesce(finite & nonzero, F.lit(False)))
    return rows.groupBy("vec_id").agg(F.min(v).alias("v"))


def search(vectors: DataFrame, is_query: Column, *, k: int = 5, width: float = 4.0, rows: int = ROWS, batch_bytes: int = BATCH_BYTES) -> DataFrame:
    """(query_id, rank, vec_id, score): the k rows of largest cosine to each query row."""
    spark = vectors.sparkSession
    held = stored(usable(vectors).withColumn("q", is_query), "vectors")
    n, asked, most = held.agg(F.count("*"), F.count(F.when(F.col("q"), 1)), F.max(F.size("v"))).head()
    schema = "query_id long, vec_id long, score double"
    found = spark.createDataFrame([], schema)
    if asked:
        blocks = math.ceil(n / rows)
        block = F.pmod(F.xxhash64("vec_id"), F.lit(blocks))
        index = held.select("vec_id", "v").groupBy(block.alias("block"), F.size("v").alias("d")).applyInArrow(_pack, "d int, ids binary, x binary, bits binary, a binary")
        # blocks in files of their own, up to 64 of them where they are many
        index = stored(index, "blocks", maxRecordsPerFile=max(1, min(64, blocks // 1000)))
        batches = math.ceil(asked * most * 8 / batch_bytes)
        for b in range(batches):
            some = held.where("q").where(F.pmod(F.xxhash64("vec_id"), F.lit(batches)) == b).select("vec_id", "v").toArrow()  # about batch_bytes
            sizes = np.diff(some.column("v").combine_chunks().offsets.to_numpy())
            queries = {int(d): _vectors(some.filter(pa.array(sizes == d))) for d in set(sizes.tolist())}
            found = found.union(stored(index.mapInArrow(_meet(spark.sparkContext.broadcast(queries), k, width), schema), "found"))
    rank = F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
