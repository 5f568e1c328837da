"""MinHash near-dedup: one-permutation hashing, banded buckets, star-shaped candidate edges.

How it runs
-----------
1. One pass over the texts gives each document the fingerprint of its shingle set, a
   one-permutation MinHash with optimal densification, its band keys and a one-bit sketch.
   Documents of equal sets form a class; its smallest id stands for it, so copies cost one
   small aggregation however many there are.
2. Each bucket (band key) links its members to its smallest member only: n members give
   n - 1 candidate edges.  Edges are confirmed on full shingle sets.
3. Connected components of the confirmed links.
4. A bucket whose members lie in different components may still hide a link that misses the
   star's centre.  Star rounds with other centres come first; then every remaining pair of
   different components in such a bucket that passes the size bound and the sketch bound is
   confirmed as well (once, in the first bucket it shares).  Only near misses are left for this
   step.  Large buckets are split into chunks of members, and chunk meets chunk in a task of its own.

What may be missed: a pair at the threshold shares no bucket with a chance of ``miss`` (1e-7).  The
size bound is exact.  The sketch bound allows SKETCH_SLACK standard deviations over the mean number
of differing bins of a pair at the threshold: a link exceeds it with a chance of about 3e-7, less the
further it is above the threshold.  All else is exact.

Defined results: a text without words (or null) is linked with nothing; a null id takes no
part and is kept; rows that repeat an id are one node; extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import stored
from .words import U, WordHashes, mix, odd_constants, shingle_set, texts

#: The sketch: this many bins, of which PLANES bits each are kept, packed into 64-bit words.
SKETCH_BINS, PLANES = 512, 4
#: Differing bins are allowed up to this many standard deviations over their mean at the threshold.
SKETCH_SLACK = 5.0
#: Members of a chunk of a large bucket.
CHUNK = 500


def plan_bands(threshold: float, miss: float = 1e-7) -> tuple[int, int]:
    """(bands, rows): a pair at the threshold shares a band with probability 0.4 or more, and
    all bands miss it with probability ``miss`` at most."""
    rows = max(1, int(math.log(0.4) / math.log(threshold)))
    return math.ceil(math.log(miss) / math.log(1 - threshold**rows)), rows


class Printer:
    """Signature of one shingle set."""

    def __init__(self, bands: int, rows: int):
        self.bands, self.rows, self.bins = bands, rows, bands * rows
        grid = mix(np.arange(self.bins * self.bins, dtype=U) + U(77)).reshape(self.bins, self.bins)
        self.order = np.argsort(np.argsort(grid, axis=1), axis=1).astype(np.int32)
        self.odd = odd_constants(rows, 5)
        self.salt = odd_constants(bands, 9)

    def signature(self, shingles: np.ndarray) -> np.ndarray:
        """The smallest hash of each bin; an empty bin takes the value of the first filled one
        in its own random order of the bins (optimal densification)."""
        where = ((shingles >> U(32)) * U(self.bins)) >> U(32)
        filled, first = np.unique(where, return_index=True)
        values = np.zeros(self.bins, dtype=U)
        filled = filled.astype(np.int64)
        values[filled] = shingles[first]
        if len(filled) < self.bins:
            empty = np.ones(self.bins, dtype=bool)
            empty[filled] = False
            rows = np.flatnonzero(empty)
            values[rows] = shingles[first][self.order[rows][:, filled].argmin(axis=1)]
        return values

    def keys(self, values: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            grid = (mix(values).reshape(self.bands, self.rows) * self.odd).sum(axis=1, dtype=U)
            return mix(grid + self.salt).view(np.int64)

    def sketch(self, shingles: np.ndarray) -> np.ndarray:
        """PLANES bits of the smallest hash of each sketch bin (0 where the bin is empty)."""
        where = ((shingles >> U(32)) * U(SKETCH_BINS)) >> U(32)
        filled, first = np.unique(where, return_index=True)
        bits = np.zeros((PLANES, SKETCH_BINS), dtype=np.uint8)
        value = mix(shingles[first] ^ U(0x5851F42D4C957F2D))
        for i in range(PLANES):
            bits[i, filled.astype(np.int64)] = (value >> U(i)) & U(1)
        return np.packbits(bits.ravel()).view(np.int64)


def _prints(bands: int, rows: int, k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, printer = WordHashes(), Printer(bands, rows)
        for batch in batches:
            n, high, low, keys, sketch = [], [], [], [], []
            for text in texts(batch.column(1)):
                found = shingle_set(seen.of((text or b"").lower().split()), k)
                n.append(len(found))
                if not len(found):
                    high.append(None), low.append(None), keys.append(None), sketch.append(None)
                    continue
                digest = np.frombuffer(xxhash.xxh3_128_digest(found.tobytes()), dtype=np.int64)
                high.append(int(digest[0])), low.append(int(digest[1]))
                values = printer.signature(found)
                keys.append(printer.keys(values))
                sketch.append(printer.sketch(found))
            longs = pa.list_(pa.int64())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(n, pa.int64()), pa.array(high, pa.int64()), pa.array(low, pa.int64()), pa.array(keys, longs), pa.array(sketch, longs)],
                ["doc_id", "n_shingles", "f1", "f2", "keys", "sketch"],
            )

    return run


def _sets(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = WordHashes()
        for batch in batches:
            found = [shingle_set(seen.of((t or b"").lower().split()), k).view(np.int64) for t in texts(batch.column(1))]
            for at in range(0, max(len(found), 1), 256):
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, 256), pa.array(found[at : at + 256], pa.list_(pa.int64()))], ["rep", "shingles"])

    return run


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, component) of the nodes in ``links(a, b)``; component is its smallest node.

    Large-star and small-star steps in turn until nothing changes; each step is an aggregation
    and a join by node, and each round's edges are written to the shared folder.
    """
    edges = stored(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")

    def measure(df: DataFrame):
        return df.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).head()

    before = measure(edges)
    for _ in range(most_rounds):
        if not before[0]:
            break
        both = edges.union(edges.select("v", "u")).toDF("u", "v")
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = stored(large.where("u <> v").distinct(), "large")
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", "m"))
        edges = stored(small.where("u <> v").distinct(), "edges")
        after = measure(edges)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError(f"components did not settle in {most_rounds} rounds")
    roots = edges.select("v").distinct().select(F.col("v").alias("node"), F.col("v").alias("component"))
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).union(roots)


def flat_sketch() -> list:
    return [F.get("sketch", F.lit(i)).alias(f"s{i}") for i in range(PLANES * SKETCH_BINS // 64)]


class _Linker:
    """Confirms candidate pairs on full shingle sets."""

    def __init__(self, docs: DataFrame, reps: DataFrame, k: int, percent: int):
        self.docs, self.k, self.percent = docs, k, percent
        self.facts = reps.select("rep", "n", *flat_sketch())

    def may_link(self, a: str, b: str):
        """Size bound (exact) and sketch bound of a pair.

        With union u, the sets of a link differ in u * (1 - t) shingles at most, so in no more
        bins; and of the bins that the union fills a share 1 - t differs, give or take chance.
        """
        t = self.percent / 100
        n, m = F.col(f"n_{a}"), F.col(f"n_{b}")
        union = (n + m) / (1 + t)

        def apart(words: range):
            total = F.lit(0)
            for i in words:
                differ = None
                for plane in range(PLANES):
                    name = f"s{plane * (SKETCH_BINS // 64) + i}"
                    bit = F.col(f"{name}_{a}").bitwiseXOR(F.col(f"{name}_{b}"))
                    differ = bit if differ is None else differ.bitwiseOR(bit)
                total = total + F.bit_count(differ)
            return total

        def bound(share: float):
            filled = SKETCH_BINS * share * (1 - F.exp(-union / SKETCH_BINS))
            return F.least(union * (1 - t) + 0.5, filled * (1 - t) + SKETCH_SLACK * F.sqrt(filled * t * (1 - t)) + 1)

        whole = SKETCH_BINS // 64
        return (100 * F.least(n, m) >= self.percent * F.greatest(n, m)) & (apart(range(1)) <= bound(1 / whole)) & (apart(range(whole)) <= bound(1))

    def fact(self, side: str) -> DataFrame:
        return self.facts.toDF(side, *(f"{c}_{side}" for c in self.facts.columns[1:]))

    def likely(self, pairs: DataFrame) -> DataFrame:
        return pairs.join(self.fact("a"), "a").join(self.fact("b"), "b").where(self.may_link("a", "b")).select("a", "b")

    def links(self, pairs: DataFrame) -> DataFrame:
        """pairs(a, b), already likely and distinct -> those whose sets are similar enough."""
        pairs = stored(pairs, "pairs")
        need = pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct()
        found = self.docs.join(need, "doc_id", "left_semi").select("doc_id", "text").mapInArrow(_sets(self.k), "rep long, shingles array<long>")
        found = stored(found, "sets")
        both = pairs.join(found.toDF("b", "set_b"), "b").join(found.toDF("a", "set_a"), "a")
        shared = F.size(F.array_intersect("set_a", "set_b"))
        both = both.select("a", "b", shared.alias("i"), (F.size("set_a") + F.size("set_b")).alias("t"))
        return stored(both.where(100 * F.col("i") >= self.percent * (F.col("t") - F.col("i"))).select("a", "b"), "links")


def near_duplicates(docs: DataFrame, *, k: int = 5, percent: int = 80, star_rounds: int = 1) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept, class_id) per row of ``docs(doc_id, text)``.

    ``k`` words a shingle; documents are linked if 100 * intersection >= ``percent`` * union.
    ``star_rounds`` further star rounds precede the exact remainder (they only save work).
    """
    bands, rows = plan_bands(percent / 100)
    docs = docs.select("doc_id", "text")
    schema = "doc_id long, n_shingles long, f1 long, f2 long, keys array<long>, sketch array<long>"
    prints = stored(docs.mapInArrow(_prints(bands, rows, k), schema), "prints")
    able = prints.where("doc_id is not null and n_shingles > 0")
    reps = able.groupBy("f1", "f2").agg(F.min_by(F.struct("doc_id", F.col("n_shingles").alias("n"), "sketch", "keys"), "doc_id").alias("x"))
    reps = stored(reps.select("f1", "f2", F.col("x.doc_id").alias("rep"), "x.n", "x.sketch", "x.keys"), "reps")
    linker = _Linker(docs, reps, k, percent)

    buckets = reps.select("rep", F.explode("keys").alias("key"))
    centres = buckets.groupBy("key").agg(F.min("rep").alias("centre"), F.count("*").alias("m")).where("m > 1").select("key", "centre")
    members = stored(buckets.join(centres, "key"), "members")
    star = members.where("rep > centre").select(F.col("centre").alias("a"), F.col("rep").alias("b")).distinct()
    links = linker.links(linker.likely(star))
    label = components(links)
    for turn in range(star_rounds + 1):
        placed = members.select("key", "rep").join(label.withColumnRenamed("node", "rep"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))
        spread = placed.groupBy("key").agg(F.min("component").alias("lo"), F.max("component").alias("hi"), F.min_by("rep", F.xxhash64("rep", F.lit(turn))).alias("centre"), F.min_by("component", F.xxhash64("rep", F.lit(turn))).alias("home"), F.ceil(F.count("*") / CHUNK).cast("int").alias("chunks")).where("lo < hi")
        mixed = placed.join(spread.select("key", "centre", "home", "chunks"), "key")
        if turn < star_rounds:
            pairs = mixed.where("component <> home").select(F.least("centre", "rep").alias("a"), F.greatest("centre", "rep").alias("b")).distinct()
            pairs = linker.likely(pairs)
        else:
            mixed = mixed.select("key", "rep", "component", "chunks", F.pmod(F.xxhash64("rep"), F.col("chunks")).cast("int").alias("chunk")).join(reps.select("rep", "n", "keys", *flat_sketch()), "rep")
            mixed = stored(mixed, "mixed")
            facts = [c for c in mixed.columns if c not in ("rep", "chunk", "chunks")]
            left, right = (mixed.select(F.col("rep").alias(s), *(F.col(c).alias(f"{c}_{s}") for c in facts), i.alias(f"i_{s}"), j.alias(f"j_{s}")) for s, i, j in (
                ("a", F.col("chunk"), F.explode(F.sequence("chunk", F.col("chunks") - 1))), ("b", F.explode(F.sequence(F.lit(0), F.col("chunk"))), F.col("chunk"))))
            together = (F.col("key_a") == F.col("key_b")) & (F.col("i_a") == F.col("i_b")) & (F.col("j_a") == F.col("j_b"))
            first = F.get(F.array_intersect("keys_a", "keys_b"), F.lit(0)) == F.col("key_a")
            once = (F.col("i_a") < F.col("j_a")) | (F.col("a") < F.col("b"))
            pairs = left.join(right, together & once & (F.col("component_a") != F.col("component_b")) & linker.may_link("a", "b") & first).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
        more = linker.links(pairs)
        if more.isEmpty():
            continue
        links = links.union(more)
        label = components(links)
    classes = reps.select("f1", "f2", "rep").join(label.withColumnRenamed("node", "rep"), "rep", "left").select("f1", "f2", F.col("rep").alias("class_id"), F.coalesce("component", "rep").alias("component"))
    out = prints.select("doc_id", "n_shingles", "f1", "f2").join(classes, ["f1", "f2"], "left")
    alone = F.col("doc_id").isNull()
    component = F.when(~alone, F.coalesce("component", "doc_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"), F.when(~alone, F.coalesce("class_id", "doc_id")).alias("class_id"))


def one_of_each(docs: DataFrame, **settings) -> DataFrame:
    """``docs`` without the documents that a near-duplicate with a smaller id makes superfluous."""
    gone = near_duplicates(docs, **settings).where("not kept").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)
