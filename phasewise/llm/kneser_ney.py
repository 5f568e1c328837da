"""LM scoring: an interpolated modified Kneser-Ney bigram model, counted in Spark.

Counting.  Each task counts its bigrams with sorted hashes and sends every part of the hash
space one sorted block (so a frequent bigram costs one entry a task, however often it stands
somewhere).  One task per part adds up the blocks of its left words, which gives the bigram
counts and the statistics of each left word in full, and passes on, per right word, how often
and after how many different words it stands; a second step adds these up.

Store.  Every part is a pair of raw files of sorted 64-bit hashes and their columns in the
shared folder.  Workers map the files into memory; lookups are sorted first, so they walk the
files in order.  On a store without local paths a worker reads the files that it needs into memory.

Probability of w after u, with discounts D from the counts of counts:
    p(w|u) = max(c(uw) - D(c(uw)), 0) / c(u.) + g(u) * q(w)
    q(w)   = max(k(w) - D'(k(w)), 0) / k(.) + g' / (V + 1),   k(w): left neighbours of w
An unknown w has k = 0; after an unseen u, p = q.

Defined results: a null or empty text is one end token; null ids count as the empty string in
the split; repeated rows count as often as they stand; with no training text at all every
probability is that of an empty model (q = 1); extra columns are ignored.
"""

from __future__ import annotations

import math
import os
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import new_path
from .words import U, WordHashes, mix, texts

#: Tokens that are read at a time, and bigrams that a counting task holds.
PORTION, HELD = 1_000_000, 3_000_000
#: Bytes of input for a part of the model, and an estimate that says nothing (a plan without files).
PART_BYTES, UNKNOWN = 16 << 20, 1 << 50
BEGIN, END = U(0x1B873593CC9E2D51), U(0x85EBCA6B27D4EB2F)
WORD_COLUMNS = (("count", np.int64), ("left", np.int64))
LEFT_COLUMNS = (("total", np.int64), ("n1", np.int64), ("n2", np.int64), ("n3", np.int64))
PAIR_COLUMNS = (("count", np.uint32),)


def pair_hash(u: np.ndarray, w: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        return mix(u * U(0x9E3779B97F4A7C15) + mix(w))


def part_of(u: np.ndarray, parts: int) -> np.ndarray:
    return ((mix(u) >> U(33)) % U(parts)).astype(np.int64)


# files ----------------------------------------------------------------------------------


def _filesystem(uri: str) -> tuple[fs.FileSystem, str, bool]:
    """(file system, path in it, whether the path is a local one)."""
    if uri.startswith("file:") or "://" not in uri:
        return fs.LocalFileSystem(), "/" + uri.split(":", 1)[-1].lstrip("/"), True
    system, path = fs.FileSystem.from_uri(uri)
    return system, path, False


def _save(uri: str, name: str, array: np.ndarray) -> None:
    """Writes under another name first: a repeated or speculative task leaves one whole file."""
    system, path, _ = _filesystem(uri)
    system.create_dir(path, recursive=True)
    draft = f"{path}/.{name}-{os.getpid()}-{np.random.default_rng().integers(1 << 60)}"
    with system.open_output_stream(draft) as out:
        out.write(memoryview(np.ascontiguousarray(array)).cast("B") if array.size else b"")
    system.move(draft, f"{path}/{name}")


def _mapped(uri: str, name: str, dtype) -> np.ndarray:
    system, path, local = _filesystem(f"{uri}/{name}")
    if not local:
        with system.open_input_stream(path) as f:
            return np.frombuffer(f.read(), dtype)
    return np.memmap(path, dtype=dtype, mode="r") if os.path.getsize(path) else np.zeros(0, dtype)


# counting -------------------------------------------------------------------------------


def _summed(keys: np.ndarray, *columns: np.ndarray) -> tuple[np.ndarray, ...]:
    """Sorted distinct keys and their columns' sums."""
    if not len(keys):
        return keys, *columns
    order = np.argsort(keys, kind="stable")
    keys = keys[order]
    first = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
    return keys[first], *(np.add.reduceat(c[order], first) for c in columns)


def _block(*columns: np.ndarray) -> bytes:
    """Columns of 64-bit numbers, byte by byte (Spark's codec then finds the empty bytes);
    the first one, which is sorted, as differences."""
    n = len(columns[0])
    first = np.diff(columns[0].astype(U), prepend=U(0))
    out = [np.int64(n).tobytes()]
    for c in (first, *columns[1:]):
        out.append(np.ascontiguousarray(c.astype(U).view(np.uint8).reshape(n, 8).T).tobytes())
    return b"".join(out)


def _unblock(blob: bytes) -> list[np.ndarray]:
    n = int(np.frombuffer(blob, np.int64, 1)[0])
    if not n:
        return []
    columns = np.frombuffer(blob, np.uint8, offset=8).reshape(-1, 8, n)
    out = [np.ascontiguousarray(c.T).view(U).ravel() for c in columns]
    out[0] = np.cumsum(out[0], dtype=U)
    return out


def _gather(table: pa.Table, columns: int) -> list[np.ndarray]:
    found = [b for b in map(_unblock, table.column("blob").to_pylist()) if b]
    return [np.concatenate([b[i] for b in found]) if found else np.zeros(0, U) for i in range(columns)]


def token_arrays(rows: list[bytes | None], seen: WordHashes) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(lengths, left words, words) of portions of the texts; each text ends with END."""
    hashed, size = [], 0
    for i, text in enumerate(rows):
        words = (text or b"").lower().split()
        hashed.append(seen.of(words))
        size += len(words) + 1
        if size >= PORTION or i == len(rows) - 1:
            lengths = np.array([len(h) + 1 for h in hashed], dtype=np.int64)
            ends = np.cumsum(lengths)
            w = np.empty(size, U)
            keep = np.ones(size, bool)
            keep[ends - 1] = False
            w[keep] = np.concatenate(hashed) if hashed else np.zeros(0, U)
            w[ends - 1] = END
            u = np.empty(size, U)
            u[1:] = w[:-1]
            u[ends - lengths] = BEGIN
            yield lengths, u, w
            hashed, size = [], 0


def _count(parts: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = WordHashes()
        held: list[tuple[np.ndarray, ...]] = []
        size = 0

        def merged() -> tuple[np.ndarray, ...]:
            u, w, c = (np.concatenate([h[i] for h in held]) for i in range(3))
            h = pair_hash(u, w)
            order = np.argsort(h)
            h, u, w, c = h[order], u[order], w[order], c[order]
            first = np.flatnonzero(np.concatenate(([True], h[1:] != h[:-1])))
            return u[first], w[first], np.add.reduceat(c, first)

        for batch in batches:
            for _, u, w in token_arrays(texts(batch.column(0)), seen):
                held.append((u, w, np.ones(len(u), U)))
                size += len(u)
                if size >= HELD:
                    held = [merged()]
                    size = len(held[0][0])
                    if size >= HELD:  # too many different ones to go on: they are sent
                        yield from _blocks(held[0], parts)
                        held, size = [], 0
        if held:
            yield from _blocks(merged(), parts)

    return run


def _blocks(counted: tuple[np.ndarray, ...], parts: int) -> Iterator[pa.RecordBatch]:
    u, w, c = counted
    part = part_of(u, parts)
    order = np.lexsort((w, u, part))
    u, w, c, part = u[order], w[order], c[order], part[order]
    cuts = np.searchsorted(part, np.arange(parts + 1))
    for p in range(parts):
        a, b = cuts[p], cuts[p + 1]
        if b > a:
            yield pa.RecordBatch.from_arrays([pa.array([p], pa.int32()), pa.array([_block(u[a:b], w[a:b], c[a:b])], pa.binary())], ["part", "blob"])


def _pairs(parts: int, uri: str):
    def run(key: tuple[pa.Scalar], table: pa.Table) -> pa.Table:
        part = key[0].as_py()
        u, w, c = _gather(table, 3)
        h = pair_hash(u, w)
        order = np.argsort(h)
        h, u, w, c = h[order], u[order], w[order], c[order].astype(np.int64)
        first = np.flatnonzero(np.concatenate(([True], h[1:] != h[:-1])))
        h, u, w, c = h[first], u[first], w[first], np.add.reduceat(c, first)
        _save(uri, f"pair-{part}-key", h)
        _save(uri, f"pair-{part}-count", np.minimum(c, 0xFFFFFFFF).astype(np.uint32))
        left = _summed(u, c, (c == 1).astype(np.int64), (c == 2).astype(np.int64), (c > 2).astype(np.int64))
        for (name, _), column in zip((("key", U), *LEFT_COLUMNS), left, strict=True):
            _save(uri, f"left-{part}-{name}", column)
        _save(uri, f"stats-pair-{part}", np.array([np.count_nonzero(c == i) for i in (1, 2, 3, 4)] + [c.sum()], np.int64))
        words, count, lefts = _summed(w, c, np.ones(len(w), np.int64))
        to = part_of(words, parts)
        order = np.lexsort((words, to))
        words, count, lefts, to = words[order], count[order], lefts[order], to[order]
        cuts = np.searchsorted(to, np.arange(parts + 1))
        found = [(p, _block(words[a:b], count[a:b], lefts[a:b])) for p, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)) if b > a]
        return pa.table({"part": pa.array([p for p, _ in found], pa.int32()), "blob": pa.array([b for _, b in found], pa.binary())})

    return run


def _words(uri: str):
    def run(key: tuple[pa.Scalar], table: pa.Table) -> pa.Table:
        part = key[0].as_py()
        w, count, left = _gather(table, 3)
        w, count, left = _summed(w, count.astype(np.int64), left.astype(np.int64))
        for name, column in (("key", w), ("count", count), ("left", left)):
            _save(uri, f"word-{part}-{name}", column)
        _save(uri, f"stats-word-{part}", np.array([np.count_nonzero(left == i) for i in (1, 2, 3, 4)] + [left.sum(), len(w)], np.int64))
        return pa.table({"part": pa.array([part], pa.int32())})

    return run


def discounts(n: np.ndarray) -> np.ndarray:
    """Discounts of counts 0, 1, 2, 3 and more from the counts of counts n1..n4."""
    n1, n2, n3, n4 = (float(x) for x in n[:4])
    if not (n1 and n2):
        return np.array([0.0, 0.5, 0.75, 0.75])  # too few counts of counts: fixed discounts
    y = n1 / (n1 + 2 * n2)
    raw = [0.0, 1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3 if n3 else 1.5]
    return np.array([0.0] + [min(max(d, 0.05), i - 0.05) for i, d in enumerate(raw) if i])


@dataclass
class KneserNey:
    """Where the model lies, and its few corpus-wide numbers."""

    uri: str
    parts: int
    have: list[int]
    have_words: list[int]
    pair_discounts: np.ndarray
    word_discounts: np.ndarray
    tokens: int
    distinct: int
    lefts: int
    word_mass: float
    files: dict = field(default_factory=dict, repr=False)

    def __getstate__(self):
        return self.__dict__ | {"files": {}}

    def _columns(self, kind: str, part: int, columns) -> list[np.ndarray]:
        key = (kind, part)
        if key not in self.files:
            self.files[key] = [_mapped(self.uri, f"{kind}-{part}-key", U)] + [_mapped(self.uri, f"{kind}-{part}-{n}", t) for n, t in columns]
        return self.files[key]

    def _find(self, kind: str, keys: np.ndarray, part: np.ndarray, columns) -> list[np.ndarray]:
        """The columns at each key (0 where there is none)."""
        have = set(self.have if kind != "word" else self.have_words)
        out = [np.zeros(len(keys), np.int64) for _ in columns]
        order = np.lexsort((keys, part))
        ordered, at = keys[order], part[order]
        cuts = np.searchsorted(at, np.arange(self.parts + 1))
        for p in range(self.parts):
            a, b = cuts[p], cuts[p + 1]
            if b == a or p not in have:
                continue
            where, *found = self._columns(kind, p, columns)
            i = np.searchsorted(where, ordered[a:b])
            i[i == len(where)] = 0
            hit = where[i] == ordered[a:b]
            rows = order[a:b][hit]
            for o, f in zip(out, found, strict=True):
                o[rows] = f[i[hit]]
        return out

    def log10(self, u: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(log10 of p(w|u), training count of w)."""
        words, back = np.unique(w, return_inverse=True)
        count, left = self._find("word", words, part_of(words, self.parts), WORD_COLUMNS)
        if self.lefts:
            q = np.maximum(left - self.word_discounts[np.minimum(left, 3)], 0) / self.lefts + self.word_mass / (self.distinct + 1)
        else:
            q = np.ones(len(words))
        q, count = q[back], count[back]
        lefts, back = np.unique(u, return_inverse=True)
        total, n1, n2, n3 = self._find("left", lefts, part_of(lefts, self.parts), LEFT_COLUMNS)
        d = self.pair_discounts
        share = (d[1] * n1 + d[2] * n2 + d[3] * n3) / np.maximum(total, 1)
        total, share = total[back], share[back]
        pairs, first, again = np.unique(pair_hash(u, w), return_index=True, return_inverse=True)
        (c,) = self._find("pair", pairs, part_of(u[first], self.parts), PAIR_COLUMNS)
        c = c[again]
        seen = total > 0
        p = np.where(seen, np.maximum(c - d[np.minimum(c, 3)], 0) / np.maximum(total, 1) + share * q, q)
        return np.log10(p), count


def parts_for(docs: DataFrame) -> int:
    """Parts that grow with the texts: one for every PART_BYTES that the plan reads, by its own estimate (the
    files' sizes), and no fewer than the shuffle has."""
    size = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))  # an int or a Scala BigInt
    least = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return max(least, math.ceil(size / PART_BYTES)) if 0 < size < UNKNOWN else least


def train(docs: DataFrame, parts: int | None = None) -> KneserNey:
    """The model of all texts of ``docs``."""
    spark = docs.sparkSession
    parts = parts or parts_for(docs)
    uri = new_path(spark, "kneser-ney")
    schema = "part int, blob binary"
    blocks = docs.select("text").mapInArrow(_count(parts), schema)
    blocks = blocks.groupBy("part").applyInArrow(_pairs(parts, uri), schema)
    blocks.groupBy("part").applyInArrow(_words(uri), "part int").write.format("noop").mode("overwrite").save()
    system, path, _ = _filesystem(uri)
    names = [f.base_name for f in system.get_file_info(fs.FileSelector(path, allow_not_found=True))]

    def stats(kind: str, width: int) -> tuple[list[int], np.ndarray]:
        have = sorted(int(n.rsplit("-", 1)[1]) for n in names if n.startswith(f"stats-{kind}-"))
        total = np.zeros(width, np.int64)
        for p in have:
            with system.open_input_stream(f"{path}/stats-{kind}-{p}") as f:
                total += np.frombuffer(f.read(), np.int64)
        return have, total

    have, pair = stats("pair", 5)
    have_words, word = stats("word", 6)
    d = discounts(word)
    ones, twos, lefts, distinct = int(word[0]), int(word[1]), int(word[4]), int(word[5])
    mass = (d[1] * ones + d[2] * twos + d[3] * (distinct - ones - twos)) / lefts if lefts else 1.0
    return KneserNey(uri, parts, have, have_words, discounts(pair), d, int(pair[4]), distinct, lefts, float(mass))


def _score(model: KneserNey):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = WordHashes()
        for batch in batches:
            n, known, base, score = [], [], [], []
            below = np.log10(model.tokens + 0.1 * (model.distinct + 1))
            for lengths, u, w in token_arrays(texts(batch.column(2)), seen):
                logs, count = model.log10(u, w)
                at = np.cumsum(lengths) - lengths
                n.append(lengths)
                known.append(np.add.reduceat((count > 0).astype(np.int64), at))
                base.append(np.add.reduceat(np.log10(count + 0.1) - below, at))
                score.append(np.add.reduceat(logs, at))
            if not n:
                continue
            n, known, base, score = (np.concatenate(x) for x in (n, known, base, score))
            total = pa.array(np.full(len(n), model.tokens, np.int64))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n), pa.array(known), total, pa.array(base), pa.array(score)], ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    return run


def scored(docs: DataFrame, model: KneserNey) -> DataFrame:
    """Per row of ``docs(doc_id, held_out, text)``: n_tokens, n_known, train_tokens, base_score, score
    (log10 of the text's probability) and perplexity."""
    schema = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    out = docs.select("doc_id", "held_out", "text").mapInArrow(_score(model), schema)
    return out.withColumn("perplexity", F.pow(F.lit(10.0), -F.col("score") / F.col("n_tokens")))


def split(docs: DataFrame, folds: int = 10) -> DataFrame:
    """``docs`` (doc_id, text) with held_out: crc32 of the id as text is divisible by ``folds``."""
    fold = F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")) % folds
    return docs.select("doc_id", (fold == 0).alias("held_out"), "text")


def train_and_score(docs: DataFrame, parts: int | None = None) -> DataFrame:
    both = split(docs)
    return scored(both, train(both.where("not held_out"), parts))
