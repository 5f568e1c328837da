"""Quality classifier by compression.

Two zstandard dictionaries are built, one from good and one from bad labelled texts.  A text is
cut into blocks, every block is compressed under both dictionaries, and the normalised
difference of the compressed sizes (with the size itself a byte) becomes a score by a logistic
calibration on labelled texts that the dictionaries have not seen.

Fitting uses a bounded sample of labelled rows: ``most`` per label (by the md5 order of their
ids) whose texts have ``most_bytes`` at most, so 2 * most * most_bytes in the driver (98 MB).  All of
them reach the dictionaries or the calibration.  Scoring covers every whole text.

Defined results: a null or empty text has the share of label 1 among the fitted rows as its
score; without any fitted rows all scores are 0.5, with one label only its share; null ids are
in the held-out fold of the empty string; repeated rows give repeated rows; of an id's several texts
the smallest is fitted, an id with both labels counts for both; extra columns are ignored; labels
other than 0 and 1 are not used.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK, LEVEL, DICTIONARY = 1024, 3, 65_536
MOST, MOST_BYTES = 3000, 16_384
THRESHOLD = 0.3


def blocks(text: bytes) -> list[bytes]:
    return [text[i : i + BLOCK] for i in range(0, len(text), BLOCK)]


def dictionary(samples: list[bytes]) -> bytes | None:
    """A trained dictionary; plain content where there are too few samples to train on."""
    parts = [b for t in samples for b in blocks(t) if len(b) >= 64]
    total = sum(map(len, parts))
    if not total:
        return None
    try:
        return zstandard.train_dictionary(min(DICTIONARY, max(1024, total // 8)), parts).as_bytes()
    except zstandard.ZstdError:
        return b"".join(parts)[-DICTIONARY:]


class Sizes:
    """Compressed sizes of texts under two dictionaries."""

    def __init__(self, good: bytes, bad: bytes):
        self.coders = []
        for content in (good, bad):
            d = zstandard.ZstdCompressionDict(content)
            d.precompute_compress(level=LEVEL)
            self.coders.append(zstandard.ZstdCompressor(level=LEVEL, dict_data=d, write_content_size=False))

    def features(self, text: bytes) -> tuple[float, float, float]:
        good, bad = (sum(len(c.compress(b)) for b in blocks(text)) for c in self.coders)
        return (bad - good) / max(good, bad, 1), (bad - good) / max(len(text), 1), min(good, bad) / max(len(text), 1)


def logistic(x: np.ndarray, y: np.ndarray, penalty: float = 1e-3, rounds: int = 40) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(means, scales, weights with the intercept last) by Newton steps."""
    mean, scale = x.mean(0), x.std(0) + 1e-9
    z = np.c_[(x - mean) / scale, np.ones(len(x))]
    w = np.zeros(z.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        h = (z * (p * (1 - p) + 1e-9)[:, None]).T @ z + penalty * len(x) * np.eye(len(w))
        step = np.linalg.solve(h, z.T @ (y - p) - penalty * len(x) * w)
        w = w + step
        if np.abs(step).max() < 1e-9:
            break
    return mean, scale, w


@dataclass
class CompressionModel:
    good: bytes | None
    bad: bytes | None
    base: float
    mean: np.ndarray | None = None
    scale: np.ndarray | None = None
    weights: np.ndarray | None = None

    def scores(self, texts: list[bytes | None]) -> np.ndarray:
        out = np.full(len(texts), self.base)
        if self.weights is None:
            return out
        sizes = Sizes(self.good, self.bad)
        rows = [i for i, t in enumerate(texts) if t]
        if rows:
            x = np.array([sizes.features(texts[i]) for i in rows])
            out[rows] = 1 / (1 + np.exp(-np.clip(((x - self.mean) / self.scale) @ self.weights[:-1] + self.weights[-1], -30, 30)))
        return out


def fit(good: list[bytes], bad: list[bytes]) -> CompressionModel:
    """Every other text goes to a dictionary, the rest to the calibration."""
    base = len(good) / (len(good) + len(bad)) if good or bad else 0.5
    model = CompressionModel(dictionary(good[::2]), dictionary(bad[::2]), base)
    held = [(t, 1.0) for t in good[1::2] if t] + [(t, 0.0) for t in bad[1::2] if t]
    y = np.array([q for _, q in held])
    if model.good is None or model.bad is None or len(set(y.tolist())) < 2:
        return model
    sizes = Sizes(model.good, model.bad)
    model.mean, model.scale, model.weights = logistic(np.array([sizes.features(t) for t, _ in held]), y)
    return model


def fold(folds: int):
    return F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")) % folds


def train(docs: DataFrame, labels: DataFrame, *, label: str = "quality", folds: int = 5, most: int = MOST, most_bytes: int = MOST_BYTES) -> CompressionModel:
    """Labels are picked before the texts are touched, so only the picked texts move."""
    usable = labels.select("doc_id", F.col(label).cast("int").alias("y")).where(f"doc_id is not null and y in (0, 1)").where(fold(folds) != 0).distinct()
    order = F.md5(F.col("doc_id").cast("string").cast("binary"))
    picked = [usable.where(f"y = {y}").orderBy(order, "doc_id").limit(most) for y in (0, 1)]
    picked = F.broadcast(picked[0].union(picked[1]))  # 2 * most rows
    size = F.octet_length("text")
    rows = docs.select("doc_id", "text").where((size > 0) & (size <= most_bytes)).join(picked, "doc_id")
    rows = rows.groupBy("doc_id", "y").agg(F.min("text").cast("binary").alias("t")).collect()
    rows = sorted(rows, key=lambda r: (r.doc_id, bytes(r.t)))
    return fit([bytes(r.t) for r in rows if r.y == 1], [bytes(r.t) for r in rows if r.y == 0])


def scored(docs: DataFrame, model: CompressionModel, folds: int = 5, threshold: float = THRESHOLD) -> DataFrame:
    """Per row of ``docs``: doc_id, held_out, score, predicted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            score = model.scores(batch.column(2).cast(pa.binary()).to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(score), pa.array((score >= threshold).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    return docs.select("doc_id", (fold(folds) == 0).alias("held_out"), "text").mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")
