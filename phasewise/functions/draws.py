"""Layout-independent draws: a number in [0, 1) from (seed, run, phase, point id).  (M8c)"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def draw_expr(seed, run, phase, point_id) -> Column:
    """The first 32 bits of md5 over ``seed|run|phase|point_id``, as a share of 2^32."""
    parts = [c if isinstance(c, Column) else F.lit(c) for c in (seed, run, phase, point_id)]
    text = F.concat_ws("|", *(p.cast("string") for p in parts))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)


def draws(kind: str, seed: int, run: int, phase: int, ids, constant: float = 0.5) -> np.ndarray:
    """``kind``: "hash", "constant" (the given number), or "always_at_price" (opens only at the full price)."""
    if kind == "constant":
        return np.full(len(ids), constant)
    if kind == "always_at_price":
        return np.full(len(ids), np.nextafter(1.0, 0.0))
    head, md5 = f"{seed}|{run}|{phase}|".encode(), hashlib.md5
    digests = b"".join([md5(head + b"%d" % i).digest() for i in np.asarray(ids).tolist()])
    return np.frombuffer(digests, ">u4")[::4] / 4294967296.0
