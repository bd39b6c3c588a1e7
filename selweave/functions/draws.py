"""Seeded draws that any engine can repeat: uniform numbers from md5."""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SCALE = float(1 << 32)


def uniform(*parts: Column | str | int) -> Column:
    """In [0, 1): the first eight hex digits of md5 over the parts joined by '|'."""
    cols = [p if isinstance(p, Column) else F.lit(p) for p in parts]
    text = F.concat_ws("|", *(c.cast("string") for c in cols))
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") / F.lit(SCALE)


def uniform_of(*parts: object) -> float:
    """The same draw for Python values (floats in Spark's own notation are the caller's business)."""
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:8], 16) / SCALE


def uniforms_of(prefix: str, n: int) -> np.ndarray:
    return np.array([uniform_of(prefix, k) for k in range(n)])
