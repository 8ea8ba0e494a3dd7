"""Reproducible randomness: every draw is a pure function of its key.

A retried or speculative task, another partitioning and another engine all give
the same draw.  Uniforms come from an md5 digest (equal in any SQL engine),
normals from two uniforms.  This is a test device, not cryptography: in
production each client keeps its own secret seed.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SCALE = float(1 << 52)


def _text(part) -> Column:  # noqa: ANN001
    return part.cast("string") if isinstance(part, Column) else F.lit(str(part))


def uniform(*parts) -> Column:  # noqa: ANN002
    """A double in [0, 1): the first 13 hex digits of the md5 of the parts joined by '|', over 2**52."""
    digits = F.substring(F.md5(F.concat_ws("|", *map(_text, parts))), 1, 13)
    return F.conv(digits, 16, 10).cast("double") / F.lit(SCALE)


def normal(*parts) -> Column:  # noqa: ANN002
    """A standard normal, rounded to 9 digits so that engines agree."""
    radius = F.sqrt(F.lit(-2.0) * F.log(F.lit(1.0) - uniform("radius", *parts)))
    return F.round(radius * F.cos(F.lit(2.0 * math.pi) * uniform("angle", *parts)), 9)


def uniform_value(*parts) -> float:  # noqa: ANN002
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:13], 16) / SCALE


def normal_value(*parts) -> float:  # noqa: ANN002
    radius = math.sqrt(-2.0 * math.log(1.0 - uniform_value("radius", *parts)))
    return round(radius * math.cos(2.0 * math.pi * uniform_value("angle", *parts)), 9)


def philox(*key: int) -> np.random.Generator:
    """A counter-based generator for a whole vector of draws."""
    seed = int.from_bytes(hashlib.md5("|".join(map(str, key)).encode()).digest()[:16], "little")
    return np.random.Generator(np.random.Philox(key=seed))


def shuffled(seq: np.ndarray, m: int, *key: int) -> np.ndarray:
    """A keyed permutation of 0..m-1 applied to seq, element by element.

    A four-round Feistel network over the next even power of two, walked until
    the value falls below m.  So `shuffled(seq) < b` picks exactly b of m
    samples without ranking, sorting or shuffling anything.
    """
    half = max(1, (max(m - 1, 1).bit_length() + 1) // 2)
    mask = np.uint64((1 << half) - 1)
    rounds = [np.uint64(int.from_bytes(hashlib.md5("|".join(map(str, (r, *key))).encode()).digest()[:8], "little")) for r in range(4)]

    def once(v: np.ndarray) -> np.ndarray:
        left, right = v >> np.uint64(half), v & mask
        for k in rounds:
            f = (right ^ k) * np.uint64(0x9E3779B97F4A7C15)
            f ^= f >> np.uint64(29)
            f *= np.uint64(0xBF58476D1CE4E5B9)
            f ^= f >> np.uint64(32)
            left, right = right, left ^ (f & mask)
        return (left << np.uint64(half)) | right

    out = once(seq.astype(np.uint64))
    while True:
        far = np.flatnonzero(out >= np.uint64(m))
        if not len(far):
            return out.astype(np.int64)
        out[far] = once(out[far])
