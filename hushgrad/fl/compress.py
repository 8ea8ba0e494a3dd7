"""Unbiased compressors.

Each says its variance `omega(d)`, how many numbers a message holds, and how to
compress a vector with the draws of a generator.  Compression follows the noise;
the opposite order needs noise made for it and is refused.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np


class OrderError(ValueError):
    pass


def check_order(order: tuple[str, ...], unsafe: bool = False) -> None:
    """Stages of a client, which must perturb before they compress."""
    if order.index("compress") < order.index("perturb") and not unsafe:
        raise OrderError("compressing before the noise is added is not private with Gaussian noise")


@dataclass(frozen=True)
class Identity:
    def omega(self, d: int) -> float:
        return 0.0

    def kept(self, d: int) -> int:
        return d

    def apply(self, v: np.ndarray, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
        return np.arange(len(v)), v

    def bits(self, d: int) -> tuple[int, int]:
        """(value bits, index bits) of a message."""
        return 32 * d, 0


@dataclass(frozen=True)
class RandomK:
    """Keeps k random coordinates, scaled by d/k."""

    fraction: float = 1 / 20
    k: int | None = None

    def kept(self, d: int) -> int:
        return self.k if self.k is not None else max(1, math.floor(d * self.fraction + 1e-9))

    def omega(self, d: int) -> float:
        return d / self.kept(d) - 1

    def apply(self, v: np.ndarray, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
        d, k = len(v), self.kept(len(v))
        at = np.sort(rng.choice(d, k, replace=False))
        return at, v[at] * (d / k)

    def bits(self, d: int) -> tuple[int, int]:
        k = self.kept(d)
        return 32 * k, k * max(1, math.ceil(math.log2(d))) if d > 1 else 0


@dataclass(frozen=True)
class RandomQuantizer:
    """Random dithering of each coordinate to `levels` steps of the vector's norm."""

    levels: int = 4

    def omega(self, d: int) -> float:
        return min(d / self.levels**2, math.sqrt(d) / self.levels)

    def kept(self, d: int) -> int:
        return d

    def apply(self, v: np.ndarray, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
        norm = float(np.linalg.norm(v))
        if norm == 0:
            return np.arange(len(v)), v
        x = np.abs(v) / norm * self.levels
        low = np.floor(x)
        q = low + (rng.random(len(v)) < x - low)
        return np.arange(len(v)), np.sign(v) * q * norm / self.levels

    def bits(self, d: int) -> tuple[int, int]:
        return 32 + d * (1 + math.ceil(math.log2(self.levels + 1))), 0
