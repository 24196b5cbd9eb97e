"""Noise as column expressions: keyed uniforms, double-geometric and Laplace draws."""

from __future__ import annotations

import hashlib
import math
import secrets

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Change of the L1 norm when one entity is added or removed.
SENSITIVITY = {"naive": 2, "hg": 1, "hc": 1, "max_size": 1}


class SecretSeed(str):
    """A release seed from the operating system's entropy. It must never be logged or stored with the release."""

    def __new__(cls):
        return super().__new__(cls, secrets.token_hex(32))

    def __repr__(self) -> str:
        return "SecretSeed(...)"


def _col(x) -> Column:
    return x if isinstance(x, Column) else F.lit(x)


def keyed_uniform(*parts) -> Column:
    """A uniform number in (0, 1) from the first 52 bits of the MD5 of the parts joined by |; the same in any engine."""
    digest = F.md5(F.concat_ws("|", *[_col(p).cast("string") for p in parts]).cast("binary"))
    return (F.conv(F.substring(digest, 1, 13), 16, 10).cast("long") + F.lit(0.5)) / F.lit(4503599627370496.0)


def geometric_noise(scale, *key) -> Column:
    """Double-geometric integer noise of the given scale (sensitivity / epsilon), as the difference of two geometrics.

    P(k) is proportional to exp(-abs(k) / scale). Uniforms have 52 bits, so draws beyond about 37 scales don't occur.
    """
    one = lambda letter: F.floor(F.ln(keyed_uniform(*key, letter)) / (F.lit(-1.0) / _col(scale)))
    return (one("a") - one("b")).cast("long")


def keyed_generator(*parts) -> np.random.Generator:
    """A generator seeded by the MD5 of the parts joined by |."""
    return np.random.Generator(np.random.PCG64(int.from_bytes(hashlib.md5("|".join(map(str, parts)).encode()).digest())))


def geometric_faces(n: int, value: int, scale: float, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
    """(totals, counts), means ascending: the isotonic fit in squares of n equal values with double-geometric noise each, drawn as a whole.

    Over all orders of any n numbers, ties included, the fit has the same law as this: cut the numbers by the cycles of a
    uniform permutation and sort the cycles by their mean. Cycle lengths are drawn one after another, each uniform up to
    what is left, and the noise of a cycle is the difference of two negative binomials. So about ln n draws stand for n.
    """
    counts, left = [], int(n)
    while left:
        counts.append(int(rng.integers(1, left + 1)))
        left -= counts[-1]
    counts = np.array(counts, dtype=np.int64)
    p = -math.expm1(-1.0 / scale)
    totals = counts * value + rng.negative_binomial(counts, p) - rng.negative_binomial(counts, p)
    order = np.argsort(totals / counts, kind="stable")
    return totals[order], counts[order]


def laplace_noise(scale, *key) -> Column:
    u = keyed_uniform(*key, "l") - F.lit(0.5)
    return -F.signum(u) * _col(scale) * F.ln(F.lit(1.0) - F.lit(2.0) * F.abs(u))


def geometric_variance(scale: float) -> float:
    a = math.exp(-1 / scale)
    return 2 * a / (1 - a) ** 2


def geometric_pmf(k: int, scale: float) -> float:
    a = math.exp(-1 / scale)
    return (1 - a) / (1 + a) * a ** abs(k)


def noise_density(scale: float) -> dict[str, float]:
    """Shares of cells that are non-zero, and positive, after noise on an empty histogram."""
    a = math.exp(-1 / scale)
    return {"nonzero": 2 * a / (1 + a), "positive": a / (1 + a)}
