"""Example scenes: the escape-time fractal on two trees, and spheres with sizes by a power law."""

from __future__ import annotations

from math import log

from pyspark.sql import Column
from pyspark.sql import functions as F

LIMIT = 30
S0, S1 = 1e-3, 1e-1


def uniform01(key: Column, salt: int) -> Column:
    """The same number in [0, 1) for the same key and salt on every engine; |key| < 2 ** 30."""
    return ((key.cast("long") * 2654435761 + salt * 40503) % 4294967296) / F.lit(4294967296.0)


def escape_steps(cre: Column, cim: Column, limit: int = LIMIT) -> Column:
    """Steps of z -> z * z + c from 0 until |z| > 2, at most ``limit``."""
    start = F.struct(F.lit(0.0).alias("x"), F.lit(0.0).alias("y"), F.lit(0).alias("n"))

    def go(s, _):
        out = s["x"] * s["x"] + s["y"] * s["y"] > 4.0
        nx, ny = s["x"] * s["x"] - s["y"] * s["y"] + cre, 2.0 * s["x"] * s["y"] + cim
        return F.struct(F.when(out, s["x"]).otherwise(nx).alias("x"), F.when(out, s["y"]).otherwise(ny).alias("y"), F.when(out, s["n"]).otherwise(s["n"] + 1).alias("n"))

    return F.aggregate(F.sequence(F.lit(1), F.lit(limit)), start, go)["n"]


def escape_counts(cre, cim, limit: int = LIMIT):
    """The same for NumPy arrays."""
    import numpy as np

    x, y, n, live = np.zeros_like(cre), np.zeros_like(cre), np.zeros(cre.shape, np.int32), np.ones(cre.shape, bool)
    for _ in range(limit):
        live &= ~(x * x + y * y > 4.0)
        x, y = np.where(live, x * x - y * y + cre, x), np.where(live, 2.0 * x * y + cim, y)
        n += live
    return n


def expected_section(s0: float = S0, s1: float = S1) -> float:
    """Mean of the density 1 / (s ln(s1 / s0)) on [s0, s1]."""
    return (s1 - s0) / log(s1 / s0)


def section(u: Column, s0: float = S0, s1: float = S1) -> Column:
    return F.lit(s0) * F.pow(F.lit(s1 / s0), u)


def poisson(u: Column, mean: float, most: int = 64) -> Column:
    """Smallest k whose Poisson distribution function reaches u."""
    from math import exp

    total, p, out = 0.0, exp(-mean), F.lit(most)
    steps = []
    for k in range(most):
        total += p
        steps.append((k, total))
        p *= mean / (k + 1)
    for k, t in reversed(steps):
        out = F.when(u <= t, k).otherwise(out)
    return out


def shell_meets_box(c: list[Column], r: Column, lo: list[Column], hi: list[Column], eps: float) -> Column:
    """Whether the shell between (1 - eps) r and (1 + eps) r meets the box."""
    near = sum((F.pow(F.greatest(a - x, x - b, F.lit(0.0)), 2) for x, a, b in zip(c, lo, hi)), F.lit(0.0))
    far = sum((F.pow(F.greatest(F.abs(x - a), F.abs(x - b)), 2) for x, a, b in zip(c, lo, hi)), F.lit(0.0))
    return (near <= F.pow(r * (1 + eps), 2)) & (far >= F.pow(r * (1 - eps), 2))
