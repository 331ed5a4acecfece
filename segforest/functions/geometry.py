"""Camera, rays, boxes and hits as Column expressions; nodes and bases as plain numbers."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def held(df: DataFrame, **columns: Column) -> DataFrame:
    """withColumns behind a generator of one row, so that later filters are not rewritten over the definitions: generated
    code stays small and each is computed once."""
    x = df.withColumn("_held", F.explode(F.array(F.struct(*[c.alias(k) for k, c in columns.items()]))))
    return x.withColumns({k: F.col(f"_held.{k}") for k in columns}).drop("_held")


def lobatto(r: int) -> list[float]:
    """r + 1 Gauss-Lobatto nodes on [0, 1], both ends among them."""
    if r < 2:
        return [0.0, 1.0][: r + 1] if r else [0.5]
    inner = np.polynomial.legendre.Legendre.basis(r).deriv().roots()
    return [0.0, *((1 + np.sort(inner.real)) / 2).tolist(), 1.0]


def lagrange(nodes: list[float], t: float) -> list[float]:
    return [float(np.prod([(t - n) / (m - n) for j, n in enumerate(nodes) if j != i])) for i, m in enumerate(nodes)]


def lagrange_columns(nodes: list[float], t: Column) -> list[Column]:
    """``lagrange`` for a column of places."""
    out = []
    for i, m in enumerate(nodes):
        v = F.lit(1.0)
        for n in nodes[:i] + nodes[i + 1 :]:
            v = v * ((t - n) / (m - n))
        out.append(v)
    return out


def map_point(ctrl: np.ndarray, t: tuple[float, ...]) -> np.ndarray:
    """Tensor-product image of a reference point; ctrl has (r + 1) ** d control points, first axis first."""
    out = np.asarray(ctrl, float)
    for x in t:
        nodes = lobatto(out.shape[0] - 1)
        out = np.tensordot(np.array(lagrange(nodes, x)), out, axes=(0, 0))
    return out


def face_points(ctrl: np.ndarray, axis: int, side: int) -> np.ndarray:
    return np.take(ctrl, 0 if side == 0 else -1, axis=axis)


def face_columns(ctrl: str, r: int, d: int, axis: int, side: int) -> Column:
    """The control points of a face from an array column of all (r + 1) ** d of an element, first axis first."""
    m = r + 1
    places = [k for k in range(m**d) if k // m ** (d - 1 - axis) % m == (0 if side == 0 else r)]
    return F.array(*[F.element_at(ctrl, k + 1) for k in places])


def bilinear(s: Column, t: Column, p00: Column, p10: Column, p01: Column, p11: Column) -> Column:
    return (1 - s) * (1 - t) * p00 + s * (1 - t) * p10 + (1 - s) * t * p01 + s * t * p11


def ray_dir(i: Column, j: Column, w: int, h: int, ell: float, v, t, u) -> list[Column]:
    """Direction of pixel (i, j): v + ell * ((i - (w-1)/2) t + (j - (h-1)/2) u), by component."""
    x, y = (i - (w - 1) / 2) * ell, (j - (h - 1) / 2) * ell
    return [F.lit(float(a)) + x * float(b) + y * float(c) for a, b, c in zip(v, t, u)]


def hit_box(lo: list[Column], hi: list[Column], o: list[Column], r: list[Column]) -> tuple[Column, Column]:
    """Entry and exit parameter of a ray and an axis-aligned box; no hit when entry >= exit."""
    big = F.lit(1e300)
    near, far = [], []
    for a, b, p, d in zip(lo, hi, o, r):
        flat = F.abs(d) < 1e-12
        t0, t1 = (a - p) / F.nullif(d, F.lit(0.0)), (b - p) / F.nullif(d, F.lit(0.0))
        inside = (p >= a) & (p < b)
        near.append(F.when(flat, F.when(inside, -big).otherwise(big)).otherwise(F.least(t0, t1)))
        far.append(F.when(flat, F.when(inside, big).otherwise(-big)).otherwise(F.greatest(t0, t1)))
    return F.greatest(*near), F.least(*far)


def hit_plane(point: list[Column], normal: list[Column], o: list[Column], r: list[Column]) -> Column:
    """Ray parameter of a plane; null when parallel."""
    down = sum((n * d for n, d in zip(normal[1:], r[1:])), normal[0] * r[0])
    up = sum((n * (p - q) for n, p, q in zip(normal[1:], point[1:], o[1:])), normal[0] * (point[0] - o[0]))
    return up / F.nullif(down, F.lit(0.0))


def hit_sphere(c: list[Column], radius: Column, o: list[Column], r: list[Column]) -> tuple[Column, Column]:
    """Both parameters; null without a hit."""
    m = [p - q for p, q in zip(o, c)]
    dot = lambda x, y: x[0] * y[0] + x[1] * y[1] + x[2] * y[2]
    a, b, k = dot(r, r), dot(m, r), dot(m, m) - radius * radius
    disc = b * b - a * k
    root = F.when(disc >= 0, F.sqrt(F.greatest(disc, F.lit(0.0))))
    return (-b - root) / a, (-b + root) / a


def pixel_bounds(lo: Column, hi: Column, z0: Column, z1: Column, size: int, n: float, ell: float) -> tuple[Column, Column]:
    """First and last pixel centre of a camera-frame interval at depths z0..z1, clamped to the image; empty when first > last."""
    a = lo / F.when(lo >= 0, z1).otherwise(z0)
    b = hi / F.when(hi >= 0, z0).otherwise(z1)
    first = F.ceil((size - 1) / 2 + a * n / ell)
    last = F.floor((size - 1) / 2 + b * n / ell)
    return F.greatest(first, F.lit(0)).cast("long"), F.least(last, F.lit(size - 1)).cast("long")


def hit_bilinear(a, b, c, d, ray, tol: float = 1e-9) -> list[tuple[float, float, float]]:
    """(alpha, s, t) of all hits of the ray alpha * ray and the patch a + b s + c t + d s t.

    Two planes through the ray give two equations bilinear in s and t; eliminating
    t leaves a quadratic in s."""
    a, b, c, d, ray = (np.asarray(x, float) for x in (a, b, c, d, ray))
    k = int(np.argmax(np.abs(ray)))
    rows = []
    for o in [x for x in range(3) if x != k]:
        n = np.zeros(3)
        n[o], n[k] = ray[k], -ray[o]
        rows.append([n @ x for x in (a, b, c, d)])
    (a1, b1, c1, d1), (a2, b2, c2, d2) = rows
    q = [b2 * d1 - d2 * b1, a2 * d1 - d2 * a1 + b2 * c1 - c2 * b1, a2 * c1 - c2 * a1]
    while len(q) > 1 and abs(q[0]) < 1e-14:
        q = q[1:]
    out = []
    for s in np.roots(q):
        if abs(s.imag) > 1e-9:
            continue
        s = s.real
        e1, e2 = c1 + d1 * s, c2 + d2 * s
        t = -(a1 + b1 * s) / e1 if abs(e1) >= abs(e2) and e1 else -(a2 + b2 * s) / e2 if e2 else np.nan
        p = a + b * s + c * t + d * s * t
        if -tol <= s <= 1 + tol and -tol <= t <= 1 + tol and p[k] / ray[k] > 0:
            out.append((float(p[k] / ray[k]), float(s), float(t)))
    return sorted(out)
