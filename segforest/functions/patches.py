"""Rays against curved patches and elements: bilinear patches as Column expressions, patches of any degree and the
elements they bound with NumPy.

Everything is in the camera frame, where rays start at the origin and their third component is positive, so
the two planes X rz = Z rx and Y rz = Z ry hold the ray."""

from __future__ import annotations

from typing import Protocol

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .geometry import face_points, lobatto, map_point


def hit_bilinear_columns(p00, p10, p01, p11, ray) -> Column:
    """array<struct<alpha,s,t>> of all hits with (s, t) in [0, 1]^2, nearest first; corners and ray are lists of
    three Columns. Eliminating t from the two planes leaves a quadratic in s."""
    b = [y - x for x, y in zip(p00, p10)]
    c = [y - x for x, y in zip(p00, p01)]
    d = [w - y - z + x for x, y, z, w in zip(p00, p10, p01, p11)]
    plane = lambda v, k: v[k] * ray[2] - v[2] * ray[k]
    a1, b1, c1, d1 = (plane(v, 0) for v in (p00, b, c, d))
    a2, b2, c2, d2 = (plane(v, 1) for v in (p00, b, c, d))
    k = F.struct(*[x.alias(n) for n, x in (("a1", a1), ("b1", b1), ("c1", c1), ("d1", d1), ("a2", a2), ("b2", b2), ("c2", c2), ("d2", d2))])
    zero = F.lit(0.0)

    def roots(e):
        q = F.struct(
            (e["b2"] * e["d1"] - e["d2"] * e["b1"]).alias("q2"),
            (e["a2"] * e["d1"] - e["d2"] * e["a1"] + e["b2"] * e["c1"] - e["c2"] * e["b1"]).alias("q1"),
            (e["a2"] * e["c1"] - e["c2"] * e["a1"]).alias("q0"),
        )
        return F.flatten(F.transform(F.array(q), solve))

    def solve(e):
        flat = F.abs(e["q2"]) <= 1e-12 * (F.abs(e["q1"]) + F.abs(e["q0"]))
        disc = e["q1"] * e["q1"] - 4 * e["q2"] * e["q0"]
        m = -0.5 * (e["q1"] + F.when(e["q1"] < 0, -1.0).otherwise(1.0) * F.sqrt(F.greatest(disc, zero)))
        two = F.array_distinct(F.array(m / F.nullif(e["q2"], zero), e["q0"] / F.nullif(m, zero)))
        return F.when(flat, F.array(-e["q0"] / F.nullif(e["q1"], zero))).when(disc >= 0, two).otherwise(F.array().cast("array<double>"))

    def place(e, s):
        e1, e2 = e["c1"] + e["d1"] * s, e["c2"] + e["d2"] * s
        t = F.when(F.abs(e1) >= F.abs(e2), -(e["a1"] + e["b1"] * s) / F.nullif(e1, zero)).otherwise(-(e["a2"] + e["b2"] * s) / F.nullif(e2, zero))
        z = p00[2] + s * b[2] + t * c[2] + s * t * d[2]
        return F.struct((z / ray[2]).alias("alpha"), s.alias("s"), t.alias("t"))

    hits = F.transform(F.array(k), lambda e: F.transform(roots(e), lambda s: place(e, s)))
    inside = lambda h: h["s"].between(0, 1) & h["t"].between(0, 1) & (h["alpha"] > 0)
    return F.array_sort(F.filter(F.flatten(hits), inside))


def bernstein(ctrl: np.ndarray) -> np.ndarray:
    """Bernstein coefficients of a tensor-product patch or cube given at Lobatto nodes; they bound it."""
    from math import comb

    out = np.asarray(ctrl, float)
    for axis in range(out.ndim - 1):
        r = out.shape[axis] - 1
        nodes = np.array(lobatto(r))
        m = np.stack([comb(r, i) * nodes**i * (1 - nodes) ** (r - i) for i in range(r + 1)], 1)
        out = np.moveaxis(np.linalg.solve(m, np.moveaxis(out, axis, 0).reshape(r + 1, -1)).reshape(np.moveaxis(out, axis, 0).shape), 0, axis)
    return out


def _halves(c: np.ndarray, axis: int) -> tuple[np.ndarray, np.ndarray]:
    """Bernstein coefficients of both halves along an axis, by repeated means."""
    c = np.moveaxis(c, axis, 0)
    left, right, row = [c[0]], [c[-1]], c
    while len(row) > 1:
        row = (row[1:] + row[:-1]) / 2
        left.append(row[0])
        right.append(row[-1])
    return np.moveaxis(np.stack(left), 0, axis), np.moveaxis(np.stack(right[::-1]), 0, axis)


def hit_patch(ctrl: np.ndarray, ray, depth: int = 5, tol: float = 1e-12) -> list[tuple[float, float, float]]:
    """(alpha, s, t) of all hits of a ray and a patch of any degree, sorted. Pieces whose Bernstein coefficients lie on
    one side of either plane are dropped, the rest is halved ``depth`` times and polished by Newton's rule; a
    ray that only grazes the patch may give its double hit once."""
    ray = np.asarray(ray, float)
    coef = bernstein(ctrl)
    uv = np.stack([coef[..., 0] * ray[2] - coef[..., 2] * ray[0], coef[..., 1] * ray[2] - coef[..., 2] * ray[1]], -1)
    todo, seeds = [(uv, 0.0, 1.0, 0.0, 1.0, 0)], []
    pad = 1e-12 * (np.abs(uv).max() + 1e-300)
    while todo:
        c, s0, s1, t0, t1, k = todo.pop()
        if (c.min((0, 1)) > pad).any() or (c.max((0, 1)) < -pad).any():
            continue
        if k == 2 * depth:
            seeds.append(((s0 + s1) / 2, (t0 + t1) / 2))
            continue
        lo, hi = _halves(c, k % 2)
        m = (s0 + s1) / 2 if k % 2 == 0 else (t0 + t1) / 2
        todo += [(lo, s0, m, t0, t1, k + 1), (hi, m, s1, t0, t1, k + 1)] if k % 2 == 0 else [(lo, s0, s1, t0, m, k + 1), (hi, s0, s1, m, t1, k + 1)]
    plane = lambda p: np.array([p[0] * ray[2] - p[2] * ray[0], p[1] * ray[2] - p[2] * ray[1]])
    out: list[tuple[float, float, float]] = []
    for s, t in seeds:
        x = np.array([s, t])
        for _ in range(30):
            f = plane(map_point(ctrl, (x[0], x[1])))
            e = 1e-6
            jac = np.stack([(plane(map_point(ctrl, (x[0] + e * (i == 0), x[1] + e * (i == 1)))) - f) / e for i in (0, 1)], 1)
            if abs(np.linalg.det(jac)) < 1e-18:
                break
            move = np.linalg.solve(jac, f)
            x = x - move
            if np.abs(move).max() < tol:
                break
        p = map_point(ctrl, (x[0], x[1]))
        if np.all(x >= -1e-9) and np.all(x <= 1 + 1e-9) and np.abs(plane(p)).max() < 1e-8 and p[2] > 0:
            if not any(abs(x[0] - b) + abs(x[1] - c) < 1e-6 for _, b, c in out):
                out.append((float(p[2] / ray[2]), float(x[0]), float(x[1])))
    return sorted(out)


def basis(r: int, t: np.ndarray) -> np.ndarray:
    """Lagrange basis at Lobatto nodes for many places: [len(t), r + 1]."""
    n = np.array(lobatto(r))
    out = np.ones((len(t), r + 1))
    for i in range(r + 1):
        for j in range(r + 1):
            if i != j:
                out[:, i] *= (t - n[j]) / (n[i] - n[j])
    return out


def mapped(df: DataFrame, r: int, d: int) -> DataFrame:
    """``df`` with ``point``: the image of ``at`` (array of d numbers in [0, 1]) under the map of degree r whose (r + 1) ** d control
    points are in ``ctrl`` (array of arrays of three, first axis first). Whole Arrow batches; a null place has a null image."""
    import pyarrow as pa

    def run(batches):
        for b in batches:
            at, ctrl = (b.column(b.schema.get_field_index(c)) for c in ("at", "ctrl"))
            ok = np.asarray(at.is_valid())
            places = np.array(at.drop_null().flatten(), float).reshape(-1, d)
            points = np.array(ctrl.filter(pa.array(ok)).flatten().flatten(), float).reshape(-1, *[r + 1] * d, 3)
            for axis in range(d):
                points = np.einsum("nk,nk...->n...", basis(r, places[:, axis]), points)
            out = iter(points.tolist())
            yield b.append_column("point", pa.array([next(out) if x else None for x in ok], pa.list_(pa.float64())))

    from pyspark.sql import types as T

    return df.mapInArrow(run, T.StructType([*df.schema.fields, T.StructField("point", T.ArrayType(T.DoubleType()))]))


class GeometryMap(Protocol):
    """What rendering needs of a tree's geometry; any map whose faces can be met with a ray will do."""

    def point(self, t: tuple[float, ...]) -> np.ndarray: ...

    def sub(self, low: tuple[float, ...], edge: float) -> GeometryMap: ...

    def box(self) -> tuple[np.ndarray, np.ndarray]: ...

    def crossings(self, ray) -> list[float]: ...


class TensorMap:
    """Tensor-product map of the reference square or cube with control points at Lobatto nodes, in the camera frame."""

    def __init__(self, ctrl):
        self.ctrl = np.asarray(ctrl, float)
        self.d = self.ctrl.ndim - 1

    def point(self, t):
        return map_point(self.ctrl, t)

    def sub(self, low, edge):
        """The map of the subcube with lower corner ``low``; exact, as degrees do not change."""
        r = self.ctrl.shape[0] - 1
        n = np.array(lobatto(r)) * edge
        grid = np.stack(np.meshgrid(*[n + x for x in low], indexing="ij"), -1).reshape(-1, self.d)
        return TensorMap(np.array([self.point(tuple(g)) for g in grid]).reshape(self.ctrl.shape))

    def box(self):
        b = bernstein(self.ctrl).reshape(-1, 3)
        return b.min(0), b.max(0)

    def crossings(self, ray):
        """Ray parameters of all points on the surface (d = 2) or through the faces (d = 3), sorted."""
        if self.d == 2:
            return [h[0] for h in hit_patch(self.ctrl, ray)]
        found = sorted(h[0] for axis in range(3) for side in (0, 1) for h in hit_patch(face_points(self.ctrl, axis, side), ray))
        return [x for i, x in enumerate(found) if i == 0 or x - found[i - 1] > 1e-9]


def element_segments(element: GeometryMap, ray) -> list[tuple[float, float]]:
    """(in, out) parameters of a ray through a 3-D element: crossings in order, in pairs. An odd last one (a graze, or
    a face in front of the eye) opens nothing."""
    x = element.crossings(ray)
    return list(zip(x[0::2], x[1::2]))


def element_points(element: TensorMap, ray) -> list[tuple[float, float]]:
    """(parameter, |cos| of the angle between ray and normal) of a ray's hits with a 2-D element."""
    ray = np.asarray(ray, float)
    out = []
    for alpha, s, t in hit_patch(element.ctrl, ray):
        e = 1e-6
        s, t = min(max(s, e), 1 - e), min(max(t, e), 1 - e)
        ds, dt = element.point((s + e, t)) - element.point((s - e, t)), element.point((s, t + e)) - element.point((s, t - e))
        n = np.cross(ds, dt)
        out.append((alpha, float(abs(n @ ray) / (np.linalg.norm(n) * np.linalg.norm(ray)))))
    return out
