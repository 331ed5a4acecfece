"""Rendering of volume elements on curved trees: every tree is the image of the unit cube under a tensor-product map of any degree.

Control points are turned into camera frames before elements join them. A task restricts the map to each of its
elements, bounds it by Bernstein coefficients, casts the rays of its pixel rectangle against all six faces, sorts the hits of a
ray and pairs them to ways in and out. Faces of degree 1 are met in closed form, others by Newton's rule
from a grid of starts, for all rays of an element at once."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import algebra
from ..functions.geometry import lobatto
from ..functions.patches import basis, bernstein
from ..functions.sfc import coordinate, morton2


def camera_trees(trees: DataFrame, cams: list) -> DataFrame:
    """Trees (tree, ctrl: control points, first axis first) in each camera's frame, with the camera's numbers: inst, w, h, n, ell, far."""
    out = None
    for cam in cams:
        axes = (cam.t, cam.u, tuple(x / cam.n for x in cam.v))
        turn = lambda p: F.array(*[sum(((F.element_at(p, a + 1) - float(cam.o[a])) * float(e[a]) for a in range(3)), F.lit(0.0)) for e in axes])  # noqa: B023, E731
        x = trees.select("tree", F.transform("ctrl", turn).alias("ctrl"), *[F.lit(v).alias(k) for k, v in (("inst", cam.inst), ("w", cam.w), ("h", cam.h), ("n", float(cam.n)), ("ell", float(cam.ell)), ("far", float(cam.far)))])
        out = x if out is None else out.unionByName(x)
    return out


def bilinear_hits(face: np.ndarray, rays: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(ray, parameter) of all hits of rays (third component positive) with a patch of four corners, [2, 2, 3]."""
    a, b, c = face[0, 0], face[1, 0] - face[0, 0], face[0, 1] - face[0, 0]
    d = face[1, 1] - face[1, 0] - face[0, 1] + face[0, 0]
    plane = lambda v, k: v[k] * rays[:, 2] - v[2] * rays[:, k]
    (a1, b1, c1, d1), (a2, b2, c2, d2) = ([plane(v, k) for v in (a, b, c, d)] for k in (0, 1))
    q2, q1, q0 = b2 * d1 - d2 * b1, a2 * d1 - d2 * a1 + b2 * c1 - c2 * b1, a2 * c1 - c2 * a1
    with np.errstate(all="ignore"):
        flat = np.abs(q2) <= 1e-12 * (np.abs(q1) + np.abs(q0))
        m = -0.5 * (q1 + np.where(q1 < 0, -1.0, 1.0) * np.sqrt(q1 * q1 - 4 * q2 * q0))
        found, at = [], []
        for s in (np.where(flat, -q0 / q1, m / q2), np.where(flat, np.nan, q0 / m)):
            e1, e2 = c1 + d1 * s, c2 + d2 * s
            t = np.where(np.abs(e1) >= np.abs(e2), -(a1 + b1 * s) / e1, -(a2 + b2 * s) / e2)
            ok = np.flatnonzero((s >= 0) & (s <= 1) & (t >= 0) & (t <= 1))
            found.append(ok)
            at.append((a[2] + b[2] * s[ok] + c[2] * t[ok] + d[2] * s[ok] * t[ok]) / rays[ok, 2])
    return np.concatenate(found), np.concatenate(at)


def newton_hits(face: np.ndarray, rays: np.ndarray, starts: int = 4, rounds: int = 12) -> tuple[np.ndarray, np.ndarray]:
    """The same for a patch of any degree, [r + 1, r + 1, 3]: Newton's rule from ``starts`` ** 2 places for every ray; equal ends count once."""
    r, m = face.shape[0] - 1, len(rays)
    step = 1e-6
    grid = (np.arange(starts) + 0.5) / starts
    s, t = (np.tile(g.ravel(), m) for g in np.meshgrid(grid, grid, indexing="ij"))
    which = np.repeat(np.arange(m), starts * starts)
    ray = rays[which]

    def image(s, t):
        return np.einsum("ni,nj,ijk->nk", basis(r, s), basis(r, t), face)

    def miss(s, t):
        p = image(s, t)
        return p[:, 0] * ray[:, 2] - p[:, 2] * ray[:, 0], p[:, 1] * ray[:, 2] - p[:, 2] * ray[:, 1]

    with np.errstate(all="ignore"):
        for _ in range(rounds):
            (f, g), (fs, gs), (ft, gt) = miss(s, t), miss(s + step, t), miss(s, t + step)
            j = np.stack([fs - f, ft - f, gs - g, gt - g]) / step
            det = j[0] * j[3] - j[1] * j[2]
            s, t = s - (f * j[3] - g * j[1]) / det, t - (g * j[0] - f * j[2]) / det
            s, t = np.clip(np.nan_to_num(s, nan=9.0), -9, 9), np.clip(np.nan_to_num(t, nan=9.0), -9, 9)
        f, g = miss(s, t)
    size = np.abs(face).max()
    ok = np.flatnonzero((np.abs(f) + np.abs(g) < 1e-9 * size) & (s >= -1e-9) & (s <= 1 + 1e-9) & (t >= -1e-9) & (t <= 1 + 1e-9))
    _, first = np.unique(np.stack([which[ok], np.rint(s[ok] * 1e6), np.rint(t[ok] * 1e6)]), axis=1, return_index=True)
    ok = ok[first]
    return which[ok], image(s[ok], t[ok])[:, 2] / ray[ok, 2]


def ways(which: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ray, in, out) from hits with the faces of one element: in order, in pairs. Hits on an edge that two faces share count
    once; an odd last one (a graze) opens nothing."""
    order = np.lexsort((at, which))
    which, at = which[order], at[order]
    new = np.ones(len(at), bool)
    new[1:] = (which[1:] != which[:-1]) | (at[1:] - at[:-1] > 1e-9)
    which, at = which[new], at[new]
    place = np.arange(len(which)) - np.searchsorted(which, which)
    k = np.flatnonzero((place % 2 == 0) & (np.append(which[1:], -1) == which))
    return which[k], at[k], at[k + 1]


def element_rays(ctrl: np.ndarray, cam: dict) -> tuple[np.ndarray, ...]:
    """i, j, in, out of one camera's rays through an element, ctrl [r + 1] * 3 + [3] in the camera frame. Its Bernstein coefficients
    bound the pixel rectangle."""
    none = (np.zeros(0, np.int64),) * 2 + (np.zeros(0),) * 2
    n, ell, w, h = cam["n"], cam["ell"], cam["w"], cam["h"]
    box = bernstein(ctrl).reshape(-1, 3)
    lo, hi = box.min(0), box.max(0)
    z0, z1 = max(lo[2], n), min(hi[2], cam["far"])
    if z0 > z1:
        return none
    ends = []
    for k, size in ((0, w), (1, h)):
        a, b = lo[k] / (z1 if lo[k] >= 0 else z0), hi[k] / (z0 if hi[k] >= 0 else z1)
        ends.append(np.arange(max(0, int(np.ceil((size - 1) / 2 + a * n / ell))), min(size - 1, int(np.floor((size - 1) / 2 + b * n / ell))) + 1))
    i, j = (g.ravel() for g in np.meshgrid(*ends, indexing="ij"))
    if not len(i):
        return none
    rays = np.stack([(i - (w - 1) / 2) * ell, (j - (h - 1) / 2) * ell, np.full(len(i), n)], 1)
    meet = bilinear_hits if ctrl.shape[0] == 2 else newton_hits
    hits = [meet(np.take(ctrl, side, axis=axis), rays) for axis in range(3) for side in (0, -1)]
    ray, near, far = ways(*(np.concatenate(x) for x in zip(*hits)))
    near, far = np.maximum(near, 1.0), np.minimum(far, cam["far"] / n)
    keep = near < far
    return i[ray[keep]], j[ray[keep]], near[keep], far[keep]


def restricted(ctrl: np.ndarray, low: np.ndarray, edge: float) -> np.ndarray:
    """The map of the subcube at ``low``, at its own Lobatto nodes; exact, as degrees do not change."""
    r = ctrl.shape[0] - 1
    n = np.array(lobatto(r)) * edge
    for axis in range(3):
        ctrl = np.moveaxis(np.tensordot(basis(r, low[axis] + n), ctrl, axes=(1, axis)), 0, axis)
    return ctrl


_RAYS = "inst int, i long, j long, z_in double, z_out double, tree int, level int, key long, beta double, gamma double, stretch double"


def render(leaves: DataFrame, trees: DataFrame, cams: list, top: int, r: int) -> DataFrame:
    """Segments of all rays through all elements ``leaves`` (tree, level, key; constant beta and gamma in each) on ``trees`` of degree r: inst,
    i, j, pix, z_in, z_out, a, b, tree, level, key. No exchange but what the join with the trees takes; Spark sends them to every task where they are few."""
    import pyarrow as pa

    low = [(coordinate(F.col("key"), a, top) / float(1 << top)).alias(f"l{a}") for a in range(3)]
    x = leaves.select(F.col("tree").cast("int").alias("tree"), F.col("level").cast("int").alias("level"), "key", "beta", "gamma", *low)
    x = x.join(camera_trees(trees, cams), "tree")

    def run(batches):
        for b in batches:
            get = {n: b.column(k) for k, n in enumerate(b.schema.names)}
            ctrl = np.array(get["ctrl"].flatten().flatten(), float).reshape(-1, *[r + 1] * 3, 3)
            rows = {n: get[n].to_pylist() for n in ("inst", "w", "h", "n", "ell", "far", "tree", "level", "key", "beta", "gamma", "l0", "l1", "l2")}
            out: list[list] = [[] for _ in range(6)]
            for k in range(b.num_rows):
                cam = {n: rows[n][k] for n in ("w", "h", "n", "ell", "far")}
                part = restricted(ctrl[k], np.array([rows[f"l{a}"][k] for a in range(3)]), 2.0 ** -rows["level"][k])
                i, j, near, far = element_rays(part, cam)
                long = np.sqrt(((i - (cam["w"] - 1) / 2) * cam["ell"]) ** 2 + ((j - (cam["h"] - 1) / 2) * cam["ell"]) ** 2 + cam["n"] ** 2)
                for held, v in zip(out, (np.full(len(i), k), i, j, near, far, long)):
                    held.append(v)
            row, i, j, near, far, long = (np.concatenate(v) if v else np.zeros(0) for v in out)
            take = pa.array(row.astype(np.int64))
            same = lambda n: get[n].take(take)  # noqa: B023, E731
            yield pa.RecordBatch.from_arrays([same("inst"), pa.array(i.astype(np.int64)), pa.array(j.astype(np.int64)), pa.array(near), pa.array(far), same("tree"), same("level"), same("key"), same("beta"), same("gamma"), pa.array(long)], names=[c.split()[0] for c in _RAYS.split(", ")])

    x = x.select(*x.columns[:5], "l0", "l1", "l2", "ctrl", "inst", "w", "h", "n", "ell", "far").mapInArrow(run, _RAYS)
    s = algebra.seg_const(F.col("beta"), F.col("gamma"), F.col("stretch") * (F.col("z_out") - F.col("z_in")))
    return x.select("inst", "i", "j", morton2(F.col("i"), F.col("j")).alias("pix"), "z_in", "z_out", s["a"].alias("a"), s["b"].alias("b"), "tree", "level", "key")
