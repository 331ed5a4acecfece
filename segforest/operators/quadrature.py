"""Numerical evaluation of segments with variable coefficients.

``STEP`` has one-step rules as Column expressions (beta, gamma: functions of a place as Column), and
``seg_eval`` the adaptive recursion over whole Arrow batches with NumPy: intervals whose length times |beta|
exceeds c at a node are halved, all at once, until none is left; halves fold with the half at larger x
(nearer to the eye) on the left."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.algebra import coefficients, seg, seg_combine, seg_const, seg_identity

# Fixed tableaux of subdiagonal-explicit Runge-Kutta rules: nodes, subdiagonal, weights.
TABLEAUX = {
    "euler": ([0.0], [], [1.0]),
    "heun2": ([0.0, 1.0], [1.0], [1 / 2, 1 / 2]),
    "heun3": ([0.0, 1 / 3, 2 / 3], [1 / 3, 2 / 3], [1 / 4, 0.0, 3 / 4]),
    "rk4": ([0.0, 1 / 2, 1 / 2, 1.0], [1 / 2, 1 / 2, 1.0], [1 / 6, 1 / 3, 1 / 3, 1 / 6]),
}
_ROOT = 3**0.5


def step(method: str, beta: Callable, gamma: Callable, x, h):
    """(A, B) of one step over [x, x + h]; works on Columns and on arrays alike."""
    sqrt, exp = (F.sqrt, F.exp) if isinstance(h, Column) else (np.sqrt, np.exp)
    if method in TABLEAUX:
        nodes, sub, weights = TABLEAUX[method]
        a_sum = b_sum = 0.0
        da = db = None
        for i, c in enumerate(nodes):
            be, ga = beta(x + h * c), gamma(x + h * c)
            a = 1.0 if i == 0 else 1.0 + h * sub[i - 1] * da
            b = 0.0 if i == 0 else h * sub[i - 1] * db
            da, db = -be * a, ga - be * b
            a_sum, b_sum = a_sum + weights[i] * da, b_sum + weights[i] * db
        return 1.0 + h * a_sum, h * b_sum
    if method == "gauss":  # node 0 is the one at smaller x: with the other order B loses two orders
        p, q = x + h * (1 / 2 - _ROOT / 6), x + h * (1 / 2 + _ROOT / 6)
        b0, b1, g0, g1 = beta(p), beta(q), gamma(p), gamma(q)
        a1, a2 = h * (b0 + b1) / 4, h * h * b0 * b1 / 12
        return (1 - a1 + a2) / (1 + a1 + a2), (h * (g0 + g1) / 2 + h * h * (b0 * g1 - b1 * g0) * _ROOT / 12) / (1 + a1 + a2)
    x1, x2 = x + h / 2, x + h
    a = exp(-h * (beta(x) + 4 * beta(x1) + beta(x2)) / 6)
    if method == "simpson":
        return a, h * (a * gamma(x) + 4 * sqrt(a) * gamma(x1) + gamma(x2)) / 6
    if method == "simpson_half":  # transmittance from the midpoint by a rule of its own
        half = exp(-h / 2 * (beta(x1) + 4 * beta(x + h * 0.75) + beta(x2)) / 6)
        return a, h * (a * gamma(x) + 4 * half * gamma(x1) + gamma(x2)) / 6
    raise ValueError(method)


def subsample(beta: Callable, gamma: Callable, x, h, pieces: int) -> Column:
    """struct<a,b> over [x, x + h] from ``pieces`` equal pieces with the constant coefficients of their midpoints."""
    d = h / pieces

    def far_first(acc, k):  # the piece at larger x is nearer
        at = x + (k + 0.5) * d
        return seg_combine(seg_const(beta(at), gamma(at), d), acc)

    return F.aggregate(F.sequence(F.lit(0), F.lit(pieces - 1)), seg_identity(), far_first)


def effective_coefficients(method: str, beta: Callable, gamma: Callable, x, h) -> Column:
    """struct<beta,gamma> of the constant medium that acts over [x, x + h] as one step of ``method`` through the variable one."""
    return coefficients(seg(*step(method, beta, gamma, x, h)), h)


METHODS = (*TABLEAUX, "gauss", "simpson", "simpson_half")


def _nodes(method: str) -> list[float]:
    if method in TABLEAUX:
        return TABLEAUX[method][0]
    return [1 / 2 - _ROOT / 6, 1 / 2 + _ROOT / 6] if method == "gauss" else [0.0, 0.5, 1.0]


def seg_eval(method: str, beta: Callable, gamma: Callable, x1: np.ndarray, x2: np.ndarray, c: float = 0.5, max_depth: int = 24) -> dict[str, np.ndarray]:
    """a, b, evals, depth, capped for each interval. ``beta`` and ``gamma`` take (row numbers, places). ``evals`` counts
    all calls for a coefficient at a place: the absorption at the nodes of every interval that is tested, and both at those of
    the step that is taken.

    max_depth bounds the recursion for coefficients without a bound; ``capped`` tells where it did."""
    n = len(x1)
    seg_, lo, hi = np.arange(n), np.asarray(x1, float), np.asarray(x2, float)
    done, evals, depth, capped = [], np.zeros(n, np.int64), np.zeros(n, np.int64), np.zeros(n, bool)

    def asked(f, rows):
        def call(x):
            evals[:] += np.bincount(rows, minlength=n)
            return f(rows, x)

        return call

    nodes = _nodes(method)
    for level in range(max_depth + 1):
        h = hi - lo
        worst = np.max([np.abs(h * beta(seg_, lo + h * t)) for t in nodes], 0) if len(seg_) else h
        evals += np.bincount(seg_, minlength=n) * len(nodes)
        bad = worst > c
        if level == max_depth:
            capped[seg_[bad]] = True
            bad[:] = False
        ok = ~bad
        s, a0, h0 = seg_[ok], lo[ok], h[ok]
        a, b = step(method, asked(beta, s), asked(gamma, s), a0, h0)
        done.append((s, a0, a + 0 * h0, b + 0 * h0))
        if not bad.any():
            break
        depth[np.unique(seg_[bad])] = level + 1
        mid = (lo[bad] + hi[bad]) / 2
        seg_, lo, hi = np.tile(seg_[bad], 2), np.concatenate([lo[bad], mid]), np.concatenate([mid, hi[bad]])
    s, at, a, b = (np.concatenate(x) for x in zip(*done))
    order = np.lexsort((-at, s))  # nearer pieces have larger x
    s, a, b = s[order], a[order], b[order]
    out_a, out_b = np.ones(n), np.zeros(n)
    place = np.arange(len(s)) - np.searchsorted(s, s, "left")
    for k in range(place.max() + 1 if len(s) else 0):
        m = place == k
        out_b[s[m]] += out_a[s[m]] * b[m]
        out_a[s[m]] *= a[m]
    return {"a": out_a, "b": out_b, "evals": evals, "depth": depth, "capped": capped}


def adaptive(df, method: str, c: float, coefficients: list[str], max_depth: int = 24):
    """``df`` (id, x1, x2 and the linear coefficients beta0, beta1, gamma0, gamma1 named by ``coefficients``) with a, b,
    evals, depth by the adaptive recursion."""
    import pyarrow as pa

    def run(batches):
        for t in batches:
            get = lambda k: t.column(t.schema.get_field_index(k)).to_numpy(zero_copy_only=False).astype(float)
            b0, b1, g0, g1 = (get(k) for k in coefficients)
            r = seg_eval(method, lambda s, x: b0[s] + b1[s] * x, lambda s, x: g0[s] + g1[s] * x, get("x1"), get("x2"), c, max_depth)
            yield pa.RecordBatch.from_arrays([t.column(t.schema.get_field_index("id")), *(pa.array(r[k]) for k in ("a", "b", "evals", "depth"))], names=["id", "a", "b", "evals", "depth"])

    return df.select(F.col("id").cast("long").alias("id"), "x1", "x2", *coefficients).mapInArrow(run, "id long, a double, b double, evals long, depth long")
