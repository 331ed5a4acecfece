"""Ray segments as affine maps I -> A * I + B, as Column expressions over struct<a,b>.

The nearer operand stands left. A lies in (0, 1] for media that absorb, above 1 for
amplifying ones, and is 0 for opaque surfaces, which have no inverse."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _c(x) -> Column:
    return x if isinstance(x, Column) else F.lit(x)


def seg(a, b) -> Column:
    return F.struct(_c(a).cast("double").alias("a"), _c(b).cast("double").alias("b"))


def seg_identity() -> Column:
    return seg(1.0, 0.0)


def seg_const(beta, gamma, dx) -> Column:
    """Constant absorption beta and emission gamma over length dx; beta may be 0 or negative."""
    beta, gamma, dx = _c(beta), _c(gamma), _c(dx)
    return seg(F.exp(-beta * dx), F.when(beta == 0, gamma * dx).otherwise(-gamma * F.expm1(-beta * dx) / F.nullif(beta, F.lit(0.0))))


def seg_transparent(emitted) -> Column:
    return seg(1.0, emitted)


def seg_combine(near: Column, far: Column) -> Column:
    """Light passes ``far`` first: A = An * Af, B = An * Bf + Bn."""
    return seg(near["a"] * far["a"], near["a"] * far["b"] + near["b"])


def seg_inverse(s: Column) -> Column:
    """Null for opaque segments."""
    return F.when(s["a"] != 0, seg(1 / F.nullif(s["a"], F.lit(0.0)), -s["b"] / F.nullif(s["a"], F.lit(0.0))))


def emission_from_intensity(a, i) -> Column:
    """B of a segment with absorption A whose equilibrium intensity is i."""
    return _c(i) * (1 - _c(a))


def seg_split(s: Column, part) -> Column:
    """The piece of relative length ``part`` of a homogeneous segment."""
    part = _c(part)
    a = F.pow(s["a"], part)
    share = F.when(s["a"] == 1, part).otherwise((1 - a) / F.nullif(1 - s["a"], F.lit(0.0)))
    return F.when(s["a"] == 0, s).otherwise(seg(a, s["b"] * share))


def coefficients(s: Column, dx) -> Column:
    """struct<beta,gamma> of the constant medium that acts like ``s`` over dx."""
    beta = -F.ln(s["a"]) / _c(dx)
    gamma = F.when(s["a"] == 1, s["b"] / _c(dx)).otherwise(beta * s["b"] / F.nullif(1 - s["a"], F.lit(0.0)))
    return F.struct(beta.alias("beta"), gamma.alias("gamma"))


def seg_average(s: Column, t: Column, mode: str = "printed") -> Column:
    """Mean of two segments over one interval. ``printed``: geometric mean of A, arithmetic of B. ``limit``:
    mean coefficients, which is what alternating ever thinner pieces of both tends to."""
    if mode == "printed":
        return seg(F.sqrt(s["a"] * t["a"]), (s["b"] + t["b"]) / 2)
    c, d = coefficients(s, 1.0), coefficients(t, 1.0)
    return seg_const((c["beta"] + d["beta"]) / 2, (c["gamma"] + d["gamma"]) / 2, 1.0)


def seg_average_n(a, b) -> tuple[Column, Column]:
    """Aggregates (A, B) of the k-way mean; any opaque member makes A 0."""
    a = _c(a)
    return F.when(F.min(a) == 0, 0.0).otherwise(F.exp(F.avg(F.when(a > 0, F.ln(a))))), F.avg(b)


def combine_coefficients(beta_near, gamma_near, dx_near, beta_far, gamma_far, dx_far) -> Column:
    """struct<beta,gamma> of two constant media in a row, over their whole length."""
    s = seg_combine(seg_const(beta_near, gamma_near, dx_near), seg_const(beta_far, gamma_far, dx_far))
    return coefficients(s, _c(dx_near) + _c(dx_far))


def seg_reverse(beta, gamma, dx) -> Column:
    """The segment with its bounds swapped, which is the inverse of the segment."""
    return seg_const(beta, gamma, -_c(dx))


def seg_surface(a, i) -> Column:
    """A surface without thickness, with prescribed transmission and intensity."""
    return seg(a, emission_from_intensity(a, i))


def seg_opaque(i) -> Column:
    return seg(0.0, i)


def seg_surface_angle(a, i, cosine) -> Column:
    """A surface that is crossed at an angle: the path grows with 1 / |cos|; grazing is opaque."""
    c = F.abs(_c(cosine))
    t = F.when(c == 0, 0.0).otherwise(F.pow(_c(a), 1 / F.nullif(c, F.lit(0.0))))
    return seg(t, emission_from_intensity(t, i))


def apply_background(s: Column, ib) -> Column:
    return s["a"] * _c(ib) + s["b"]


def to_rgb(i) -> Column:
    """0 to 255, clamped."""
    return F.least(F.greatest(F.floor(_c(i) * 255 + 0.5), F.lit(0)), F.lit(255)).cast("int")


def to_alpha(s: Column) -> Column:
    return 1 - s["a"]


def seg_general(beta_integral, gamma_weighted) -> Column:
    """From the integral of the absorption and that of the emission as dimmed on its way to the near end."""
    return seg(F.exp(-_c(beta_integral)), gamma_weighted)


def segments(df: DataFrame, a: Column, b: Column | None = None, i: Column | None = None) -> DataFrame:
    """What an application gives, as segment columns a and b: transmission with emission ``b``, or with the intensity ``i`` that the
    medium tends to. Columns a and b of ``df`` are replaced; null coefficients give null segments."""
    if (b is None) == (i is None):
        raise ValueError("give either b or i")
    s = seg(a, b if b is not None else emission_from_intensity(a, i))
    return df.withColumn("_s", s).withColumn("a", F.col("_s.a")).withColumn("b", F.col("_s.b")).drop("_s")
