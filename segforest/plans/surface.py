"""The pipeline for surfaces: quadtrees on bilinear patches in space, one point hit per ray, element and sheet.

A hit is computed on the patch of the whole tree and given to the leaf whose half-open reference square
holds it, so neighbours neither share nor lose a hit. Trees are few numbers a row (four corners); they are joined by
tree number, and Spark chooses how."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import geometry
from ..functions.geometry import held
from ..functions.sfc import coordinate, morton2
from ..operators import forest
from .scenes import escape_counts

CORNERS = ("p00", "p10", "p01", "p11")

# Fixed geometry of the fractal example: a hexagon of two quadrangles in the plane, corners as p00, p10, p01, p11.
HEXAGON = [
    (0, (-2.3, -0.75), (-0.25, -1.8), (-2.3, 0.75), (-0.25, 1.8)),
    (1, (-0.25, -1.8), (1.3, -1.0), (-0.25, 1.8), (1.3, 1.0)),
]


def hexagon(spark: SparkSession, depth: float = 5.0) -> DataFrame:
    """Both trees with corners as arrays of three numbers, in a plane across the view."""
    rows = [(t, *[[x, y, depth] for x, y in c]) for t, *c in HEXAGON]
    return spark.createDataFrame(rows, "tree int, p00 array<double>, p10 array<double>, p01 array<double>, p11 array<double>")


def on_patch(s: Column, t: Column, axis: int) -> Column:
    """One coordinate of the tree's patch at (s, t)."""
    return geometry.bilinear(s, t, *[F.element_at(c, axis + 1) for c in CORNERS])


def squares(leaves: DataFrame, top: int) -> DataFrame:
    """Leaves with their reference square: s0, t0 and edge e."""
    x = leaves.withColumn("e", F.expr("power(2.0D, -level)"))
    return x.withColumn("s0", coordinate(F.col("key"), 0, top, 2) / float(1 << top)).withColumn("t0", coordinate(F.col("key"), 1, top, 2) / float(1 << top))


def corner_steps(leaves: DataFrame, trees: DataFrame, top: int, limit: int) -> DataFrame:
    """Leaves with the escape steps n00, n10, n01, n11 at their corners, for whole Arrow batches at once."""
    import numpy as np
    import pyarrow as pa

    x = squares(leaves.select("tree", "level", "key"), top).join(trees, "tree")
    ends = [(i, j) for i in (0, 1) for j in (0, 1)]
    at = [F.array(*[on_patch(F.col("s0") + F.col("e") * i, F.col("t0") + F.col("e") * j, axis) for i, j in ends]) for axis in (0, 1)]
    x = x.select("tree", F.col("level").cast("int").alias("level"), F.col("key").cast("long").alias("key"), "e", "s0", "t0", at[0].alias("_x"), at[1].alias("_y"))

    def run(batches):
        for b in batches:
            c = [np.array(b.column(k).flatten(), float).reshape(-1, 4) for k in (6, 7)]
            n = escape_counts(*c, limit)
            yield pa.RecordBatch.from_arrays([*b.columns[:6], *(pa.array(n[:, k], pa.int32()) for k in range(4))], names=[*b.schema.names[:6], *(f"n{i}{j}" for i, j in ends)])

    return x.mapInArrow(run, "tree int, level int, key long, e double, s0 double, t0 double, n00 int, n01 int, n10 int, n11 int")


def fractal_mesh(trees: DataFrame, start: int, top: int, limit: int = 30, balanced: bool = True, points: DataFrame | None = None) -> DataFrame:
    """Leaves with corner steps: a uniform mesh of level ``start``, refined to level ``top`` wherever corners differ, and
    with ``points`` (tree, key of level ``top``) only where points lie, then 2:1 balanced. Only the leaves that were just made are looked at again."""
    spark = trees.sparkSession
    fresh = forest.uniform(spark, trees.count(), start, top, 2)
    done, cells = None, None if points is None else forest.cut(points.select("tree", "key").distinct())
    for level in range(start, top + 1):
        x = corner_steps(fresh, trees, top, limit)
        split = F.lit(level < top) & ~((F.col("n00") == F.col("n10")) & (F.col("n00") == F.col("n01")) & (F.col("n00") == F.col("n11")))
        if cells is not None:
            low = 2 * (top - level)
            held = cells.select("tree", F.shiftleft(F.shiftright("key", low), low).alias("key"), F.lit(True).alias("_held")).distinct()
            x = x.join(held, ["tree", "key"], "left")
            split = split & F.col("_held").isNotNull()
        x = forest.cut(x.withColumn("_split", split))
        keep = x.filter("not _split").select("tree", "level", "key")
        done = keep if done is None else done.unionByName(keep)
        fresh = forest.children(x.filter("_split"), top, 2)
    return corner_steps(forest.balance(done, top, 2) if balanced else done, trees, top, limit)


def frames(trees: DataFrame, cams: list) -> DataFrame:
    """Trees in every camera's frame, with the camera's numbers: the one place where coordinates are turned. Rows: trees x
    cameras; elements join them by tree."""
    out = None
    for cam in cams:
        axes = (cam.t, cam.u, tuple(x / cam.n for x in cam.v))
        turn = lambda c: F.array(*[sum((F.element_at(c, a + 1) * float(e[a]) for a in range(3)), F.lit(-sum(o * y for o, y in zip(cam.o, e)))) for e in axes])  # noqa: B023, E731
        x = trees.select("tree", *[turn(c).alias(c) for c in CORNERS], *[F.lit(v).alias(k) for k, v in (("inst", cam.inst), ("w", cam.w), ("h", cam.h), ("n", float(cam.n)), ("ell", float(cam.ell)), ("far", float(cam.far)))])
        out = x if out is None else out.unionByName(x)
    return out


def cull(leaves: DataFrame, trees: DataFrame, cams: list, top: int) -> DataFrame:
    """Visible leaves by instance with their pixel rectangle. The box of the four corners holds a bilinear piece."""
    x = squares(leaves, top).join(frames(trees, cams), "tree")
    ends = [(F.col("s0") + F.col("e") * i, F.col("t0") + F.col("e") * j) for i in (0, 1) for j in (0, 1)]
    x = held(x, **{f"_c{k}": F.array(*[on_patch(s, t, k) for s, t in ends]) for k in range(3)})
    x = held(x, **{f"_{side}{k}": f(f"_c{k}") for k in range(3) for side, f in (("lo", F.array_min), ("hi", F.array_max))})
    x = held(x, _z0=F.greatest("_lo2", "n"), _z1=F.least("_hi2", "far")).filter("_z0 <= _z1")
    i = geometry.pixel_bounds(F.col("_lo0"), F.col("_hi0"), F.col("_z0"), F.col("_z1"), F.col("w"), F.col("n"), F.col("ell"))
    j = geometry.pixel_bounds(F.col("_lo1"), F.col("_hi1"), F.col("_z0"), F.col("_z1"), F.col("h"), F.col("n"), F.col("ell"))
    x = held(x, i0=i[0], i1=i[1], j0=j[0], j1=j[1]).filter("i0 <= i1 and j0 <= j1")
    return x.drop(*[c for c in x.columns if c.startswith("_")])


def patch_hits(df: DataFrame, ray: list[Column]) -> DataFrame:
    """Rows (corners in the camera frame) times their hits with a ray: alpha, s, t in [0, 1]; the quadratic of
    ``hit_bilinear_columns`` in steps that stay in generated code."""
    at = lambda c, k: F.element_at(c, k + 1)
    x = held(df, _r0=ray[0], _r1=ray[1], _r2=ray[2])
    x = held(x, **{f"_{c}{k}": at(c, k) * F.col("_r2") - at(c, 2) * F.col(f"_r{k}") for c in CORNERS for k in (0, 1)})
    p = lambda c, k: F.col(f"_{c}{k}")
    named = {f"_a{k}": p("p00", k) for k in (0, 1)} | {f"_b{k}": p("p10", k) - p("p00", k) for k in (0, 1)} | {f"_c{k}": p("p01", k) - p("p00", k) for k in (0, 1)} | {f"_d{k}": p("p11", k) - p("p10", k) - p("p01", k) + p("p00", k) for k in (0, 1)}
    x = held(x, **named)
    a, b, c, d = ([F.col(f"_{n}{k}") for k in (0, 1)] for n in "abcd")
    x = held(x, _q2=b[1] * d[0] - d[1] * b[0], _q1=a[1] * d[0] - d[1] * a[0] + b[1] * c[0] - c[1] * b[0], _q0=a[1] * c[0] - c[1] * a[0])
    q2, q1, q0, zero = F.col("_q2"), F.col("_q1"), F.col("_q0"), F.lit(0.0)
    x = held(x, _flat=F.abs(q2) <= 1e-12 * (F.abs(q1) + F.abs(q0)), _m=-0.5 * (q1 + F.when(q1 < 0, -1.0).otherwise(1.0) * F.sqrt(F.when(q1 * q1 - 4 * q2 * q0 >= 0, q1 * q1 - 4 * q2 * q0))))
    one, two = F.when(F.col("_flat"), -q0 / F.nullif(q1, zero)).otherwise(F.col("_m") / F.nullif(q2, zero)), F.when(~F.col("_flat"), q0 / F.nullif(F.col("_m"), zero))
    x = x.withColumn("s", F.explode(F.array_distinct(F.array(one, two)))).filter(F.col("s").between(0, 1))
    e = [c[k] + d[k] * F.col("s") for k in (0, 1)]
    x = held(x, t=F.when(F.abs(e[0]) >= F.abs(e[1]), -(a[0] + b[0] * F.col("s")) / F.nullif(e[0], zero)).otherwise(-(a[1] + b[1] * F.col("s")) / F.nullif(e[1], zero))).filter(F.col("t").between(0, 1))
    x = held(x, alpha=on_patch(F.col("s"), F.col("t"), 2) / F.col("_r2"))
    return x.drop(*[c for c in x.columns if c.startswith("_")])


def cosine(df: DataFrame, ray: list[Column]) -> DataFrame:
    """Hits of ``patch_hits`` with ``cosine``, |cos| of the angle between the ray and the patch's normal there."""
    at = lambda c, k: F.element_at(c, k + 1)
    bend = [at("p11", k) - at("p10", k) - at("p01", k) + at("p00", k) for k in range(3)]
    ds = [at("p10", k) - at("p00", k) + bend[k] * F.col("t") for k in range(3)]
    dt = [at("p01", k) - at("p00", k) + bend[k] * F.col("s") for k in range(3)]
    x = held(df, **{f"_s{k}": ds[k] for k in range(3)}, **{f"_t{k}": dt[k] for k in range(3)}, **{f"_r{k}": ray[k] for k in range(3)})
    c = lambda n, k: F.col(f"_{n}{k}")
    x = held(x, **{f"_n{k}": c("s", (k + 1) % 3) * c("t", (k + 2) % 3) - c("s", (k + 2) % 3) * c("t", (k + 1) % 3) for k in range(3)})
    dot = lambda m, n: c(m, 0) * c(n, 0) + c(m, 1) * c(n, 1) + c(m, 2) * c(n, 2)
    x = held(x, cosine=F.abs(dot("n", "r")) / F.nullif(F.sqrt(dot("n", "n") * dot("r", "r")), F.lit(0.0)))
    return x.drop(*[k for k in x.columns if k.startswith("_")])


def points(visible: DataFrame, shade: dict[int, Callable[[Column], tuple[Column, Column]]]) -> DataFrame:
    """Segments of all rays at their hits: inst, i, j, pix, z_in, z_out, v, a, b, tree, level, key. v is the bilinear value of
    the corner steps; ``shade`` gives (A, B) of v for each instance. No exchange."""
    x = visible.withColumn("i", F.explode(F.sequence("i0", "i1"))).withColumn("j", F.explode(F.sequence("j0", "j1")))
    y = patch_hits(x, [(F.col("i") - (F.col("w") - 1) / 2) * F.col("ell"), (F.col("j") - (F.col("h") - 1) / 2) * F.col("ell"), F.col("n")])
    end = lambda c, o: (F.col(c) >= F.col(o)) & ((F.col(c) < F.col(o) + F.col("e")) | ((F.col(o) + F.col("e") == 1) & (F.col(c) == 1)))
    y = y.filter(end("s", "s0") & end("t", "t0") & F.col("alpha").between(F.lit(1.0), F.col("far") / F.col("n")))
    s, t = (F.col("s") - F.col("s0")) / F.col("e"), (F.col("t") - F.col("t0")) / F.col("e")
    y = held(y, v=geometry.bilinear(s, t, F.col("n00"), F.col("n10"), F.col("n01"), F.col("n11")))
    a = b = F.lit(None).cast("double")
    for inst, f in shade.items():
        fa, fb = f(F.col("v"))
        a, b = F.when(F.col("inst") == inst, fa).otherwise(a), F.when(F.col("inst") == inst, fb).otherwise(b)
    return y.select("inst", "i", "j", morton2(F.col("i"), F.col("j")).alias("pix"), F.col("alpha").alias("z_in"), F.col("alpha").alias("z_out"), "v", a.cast("double").alias("a"), b.cast("double").alias("b"), "tree", "level", "key")


def opaque_grey(limit: int) -> Callable[[Column], tuple[Column, Column]]:
    """Opaque, from grey to white with the value."""
    return lambda v: (F.lit(0.0), 0.5 + 0.5 * v / limit)


#: Colours of the light of both instances of the fractal example: white, and yellow.
TINTS = {0: (1.0, 1.0, 1.0), 1: (1.0, 1.0, 0.0)}


def glowing(limit: int) -> Callable[[Column], tuple[Column, Column]]:
    """Transparent, with light only just below the limit."""
    return lambda v: (F.when(v < 0.9 * limit, 1.0).when(v < limit, 0.3).otherwise(0.6), F.when((v >= 0.9 * limit) & (v < limit), 0.7).otherwise(0.0))
