"""The rendering pipeline over leaves: descend, cull, complete, cut by pixels and transfer, render, condense, tiles, composite.

Trees are axis-aligned cubes here (leaf boxes in world coordinates; ``elements`` has curved ones), cameras look along one axis with
a frame (o, v, t, u). Every phase is a DataFrame step and can be left out; results agree to roundoff."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import algebra, geometry
from ..functions.geometry import held
from ..functions.sfc import coordinate, morton2
from ..operators import forest
from ..operators.fold import composite
from ..operators.forest import cut
from ..operators.metrics import weighted_pixels


@dataclass(frozen=True)
class Camera:
    """o: origin, v: view vector (its length is the distance n of the image plane), t and u: unit axes."""

    inst: int
    o: tuple[float, float, float]
    v: tuple[float, float, float]
    t: tuple[float, float, float]
    u: tuple[float, float, float]
    w: int
    h: int
    ell: float
    far: float = 100.0

    @property
    def n(self) -> float:
        return sum(x * x for x in self.v) ** 0.5


def front_cameras(count: int, size: int = 64) -> list[Camera]:
    """Cameras in front of the unit cube, each a little to the side of the one before."""
    return [Camera(i, (0.5 + 0.2 * i, 0.5 - 0.1 * i, -2.0), (0.0, 0.0, 1.0), (1.0, 0.0, 0.0), (0.0, 1.0, 0.0), size, size, 1.0 / size) for i in range(count)]


def boxes(leaves: DataFrame, top: int) -> DataFrame:
    """Leaves with their world boxes x0..z1 in the unit cube."""
    edge = F.expr(f"power(2.0, -level)")
    for a, c in enumerate("xyz"):
        leaves = leaves.withColumn(f"{c}0", coordinate(F.col("key"), a, top) / float(1 << top))
    for c in "xyz":
        leaves = leaves.withColumn(f"{c}1", F.col(f"{c}0") + edge)
    return leaves


def camera_of(cams: list[Camera], inst: Column) -> Column:
    """The numbers of a row's camera as a struct, out of a literal map."""
    vec = lambda v, n: [F.lit(float(x)).alias(f"{n}{k}") for k, x in enumerate(v)]
    pairs = []
    for c in cams:
        numbers = [*vec(c.o, "o"), *vec(c.t, "t"), *vec(c.u, "u"), *vec([x / c.n for x in c.v], "e"), *vec(c.v, "v"), F.lit(float(c.n)).alias("n"), F.lit(float(c.ell)).alias("ell"), F.lit(float(c.far)).alias("far"), F.lit(c.w).alias("w"), F.lit(c.h).alias("h")]
        pairs += [F.lit(c.inst), F.struct(*numbers)]
    return F.create_map(*pairs)[inst]


def _bound(axis: str, low: bool, cam: str = "_cam") -> Column:
    """Least or greatest value over the box x0..z1 of the camera coordinate along ``axis``: the sign of each component says
    which side of the box counts."""
    out = F.lit(0.0)
    for k, c in enumerate("xyz"):
        e = F.col(f"{cam}.{axis}{k}")
        side = F.when((e > 0) == low, F.col(f"{c}0")).otherwise(F.col(f"{c}1"))
        out = out + F.when(e != 0, e * (side - F.col(f"{cam}.o{k}"))).otherwise(0.0)
    return out


def seen(nodes: DataFrame, cams: list[Camera], clip: bool = True) -> DataFrame:
    """Rows with a box x0..z1 and inst: those that the camera sees, with the pixel rectangle i0..i1, j0..j1 and npix. Dropped are boxes before or
    behind the clipping planes, outside the image, or hit by no pixel centre; without ``clip`` nothing is dropped, and the rectangle
    is the image."""
    x = held(nodes, _cam=camera_of(cams, F.col("inst")))
    if not clip:
        x = x.withColumns({"i0": F.lit(0).cast("long"), "i1": (F.col("_cam.w") - 1).cast("long"), "j0": F.lit(0).cast("long"), "j1": (F.col("_cam.h") - 1).cast("long")})
    else:
        x = held(x, **{f"_{side}{k}": _bound(axis, side == "lo") for k, axis in enumerate("tue") for side in ("lo", "hi")})
        x = held(x, _z0=F.greatest("_lo2", "_cam.n"), _z1=F.least("_hi2", "_cam.far")).filter("_z0 < _z1")
        for k, (a, b, size) in enumerate((("i0", "i1", "w"), ("j0", "j1", "h"))):
            ends = geometry.pixel_bounds(F.col(f"_lo{k}"), F.col(f"_hi{k}"), F.col("_z0"), F.col("_z1"), F.col(f"_cam.{size}"), F.col("_cam.n"), F.col("_cam.ell"))
            x = held(x, **{a: ends[0], b: ends[1]}).filter(F.col(a) <= F.col(b))
    x = x.withColumn("npix", (F.col("i1") - F.col("i0") + 1) * (F.col("j1") - F.col("j0") + 1))
    return x.drop(*[c for c in x.columns if c.startswith("_")])


def frontier(leaves: DataFrame, cams: list[Camera], top: int, depth: int = 4, step: int = 2) -> DataFrame:
    """Nodes (tree, p) at level ``depth`` that some camera sees, with ``insts``: the cameras that see it. Top-down from the roots, ``step`` levels at a
    time; a node is tried only for the cameras that see its ancestor. Nodes come from nothing but the tree numbers, so there
    are at most trees * 8 ** depth, whatever the number of leaves."""
    x = leaves.select("tree").distinct().select("tree", F.lit(0).cast("long").alias("p"), F.array(*[F.lit(c.inst) for c in cams]).alias("insts"))
    level = 0
    while level < depth:
        go = min(step, depth - level)
        level += go
        x = x.withColumn("p", F.explode(F.sequence(F.shiftleft("p", 3 * go), F.shiftleft("p", 3 * go) + (8**go - 1)))).withColumn("inst", F.explode("insts"))
        box = boxes(x.select("tree", "p", "inst", F.lit(level).alias("level"), F.shiftleft("p", 3 * (top - level)).alias("key")), top)
        x = seen(box, cams).groupBy("tree", "p").agg(F.array_sort(F.collect_list("inst")).alias("insts"))
    return x


def descend(leaves: DataFrame, cams: list[Camera], top: int, depth: int = 4) -> DataFrame:
    """Leaves below the nodes of ``frontier``, each with ``insts``, the cameras that its ancestor is seen by; leaves above that level keep all cameras."""
    nodes = frontier(leaves, cams, top, depth).select(F.col("tree").alias("_t"), F.col("p").alias("_p"), "insts")
    fine = leaves.filter(F.col("level") >= depth).join(nodes, (F.col("tree") == F.col("_t")) & (F.shiftright("key", 3 * (top - depth)) == F.col("_p"))).drop("_t", "_p")
    return fine.unionByName(leaves.filter(F.col("level") < depth).withColumn("insts", F.array(*[F.lit(c.inst) for c in cams])))


def cull(leaves: DataFrame, cams: list[Camera], top: int, clip: bool = True) -> DataFrame:
    """Visible leaves by instance: inst, pixel rectangle i0..i1, j0..j1, npix. One pass for all cameras, or for those
    that ``insts`` names."""
    listed = F.col("insts") if "insts" in leaves.columns else F.array(*[F.lit(c.inst) for c in cams])
    return seen(boxes(leaves.withColumn("inst", F.explode(listed)).drop("insts"), top), cams, clip)


def visible_leaves(leaves: DataFrame, cams: list[Camera], top: int, depth: int | None = None) -> DataFrame:
    """``cull``, after ``descend`` to ``depth`` if that is given, checkpointed: few rows against the forest."""
    leaves = cut(leaves)
    return cut(cull(leaves if depth is None else descend(leaves, cams, top, depth), cams, top))


def prepartition(visible: DataFrame, parts: int, top: int, c: float | None = None) -> DataFrame:
    """``visible`` with pid, moved so that partition pid holds the leaves of owner pid in curve order. Owners are an even cut of the visible
    leaves, completed to whole trees, by pixels summed over instances; with ``c`` pixels count by the pieces that adaptive integration at c
    cuts a ray in (column beta)."""
    work = F.col("npix") if c is None else F.ceil(weighted_pixels(F.col("npix"), F.expr("power(2.0D, -level)"), F.col("beta"), c))
    w = visible.groupBy("tree", "level", "key").agg(F.sum(work).cast("long").alias("work"))
    whole = forest.complete(w, top).join(w.drop("level"), ["tree", "key"], "left").withColumn("work", F.when(F.col("filled"), 0).otherwise(F.col("work")).cast("long"))
    owners = forest.with_owner(whole, "work", parts).filter("not filled").select("tree", "key", "pid")
    return visible.join(owners, ["tree", "key"]).repartitionById(parts, "pid").sortWithinPartitions("tree", "key")


def render(visible: DataFrame, cams: list[Camera], tile: int | None = None) -> DataFrame:
    """Segments of all rays through all visible leaves (constant beta, gamma in each): inst, i, j, pix, z_in, z_out, a, b,
    tree, level, key. z is the ray parameter. No exchange. With ``tile`` also the image tile, so that segments can go to it at once."""
    x = visible.withColumn("i", F.explode(F.sequence("i0", "i1"))).withColumn("j", F.explode(F.sequence("j0", "j1")))
    x = held(x, _cam=camera_of(cams, F.col("inst")))
    k = lambda n: F.col(f"_cam.{n}")
    p, q = (F.col("i") - (k("w") - 1) / 2) * k("ell"), (F.col("j") - (k("h") - 1) / 2) * k("ell")
    x = held(x, **{f"_r{a}": k(f"v{a}") + p * k(f"t{a}") + q * k(f"u{a}") for a in range(3)})
    r = [F.col(f"_r{a}") for a in range(3)]
    near, far = geometry.hit_box([F.col(f"{c}0") for c in "xyz"], [F.col(f"{c}1") for c in "xyz"], [k(f"o{a}") for a in range(3)], r)
    x = held(x, z_in=F.greatest(near, F.lit(1.0)), z_out=F.least(far, k("far") / k("n"))).filter("z_in < z_out")
    s = algebra.seg_const(F.col("beta"), F.col("gamma"), F.sqrt(r[0] * r[0] + r[1] * r[1] + r[2] * r[2]) * (F.col("z_out") - F.col("z_in")))
    x = x.select("inst", "i", "j", morton2(F.col("i"), F.col("j")).alias("pix"), "z_in", "z_out", s["a"].alias("a"), s["b"].alias("b"), "tree", "level", "key")
    return x if tile is None else x.withColumn("tile", F.shiftright("pix", 2 * tile))


def _cycle(x: DataFrame, level: int, top: int, d: int, together: list[str]) -> DataFrame:
    """One fold inside the nodes of ``level``; ``together`` are columns by which rows already lie together."""
    ends = {"z0": F.min("z_in"), "z1": F.max("z_out"), "m": F.sum("n")}
    x = x.withColumn("p", F.shiftright("key", d * (top - level)))
    x = composite(x, ["inst", "tree", *together, "pix", "p"], ["z_in", "key"], extra=ends)
    return x.select("inst", *together, "pix", "tree", F.lit(level).alias("level"), F.shiftleft("p", d * (top - level)).alias("key"), F.col("z0").alias("z_in"), F.col("z1").alias("z_out"), "a", "b", F.col("m").alias("n"))


def condense(segments: DataFrame, top: int, cycles: int, d: int = 3, near: int = 4, min_elements: int | None = None, most_imbalance: float | None = None) -> DataFrame:
    """Folds segments of a ray inside ever coarser nodes. A node is convex, so what a ray crosses in it is one run,
    and the fold loses nothing but roundoff.

    One exchange brings the children of the coarsest nodes together, by square of 2 ** ``near`` pixels (a ray's fold needs no other ray), and all
    cycles run inside it. With stop rules each cycle is checkpointed and counted, and the cycles end when fewer than ``min_elements``
    elements are left, or when the square with most segments has more than ``most_imbalance`` times the mean."""
    x = segments.withColumn("n", F.lit(1).cast("long"))
    ruled = min_elements is not None or most_imbalance is not None
    if not ruled:
        coarse = max(0, top - cycles)
        x = x.withColumn("_whole", F.shiftright("key", d * (top - coarse))).withColumn("_square", F.shiftright("pix", 2 * near)).repartition("inst", "tree", "_whole", "_square")
        for c in range(min(cycles, top)):
            x = _cycle(x, top - 1 - c, top, d, ["_whole", "_square"])
        return x.drop("_whole", "_square")
    for c in range(min(cycles, top)):
        x = cut(_cycle(x, top - 1 - c, top, d, []))
        if min_elements is not None and x.select("tree", "level", "key").distinct().count() < min_elements:
            break
        if most_imbalance is not None:
            by = x.groupBy("inst", F.shiftright("pix", 2 * near).alias("s")).agg(F.count("*").alias("n"))
            if (by.agg(F.max("n") / F.avg("n")).first()[0] or 0) > most_imbalance:
                break
    return x


def image(segments: DataFrame, tile: int = 4) -> DataFrame:
    """One segment per (inst, tile, pix)."""
    x = segments if "tile" in segments.columns else segments.withColumn("tile", F.shiftright("pix", 2 * tile))
    return composite(x, ["inst", "tile", "pix"], ["z_in", "tree", "key"])


def checkerboard(i, j, cell: int = 8):
    return F.when((F.floor(i / cell) + F.floor(j / cell)) % 2 == 0, 0.25).otherwise(0.75)


def render_pipeline(leaves: DataFrame, cams: list[Camera], top: int, cycles: int = 2, tile: int = 4, depth: int | None = None, parts: int | None = None, c: float | None = None, clip: bool = True, min_elements: int | None = None, most_imbalance: float | None = None) -> DataFrame:
    """leaves (tree, level, key, beta, gamma) to pixel segments of all cameras in one run: inst, tile, pix, a, b, k.

    ``depth`` descends to that level before leaves are looked at; ``clip=False`` looks at every ray and leaf. ``parts`` cuts the visible leaves into so many
    owners by pixels (with ``c`` by expected work) and moves them before rendering. ``cycles`` 0 sends segments to their tiles as they are rendered;
    the stop rules are those of ``condense``. The visible leaves, few against the forest, are checkpointed: plans stay small and a lost
    executor repeats no culling."""
    v = visible_leaves(leaves, cams, top, depth) if clip else cut(cull(cut(leaves), cams, top, False))
    if parts is not None:
        v = prepartition(v, parts, top, c)
    if not cycles:
        return image(render(v, cams, tile))
    return image(condense(render(v, cams), top, cycles, min_elements=min_elements, most_imbalance=most_imbalance), tile)
