"""The pipeline's phases and switches, and curved elements, as queries. Adds to ``queries.QUERIES`` and ``queries.SQL``."""

from __future__ import annotations

from pyspark.sql import functions as F

from . import queries as base
from .experiments import _CAMS, _CELL, _FN, _FRACTAL, _N, _OWN, _TREES, _cell, _culled, _fractal_cams, _image, _nation_trees, _plane_points, _visible
from .functions import algebra as A
from .functions.sfc import morton2
from .functions.sfc import morton2
from .methods import _CUBES, _cubes
from .operators import fold, forest
from .plans import elements, pipeline, surface
from .queries import TOP, _leaves, _q, _r, _scene, _t

base.SQL["q_render_pipeline"] = _image(64)
_q(_CELL + " select count(distinct (inst, pix)) as pixels, 0 as differ from cell")(base.q_condense_lossless)


@_q(_culled(_N, "select 2 as level, range << 24 as key from range(64)", "with") + " select key >> 24 as p, string_agg(inst, ',' order by inst) as insts from v group by key")
def q_descend(spark, d):
    """Nodes of level 2 that cameras see, with the list of these cameras."""
    x = pipeline.frontier(_leaves(spark, d), _CAMS, TOP, 2, 1)
    return x.select("p", F.array_join("insts", ",").alias("insts"))


_SWITCHES = {
    "descend": {"depth": 3},
    "transfer": {"parts": 4},
    "work": {"parts": 3, "c": 0.5},
    "direct": {"cycles": 0},
    "all_rays": {"cycles": 0, "clip": False},
    "stop": {"depth": 2, "parts": 4, "cycles": 8, "min_elements": 20},
}


@_q(f"select w.switch, i.* from ({_image(_N)}) i, (select unnest({list(_SWITCHES)}) as switch) w")
def q_prepartition(spark, d):
    """The image with each switch of the pipeline: none changes a pixel. ``all_rays`` is the baseline of every ray and every leaf."""
    scene, out = forest.cut(_scene(spark, d)), None
    for name, how in _SWITCHES.items():
        x = pipeline.render_pipeline(scene, _CAMS, TOP, **how).select(F.lit(name).alias("switch"), "inst", "tile", "pix", _r("a").alias("a"), _r("b").alias("b"))
        out = x if out is None else out.unionByName(x)
    return out


@_q(_OWN + " select o.pid, count(*) as leaves, sum(v.npix)::bigint as pixels, true as together from v join o using (key) group by 1")
def q_transfer(spark, d):
    """Leaves and pixels by owner after the move, and whether an owner's leaves are in the partition of its number."""
    x = pipeline.prepartition(_visible(spark, d), 8, TOP).withColumn("at", F.spark_partition_id())
    return x.groupBy("pid").agg(F.count("*").alias("leaves"), F.sum("npix").alias("pixels"), F.bool_and(F.col("at") == F.col("pid")).alias("together"))


@_q(_CELL + """, n as (select c.c::int as cycles, count(distinct (inst, pix, key >> (3 * c.c)::int)) as segments, count(distinct key >> (3 * c.c)::int) as elements from cell, range(1, 9) c(c) group by 1)
  select * from n where cycles = coalesce((select min(cycles) from n where elements < 100), 8)""")
def q_condense_stop(spark, d):
    """Where the cycles end when fewer than 100 elements are to be left."""
    raw = pipeline.render(_visible(spark, d).withColumn("beta", F.lit(1.0)).withColumn("gamma", F.lit(1.0)), _CAMS)
    x = pipeline.condense(raw, TOP, 8, min_elements=100)
    return x.agg((F.lit(TOP) - F.max("level")).alias("cycles"), F.count("*").alias("segments"), F.countDistinct("tree", "level", "key").alias("elements"))


# --- curved trees ---

_W, _ELL = 24, 0.03
_EYES = [pipeline.Camera(i, (2.5 + 0.2 * i, 2.5, -2.0), (0.0, 0.0, 1.0), (1.0, 0.0, 0.0), (0.0, 1.0, 0.0), _W, _W, _ELL) for i in (0, 1)]


_EYE = [(e.o, e.ell) for e in _EYES]


def _patch_hits(faces: str, eyes=_EYE, size: int = _W) -> str:
    """CTEs from faces (tree, face, pax..pdz: corners at (0, 0), (1, 0), (0, 1), (1, 1)) to hit (inst, i, j, tree, face, s, t, alpha, rx, ry)."""
    m = (size - 1) / 2
    per = lambda values: "case inst " + " ".join(f"when {k} then {v!r}::double" for k, v in enumerate(values)) + " end"
    shift = ", ".join(f"p{p}{c} - {per([o[a] for o, _ in eyes])} as p{p}{c}" for p in "abcd" for a, c in enumerate("xyz"))
    line = lambda v, k: f"(p{v}{k} - p{v}z * r{k})"
    coef = ", ".join(f"{line('a', k)} as a{n}, {line('b', k)} - {line('a', k)} as b{n}, {line('c', k)} - {line('a', k)} as c{n}, {line('d', k)} - {line('b', k)} - {line('c', k)} + {line('a', k)} as d{n}" for n, k in ((1, "x"), (2, "y")))
    return f"""faces as ({faces}), moved as (select inst::int as inst, tree, face, {shift} from faces, range(2) n(inst)),
  cast_ as (select moved.*, i, j, (i - {m}) * {per([e for _, e in eyes])} as rx, (j - {m}) * {per([e for _, e in eyes])} as ry from moved, range({size}) a(i), range({size}) b(j)),
  coef as (select *, {coef} from cast_),
  quad as (select *, b2 * d1 - d2 * b1 as q2, a2 * d1 - d2 * a1 + b2 * c1 - c2 * b1 as q1, a2 * c1 - c2 * a1 as q0 from coef),
  root as (select *, abs(q2) <= 1e-12 * (abs(q1) + abs(q0)) as flat, case when q1 * q1 - 4 * q2 * q0 >= 0 then -0.5 * (q1 + case when q1 < 0 then -1 else 1 end * sqrt(q1 * q1 - 4 * q2 * q0)) end as m from quad),
  at_s as (select *, case when flat then -q0 / nullif(q1, 0) else m / nullif(q2, 0) end as s from root union all select *, q0 / nullif(m, 0) from root where not flat),
  at_t as (select *, case when abs(c1 + d1 * s) >= abs(c2 + d2 * s) then -(a1 + b1 * s) / nullif(c1 + d1 * s, 0) else -(a2 + b2 * s) / nullif(c2 + d2 * s, 0) end as t from at_s where s between 0 and 1),
  hit as (select *, (1 - s) * (1 - t) * paz + s * (1 - t) * pbz + (1 - s) * t * pcz + s * t * pdz as alpha from at_t where t between 0 and 1)"""


def _face(n: int, corners: str) -> str:
    """A face from four corner names out of p00..p11 (near) and q00..q11 (deep)."""
    cols = ", ".join(f"{c}{k[1:]} as p{p}{c}" if k[0] == "p" else f"{c}{k[1:]}_ as p{p}{c}" for p, k in zip("abcd", corners.split()) for c in "xyz")
    return f"select tree, {n} as face, {cols} from cubes"


_FACES = " union all ".join(_face(n, c) for n, c in enumerate(("p00 p10 p01 p11", "q00 q10 q01 q11", "p00 p01 q00 q01", "p10 p11 q10 q11", "p00 p10 q00 q10", "p01 p11 q01 q11")))
_WAYS = f"""with cubes as materialized {_CUBES}, {_patch_hits(_FACES)},
  uniq as (select inst, i, j, tree, alpha, rx, ry from (select *, lag(alpha) over (partition by inst, i, j, tree order by alpha) as p from hit) where p is null or alpha - p > 1e-9),
  num as (select *, row_number() over (partition by inst, i, j, tree order by alpha) as k, lead(alpha) over (partition by inst, i, j, tree order by alpha) as z_out from uniq),
  way as (select inst, i, j, tree, alpha as z_in, z_out, rx, ry from num where k % 2 = 1 and z_out is not null)"""


def _roots(spark, d):
    return _cubes(spark, d).select("tree", F.lit(0).alias("level"), F.lit(0).cast("long").alias("key"), F.lit(0.2).alias("beta"), F.lit(0.3).alias("gamma"))


@_q(_WAYS + " select inst, i, j, tree, round(z_in, 5) as z_in, round(z_out, 5) as z_out from way")
def q_element_segments(spark, d):
    """Ways of all rays of two cameras through 25 cells with bent faces: hits with all faces, in order, in pairs."""
    x = elements.render(_roots(spark, d), _cubes(spark, d), _EYES, TOP, 1)
    return x.select("inst", "i", "j", "tree", _r("z_in", 5).alias("z_in"), _r("z_out", 5).alias("z_out"))


@_q(_WAYS + " select inst, i, j, tree, round(z_in, 5) as z_in, round(z_out, 5) as z_out from way")
def q_curved_segments(spark, d):
    """The same cells as maps of degree 2, met by Newton's rule."""
    grid = [0.0, 0.5, 1.0]
    at = lambda s, t, u, a: sum(((s if i else 1 - s) * (t if j else 1 - t) * (u if k else 1 - u) * F.element_at(F.element_at("ctrl", 4 * i + 2 * j + k + 1), a + 1) for i in (0, 1) for j in (0, 1) for k in (0, 1)), F.lit(0.0))
    fine = _cubes(spark, d).select("tree", F.array(*[F.array(*[at(s, t, u, a) for a in range(3)]) for s in grid for t in grid for u in grid]).alias("ctrl"))
    x = elements.render(_roots(spark, d), fine, _EYES, TOP, 2)
    return x.select("inst", "i", "j", "tree", _r("z_in", 5).alias("z_in"), _r("z_out", 5).alias("z_out"))


@_q(_WAYS + """, t as (select inst, i, j, sum(z_out - z_in) as z, sum((z_out - z_in) * sqrt(rx * rx + ry * ry + 1)) as len from way group by 1, 2, 3)
  select inst, i, j, round(z, 5) as z, round(exp(-0.2 * len), 5) as a, round(1.5 * (1 - exp(-0.2 * len)), 5) as b from t""")
def q_render_trees25(spark, d):
    """Pixels of 25 trees of eight curved elements each, condensed and folded: their way is that through the whole trees."""
    leaves = forest.children(_roots(spark, d), TOP).withColumn("beta", F.lit(0.2)).withColumn("gamma", F.lit(0.3))
    x = elements.render(leaves, _cubes(spark, d), _EYES, TOP, 1)
    img = fold.composite(x, ["inst", "i", "j"], ["z_in", "tree", "key"], extra={"z": F.sum(F.col("z_out") - F.col("z_in"))})
    return img.select("inst", "i", "j", _r("z", 5).alias("z"), _r("a", 5).alias("a"), _r("b", 5).alias("b"))


_SHEET = "select tree, 0 as face, " + ", ".join(f"{c}{k} as p{p}{c}" for p, k in zip("abcd", ("00", "10", "01", "11")) for c in "xyz") + f" from {_TREES}"


@_q(f"""with {_patch_hits(_SHEET)}, n as (select *, {', '.join(f'pb{c} - pa{c} + (pd{c} - pb{c} - pc{c} + pa{c}) * t as u{c}, pc{c} - pa{c} + (pd{c} - pb{c} - pc{c} + pa{c}) * s as w{c}' for c in 'xyz')} from hit),
  m as (select *, uy * wz - uz * wy as nx, uz * wx - ux * wz as ny, ux * wy - uy * wx as nz from n),
  a as (select *, abs(nx * rx + ny * ry + nz) / sqrt((nx * nx + ny * ny + nz * nz) * (rx * rx + ry * ry + 1)) as cosine from m)
  select inst, i, j, tree, round(alpha, 5) as z, round(cosine, 5) as cosine, round(power(0.5, 1 / cosine), 5) as a, round(0.8 * (1 - power(0.5, 1 / cosine)), 5) as b from a""")
def q_surface_cosine(spark, d):
    """Rays through 25 bent sheets at an angle: place, cosine, and the segment that the angle makes of a half-transparent sheet."""
    grid = spark.range(_W * _W).select((F.col("id") % _W).alias("i"), F.floor(F.col("id") / _W).alias("j"))
    x = surface.frames(_nation_trees(spark, d), _EYES).join(grid)
    ray = [(F.col("i") - (_W - 1) / 2) * _ELL, (F.col("j") - (_W - 1) / 2) * _ELL, F.lit(1.0)]
    y = surface.cosine(surface.patch_hits(x, ray), ray)
    y = y.withColumn("s_", A.seg_surface_angle(F.lit(0.5), F.lit(0.8), F.col("cosine")))
    return y.select("inst", "i", "j", "tree", _r("alpha", 5).alias("z"), _r("cosine", 5).alias("cosine"), _r("s_.a", 5).alias("a"), _r("s_.b", 5).alias("b"))


# --- the fractal's image, and growth ---

_HEX = " union all ".join(f"select {t} as tree, 0 as face, " + ", ".join(f"{v}::double as p{p}{c}" for p, q in zip("abcd", corners) for c, v in zip("xyz", (*q, 5.0))) for t, *corners in surface.HEXAGON)


@_q(f"""{_FRACTAL}, leaf as (select tree, level, x, y, (64 >> level) as e from kid where not exists (select 1 from split t where t.tree = kid.tree and t.level = kid.level and t.x = kid.x and t.y = kid.y)),
  four as (select leaf.*, a.n as n00, b.n as n10, c.n as n01, d.n as n11 from leaf join st a on a.tree = leaf.tree and a.i = x * e and a.j = y * e join st b on b.tree = leaf.tree and b.i = (x + 1) * e and b.j = y * e join st c on c.tree = leaf.tree and c.i = x * e and c.j = (y + 1) * e join st d on d.tree = leaf.tree and d.i = (x + 1) * e and d.j = (y + 1) * e),
  {_patch_hits(_HEX, [(c.o, c.ell) for c in _fractal_cams()], _FN)},
  own as materialized (select inst, i, j, hit.tree, hit.s * (1 << level) - x as s, hit.t * (1 << level) - y as t, n00, n10, n01, n11 from hit join four on four.tree = hit.tree and least(floor(hit.s * (1 << level)), (1 << level) - 1) = x and least(floor(hit.t * (1 << level)), (1 << level) - 1) = y),
  shade as (select inst, i, j, (1 - s) * (1 - t) * n00 + s * (1 - t) * n10 + (1 - s) * t * n01 + s * t * n11 as v from own),
  seg as (select inst, i, j, case when inst = 0 then 0.0 when v < 27 then 1.0 when v < 30 then 0.3 else 0.6 end as a, case when inst = 0 then 0.5 + 0.5 * v / 30 when v >= 27 and v < 30 then 0.7 else 0.0 end as b from shade)
  select g.inst::int as inst, g.i, g.j, round(coalesce(a, 1) * sky + coalesce(b, 0), 4) as red, round(coalesce(a, 1) * sky + coalesce(b, 0), 4) as green, round(coalesce(a, 1) * sky + coalesce(b, 0) * (1 - g.inst), 4) as blue
  from (select inst, i, j, case when inst = 0 then case when (i // 8 + j // 8) % 2 = 0 then 0.25 else 0.75 end else 0.1 end as sky from range(2) a(inst), range({_FN}) b(i), range({_FN}) c(j)) g left join seg on seg.inst = g.inst and seg.i = g.i and seg.j = g.j""")
def q_fractal_image(spark, d):
    """The mesh adapted where line items lie, both instances in one run, each with a camera of its own: opaque grey to white before a checkerboard sky, and yellow just below the limit."""
    trees, cams = surface.hexagon(spark), _fractal_cams()
    m = forest.cut(surface.fractal_mesh(trees, 2, 6, points=_plane_points(spark, d)))
    s = surface.points(surface.cull(m, trees, cams, 6), {0: surface.opaque_grey(30), 1: surface.glowing(30)})
    img = pipeline.image(pipeline.condense(s, 6, 2, 2))
    grid = spark.range(2 * _FN * _FN).select(F.floor(F.col("id") / _FN**2).cast("int").alias("inst"), (F.col("id") % _FN).alias("i"), F.floor(F.col("id") % _FN**2 / _FN).alias("j"))
    x = grid.withColumn("pix", morton2(F.col("i"), F.col("j"))).join(img, ["inst", "pix"], "left")
    sky = F.when(F.col("inst") == 0, pipeline.checkerboard(F.col("i"), F.col("j"))).otherwise(0.1)
    tint = lambda k: F.when(F.col("inst") == 0, surface.TINTS[0][k]).otherwise(surface.TINTS[1][k])
    return x.select("inst", "i", "j", *[_r(F.coalesce("a", F.lit(1.0)) * sky + F.coalesce("b", F.lit(0.0)) * tint(k), 4).alias(c) for k, c in enumerate(("red", "green", "blue"))])


@_q(_cell(_N, _culled(_N, " union all ".join(f"select {n} as level, range << {3 * (TOP - n)} as key from range({8**n})" for n in (3, 4, 5)), "with", 1)) + f""", n as (select level, count(*) as segments, count(distinct (pix, key >> (3 * ({TOP} - level + 1))::int)) as condensed from cell where zo - zi > 1e-9 group by level)
  select level, power(8, level)::bigint as leaves, (select count(*) from v where v.level = n.level) as visible, segments, condensed, w.w as writers, (select min(t) from range(0, 8) t(t) where power(ceil({_N} / power(2, t)), 2) <= w.w)::int as tile from n, (select unnest([1, 4, 12]) as w) w""")
def q_scaling(spark, d):
    """Growth with the mesh and with the writers: leaves, visible leaves, segments, segments after a cycle, and the tile that so many writers take."""
    from .operators import imagetree

    out = None
    for level in (3, 4, 5):
        leaves = forest.uniform(spark, 1, level, TOP).withColumn("beta", F.lit(1.0)).withColumn("gamma", F.lit(1.0))
        v = pipeline.visible_leaves(leaves, _CAMS[:1], TOP)
        raw = forest.cut(pipeline.render(v, _CAMS[:1]).filter("z_out - z_in > 1e-9"))
        cells = raw.select("pix", F.shiftright("key", 3 * (TOP - level + 1)).alias("p")).distinct()
        row = raw.agg(F.lit(level).cast("long").alias("level"), F.lit(8**level).cast("long").alias("leaves"), F.count("*").alias("segments")).join(v.agg(F.count("*").alias("visible"))).join(cells.agg(F.count("*").alias("condensed")))
        for writers in (1, 4, 12):
            one = row.select("level", "leaves", "visible", "segments", "condensed", F.lit(writers).alias("writers"), F.lit(imagetree.tile_exponent([(_N, _N)], writers)).alias("tile"))
            out = one if out is None else out.unionByName(one)
    return out
