"""Further methods as queries: general segments, subsampling, bases and faces, ancestors, owners, candidates, image nodes and
lists. Adds to ``queries.QUERIES`` and ``queries.SQL``."""

from __future__ import annotations

from pyspark.sql import functions as F

from .experiments import _CAMS, _CULLED, _N, _TREES, _U, _nation_trees, _vsql
from .functions import algebra as A
from .functions import geometry as G
from .functions import sfc
from .functions.patches import mapped
from .operators import fold, forest, imagetree, metrics, quadrature
from .plans import pipeline, scenes, spheres, surface
from .queries import _FULL, _LEAVES, _LIN, _PID, _PIX, _RAYS, _SPH, L4, L5, TOP, _cells, _leaves, _linear, _pixels, _q, _r, _rays, _scene, _spheres, _t

# --- segments ---


@_q(f"select event_id, round(exp(-(b0 * h + b1 * h * h / 2)), 8) as a, round(g1, 8) as b from {_LIN}")
def q_seg_general(spark, d):
    """Linear absorption, whose integral is known, and a given emission."""
    s = A.seg_general(F.col("b0") * F.col("h") + F.col("b1") * F.col("h") * F.col("h") / 2, F.col("g1"))
    return _linear(spark, d).select("event_id", _r(s["a"], 8).alias("a"), _r(s["b"], 8).alias("b"))


@_q(f"select {L4}, 'ab' as given, round(exp(-l_quantity / 50), 6) as a, round(l_discount, 6) as b from lineitem union all select {L4}, 'ai', round(exp(-l_quantity / 50), 6), round(l_tax * (1 - exp(-l_quantity / 50)), 6) from lineitem")
def q_segments_given(spark, d):
    """Both forms in which an application may give its segments."""
    x = _t(spark, d, "lineitem")
    two = [(n, A.segments(x, F.exp(-F.col("l_quantity") / 50), **{k: F.col(c)})) for n, k, c in (("ab", "b", "l_discount"), ("ai", "i", "l_tax"))]
    rows = [y.select(*L5[:4], F.lit(n).alias("given"), _r("a").alias("a"), _r("b").alias("b")) for n, y in two]
    return rows[0].unionByName(rows[1])


_SUB = f"""with p as (select event_id, h / 8 as dx, k, b0 + b1 * (k + 0.5) * h / 8 as be, g0 + g1 * (k + 0.5) * h / 8 as ga from {_LIN}, range(8) r(k)),
  f as (select *, exp(-coalesce(sum(be * dx) over (partition by event_id order by k desc rows between unbounded preceding and 1 preceding), 0)) as t from p)"""


@_q(_SUB + " select event_id, round(exp(-sum(be * dx)), 8) as a, round(sum(t * ga / be * (1 - exp(-be * dx))), 8) as b from f group by event_id")
def q_subsample(spark, d):
    """Variable media as eight constant pieces."""
    be, ga = (lambda x: F.col("b0") + F.col("b1") * x), (lambda x: F.col("g0") + F.col("g1") * x)
    s = quadrature.subsample(be, ga, F.lit(0.0), F.col("h"), 8)
    return _linear(spark, d).withColumn("s", s).select("event_id", _r("s.a", 8).alias("a"), _r("s.b", 8).alias("b"))


@_q(_SUB.replace("with p as", "with g as (select event_id, h, (1 - a1 + a2) / (1 + a1 + a2) as a, (h * (s0 + s1) / 2 + h * h * (p0 * s1 - p1 * s0) * sqrt(3) / 12) / (1 + a1 + a2) as b from (select *, h * (p0 + p1) / 4 as a1, h * h * p0 * p1 / 12 as a2 from (select *, b0 + b1 * h * (0.5 - sqrt(3) / 6) as p0, b0 + b1 * h * (0.5 + sqrt(3) / 6) as p1, g0 + g1 * h * (0.5 - sqrt(3) / 6) as s0, g0 + g1 * h * (0.5 + sqrt(3) / 6) as s1 from " + _LIN + "))), p as") + " select event_id, round(-ln(a) / h, 6) as beta, round(-ln(a) / h * b / (1 - a), 6) as gamma from g")
def q_effective_coeffs(spark, d):
    """The constant medium that acts like a variable one."""
    be, ga = (lambda x: F.col("b0") + F.col("b1") * x), (lambda x: F.col("g0") + F.col("g1") * x)
    c = quadrature.effective_coefficients("gauss", be, ga, F.lit(0.0), F.col("h"))
    return _linear(spark, d).withColumn("c", c).select("event_id", _r("c.beta").alias("beta"), _r("c.gamma").alias("gamma"))


@_q(f"with recursive p as (select *, row_number() over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_shipdate) as n, count(*) over (partition by l_orderkey) as m from {_RAYS}), f as (select l_orderkey, n, a, b from p where n = m union all select p.l_orderkey, p.n, p.a * f.a, p.a * f.b + p.b from p join f on p.l_orderkey = f.l_orderkey and p.n = f.n - 1) select l_orderkey, round(a, 6) as a, round(b, 6) as b from f where n = 1")
def q_fold_streamable(spark, d):
    """Folds of the halves of each ray, each sorted, merged: the parts may come from anywhere."""
    x = _rays(spark, d)
    halves = [imagetree.lists(x.filter(F.col("l_linenumber") % 2 == k), ["l_orderkey"], L5[1:]) for k in (0, 1)]
    m = imagetree.merge_lists(*halves, ["l_orderkey"])
    s = F.aggregate("s", A.seg_identity(), lambda acc, e: A.seg_combine(acc, e))
    return m.withColumn("f", s).select("l_orderkey", _r("f.a").alias("a"), _r("f.b").alias("b"))


# --- bases, maps, faces ---


_NODES = {1: ["0.0", "1.0"], 2: ["0.0", "0.5", "1.0"], 3: ["0.0", "(0.5 - sqrt(5) / 10)", "(0.5 + sqrt(5) / 10)", "1.0"], 4: ["0.0", "(0.5 - sqrt(21) / 14)", "0.5", "(0.5 + sqrt(21) / 14)", "1.0"]}


def _basis(nodes: list[str]) -> str:
    """The basis functions of some nodes at t as columns v0, v1, .. in SQL."""
    return ", ".join(" * ".join(f"(t - {n}) / ({m} - {n})" for n in nodes if n != m) + f" as v{i}" for i, m in enumerate(nodes))


@_q(" union all ".join(f"select o_orderkey, {r}::int as r, round({' + '.join(f'v{i}' for i in range(r + 1))}, 8) as total, round({' + '.join(f'v{i} * {n}' for i, n in enumerate(nodes))}, 8) as place, round({' + '.join(f'v{i} * v{i}' for i in range(r + 1))}, 6) as squares from (select o_orderkey, {_basis(nodes)} from (select o_orderkey, o_totalprice / 500000 as t from orders))" for r, nodes in _NODES.items()))
def q_lagrange_unity(spark, d):
    """Basis functions at Gauss-Lobatto nodes, at a place for each order (its price in the range): they sum to 1 and give the place back."""
    x, out = _t(spark, d, "orders").select("o_orderkey", (F.col("o_totalprice") / 500000).alias("t")), None
    for r in (1, 2, 3, 4):
        n = G.lobatto(r)
        y = G.held(x, **{f"v{i}": v for i, v in enumerate(G.lagrange_columns(n, F.col("t")))})
        v = [F.col(f"v{i}") for i in range(r + 1)]
        dot = lambda w: sum((a * b for a, b in zip(v[1:], w[1:])), v[0] * w[0])  # noqa: B023, E731
        y = y.select("o_orderkey", F.lit(r).alias("r"), _r(dot([F.lit(1.0)] * (r + 1)), 8).alias("total"), _r(dot([F.lit(a) for a in n]), 8).alias("place"), _r(dot(v), 6).alias("squares"))
        out = y if out is None else out.unionByName(y)
    return out


def _cubes(spark, d):
    """One trilinear cell a nation: the bilinear tree of its grid cell and the same a unit deeper, moved by another hash."""
    x = _nation_trees(spark, d)
    for i, j in ((0, 0), (1, 0), (0, 1), (1, 1)):
        v = (F.floor(F.col("tree") / 5) + j) * 6 + F.col("tree") % 5 + i
        x = x.withColumn(f"q{i}{j}", F.array(*[F.element_at(f"p{i}{j}", a + 1) + (1.0 if a == 2 else 0.0) + 0.2 * scenes.uniform01(v, 21 + a) for a in range(3)]))
    # ctrl[i][j][k], first axis first
    corner = lambda i, j, k: F.col(f"{'pq'[k]}{i}{j}")
    return x.select("tree", F.array(*[corner(i, j, k) for i in (0, 1) for j in (0, 1) for k in (0, 1)]).alias("ctrl"))


def _deep(i, j):
    u = lambda s: f"0.2 * ((((gy + {j}) * 6 + gx + {i}) * 2654435761 + {s} * 40503) % 4294967296) / 4294967296.0"
    return f"x{i}{j} + {u(21)} as X{i}{j}_, y{i}{j} + {u(22)} as Y{i}{j}_, z{i}{j} + 1.0 + {u(23)} as Z{i}{j}_"


_CORNERS = ((0, 0), (1, 0), (0, 1), (1, 1))
_CUBES = f"(select *, {', '.join(_deep(i, j) for i, j in _CORNERS)} from (select tree, gx, gy, {', '.join(_vsql(i, j) for i, j in _CORNERS)} from (select n_nationkey as tree, (n_nationkey % 5)::bigint as gx, (n_nationkey // 5)::bigint as gy from nation)))"
_TRI = lambda c: "(1 - u) * (" + " + ".join(f"{'s' if i else '(1 - s)'} * {'t' if j else '(1 - t)'} * {c}{i}{j}" for i, j in _CORNERS) + ") + u * (" + " + ".join(f"{'s' if i else '(1 - s)'} * {'t' if j else '(1 - t)'} * {c.upper()}{i}{j}_" for i, j in _CORNERS) + ")"


@_q(f"select c_custkey, {', '.join(f'round({_TRI(c)}, 6) as {c}' for c in 'xyz')} from (select c_custkey, c_nationkey, {_U('c_custkey', 1)} as s, {_U('c_custkey', 2)} as t, {_U('c_custkey', 3)} as u from customer) join {_CUBES} on tree = c_nationkey")
def q_map_volume(spark, d):
    """Customers as points of their nation's cell in space, by the map that takes any degree."""
    c = _t(spark, d, "customer").select("c_custkey", F.col("c_nationkey").cast("int").alias("tree"), F.array(*[scenes.uniform01(F.col("c_custkey"), k) for k in (1, 2, 3)]).alias("at"))
    x = mapped(c.join(_cubes(spark, d), "tree"), 1, 3)
    return x.select("c_custkey", *[_r(F.element_at("point", a + 1)).alias(n) for a, n in enumerate("xyz")])


@_q(f"select tree, side, round(case side when 0 then {' + '.join(f'z{i}{j}' for i, j in _CORNERS)} else {' + '.join(f'Z{i}{j}_' for i, j in _CORNERS)} end / 4, 6) as z from {_CUBES}, range(2) r(side)")
def q_face_restriction(spark, d):
    """Mean depth of the control points of each cell's near and far face: a face has a subset of them."""
    c = _cubes(spark, d)
    rows = [c.select("tree", F.lit(side).cast("long").alias("side"), G.face_columns("ctrl", 1, 3, 2, side).alias("f")) for side in (0, 1)]
    return rows[0].unionByName(rows[1]).select("tree", "side", _r(F.aggregate("f", F.lit(0.0), lambda acc, p: acc + F.element_at(p, 3)) / 4).alias("z"))


# --- trees ---


@_q(_FULL.replace(", kid as", ", kid_ as", 1).split(", kid_ as")[0] + " select level, p from anc")
def q_ancestors(spark, d):
    return forest.ancestors(_leaves(spark, d), TOP).select(F.col("level").cast("bigint").alias("level"), "p")


@_q(_FULL + " select level - 1 as level, p >> 3 as parent, count(*) as children, count(*) = 8 as family from full_ where level > 0 group by 1, 2")
def q_families(spark, d):
    x = forest.complete(_leaves(spark, d), TOP).filter("level > 0").withColumn("parent", F.call_function("shiftright", F.col("key"), F.expr(f"cast(3 * ({TOP} + 1 - level) as int)")))
    return x.groupBy((F.col("level") - 1).cast("bigint").alias("level"), "parent").agg(F.count("*").alias("children")).withColumn("family", F.col("children") == 8)


@_q(_FULL + f""" select level, p << (3 * ({TOP} - level))::int as key from full_ where level >= 3
  union all select level + 1, (p * 8 + c.c) << (3 * ({TOP} - 1 - level))::int from full_, (select unnest(range(0, 8)) as c) c where level < 3""")
def q_refine(spark, d):
    full = forest.complete(_leaves(spark, d), TOP).select("tree", F.col("level").cast("int").alias("level"), "key")
    return forest.refine(full, F.col("level") < 3, TOP).select(F.col("level").cast("bigint").alias("level"), "key")


_XYZ = lambda k: ", ".join(f"({' + '.join(f'((({k} >> {3 * i + a}) & 1) << {i})' for i in range(TOP))})::bigint as {c}" for a, c in enumerate("xyz"))


@_q(_FULL + f""", own as (select level, p, {_XYZ('p')} from full_),
  nb as (select distinct level, x + i.i as x, y + j.j as y, z + k.k as z from own, range(-1, 2) i(i), range(-1, 2) j(j), range(-1, 2) k(k)
    where level >= 2 and x + i.i between 0 and (1 << level::int) - 1 and y + j.j between 0 and (1 << level::int) - 1 and z + k.k between 0 and (1 << level::int) - 1),
  up as (select distinct a.level, x >> (nb.level - a.level)::int as x, y >> (nb.level - a.level)::int as y, z >> (nb.level - a.level)::int as z from nb, (select unnest(range(0, 11)) as level) a where a.level <= nb.level - 2)
  select own.level, own.p << (3 * ({TOP} - own.level))::int as key from own join up using (level, x, y, z)""")
def q_balance_defects(spark, d):
    """Leaves two or more levels coarser than a neighbour."""
    full = forest.complete(_leaves(spark, d), TOP)
    return forest.unbalanced(full, TOP).select(F.col("level").cast("bigint").alias("level"), "key")


@_q(_PID + ", m as (select pid, min(key) as first from own group by pid) select p.vec_id, m.pid from p asof join m on p.key >= m.first")
def q_owner(spark, d):
    """The owner of each point, from markers alone: an as-of join."""
    m = forest.markers(forest.with_owner(_leaves(spark, d), "n", 8))
    return forest.owner_of(_cells(spark, d), m, TOP).select("vec_id", "pid")


@_q(f"""with c as (select x.x + 8 * y.x + 64 * z.x as cell, x.x / 8.0 as x0, y.x / 8.0 as y0, z.x / 8.0 as z0 from range(8) x(x), range(8) y(x), range(8) z(x))
  select x0, y0, z0, count(*) as spheres, min(p_partkey) as first from c, {_SPH} where power(greatest(x0 - cx, cx - x0 - 0.125, 0), 2) + power(greatest(y0 - cy, cy - y0 - 0.125, 0), 2) + power(greatest(z0 - cz, cz - z0 - 0.125, 0), 2) <= power(r * 1.05, 2) group by 1, 2, 3""")
def q_sphere_candidates(spark, d):
    """All parts' balls that meet each element of level 3, found by descent."""
    s = _spheres(spark, d).select(F.col("p_partkey").alias("sid"), "cx", "cy", "cz", "r")
    x = pipeline.boxes(spheres.spheres_of_leaves(forest.uniform(spark, 1, 3, 3), s, 0.05, 3), 3)
    return x.filter(F.size("near") > 0).select("x0", "y0", "z0", F.size("near").cast("long").alias("spheres"), F.col("near")[0]["sid"].alias("first"))


_MEET = "power(greatest({x} * {e} - cx, cx - ({x} + 1) * {e}, 0), 2) + power(greatest({y} * {e} - cy, cy - ({y} + 1) * {e}, 0), 2) + power(greatest({z} * {e} - cz, cz - ({z} + 1) * {e}, 0), 2) <= power(r * 1.05, 2)"


@_q(f"""with recursive n as (select 0 as level, 0::bigint as x, 0::bigint as y, 0::bigint as z, p_partkey, cx, cy, cz, r from {_SPH} where {_MEET.format(x='0', y='0', z='0', e='1.0')}
    union all select n.level + 1, 2 * n.x + i.i, 2 * n.y + j.j, 2 * n.z + k.k, p_partkey, cx, cy, cz, r from n, range(2) i(i), range(2) j(j), range(2) k(k) where n.level < 3 and {_MEET.format(x='(2 * n.x + i.i)', y='(2 * n.y + j.j)', z='(2 * n.z + k.k)', e='power(2.0, -n.level - 1)')})
  select k.level, case when k.level = 0 then (select count(*) from part) else 8 * (select count(*) from n p where p.level = k.level - 1) end as checked, count(*) as needed, (select count(*) from part) * power(8, k.level)::bigint as all_pairs from n k group by k.level""")
def q_pair_checks(spark, d):
    """Sphere and element pairs that the descent checks at each level, those that meet, and all that there are."""
    s = _spheres(spark, d).select(F.col("p_partkey").alias("sid"), "cx", "cy", "cz", "r")
    return spheres.pair_checks(s, 3, 0.05)


_POIS = "(select *, unnest(range(0, 12)) as k from (select p_partkey, " + _U("p_partkey", 4) + " as u from part))"


@_q(f"""with e as (select (0.1 - 0.001) / ln(100.0) as e), m as (select power(4.0, -3) / e as m from e),
  c as (select p_partkey, u, k, sum(exp(-m) * power(m, k) / gamma(k + 1)) over (partition by p_partkey order by k) as f from {_POIS}, m)
  select p_partkey as u_id, min(k)::int as n from c where f >= u group by p_partkey""")
def q_spheres_poisson(spark, d):
    """Counts of spheres in elements of level 3, by the library's inverse distribution."""
    mean = 4.0**-3 / scenes.expected_section()
    return _t(spark, d, "part").select(F.col("p_partkey").alias("u_id"), scenes.poisson(scenes.uniform01(F.col("p_partkey"), 4), mean).cast("int").alias("n"))


_WHOLE = """select 'embedding' as kind, vec_id as id, round(embedding[1]::double + 0.5, 6) as cx, round(sqrt(0.001 * power(100.0, {u}) / pi()), 8) as r from embeddings
  union all select 'document', doc_id, round({x}, 6), round(sqrt(0.001 * power(100.0, least(1.0, ln(1 + coalesce(length(text), 0)) / ln(200001))) / pi()), 8) from documents"""


@_q(_WHOLE.format(u=_U("vec_id", 4), x=_U("doc_id", 1)))
def q_spheres_tables(spark, d):
    """Spheres from embeddings (centre by the first numbers) and from documents (section by the length of the whole text)."""
    e = _t(spark, d, "embeddings").select(F.lit("embedding").alias("kind"), F.col("vec_id").alias("id"), _r(F.element_at("embedding", 1).cast("double") + 0.5).alias("cx"), scenes.uniform01(F.col("vec_id"), 4).alias("u"))
    long = F.least(F.lit(1.0), F.ln(1 + F.coalesce(F.length("text"), F.lit(0))) / F.ln(F.lit(200001)))
    t = _t(spark, d, "documents").select(F.lit("document").alias("kind"), F.col("doc_id").alias("id"), _r(scenes.uniform01(F.col("doc_id"), 1)).alias("cx"), long.alias("u"))
    return e.unionByName(t).select("kind", "id", "cx", _r(F.sqrt(scenes.section(F.col("u")) / F.pi()), 8).alias("r"))


_LI = "(select l_discount, l_tax, " + ", ".join(f"least(63, greatest(0, floor({v} * 64)))::bigint as {c}" for c, v in zip("xyz", ("(l_quantity - 1) / 49", "(l_extendedprice - 900) / 104100", "date_diff('day', timestamp '1995-01-01', l_shipdate) / 2500.0"))) + " from lineitem)"
_LIKEY = f"(select *, {' + '.join(f'(((x >> {i}) & 1) << {3 * i}) + (((y >> {i}) & 1) << {3 * i + 1}) + (((z >> {i}) & 1) << {3 * i + 2})' for i in range(6))} as key from {_LI})"


@_q(f"""with p as materialized {_LIKEY}, u as (select l.level, key >> (3 * (6 - l.level))::int as p, count(*) as n from p, (select unnest(range(0, 7)) as level) l group by 1, 2),
  leaf as (select u.* from u left join u o on o.level = u.level - 1 and o.p = u.p >> 3 where (u.n <= 32 or u.level = 6) and (u.level = 0 or o.n > 32))
  select level, leaf.p << (3 * (6 - level))::int as key, count(*) as n, round(avg(l_discount) * 20, 6) as beta, round(avg(l_tax) * 20, 6) as gamma from p join leaf on p.key >> (3 * (6 - leaf.level))::int = leaf.p group by 1, 2""")
def q_insitu_payload(spark, d):
    """A forest of at most 32 line items a leaf, and what its leaves hold: count, mean discount and tax as coefficients."""
    at = [(F.col("l_quantity") - 1) / 49, (F.col("l_extendedprice") - 900) / 104100, F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-01").cast("date")) / 2500.0]
    p = _t(spark, d, "lineitem").select(F.lit(0).alias("tree"), sfc.morton3(*[sfc.cell(v, 6) for v in at]).alias("key"), "l_discount", "l_tax")
    x = forest.locate(p, forest.from_points(p, 32, 6), 6).groupBy(F.col("leaf_level").cast("bigint").alias("level"), F.col("leaf_key").alias("key"))
    return x.agg(F.count("*").alias("n"), _r(F.avg("l_discount") * 20).alias("beta"), _r(F.avg("l_tax") * 20).alias("gamma"))


@_q(f"select r_regionkey as inst, tree, round(x00 - 2.5 - 0.2 * r_regionkey, 6) as cx, round(y00 - 2.5, 6) as cy, round(z00 + 2.0, 6) as cz from {_TREES} cross join region")
def q_to_camera(spark, d):
    """A control point of every tree in every camera's frame, from the step that turns trees before elements meet them."""
    cams = [pipeline.Camera(int(r.r_regionkey), (2.5 + 0.2 * r.r_regionkey, 2.5, -2.0), (0.0, 0.0, 1.0), (1.0, 0.0, 0.0), (0.0, 1.0, 0.0), 8, 8, 0.1) for r in _t(spark, d, "region").collect()]
    x = surface.frames(_nation_trees(spark, d), cams)
    p = lambda a: F.element_at("p00", a)
    return x.select(F.col("inst").cast("long").alias("inst"), "tree", _r(p(1)).alias("cx"), _r(p(2)).alias("cy"), _r(p(3)).alias("cz"))


@_q("with t as (select r_regionkey as inst, (r_regionkey + 1) * 100 as w, w.w as writers, t from region, (select unnest([1, 4, 12]) as w) w, (select unnest(range(0, 12)) as t) t) select inst, w, writers, min(t)::int as t from t where ceil(w / power(2, t)) * ceil(75.0 / power(2, t)) <= writers group by 1, 2, 3")
def q_tile_choice(spark, d):
    """The least tile for each camera's image and number of writers."""
    rows = [(int(r.r_regionkey), (int(r.r_regionkey) + 1) * 100, w, imagetree.tile_exponent([((int(r.r_regionkey) + 1) * 100, 75)], w)) for r in _t(spark, d, "region").collect() for w in (1, 4, 12)]
    return spark.createDataFrame(rows, "inst long, w long, writers int, t int")


# --- images ---


@_q("""with q as (select least(31, floor((l_quantity - 1) / 49 * 32))::bigint as x, least(31, floor((l_extendedprice - 900) / 104100 * 32))::bigint as y, count(*) as items from lineitem group by 1, 2),
  u as (select l.level::int as level, x >> (5 - l.level::int) as x, y >> (5 - l.level::int) as y, sum(items) as items from q, range(6) l(level) group by 1, 2, 3),
  n as (select level, x * (1 << (10 - level)) as x, y * (1 << (10 - level)) as y, 1 << (10 - level) as e, items from u)
  select level, case when x >= 800 or y >= 600 then 'out' when x + e <= 800 and y + e <= 600 then 'in' else 'split' end as state, count(*) as nodes, sum(items)::bigint as items from n group by 1, 2""")
def q_image_nodes(spark, d):
    """Nodes of an image's tree that hold line items: inside it, outside, or cut by its border; and the line items in them."""
    depth = imagetree.depth(800, 600)
    at = [sfc.cell(v, 5) for v in ((F.col("l_quantity") - 1) / 49, (F.col("l_extendedprice") - 900) / 104100)]
    x = _t(spark, d, "lineitem").select(at[0].alias("x"), at[1].alias("y")).groupBy("x", "y").agg(F.count("*").alias("items"))
    x = x.withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(5))))
    x = x.groupBy("level", *[F.expr(f"shiftright({c}, 5 - level)").alias(c) for c in "xy"]).agg(F.sum("items").alias("items"))
    e = F.expr(f"shiftleft(1, {depth} - level)")
    x = x.select("level", imagetree.node_state(F.col("x") * e, F.col("y") * e, e, 800, 600).alias("state"), "items")
    return x.groupBy("level", "state").agg(F.count("*").alias("nodes"), F.sum("items").alias("items"))


@_q(f"select pix >> 8 as tile, count(distinct pix) as pixels, count(*) as segments, sum(l_orderkey)::double as keys, round(sum(a), 4) as a, round(sum(b), 4) as b from {_PIX} group by 1")
def q_imagetree_union(spark, d):
    """Rectangle trees of the even and the odd line numbers of each tile, united: all pixels and all segments again."""
    x = _pixels(spark, d).select(F.lit(0).alias("inst"), imagetree.tile_of(F.col("pix"), 4).alias("tile"), "i", "j", F.col("l_orderkey").cast("double").alias("z"), "a", "b", (F.col("l_linenumber") % 2).alias("half"))
    parts = [imagetree.tree_images(x.filter(F.col("half") == k), ["inst", "tile"], 4) for k in (0, 1)]
    u = imagetree.union_images(*parts, ["inst", "tile"], 4)
    return u.select("tile", "pixels", "segments", F.aggregate("z", F.lit(0.0), lambda s, v: s + v).alias("keys"), *[_r(F.aggregate(c, F.lit(0.0), lambda s, v: s + v), 4).alias(c) for c in "ab"])


@_q(f"""with g as (select size, cell, count(*) as n from (select z.size, least(z.size - 1, floor((l_quantity - 1) / 49 * z.size))::bigint * 4096 + least(z.size - 1, floor((l_extendedprice - 900) / 104100 * z.size))::bigint as cell from lineitem, (select unnest([16, 64, 256]) as size) z) group by 1, 2)
  select size::int as size, count(*) as pixels, sum(n)::bigint as segments, (12 * count(*) + 4 + 24 * sum(n))::bigint as bytes from g group by size""")
def q_pack_size(spark, d):
    """Bytes of packed images of three sizes from the same segments: 24 a segment and 12 a pixel that is not empty."""
    size = F.col("size")
    x = _t(spark, d, "lineitem").select("l_orderkey", "l_quantity", "l_extendedprice", "l_discount", F.explode(F.array(*[F.lit(n) for n in (16, 64, 256)])).alias("size"))
    at = [F.least(size - 1, F.floor(v * size)).cast("long") for v in ((F.col("l_quantity") - 1) / 49, (F.col("l_extendedprice") - 900) / 104100)]
    x = x.select("size", sfc.morton2(*at).alias("pix"), F.col("l_orderkey").cast("double").alias("z"), F.exp(-F.col("l_quantity") / 50).alias("a"), F.col("l_discount").alias("b"))
    return imagetree.packed_image(imagetree.pack_blocks(x, ["size"]), ["size"])


@_q(_CULLED + f""", m as (select leaf.level, leaf.p << (3 * ({TOP} - leaf.level))::int as key, avg(label) / 3.0 + 0.5 as beta from p join embeddings using (vec_id) join leaf on p.key >> (3 * ({TOP} - leaf.level))::int = leaf.p group by 1, 2)
  select v.inst, v.level, v.key, round(npix * greatest(1.0, power(2.0, ceil(log2(greatest(e * beta / 0.02, 1e-12))))), 4) as work from v join m using (level, key)""")
def q_weight_correction(spark, d):
    """Pixels of visible leaves, corrected for the pieces that adaptive integration at c = 0.02 is expected to cut."""
    v = pipeline.visible_leaves(_scene(spark, d), _CAMS, TOP)
    work = metrics.weighted_pixels(F.col("npix"), F.expr("power(2.0D, -level)"), F.col("beta"), 0.02)
    return v.select("inst", F.col("level").cast("bigint").alias("level"), "key", _r(work, 4).alias("work"))
