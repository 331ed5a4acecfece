"""Further methods, baselines, measures and workloads as queries: routing, culling, surfaces, spheres, balances,
channels, trees in space. Adds to ``queries.QUERIES`` and ``queries.SQL``."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .functions import algebra as A
from .functions import geometry as G
from .functions import sfc
from .functions.patches import hit_bilinear_columns
from .operators import fold, forest, metrics, quadrature, routing
from .plans import pipeline, scenes, spheres, surface
from .queries import _CONST, _LEAVES, _MEDIA, _OVER, _PAIR, _PIX, _RAYS, _SPH, L4, L5, TOP, _events, _lagged, _leaves, _media, _pixels, _q, _r, _rays, _scene, _spheres, _t

# --- segments and folds ---


@_q(f"select {L4}, round(gamma * dx, 6) as b, 1.0::double as a from {_MEDIA % '0.0'}")
def q_seg_transparent(spark, d):
    s = A.seg_transparent(F.col("gamma") * F.col("dx"))
    return _media(spark, d).select(*L5[:4], _r(s["b"]).alias("b"), s["a"].alias("a"))


@_q(f"select {L4}, round(a, 6) as a, round(l_i * (1 - a), 6) as b from (select *, b as l_i from {_RAYS})")
def q_emission_from_intensity(spark, d):
    return _rays(spark, d).select(*L5[:4], _r("a").alias("a"), _r(A.emission_from_intensity(F.col("a"), F.col("b"))).alias("b"))


@_q(f"select {L4}, round(a, 6) as a, round(b, 6) as b from {_PAIR} where pa is not null")
def q_peel_near(spark, d):
    """Each segment again, from its fold with the one before by peeling that off."""
    s = fold.peel(A.seg_combine(F.col("p1"), F.col("s")), F.col("p1"))
    return _lagged(spark, d).filter("p1 is not null").select(*L5[:4], _r(s["a"]).alias("a"), _r(s["b"]).alias("b"))


@_q(f"select {L4}, round(pa, 6) as a, round(pb, 6) as b from {_PAIR} where pa is not null")
def q_peel_far(spark, d):
    s = fold.peel(A.seg_combine(F.col("p1"), F.col("s")), F.col("s"), "far")
    return _lagged(spark, d).filter("p1 is not null").select(*L5[:4], _r(s["a"]).alias("a"), _r(s["b"]).alias("b"))


_EVA = "exp(-value / 500)"
_CHSQL = ", ".join(f"round(exp(sum(ln(a_{c}))), 6) as a_{c}, round(sum(t_{c} * b_{c}), 6) as b_{c}" for c in ("even", "odd"))
_CHT = ", ".join(f"exp(coalesce(sum(ln(a_{c})) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding), 0)) as t_{c}" for c in ("even", "odd"))


@_q(f"""select user_id, {_CHSQL}, count(*) as k from (select *, {_CHT} from (select user_id, ts, event_id, case when event_id % 2 = 0 then {_EVA} else 1.0 end as a_even,
  case when event_id % 2 = 0 then (1 - {_EVA}) / 2 else 0.0 end as b_even, case when event_id % 2 = 1 then {_EVA} else 1.0 end as a_odd, case when event_id % 2 = 1 then (1 - {_EVA}) / 2 else 0.0 end as b_odd from events)) group by user_id""")
def q_fold_channels(spark, d):
    """Two channels, one sort: a segment acts on its own channel and is the identity for the other."""
    x = _events(spark, d)
    for c, k in (("even", 0), ("odd", 1)):
        own = F.col("event_id") % 2 == k
        x = x.withColumn(f"a_{c}", F.when(own, F.col("a")).otherwise(1.0)).withColumn(f"b_{c}", F.when(own, F.col("b")).otherwise(0.0))
    f = fold.composite_channels(x, ["user_id"], ["ts", "event_id"], ["even", "odd"])
    return f.select("user_id", *[_r(f"{s}_{c}").alias(f"{s}_{c}") for c in ("even", "odd") for s in "ab"], "k")


@_q("select user_id, round(coalesce(sum(case when l_c = 0 then value end), 0), 4) as c0, round(coalesce(sum(case when l_c = 1 then value end), 0), 4) as c1 from (select *, event_id % 2 as l_c from events) group by user_id")
def q_pivot_channels(spark, d):
    x = _t(spark, d, "events").select("user_id", (F.col("event_id") % 2).alias("c"), "value")
    p = x.groupBy("user_id").pivot("c", [0, 1]).agg(F.sum("value"))
    return p.select("user_id", *[_r(F.coalesce(F.col(str(k)), F.lit(0.0)), 4).alias(f"c{k}") for k in (0, 1)])


@_q(f"select l_orderkey, round(exp(sum(ln(a))), 6) as a, round(sum(t * b), 6) as b from (select *, exp(coalesce(sum(ln(a)) over (partition by l_orderkey order by l_linenumber, a, b rows between unbounded preceding and 1 preceding), 0)) as t from {_RAYS}) group by l_orderkey")
def q_sql_fold(spark, d):
    """The fold as an aggregate in SQL text."""
    from .functions.sql import register

    register(spark)
    x = _rays(spark, d).withColumn("z", F.col("l_linenumber").cast("double"))
    return spark.sql("select l_orderkey, round(s.a, 6) as a, round(s.b, 6) as b from (select l_orderkey, seg_fold(collect_list(seg_item(z, a, b))) as s from {x} group by l_orderkey)", x=x)


@_q(f"select {L4}, round(a, 6) as a, round(b, 6) as b, round(a * 0.5 + b, 6) as i from (select *, {_CONST} from {_MEDIA % '0.0'})")
def q_sql_functions(spark, d):
    from .functions.sql import register

    register(spark)
    x = _media(spark, d)
    return spark.sql(f"select {L4}, round(s.a, 6) as a, round(s.b, 6) as b, round(seg_apply(s, 0.5), 6) as i from (select *, seg_combine(seg_const(beta, gamma, dx / 2), seg_const(beta, gamma, dx / 2)) as s from {{x}})", x=x)


@_q(f"select l_orderkey, l_linenumber, l_partkey, l_suppkey, round(a, 6) as a from (select *, row_number() over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_shipdate) as k from {_RAYS}) where k = 1")
def q_first_hit(spark, d):
    w = Window.partitionBy("l_orderkey").orderBy(*L5[1:])
    return _rays(spark, d).withColumn("k", F.row_number().over(w)).filter("k = 1").select(*L5[:4], _r("a").alias("a"))


_SESSION = """with e as (select *, exp(-value / 500) as a, (1 - exp(-value / 500)) / 2 as b, lag(ts) over (partition by user_id order by ts, event_id) as p from events),
  s as (select *, sum(case when p is null or ts >= p + interval 10 days then 1 else 0 end) over (partition by user_id order by ts, event_id rows unbounded preceding) as g from e),
  t as (select *, exp(coalesce(sum(ln(a)) over (partition by user_id, g order by ts, event_id rows between unbounded preceding and 1 preceding), 0)) as t from s)
  select user_id, min(ts) as start, round(exp(sum(ln(a))), 6) as a, round(sum(t * b), 6) as b, count(*) as k from t group by user_id, g"""


@_q(_SESSION)
def q_window_session(spark, d):
    """The batch twin of the streaming session composite."""
    from .streaming.composite import windowed

    x = _events(spark, d).withColumn("ts", F.col("ts").cast("timestamp")).withColumnRenamed("event_id", "tie")
    w = windowed(x, ["user_id"], "ts", "", "1 hour", gap="10 days")
    return w.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), _r("a").alias("a"), _r("b").alias("b"), "k")


_BE, _GA = (lambda x: f"(m * (1 + 0.8 * sin(3 * ({x})) + ({x})))"), (lambda x: f"(2 + cos(5 * ({x})) + ({x}) * ({x}))")


def _sql_rk(stages: list[tuple[str, str]], weights: list[str]) -> tuple[str, str]:
    """One step of a subdiagonal rule as SQL: places and subdiagonal entries of the stages, and their weights."""
    da, db, a_sum, b_sum = "", "", [], []
    for (at, sub), w in zip(stages, weights):
        be, ga = _BE(f"x + {at} * h"), _GA(f"x + {at} * h")
        a, b = (f"(1 + h * {sub} * {da})", f"(h * {sub} * {db})") if da else ("1.0", "0.0")
        da, db = f"(-{be} * {a})", f"({ga} - {be} * {b})"
        a_sum.append(f"{w} * {da}")
        b_sum.append(f"{w} * {db}")
    return f"1 + h * ({' + '.join(a_sum)})", f"h * ({' + '.join(b_sum)})"


_G0, _G1 = "(0.5 - sqrt(3) / 6)", "(0.5 + sqrt(3) / 6)"
_QA = f"exp(-h * ({_BE('x')} + 4 * {_BE('x + h / 2')} + {_BE('x + h')}) / 6)"
_GAUSS = [_BE(f"x + {_G0} * h"), _BE(f"x + {_G1} * h"), _GA(f"x + {_G0} * h"), _GA(f"x + {_G1} * h")]
_DEN = f"(1 + h * ({_GAUSS[0]} + {_GAUSS[1]}) / 4 + h * h * {_GAUSS[0]} * {_GAUSS[1]} / 12)"
_SQL_STEPS = {
    "euler": _sql_rk([("0", "")], ["1"]),
    "heun2": _sql_rk([("0", ""), ("1", "1")], ["0.5", "0.5"]),
    "heun3": _sql_rk([("0", ""), ("(1 / 3)", "(1 / 3)"), ("(2 / 3)", "(2 / 3)")], ["0.25", "0", "0.75"]),
    "rk4": _sql_rk([("0", ""), ("0.5", "0.5"), ("0.5", "0.5"), ("1", "1")], ["(1 / 6)", "(1 / 3)", "(1 / 3)", "(1 / 6)"]),
    "gauss": (f"({_DEN} - h * ({_GAUSS[0]} + {_GAUSS[1]}) / 2) / {_DEN}", f"(h * ({_GAUSS[2]} + {_GAUSS[3]}) / 2 + h * h * ({_GAUSS[0]} * {_GAUSS[3]} - {_GAUSS[1]} * {_GAUSS[2]}) * sqrt(3) / 12) / {_DEN}"),
    "simpson": (_QA, f"h * ({_QA} * {_GA('x')} + 4 * sqrt({_QA}) * {_GA('x + h / 2')} + {_GA('x + h')}) / 6"),
    "simpson_half": (_QA, f"h * ({_QA} * {_GA('x')} + 4 * exp(-h / 2 * ({_BE('x + h / 2')} + 4 * {_BE('x + 0.75 * h')} + {_BE('x + h')}) / 6) * {_GA('x + h / 2')} + {_GA('x + h')}) / 6"),
}


@_q("with medium as (select l_returnflag, sum(l_quantity::bigint) / count(*) / 25.0 as m from lineitem group by 1), g as (select l_returnflag, m, n, k, k / n::double as x, 1.0::double / n as h from medium, (select unnest([8, 16, 32, 1024]) as n) n, range(1024) k(k) where k < n), s as (" + " union all ".join(f"select l_returnflag, '{m}' as method, n, k, {a} as a, {b} as b from g" for m, (a, b) in _SQL_STEPS.items()) + """),
  f as (select *, exp(coalesce(sum(ln(a)) over (partition by l_returnflag, method, n order by k desc rows between unbounded preceding and 1 preceding), 0)) as t from s), w as (select l_returnflag, method, n, exp(sum(ln(a))) as a, sum(t * b) as b from f group by 1, 2, 3),
  e as (select w.l_returnflag, w.method, w.n, p.part, abs(case p.part when 'a' then w.a - x.a else w.b - x.b end) as err from w, w x, (select unnest(['a', 'b']) as part) p where x.l_returnflag = w.l_returnflag and x.method = 'rk4' and x.n = 1024 and w.n < 1024)
  select e.l_returnflag, e.method, e.part, e.n::int as n, round(e.err, 9) as err, round(log2(u.err / e.err), 2) as "order" from e join e u on u.l_returnflag = e.l_returnflag and u.method = e.method and u.part = e.part and u.n * 2 = e.n""")
def q_observed_order(spark, d):
    """Error of each rule with n equal steps on a medium for each return flag, as dense as the mean quantity, and the order that halving shows: explicit rules 1 to 4, Gauss 4,
    Simpson 4 in A and 2 in B (4 with a midpoint transmittance of its own)."""
    be, ga = (lambda x: F.col("m") * (1 + 0.8 * F.sin(3 * x) + x)), (lambda x: 2 + F.cos(5 * x) + x * x)
    media = _t(spark, d, "lineitem").groupBy("l_returnflag").agg((F.sum(F.col("l_quantity").cast("long")) / F.count("*") / 25.0).alias("m"))
    grid = media.select("l_returnflag", "m", F.explode(F.array(*[F.lit(n) for n in (8, 16, 32, 1024)])).alias("n")).select("l_returnflag", "m", "n", F.explode(F.sequence(F.lit(0), F.col("n") - 1)).alias("k"))
    h, x0 = 1.0 / F.col("n"), F.col("k") / F.col("n")
    steps = grid.select("l_returnflag", "n", (-F.col("k")).alias("z"), F.explode(F.array(*[F.struct(F.lit(m).alias("method"), *[c.cast("double").alias(k) for c, k in zip(quadrature.step(m, be, ga, x0, h), "ab")]) for m in quadrature.METHODS])).alias("s")).select("l_returnflag", "n", "z", "s.*")
    f = fold.composite(steps, ["l_returnflag", "method", "n"], ["z"])
    exact = f.filter("method = 'rk4' and n = 1024").select("l_returnflag", F.col("a").alias("ea"), F.col("b").alias("eb"))
    x = f.filter("n < 1024").join(F.broadcast(exact), "l_returnflag").select("l_returnflag", "method", "n", F.explode(F.array(F.struct(F.lit("a").alias("part"), F.abs(F.col("a") - F.col("ea")).alias("err")), F.struct(F.lit("b").alias("part"), F.abs(F.col("b") - F.col("eb")).alias("err")))).alias("e")).select("l_returnflag", "method", "n", "e.*")
    return metrics.observed_order(x, ["l_returnflag", "method", "part"]).select("l_returnflag", "method", "part", "n", _r("err", 9).alias("err"), _r("order", 2).alias("order"))


@_q("""with r as (select *, case when b <= c then 0 else ceil(log2(b / c))::bigint end as depth from (select value / 100 as b from events), (select unnest([1.0, 0.5, 0.02])::double as c), (select unnest(['euler', 'rk4', 'gauss', 'simpson']) as method, unnest([1, 4, 2, 3]) as nodes)),
  s as (select *, power(2.0, depth) as n, b / power(2.0, depth) as z from r)
  select method, c, sum(nodes * (power(2, depth + 1) - 1) + 2 * nodes * n)::bigint as evals, max(depth) as depth, round(max(abs(exp(-b) - case method when 'euler' then power(1 - z, n) when 'rk4' then power(1 - z + z * z / 2 - z * z * z / 6 + z * z * z * z / 24, n) when 'gauss' then power((1 - z / 2 + z * z / 12) / (1 + z / 2 + z * z / 12), n) else exp(-b) end)), 8) as max_error from s group by method, c""")
def q_adaptive_cost(spark, d):
    """Evaluations, depth and greatest error of the adaptive recursion by rule and threshold, on one medium an event."""
    x = _t(spark, d, "events").select(F.col("event_id").alias("id"), F.lit(0.0).alias("x1"), F.lit(1.0).alias("x2"), (F.col("value") / 100).alias("b0"), F.lit(0.0).alias("z"), F.lit(1.0).alias("g0"))
    out = None
    for method in ("euler", "rk4", "gauss", "simpson"):
        for c in (1.0, 0.5, 0.02):
            y = quadrature.adaptive(x, method, c, ["b0", "z", "g0", "z"]).join(x.select("id", "b0"), "id")
            row = y.agg(F.lit(method).alias("method"), F.lit(c).alias("c"), F.sum("evals").alias("evals"), F.max("depth").alias("depth"), _r(F.max(F.abs(F.col("a") - F.exp(-F.col("b0")))), 8).alias("max_error"))
            out = row if out is None else out.unionByName(row)
    return out


# --- geometry ---


def _jit(v, salt):
    return 0.3 * scenes.uniform01(v, salt)


def _nation_trees(spark, d):
    """One bilinear tree a nation: cells of a 5 x 5 grid whose vertices are moved by a hash of their number."""
    x = _t(spark, d, "nation").select(F.col("n_nationkey").cast("int").alias("tree"), F.col("n_nationkey") % 5, F.floor(F.col("n_nationkey") / 5)).toDF("tree", "gx", "gy")
    for i, j in ((0, 0), (1, 0), (0, 1), (1, 1)):
        v = (F.col("gy") + j) * 6 + F.col("gx") + i
        x = x.withColumn(f"p{i}{j}", F.array(F.col("gx") + i + _jit(v, 11), F.col("gy") + j + _jit(v, 12), 8.0 + _jit(v, 13)))
    return x.drop("gx", "gy")


def _vsql(i, j):
    u = lambda s: f"0.3 * ((((gy + {j}) * 6 + gx + {i}) * 2654435761 + {s} * 40503) % 4294967296) / 4294967296.0"
    return f"gx + {i} + {u(11)} as x{i}{j}, gy + {j} + {u(12)} as y{i}{j}, 8.0 + {u(13)} as z{i}{j}"


_TREES = f"(select tree, {', '.join(_vsql(i, j) for i, j in ((0, 0), (1, 0), (0, 1), (1, 1)))} from (select n_nationkey as tree, (n_nationkey % 5)::bigint as gx, (n_nationkey // 5)::bigint as gy from nation))"
_U = lambda k, s: f"((({k}) * 2654435761 + {s} * 40503) % 4294967296) / 4294967296.0"


@_q(f"""select c_custkey, round((1 - s) * (1 - t) * x00 + s * (1 - t) * x10 + (1 - s) * t * x01 + s * t * x11, 6) as x, round((1 - s) * (1 - t) * y00 + s * (1 - t) * y10 + (1 - s) * t * y01 + s * t * y11, 6) as y
  from (select c_custkey, c_nationkey, {_U('c_custkey', 1)} as s, {_U('c_custkey', 2)} as t from customer) join {_TREES} on tree = c_nationkey""")
def q_map_point(spark, d):
    """Customers as points of their nation's tree, in space."""
    c = _t(spark, d, "customer").select("c_custkey", F.col("c_nationkey").cast("int").alias("tree"), scenes.uniform01(F.col("c_custkey"), 1).alias("s"), scenes.uniform01(F.col("c_custkey"), 2).alias("t"))
    x = c.join(_nation_trees(spark, d), "tree")
    return x.select("c_custkey", *[_r(surface.on_patch(F.col("s"), F.col("t"), a)).alias(n) for a, n in enumerate("xy")])


@_q(f"select p_partkey, round((0.3 * cx + 0.5 * cy + 0.8 * (cz + 1)) / 0.8, 6) as alpha from {_SPH}")
def q_hit_plane(spark, d):
    """A ray along z from (0, 0, -1) and the plane through each sphere's centre with normal (0.3, 0.5, 0.8)."""
    a = G.hit_plane([F.col(f"c{k}") for k in "xyz"], [F.lit(v) for v in (0.3, 0.5, 0.8)], [F.lit(0.0), F.lit(0.0), F.lit(-1.0)], [F.lit(0.0), F.lit(0.0), F.lit(1.0)])
    return _spheres(spark, d).select("p_partkey", _r(a).alias("alpha"))


@_q(f"""select p_partkey, round(greatest((cx - r + 1) / 1.0, (cy - r + 1) / 0.9, (cz - r + 1) / 1.1), 6) as near, round(least((cx + r + 1) / 1.0, (cy + r + 1) / 0.9, (cz + r + 1) / 1.1), 6) as far from {_SPH}
  where greatest((cx - r + 1) / 1.0, (cy - r + 1) / 0.9, (cz - r + 1) / 1.1) < least((cx + r + 1) / 1.0, (cy + r + 1) / 0.9, (cz + r + 1) / 1.1)""")
def q_hit_box(spark, d):
    c = [F.col(f"c{k}") for k in "xyz"]
    n, f = G.hit_box([v - F.col("r") for v in c], [v + F.col("r") for v in c], [F.lit(-1.0)] * 3, [F.lit(v) for v in (1.0, 0.9, 1.1)])
    return _spheres(spark, d).filter(n < f).select("p_partkey", _r(n).alias("near"), _r(f).alias("far"))


@_q(f"""with p as (select p_partkey, {_U('p_partkey', 1)} as s, {_U('p_partkey', 2)} as t, {_U('p_partkey', 3)} * 0.5 as k from part) select p_partkey, round(s, 6) as s, round(t, 6) as t, 1 as hits from p""")
def q_hit_bilinear(spark, d):
    """A bent patch a part; the ray goes through a known place (s, t) of it, which must come back."""
    p = _t(spark, d, "part").select("p_partkey", *[scenes.uniform01(F.col("p_partkey"), i).alias(c) for i, c in ((1, "s"), (2, "t"), (3, "k"))])
    corner = {"p00": [-1.0, -1.0, 4.0], "p10": [1.0, -1.0, 4.5], "p01": [-1.0, 1.0, 4.25]}
    cols = {n: [F.lit(v) for v in c] for n, c in corner.items()}
    cols["p11"] = [F.lit(1.0), F.lit(1.0), 4.75 + F.col("k") * 0.5]
    at = [G.bilinear(F.col("s"), F.col("t"), *[cols[c][a] for c in surface.CORNERS]) for a in range(3)]
    x = p.select("p_partkey", "k", F.col("s").alias("s_"), F.col("t").alias("t_"), *[v.alias(f"w{a}") for a, v in enumerate(at)])
    h = x.withColumn("h", hit_bilinear_columns(*[cols[c] for c in surface.CORNERS], [F.col("w0") / F.col("w2"), F.col("w1") / F.col("w2"), F.lit(1.0)]))
    return h.select("p_partkey", _r(F.element_at("h", 1)["s"]).alias("s"), _r(F.element_at("h", 1)["t"]).alias("t"), F.size("h").alias("hits"))


# --- culling, rendering, routing ---

_N = 32
_CAMS = pipeline.front_cameras(2, _N)
_BOX = ", ".join(f"({' + '.join(f'(((key >> {3 * i + a}) & 1) << {i})' for i in range(TOP))}) / 1024.0 as {c}0" for a, c in enumerate("xyz"))


def _culled(n: int, boxes: str = f"select level, p << (3 * ({TOP} - level))::int as key, n from leaf", head: str | None = None, cams: int = 2) -> str:
    """CTEs of culling for cameras of n x n pixels over boxes (level, key)."""
    m = (n - 1) / 2
    return (_LEAVES + "," if head is None else head) + f""" k as ({boxes}), b as (select *, {_BOX}, power(2.0, -level) as e from k),
  c as (select inst.inst::int as inst, b.*, x0 - (0.5 + 0.2 * inst.inst::double) as lx, x0 + e - (0.5 + 0.2 * inst.inst::double) as hx, y0 - (0.5 - 0.1 * inst.inst::double) as ly, y0 + e - (0.5 - 0.1 * inst.inst::double) as hy, greatest(z0 + 2.0, 1.0) as za, least(z0 + e + 2.0, 100.0) as zb from b, range({cams}) inst(inst)),
  r as (select *, greatest(ceil({m} + lx / (case when lx >= 0 then zb else za end) * {n}), 0)::bigint as i0, least(floor({m} + hx / (case when hx >= 0 then za else zb end) * {n}), {n - 1})::bigint as i1,
    greatest(ceil({m} + ly / (case when ly >= 0 then zb else za end) * {n}), 0)::bigint as j0, least(floor({m} + hy / (case when hy >= 0 then za else zb end) * {n}), {n - 1})::bigint as j1 from c where za < zb),
  v as (select *, (i1 - i0 + 1) * (j1 - j0 + 1) as npix from r where i0 <= i1 and j0 <= j1)"""


_CULLED = _culled(_N)


def _visible(spark, d):
    return pipeline.visible_leaves(_leaves(spark, d), _CAMS, TOP)


@_q(_CULLED + " select inst, level, key, i0, i1, j0, j1, npix from v")
def q_culled(spark, d):
    return _visible(spark, d).select("inst", F.col("level").cast("bigint").alias("level"), "key", "i0", "i1", "j0", "j1", "npix")


def _owned(spark, d, weight="npix", parts=8):
    """Visible leaves with the owner that an even cut by visible pixels of all instances gives."""
    v = _visible(spark, d)
    w = v.groupBy("tree", "level", "key").agg(F.sum("npix").alias("npix"), F.lit(1).cast("long").alias("one"))
    o = forest.with_owner(w, weight, parts)
    return v, o


_OWN = _CULLED + """, w as (select key, level, sum(npix) as npix from v group by 1, 2),
  o as (select key, npix, least(7, (coalesce(sum(npix) over (order by key rows between unbounded preceding and 1 preceding), 0) * 8) // sum(npix) over ())::int as pid,
    least(7, ((row_number() over (order by key) - 1) * 8) // count(*) over ())::int as even from w)"""


@_q(_OWN + """ select 'pixels' as weight, round(max(s) * 8.0 / sum(s), 6) as imbalance from (select sum(npix) as s from o group by pid)
  union all select 'elements', round(max(s) * 8.0 / sum(s), 6) from (select sum(npix) as s from o group by even)""")
def q_partition_balance(spark, d):
    """Pixels of the heaviest owner over the mean: cut by visible pixels, and by element count (the baseline)."""
    out = None
    for name, weight in (("pixels", "npix"), ("elements", "one")):
        _, o = _owned(spark, d, weight)
        row = metrics.load_balance(o, "npix", 8).select(F.lit(name).alias("weight"), _r("imbalance").alias("imbalance"))
        out = row if out is None else out.unionByName(row)
    return out


_SENT = _OWN + """, s as (select distinct inst, pid, (ty * 4 + tx)::bigint as tile from v join o using (key), range(4) x(tx), range(4) y(ty) where tx between i0 >> 3 and i1 >> 3 and ty between j0 >> 3 and j1 >> 3)"""


@_q(_SENT + " select inst, pid, tile from s")
def q_senders(spark, d):
    v, o = _owned(spark, d)
    return routing.senders(v.join(o.select("tree", "key", "pid"), ["tree", "key"]), _N, 3)


@_q(_SENT + " select inst, pid, tile from s")
def q_routes_all_pairs(spark, d):
    """The baseline by trying every leaf on every tile."""
    v, o = _owned(spark, d)
    return routing.senders_all_pairs(v.join(o.select("tree", "key", "pid"), ["tree", "key"]), _N, _N, 3)


def _bits(key: str) -> str:
    return ", ".join(f"({' + '.join(f'(((({key}) >> {3 * i + a}) & 1) << {i})' for i in range(TOP))}) / 1024.0 as {c}0" for a, c in enumerate("xyz"))


def _meets(nodes: str) -> str:
    """Those of ``nodes`` (inst, tile, level, key) whose pixel rectangle meets the tile, with the first and last owner number of their keys."""
    m = (_N - 1) / 2
    last = f"key + (1::bigint << (3 * ({TOP} - level))) - 1"
    upto = lambda k: " + ".join(f"(f{i} <= {k})::int" for i in range(8))
    side = lambda c: f"greatest(ceil({m} + l{c} / (case when l{c} >= 0 then zb else za end) * {_N}), 0) as {c}a, least(floor({m} + h{c} / (case when h{c} >= 0 then za else zb end) * {_N}), {_N - 1}) as {c}b"
    return f"""(select * from (select *, {side('x')}, {side('y')}, greatest(0, {upto('key')} - 1) as lo, greatest(greatest(0, {upto('key')} - 1), {upto(last)} - 1) as hi from (
      select *, x0 - (0.5 + 0.2 * inst) as lx, x0 + e - (0.5 + 0.2 * inst) as hx, y0 - (0.5 - 0.1 * inst) as ly, y0 + e - (0.5 - 0.1 * inst) as hy, greatest(z0 + 2.0, 1.0) as za, least(z0 + e + 2.0, 100.0) as zb from (
      select *, {_bits('key')}, power(2.0, -level) as e from {nodes})) where za < zb)
      where xa <= xb and ya <= yb and xa < (tile % 4) * 8 + 8 and xb >= (tile % 4) * 8 and ya < (tile // 4) * 8 + 8 and yb >= (tile // 4) * 8)"""


_EXPECTED = _SENT.replace("with p as", "with recursive p as", 1) + f""", mk as (select pid, min(key) as first, row_number() over (order by min(key)) - 1 as idx from o group by pid),
  f as (select {', '.join(f'coalesce(max(case when idx = {i} then first end), 1099511627776) as f{i}' for i in range(8))} from mk),
  n as (select inst, tile, level, key, lo, hi from {_meets('(select inst, tile, 0 as level, 0::bigint as key from range(2) a(inst), range(16) b(tile)), f')}
    union all select inst, tile, level, key, lo, hi from {_meets(f'(select inst, tile, level + 1 as level, key + c * (1::bigint << (3 * ({TOP} - 1 - level))) as key from n, range(8) c(c) where lo < hi and level < {TOP}), f')}),
  x as (select distinct n.inst::int as inst, mk.pid, n.tile::bigint as tile from n join mk on mk.idx between n.lo and n.hi where n.lo = n.hi or n.level = {TOP})"""


@_q(_EXPECTED + " select (select count(*) from s) as sent, (select count(*) from s anti join x using (inst, pid, tile)) as missed")
def q_receivers_superset(spark, d):
    """Routes from markers alone hold all that is sent."""
    f = _route_check(spark, d)
    return f.select("sent", "missed")


@_q(_EXPECTED + " select (select count(*) from s) as sent, (select count(*) from x) as expected, (select count(*) from x anti join s using (inst, pid, tile)) as false_pairs, (select count(*) from s anti join x using (inst, pid, tile)) as missed")
def q_false_pairs(spark, d):
    """Pairs of owner and tile that are sent, that markers alone let expect, and how far the two differ."""
    return _route_check(spark, d)


def _route_check(spark, d):
    v, o = _owned(spark, d)
    o = forest.cut(o)
    sent = routing.senders(v.join(o.select("tree", "key", "pid"), ["tree", "key"]), _N, 3)
    return routing.false_pairs(sent, routing.receivers(spark, forest.markers(o), _CAMS, 3, TOP))


def _cell(n: int, culled: str | None = None) -> str:
    """CTEs of rendering: the way of every ray through every visible box."""
    m = (n - 1) / 2
    return (culled or _culled(n)) + f""", g as (select v.*, i, j, {' + '.join(f'(((i >> {k}) & 1) << {2 * k}) + (((j >> {k}) & 1) << {2 * k + 1})' for k in range(6))} as pix, (i - {m}) / {n}.0 as dx, (j - {m}) / {n}.0 as dy from v, range({n}) a(i), range({n}) b(j) where i between i0 and i1 and j between j0 and j1),
  h as (select *, greatest(least(lx / dx, hx / dx), least(ly / dy, hy / dy), z0 + 2.0, 1.0) as zi, least(greatest(lx / dx, hx / dx), greatest(ly / dy, hy / dy), z0 + e + 2.0, 100.0) as zo from g), cell as (select * from h where zi < zo)"""


_CELL = _cell(_N)


@_q(_CELL + " select inst, pix, level, key, round(zi, 6) as z_in, round(zo, 6) as z_out from cell where zo - zi > 1e-9")
def q_render_cells(spark, d):
    x = pipeline.render(_visible(spark, d).withColumn("beta", F.lit(1.0)).withColumn("gamma", F.lit(1.0)), _CAMS)
    return x.filter("z_out - z_in > 1e-9").select("inst", "pix", F.col("level").cast("bigint").alias("level"), "key", _r("z_in").alias("z_in"), _r("z_out").alias("z_out"))


def _image(n: int) -> str:
    """Pixels of the scene with constant media, folded."""
    return _cell(n) + f""", m as (select leaf.level, leaf.p << (3 * ({TOP} - leaf.level))::int as key, avg(label) / 3.0 + 0.5 as beta, avg(label / 9.0) as gamma from p join embeddings using (vec_id) join leaf on p.key >> (3 * ({TOP} - leaf.level))::int = leaf.p group by 1, 2),
  s as (select cell.*, exp(-beta * sqrt(dx * dx + dy * dy + 1) * (zo - zi)) as a, gamma / beta * (1 - exp(-beta * sqrt(dx * dx + dy * dy + 1) * (zo - zi))) as b from cell join m using (level, key)),
  f as (select *, exp(coalesce(sum(ln(a)) over (partition by inst, pix order by zi, key rows between unbounded preceding and 1 preceding), 0)) as t from s)
  select inst, pix >> 8 as tile, pix, round(exp(sum(ln(a))), 6) as a, round(sum(t * b), 6) as b from f group by inst, pix"""


@_q(_image(_N))
def q_render_image(spark, d):
    """The whole pipeline, two cameras, two condense cycles."""
    return pipeline.render_pipeline(_scene(spark, d), _CAMS, TOP).select("inst", "tile", "pix", _r("a").alias("a"), _r("b").alias("b"))


@_q(_CELL + " select c.c::int as cycle, count(distinct (pix, key >> (3 * c.c)::int)) as segments, count(distinct key >> (3 * c.c)::int) as elements from cell, (select unnest([2, 4, 6, 8]) as c) c where inst = 0 group by 1")
def q_condense_ratio(spark, d):
    """Segments and elements left after condense cycles."""
    cams = pipeline.front_cameras(1, _N)
    raw = forest.cut(pipeline.render(pipeline.visible_leaves(_scene(spark, d), cams, TOP), cams))
    out = None
    for c in (2, 4, 6, 8):
        row = pipeline.condense(raw, TOP, c).agg(F.lit(c).alias("cycle"), F.count("*").alias("segments"), F.countDistinct("tree", "level", "key").alias("elements"))
        out = row if out is None else out.unionByName(row)
    return out


@_q(_CELL + """, n as (select 'leaves' as stage, count(*) as segments, count(*) as elements from leaf union all select 'visible', count(*), count(distinct key) from v union all select 'rendered', count(*), count(distinct key) from cell
  union all select 'condensed_' || c.c, count(distinct (inst, pix, key >> (3 * c.c)::int)), count(distinct key >> (3 * c.c)::int) from cell, (select unnest([4, 8]) as c) c group by c.c) select *, segments * 48 as bytes from n""")
def q_phase_counts(spark, d):
    """Segments, elements and bytes after each stage: all, visible, rendered, condensed."""
    leaves = forest.cut(_scene(spark, d))
    seen = pipeline.visible_leaves(leaves, _CAMS, TOP)
    raw = forest.cut(pipeline.render(seen, _CAMS))
    return metrics.reduction({"leaves": leaves, "visible": seen, "rendered": raw, "condensed_4": pipeline.condense(raw, TOP, 4), "condensed_8": pipeline.condense(raw, TOP, 8)})


_ITEM_KEY = " + ".join(f"(((least(31, greatest(0, floor({v} * 32)))::bigint >> {i}) & 1) << {3 * i + a})" for i in range(5) for a, v in enumerate(("(l_quantity - 1) / 49", "(l_extendedprice - 900) / 104100", "date_diff('day', date '1995-01-01', l_shipdate::date) / 2500.0")))


@_q(_cell(48, _culled(48, "select 5 as level, range << 15 as key from range(32768)", "with", 1)) + f", held as (select ({_ITEM_KEY}) << 15 as key, avg(l_discount) as mean from lineitem group by 1), seg as (select pix, key, zo - zi as way, (1 + 20 * coalesce(mean, 0)) * sqrt(dx * dx + dy * dy + 1) * (zo - zi) as depth from cell left join held using (key))" + " select 'cycle_' || c.c as stage, count(distinct (pix, key >> (15 + 3 * c.c)::int)) as segments, count(distinct key >> (15 + 3 * c.c)::int) as elements, 48 * count(distinct (pix, key >> (15 + 3 * c.c)::int)) as bytes, round(sum(depth), 3) as depth from seg, range(4) c(c) where way > 1e-9 group by c.c")
def q_condense_uniform(spark, d):
    """On a uniform mesh over the line items, each cycle leaves an eighth of the elements, about half of the segments, and all of the depth
    (sum of -ln a). An element's absorption is 1 and 20 times the mean discount of the line items in it."""
    cams = pipeline.front_cameras(1, 48)
    at = [(F.col("l_quantity") - 1) / 49, (F.col("l_extendedprice") - 900) / 104100, F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-01").cast("date")) / 2500.0]
    held = _t(spark, d, "lineitem").groupBy(sfc.morton3(*[sfc.cell(v, 5) for v in at]).alias("key")).agg(F.avg("l_discount").alias("mean"))
    leaves = forest.uniform(spark, 1, 5, 5).join(held, "key", "left").select("tree", "level", "key", (1 + 20 * F.coalesce("mean", F.lit(0.0))).alias("beta"), F.lit(1.0).alias("gamma"))
    raw = forest.cut(pipeline.render(pipeline.visible_leaves(leaves, cams, 5), cams).filter("z_out - z_in > 1e-9"))  # rays along faces
    return metrics.reduction({"cycle_0": raw} | {f"cycle_{c}": pipeline.condense(raw, 5, c) for c in (1, 2, 3)}, depth=_r(-F.sum(F.ln("a")), 3))


@_q(_CELL + ", s as (select inst, level, key, count(*) as segments from cell group by 1, 2, 3) select round(corr(npix, segments), 6) as correlation, count(*) as leaves from v join s using (inst, level, key)")
def q_work_linear(spark, d):
    """How far segments follow pixels of a leaf: correlation (near 1) over visible leaves."""
    v = _visible(spark, d).withColumn("beta", F.lit(1.0)).withColumn("gamma", F.lit(1.0))
    s = pipeline.render(v, _CAMS).groupBy("inst", "tree", "level", "key").agg(F.count("*").alias("segments"))
    return v.join(s, ["inst", "tree", "level", "key"]).agg(_r(F.corr("npix", "segments")).alias("correlation"), F.count("*").alias("leaves"))


@_q(_LEAVES + f" select level, p << (3 * ({TOP} - level))::int as key, n from leaf order by n desc, key limit 10")
def q_top_leaves(spark, d):
    return _leaves(spark, d).select(F.col("level").cast("bigint").alias("level"), "key", "n").orderBy(F.desc("n"), "key").limit(10)


_XY = ", ".join(f"(({' + '.join(f'(((key >> {2 * i + a}) & 1) << {i})' for i in range(8))}))::bigint as {c}" for a, c in enumerate("xy"))


@_q(f"""with q as (select distinct least(255, floor((l_quantity - 1) / 49 * 256))::bigint as x, least(255, floor((l_extendedprice - 900) / 104100 * 256))::bigint as y from lineitem),
  anc as (select distinct l.level, x >> (8 - l.level)::int as x, y >> (8 - l.level)::int as y from q, range(0, 4) l(level)),
  kid as (select level + 1 as level, 2 * x + i.i as x, 2 * y + j.j as y from anc, range(2) i(i), range(2) j(j)),
  leaf as (select * from kid k where not exists (select 1 from anc a where a.level = k.level and a.x = k.x and a.y = k.y)),
  c as (select (x + i.i) << (8 - level)::int as vx, (y + j.j) << (8 - level)::int as vy from leaf, range(2) i(i), range(2) j(j))
  select vx, vy, count(*) as corners, count(*) < (case when vx > 0 and vx < 256 then 2 else 1 end) * (case when vy > 0 and vy < 256 then 2 else 1 end) as hanging from c group by vx, vy""")
def q_vertices_hanging(spark, d):
    """Vertices of the quadtree that is split wherever line items lie, to level 4."""
    x = _t(spark, d, "lineitem").select(sfc.morton2(F.least(F.lit(255), F.floor((F.col("l_quantity") - 1) / 49 * 256)), F.least(F.lit(255), F.floor((F.col("l_extendedprice") - 900) / 104100 * 256))).alias("k"))
    own = x.select(F.lit(0).alias("tree"), F.lit(4).alias("level"), F.shiftleft(F.shiftright("k", 8), 8).alias("key")).distinct()
    return forest.vertices(forest.complete(own, 8, 2), 8).select("vx", "vy", "corners", "hanging")


# --- the fractal on two trees ---

_FN = 48


def _fractal_cams():
    """One that sees all, one nearer to the side of a bulb."""
    at = [((-0.5, 0.0, 0.0), 0.8 / _FN), ((-0.72, 0.31, 0.5), 0.35 / _FN)]
    return [pipeline.Camera(i, o, (0.0, 0.0, 1.0), (1.0, 0.0, 0.0), (0.0, 1.0, 0.0), _FN, _FN, ell) for i, (o, ell) in enumerate(at)]


def _plane_points(spark, d):
    """Line items as points of the two trees: even and odd orders, by quantity and price."""
    at = [sfc.cell(v, 6) for v in ((F.col("l_quantity") - 1) / 49, (F.col("l_extendedprice") - 900) / 104100)]
    return _t(spark, d, "lineitem").select((F.col("l_orderkey") % 2).cast("int").alias("tree"), sfc.morton2(*at).alias("key"))


def _quad(c: int) -> str:
    """One coordinate (0 or 1) of the place (s, t) of both trees of the hexagon."""
    by = {t: [p[c] for p in q] for t, *q in surface.HEXAGON}
    w = ["(1 - s) * (1 - t)", "s * (1 - t)", "(1 - s) * t", "s * t"]
    return "case tree " + " ".join(f"when {t} then " + " + ".join(f"{a} * {v}" for a, v in zip(w, q)) for t, q in by.items()) + " end"


_FRACTAL = f"""with recursive v as (select tree, i, j, {_quad(0)} as cr, {_quad(1)} as ci from (select tree::int as tree, i, j, i / 64.0 as s, j / 64.0 as t from range(2) a(tree), range(65) b(i), range(65) c(j))),
  z as (select tree, i, j, cr, ci, 0.0::double as x, 0.0::double as y, 0 as n, false as out from v union all select tree, i, j, cr, ci, case when x * x + y * y > 4 then x else x * x - y * y + cr end, case when x * x + y * y > 4 then y else 2 * x * y + ci end, n + 1, x * x + y * y > 4 from z where n < 30),
  st as (select tree, i, j, sum(case when n > 0 and not out then 1 else 0 end) as n from z group by 1, 2, 3),
  node as (select a.tree, l.level::int as level, x.x, y.y, (64 >> l.level::int) as e from range(2) a(tree), range(2, 6) l(level), range(32) x(x), range(32) y(y) where x.x < (1 << l.level::int) and y.y < (1 << l.level::int)),
  pts as (select (l_orderkey % 2)::int as tree, least(63, floor((l_quantity - 1) / 49 * 64))::bigint as x, least(63, floor((l_extendedprice - 900) / 104100 * 64))::bigint as y, count(*) as items from lineitem group by 1, 2, 3),
  held as (select tree, l.level::int as level, x >> (6 - l.level::int) as x, y >> (6 - l.level::int) as y, sum(items) as items from pts, range(2, 7) l(level) group by 1, 2, 3, 4),
  d0 as (select node.tree, level, x, y, min(n) < max(n) as differ from node join st on st.tree = node.tree and st.i in (x * e, (x + 1) * e) and st.j in (y * e, (y + 1) * e) group by 1, 2, 3, 4),
  d as (select d0.tree, d0.level, d0.x, d0.y, differ and held.tree is not null as differ from d0 left join held on held.tree = d0.tree and held.level = d0.level and held.x = d0.x and held.y = d0.y),
  s0 as (select tree, level, x, y from d where differ and not exists (select 1 from d u where u.tree = d.tree and u.level < d.level and u.x = d.x >> (d.level - u.level) and u.y = d.y >> (d.level - u.level) and not u.differ)),
  up as (select a.tree, l.level::int as level, x.x, y.y from range(2) a(tree), range(2) l(level), range(2) x(x), range(2) y(y) where x.x < (1 << l.level::int) and y.y < (1 << l.level::int)),
  split as (select * from s0 union select * from up union select tree, level - 1, (x + i.i) >> 1, (y + j.j) >> 1 from split, range(-1, 2) i(i), range(-1, 2) j(j) where level > 0 and x + i.i between 0 and (1 << level) - 1 and y + j.j between 0 and (1 << level) - 1),
  kid as (select tree, level + 1 as level, 2 * x + i.i as x, 2 * y + j.j as y from split, range(2) i(i), range(2) j(j))"""


@_q(_FRACTAL + """
  select kid.tree::int as tree, kid.level, count(*) as leaves, 4096 as uniform, coalesce(sum(items), 0)::bigint as items from kid left join held on held.tree = kid.tree and held.level = kid.level and held.x = kid.x and held.y = kid.y where not exists (select 1 from split t where t.tree = kid.tree and t.level = kid.level and t.x = kid.x and t.y = kid.y) group by 1, 2""")
def q_fractal_mesh(spark, d):
    """Leaves by tree and level of the mesh adapted where line items lie, and balanced, with the line items in them; and what a uniform mesh of the finest level has."""
    p = _plane_points(spark, d)
    m = surface.fractal_mesh(surface.hexagon(spark), 2, 6, points=p)
    low = F.expr("2 * (6 - level)")
    held = p.groupBy("tree", "key").agg(F.count("*").alias("items")).withColumn("level", F.explode(F.sequence(F.lit(2), F.lit(6))))
    held = held.groupBy("tree", "level", F.call_function("shiftleft", F.call_function("shiftright", F.col("key"), low), low).alias("key")).agg(F.sum("items").alias("items"))
    return m.join(held, ["tree", "level", "key"], "left").groupBy("tree", "level").agg(F.count("*").alias("leaves"), F.lit(4**6).alias("uniform"), F.coalesce(F.sum("items"), F.lit(0)).alias("items"))


# --- spheres ---


_CLOUD = f"""with e as (select (0.1 - 0.001) / ln(100.0) as e), m as (select 4.0 * power(4.0, -4) / e as m, e from e),
  f as (select k, exp(-m) * power(m, k) / gamma(k + 1) as p from m, range(80) r(k)), g as (select k, sum(p) over (order by k) as f from f),
  c as (select cell, (select min(k) from g where g.f >= u) as c from (select range as cell, {_U('range', 7)} as u from range(4096))),
  s as (select cell * (trunc(m + 12 * sqrt(m) + 16)::bigint + 1) + k.k as sid from c, m, range(1, 80) k(k) where k.k <= c.c),
  x as (select 0.001 * power(100.0, {_U('sid', 4)}) as s from s)"""


@_q(_CLOUD + " select count(*) as spheres, round(avg(s), 8) as mean, round(any_value(e), 8) as expected, round((avg(s) - any_value(e)) / (stddev(s) / sqrt(count(*))), 5) as z_section, round((count(*) - 4096 * any_value(m)) / sqrt(4096 * any_value(m)), 5) as z_count from x, m")
def q_sphere_section(spark, d):
    """Sampled mean section and count of a cloud against what the law expects (z scores)."""
    e = scenes.expected_section()
    n = 4.0 * 2.0**4 / e  # elements x coverage x face over the expected section
    x = spheres.cloud(spark, 4, 4.0)
    s = F.pi() * F.col("r") * F.col("r")
    return x.agg(F.count("*").alias("spheres"), _r(F.avg(s), 8).alias("mean"), _r(F.lit(e), 8).alias("expected"), _r((F.avg(s) - e) / (F.stddev(s) / F.sqrt(F.count("*"))), 5).alias("z_section"), _r((F.count("*") - F.lit(n)) / F.lit(n**0.5), 5).alias("z_count"))


def _picture(spark, most=44):
    """The 44 spheres of the picture, by the size law from their numbers."""
    k = spark.range(1, most + 1).withColumnRenamed("id", "sid")
    at = [scenes.uniform01(F.col("sid"), a).alias(f"c{n}") for a, n in ((1, "x"), (2, "y"), (3, "z"))]
    return k.select("sid", *at, F.sqrt(scenes.section(scenes.uniform01(F.col("sid"), 4)) / F.pi()).alias("r"))


@_q(f"""with recursive s as (select p_partkey, cx, cy, cz, r from {_SPH}),
  n as (select 0 as level, 0::bigint as x, 0::bigint as y, 0::bigint as z, p_partkey from s where {'{0}'}
    union all select n.level + 1, 2 * n.x + i.i, 2 * n.y + j.j, 2 * n.z + k.k, n.p_partkey from n join s using (p_partkey), range(2) i(i), range(2) j(j), range(2) k(k) where n.level < 3 and {'{1}'}),
  split as (select distinct level, x, y, z from n), kid as (select level + 1 as level, 2 * x + i.i as x, 2 * y + j.j as y, 2 * z + k.k as z from split, range(2) i(i), range(2) j(j), range(2) k(k))
  select level, count(*) as leaves from kid where not exists (select 1 from split t where t.level = kid.level and t.x = kid.x and t.y = kid.y and t.z = kid.z) group by level""".format(
    *["power(greatest({x} * {e} - cx, cx - ({x} + 1) * {e}, 0), 2) + power(greatest({y} * {e} - cy, cy - ({y} + 1) * {e}, 0), 2) + power(greatest({z} * {e} - cz, cz - ({z} + 1) * {e}, 0), 2) <= power(r * 1.1, 2) and power(greatest(abs(cx - {x} * {e}), abs(cx - ({x} + 1) * {e})), 2) + power(greatest(abs(cy - {y} * {e}), abs(cy - ({y} + 1) * {e})), 2) + power(greatest(abs(cz - {z} * {e}), abs(cz - ({z} + 1) * {e})), 2) >= power(r * 0.9, 2) and {e} >= r * 0.05".format(**v) for v in ({"x": "0", "y": "0", "z": "0", "e": "1.0"}, {"x": "(2 * n.x + i.i)", "y": "(2 * n.y + j.j)", "z": "(2 * n.z + k.k)", "e": "power(2.0, -n.level - 1)"})]
))
def q_sphere_mesh(spark, d):
    """Leaves by level of the mesh refined at the shells of all parts' spheres, to level 4."""
    s = _spheres(spark, d).select(F.col("p_partkey").alias("sid"), "cx", "cy", "cz", "r")
    return spheres.shell_mesh(s, 4, 0.1, 7).groupBy("level").agg(F.count("*").alias("leaves"))


def _sphere_scene(spark, level, size=24):
    """Mesh of a level at the picture's spheres, and the leaves that the camera sees, with the spheres near them."""
    cams, s = pipeline.front_cameras(1, size), _picture(spark)
    leaves = forest.cut(spheres.shell_mesh(s, level, 0.1, 7))
    return cams, leaves, forest.cut(pipeline.cull(spheres.spheres_of_leaves(leaves, s, 0.1, 7), cams, 7))


def _sphere_image(scene, method, c):
    """Segments of a scene by a rule and threshold, and their image."""
    seg = forest.cut(spheres.render(scene[2], scene[0], method, c, 0.1))
    return seg, pipeline.image(seg).select("inst", "pix", F.col("b").alias("v"))


@_q()
def q_sphere_errors(spark, d):
    """The picture of 44 spheres: error of coarse settings against Gauss at c = 0.02 on level 7: one Simpson step an element without recursion,
    Simpson at c = 1 on levels 4 and 5, Gauss at c = 0.02 on level 4; with leaves, segments and density evaluations. A mesh serves all settings of
    its level."""
    scene, ref, out = {level: _sphere_scene(spark, level, 48) for level in (4, 5, 7)}, None, None
    for name, level, method, c in (("gauss_c002_level7", 7, "gauss", 0.02), ("simpson_one_step", 4, "simpson", 0.0), ("simpson_c1_level4", 4, "simpson", 1.0), ("simpson_c1_level5", 5, "simpson", 1.0), ("gauss_c002_level4", 4, "gauss", 0.02)):
        seg, img = _sphere_image(scene[level], method, c)
        ref = forest.cut(img) if ref is None else ref
        work = seg.agg(F.count("*").alias("segments"), F.sum("evals").alias("evals"))
        row = metrics.image_error(img, ref, ["inst", "pix"]).join(work).join(scene[level][1].agg(F.count("*").alias("leaves"))).select(F.lit(name).alias("setting"), "leaves", "segments", "evals", "max_error", "rmse")
        out = row if out is None else out.unionByName(row)
    return out
