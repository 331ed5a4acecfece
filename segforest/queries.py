"""Methods, variants, baselines and workloads as queries over the given tables, with SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import algebra as A
from .functions import geometry as G
from .functions import sfc
from .operators import fold, forest, imagetree, quadrature
from .plans import pipeline, scenes

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
L5 = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate"]
L4 = "l_orderkey, l_linenumber, l_partkey, l_suppkey"
TOP = 10


def _q(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            SQL[name or f.__name__] = sql
        return f

    return add


def _t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def _r(c, n: int = 6):
    return F.round(c, n)


def _media(spark, d, shift: float = 0.0) -> DataFrame:
    return _t(spark, d, "lineitem").select(*L5, ((F.col("l_discount") - shift) * 20).alias("beta"), (F.col("l_tax") * 20).alias("gamma"), (F.col("l_quantity") / 50).alias("dx"))


_MEDIA = f"(select {L4}, l_shipdate, (l_discount - %s) * 20 as beta, l_tax * 20 as gamma, l_quantity / 50 as dx from lineitem)"
_CONST = "exp(-beta * dx) as a, case when beta = 0 then gamma * dx else gamma / beta * (1 - exp(-beta * dx)) end as b"


@_q(f"select {L4}, round(a, 6) as a, round(b, 6) as b from (select *, {_CONST} from {_MEDIA % '0.0'})")
def q_seg_const(spark, d):
    s = A.seg_const(F.col("beta"), F.col("gamma"), F.col("dx"))
    return _media(spark, d).select(*L5[:4], _r(s["a"]).alias("a"), _r(s["b"]).alias("b"))


@_q(f"select {L4}, round(exp(-beta * dx), 6) as a, round(case when abs(beta) < 1e-12 then gamma * dx else gamma / beta * (1 - exp(-beta * dx)) end, 6) as b from {_MEDIA % '0.05'}")
def q_seg_negative(spark, d):
    s = A.seg_const(F.col("beta"), F.col("gamma"), F.col("dx"))
    return _media(spark, d, 0.05).select(*L5[:4], _r(s["a"]).alias("a"), _r(s["b"]).alias("b"))


def _rays(spark, d) -> DataFrame:
    return _t(spark, d, "lineitem").select(*L5, F.exp(-F.col("l_quantity") / 50).alias("a"), F.col("l_discount").alias("b"))


_RAYS = f"(select {L4}, l_shipdate, exp(-l_quantity / 50) as a, l_discount as b from lineitem)"
_OVER = "over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_shipdate)"


def _lagged(spark, d, n=1):
    w = Window.partitionBy("l_orderkey").orderBy(*L5[1:])
    x = _rays(spark, d).withColumn("s", F.struct("a", "b"))
    for k in range(1, n + 1):
        x = x.withColumn(f"p{k}", F.lag("s", k).over(w))
    return x


@_q(f"select {L4}, round(pa * a, 6) as a, round(pa * b + pb, 6) as b from (select *, lag(a) {_OVER} as pa, lag(b) {_OVER} as pb from {_RAYS}) where pa is not null")
def q_combine_pairs(spark, d):
    c = A.seg_combine(F.col("p1"), F.col("s"))
    return _lagged(spark, d).filter("p1 is not null").select(*L5[:4], _r(c["a"]).alias("a"), _r(c["b"]).alias("b"))


@_q(f"select {L4}, round(1 / a, 6) as ia, round(-b / a, 6) as ib, 1.0::double as one, 0.0::double as zero from {_RAYS}")
def q_inverse_identity(spark, d):
    s = F.struct("a", "b")
    i = A.seg_inverse(s)
    e = A.seg_combine(s, i)
    return _rays(spark, d).select(*L5[:4], _r(i["a"]).alias("ia"), _r(i["b"]).alias("ib"), _r(e["a"]).alias("one"), F.abs(_r(e["b"])).alias("zero"))


@_q(f"select count(*) as triples, 0 as defects from (select lag(a, 2) {_OVER} as p from {_RAYS}) where p is not null")
def q_assoc_defect(spark, d):
    x = _lagged(spark, d, 2).filter("p2 is not null")
    left = A.seg_combine(A.seg_combine(F.col("p2"), F.col("p1")), F.col("s"))
    right = A.seg_combine(F.col("p2"), A.seg_combine(F.col("p1"), F.col("s")))
    far = (F.abs(left["a"] - right["a"]) > 1e-12) | (F.abs(left["b"] - right["b"]) > 1e-12)
    return x.agg(F.count("*").alias("triples"), F.sum(F.when(far, 1).otherwise(0)).cast("int").alias("defects"))


@_q(f"select {L4}, round(power(a, 0.25), 6) as near_a, round(b * (1 - power(a, 0.25)) / (1 - a), 6) as near_b, round(a, 6) as a, round(b, 6) as b from {_RAYS}")
def q_split_recombine(spark, d):
    s = F.struct("a", "b")
    n, f = A.seg_split(s, 0.25), A.seg_split(s, 0.75)
    c = A.seg_combine(n, f)
    return _rays(spark, d).select(*L5[:4], _r(n["a"]).alias("near_a"), _r(n["b"]).alias("near_b"), _r(c["a"]).alias("a"), _r(c["b"]).alias("b"))


_PAIR = f"(select {L4}, a, b, lag(a) {_OVER} as pa, lag(b) {_OVER} as pb from {_RAYS})"


@_q(f"select {L4}, round(sqrt(a * pa), 6) as a, round((b + pb) / 2, 6) as b from {_PAIR} where pa is not null")
def q_average_printed(spark, d):
    m = A.seg_average(F.col("s"), F.col("p1"))
    return _lagged(spark, d).filter("p1 is not null").select(*L5[:4], _r(m["a"]).alias("a"), _r(m["b"]).alias("b"))


@_q(f"""select {L4}, round(exp(-be), 6) as a, round(ga / be * (1 - exp(-be)), 6) as b from (select *, (-ln(a) - ln(pa)) / 2 as be,
  (-ln(a) * b / (1 - a) - ln(pa) * pb / (1 - pa)) / 2 as ga from {_PAIR} where pa is not null)""")
def q_average_limit(spark, d):
    m = A.seg_average(F.col("s"), F.col("p1"), "limit")
    return _lagged(spark, d).filter("p1 is not null").select(*L5[:4], _r(m["a"]).alias("a"), _r(m["b"]).alias("b"))


@_q(f"select l_orderkey, round(power(exp(sum(ln(a))), 1.0 / count(*)), 6) as a, round(sum(b) / count(*), 6) as b from {_RAYS} group by l_orderkey")
def q_average_kway(spark, d):
    a, b = A.seg_average_n(F.col("a"), F.col("b"))
    return _rays(spark, d).groupBy("l_orderkey").agg(a.alias("x"), b.alias("y")).select("l_orderkey", _r("x").alias("a"), _r("y").alias("b"))


@_q(f"select {L4}, round(beta, 6) as beta, round(gamma, 6) as gamma from {_MEDIA % '0.0'}")
def q_coeffs_roundtrip(spark, d):
    c = A.coefficients(A.seg_const(F.col("beta"), F.col("gamma"), F.col("dx")), F.col("dx"))
    return _media(spark, d).select(*L5[:4], F.abs(_r(c["beta"])).alias("beta"), _r(c["gamma"]).alias("gamma"))


@_q("select l_suppkey, l_partkey, l_orderkey, l_linenumber, round(-b, 6) as b, round(exp(beta * dx), 6) as a from (select *, case when beta = 0 then gamma * dx else gamma / beta * (exp(beta * dx) - 1) end as b from " + _MEDIA % "0.0" + ")")
def q_reverse(spark, d):
    s = A.seg_reverse(F.col("beta"), F.col("gamma"), F.col("dx"))
    return _media(spark, d).select(*L5[:4], _r(s["a"]).alias("a"), _r(s["b"]).alias("b"))


@_q(f"""select {L4}, round((b1 * x1 + b2 * x2) / (x1 + x2), 6) as beta, round((g1 / b1 * w1 + g2 / b2 * w2) / (w1 + w2) * (b1 * x1 + b2 * x2) / (x1 + x2), 6) as gamma
  from (select *, exp(-b1 * x1) * (1 - exp(-b2 * x2)) as w2, 1 - exp(-b1 * x1) as w1 from (select {L4}, beta + 0.5 as b1, gamma as g1, dx as x1, beta + 1.5 as b2, gamma + 0.25 as g2, dx / 2 as x2 from {_MEDIA % '0.0'}))""")
def q_weighted_coeffs(spark, d):
    c = A.combine_coefficients(F.col("beta") + 0.5, F.col("gamma"), F.col("dx"), F.col("beta") + 1.5, F.col("gamma") + 0.25, F.col("dx") / 2)
    return _media(spark, d).select(*L5[:4], _r(c["beta"]).alias("beta"), _r(c["gamma"]).alias("gamma"))


@_q("select p_partkey, round(p_size / 50.0 * (1 - exp(-p_size / 25.0)), 6) as b, round(power(exp(-p_size / 25.0), 50.0 / p_size), 6) as angle_a, round(p_size / 50.0, 6) as opaque_b from part")
def q_surfaces(spark, d):
    a, i = F.exp(-F.col("p_size") / 25.0), F.col("p_size") / 50.0
    s, g, o = A.seg_surface(a, i), A.seg_surface_angle(a, i, F.col("p_size") / 50.0), A.seg_opaque(i)
    return _t(spark, d, "part").select("p_partkey", _r(s["b"]).alias("b"), _r(g["a"]).alias("angle_a"), _r(o["b"]).alias("opaque_b"))


_SCAN = f"""select l_orderkey, exp(sum(ln(a))) as a, sum(t * b) as b, count(*) as k from (select *, exp(coalesce(sum(ln(a)) over
  (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_shipdate rows between unbounded preceding and 1 preceding), 0)) as t from {_RAYS}) group by l_orderkey"""
_FOLD = f"select l_orderkey, round(a, 6) as a, round(b, 6) as b, k from ({_SCAN})"


def _folded(df, key="l_orderkey"):
    return df.select(key, _r("a").alias("a"), _r("b").alias("b"), "k")


@_q(_FOLD)
def q_fold_scan(spark, d):
    return _folded(fold.composite(_rays(spark, d), ["l_orderkey"], L5[1:]))


@_q(_FOLD)
def q_fold_array(spark, d):
    return _folded(fold.composite(_rays(spark, d), ["l_orderkey"], L5[1:], "array"))


@_q(_FOLD)
def q_fold_levels(spark, d):
    x = _rays(spark, d).withColumn("c1", F.floor(F.col("l_linenumber") / 4)).withColumn("c2", F.floor(F.col("l_linenumber") / 2))
    return _folded(fold.composite(x, ["l_orderkey"], L5[1:], "levels", ["c1", "c2"]))


@_q("""select user_id, round(exp(sum(ln(a))), 6) as a, round(sum(t * b), 6) as b, count(*) as k from (select *, exp(coalesce(sum(ln(a)) over
  (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding), 0)) as t from (select *, exp(-value / 500) as a, (1 - exp(-value / 500)) / 2 as b from events)) group by user_id""")
def q_fold_events(spark, d):
    return _folded(fold.composite(_events(spark, d), ["user_id"], ["ts", "event_id"]), "user_id")


def _events(spark, d):
    a = F.exp(-F.col("value") / 500)
    return _t(spark, d, "events").select("user_id", "ts", "event_id", "event_type", a.alias("a"), ((1 - a) / 2).alias("b"))


@_q("""select event_type, round(exp(sum(ln(a))), 6) as a, round(sum(t * b), 6) as b, count(*) as k from (select *, exp(coalesce(sum(ln(a)) over
  (partition by event_type order by ts, event_id rows between unbounded preceding and 1 preceding), 0)) as t from (select *, exp(-value / 500) as a, (1 - exp(-value / 500)) / 2 as b from events)) group by event_type""")
def q_fold_hot_rays(spark, d):
    """Few long rays: runs of one hour fold first, so no task holds a whole ray's rows."""
    x = _events(spark, d).withColumn("hour", F.date_trunc("hour", "ts"))
    return _folded(fold.composite(x, ["event_type"], ["ts", "event_id"], "levels", ["hour"]), "event_type")


@_q("""select conv_id, round(exp(sum(-dx)), 6) as a, round(sum(exp(-coalesce(before, 0)) * g * (1 - exp(-dx))), 6) as b, count(*) as k from (select *, sum(dx) over
  (partition by conv_id order by turn rows between unbounded preceding and 1 preceding) as before from (select conv_id, turn, length(text) / 1000.0 as dx, case role when 'user' then 1.0 when 'assistant' then 2.0 else 0.5 end as g from conversations)) group by conv_id""")
def q_fold_conversations(spark, d):
    g = F.when(F.col("role") == "user", 1.0).when(F.col("role") == "assistant", 2.0).otherwise(0.5)
    s = A.seg_const(F.lit(1.0), g, F.length("text") / 1000.0)
    x = _t(spark, d, "conversations").select("conv_id", "turn", s["a"].alias("a"), s["b"].alias("b"))
    return _folded(fold.composite(x, ["conv_id"], ["turn"]), "conv_id")


@_q(f"select l_orderkey, round(a * o_totalprice / 500000 + b, 6) as i from ({_SCAN}) join orders on l_orderkey = o_orderkey")
def q_classic_back_to_front(spark, d):
    x = _rays(spark, d).join(_t(spark, d, "orders").select("o_orderkey", (F.col("o_totalprice") / 500000).alias("ib")), F.col("l_orderkey") == F.col("o_orderkey"))
    return fold.classic_composite(x, ["l_orderkey"], L5[1:], "ib").select("l_orderkey", _r("i").alias("i"))


@_q(f"select l_orderkey, least(greatest(floor((a * o_totalprice / 500000 + b) * 255 + 0.5), 0), 255)::int as rgb, round(1 - a, 6) as alpha from ({_SCAN}) join orders on l_orderkey = o_orderkey")
def q_background_rgb(spark, d):
    s = fold.composite(_rays(spark, d), ["l_orderkey"], L5[1:]).join(_t(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    i = A.apply_background(F.struct("a", "b"), F.col("o_totalprice") / 500000)
    return s.select("l_orderkey", A.to_rgb(i).alias("rgb"), _r(A.to_alpha(F.struct("a", "b"))).alias("alpha"))


@_q(f"""select {L4}, round(exp(sum(ln(a)) over w), 6) as a, round(sum(t * b) over w, 6) as b from (select *, exp(coalesce(sum(ln(a)) over
  (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_shipdate rows between unbounded preceding and 1 preceding), 0)) as t from {_RAYS})
  window w as (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_shipdate rows between unbounded preceding and current row)""")
def q_running(spark, d):
    return fold.running_composite(_rays(spark, d), ["l_orderkey"], L5[1:]).select(*L5[:4], _r("run_a").alias("a"), _r("run_b").alias("b"))


_ROLL = f"""select {L4}, round(a * coalesce(a1, 1) * coalesce(a2, 1), 5) as a,
  round(case when a2 is not null then b2 + a2 * (b1 + a1 * b) when a1 is not null then b1 + a1 * b else b end, 5) as b
  from (select *, lag(a) {_OVER} as a1, lag(b) {_OVER} as b1, lag(a, 2) {_OVER} as a2, lag(b, 2) {_OVER} as b2 from {_RAYS})"""


@_q(_ROLL)
def q_rolling_inverse(spark, d):
    return fold.rolling_composite(_rays(spark, d), ["l_orderkey"], L5[1:], 3).select(*L5[:4], _r("roll_a", 5).alias("a"), _r("roll_b", 5).alias("b"))


@_q(_ROLL)
def q_rolling_refold(spark, d):
    return fold.rolling_composite(_rays(spark, d), ["l_orderkey"], L5[1:], 3, 2.0).select(*L5[:4], _r("roll_a", 5).alias("a"), _r("roll_b", 5).alias("b"))


def _spans(spark, d):
    z = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1992-01-01").cast("date")).cast("double")
    x = _t(spark, d, "lineitem").select("l_partkey", *[c for c in L5 if c != "l_partkey"], z.alias("z_in"), (z + F.col("l_quantity")).alias("z_out"), F.exp(-F.col("l_quantity") / 50).alias("a"), F.col("l_discount").alias("b"))
    return x


_SPANS = f"(select {L4}, l_shipdate, datediff('day', date '1992-01-01', l_shipdate::date)::double as z_in, datediff('day', date '1992-01-01', l_shipdate::date)::double + l_quantity as z_out, exp(-l_quantity / 50) as a, l_discount as b from lineitem)"
_CELLS = f"""with s as {_SPANS}, e as (select l_partkey, z_in as lo from s union select l_partkey, z_out from s),
  c as (select *, lead(lo) over (partition by l_partkey order by lo) as hi from e),
  m as (select c.l_partkey, lo, hi, power(a, (hi - lo) / (z_out - z_in)) as pa, b * (1 - power(a, (hi - lo) / (z_out - z_in))) / (1 - a) as pb
    from c join s on c.l_partkey = s.l_partkey and z_in < hi and z_out > lo where hi is not null)"""


@_q(_CELLS + " select l_partkey, lo as z_in, hi as z_out, round(exp(avg(ln(pa))), 6) as a, round(avg(pb), 6) as b, count(*) as covers from m group by l_partkey, lo, hi")
def q_overlap_resolve(spark, d):
    return fold.resolve_overlaps(_spans(spark, d), ["l_partkey"]).select("l_partkey", "z_in", "z_out", _r("a").alias("a"), _r("b").alias("b"), "covers")


@_q(_CELLS + """ select l_partkey, z_in, z_out, round(exp(-be * x), 6) as a, round(ga / be * (1 - exp(-be * x)), 6) as b from (
  select l_partkey, lo as z_in, hi as z_out, hi - lo as x, avg(-ln(pa) / (hi - lo)) as be, avg(-ln(pa) / (hi - lo) * pb / (1 - pa)) as ga from m group by l_partkey, lo, hi)""")
def q_overlap_limit(spark, d):
    return fold.resolve_overlaps(_spans(spark, d), ["l_partkey"], "limit").select("l_partkey", "z_in", "z_out", _r("a").alias("a"), _r("b").alias("b"))


@_q(f"""with s as (select *, max(z_out) over (partition by l_partkey order by z_in, l_orderkey, l_linenumber, l_suppkey rows between unbounded preceding and 1 preceding) as reach from {_SPANS}),
  g as (select *, sum(case when reach is null or z_in > reach then 1 else 0 end) over (partition by l_partkey order by z_in, l_orderkey, l_linenumber, l_suppkey rows unbounded preceding) as run from s)
  select l_partkey, run::bigint as run, min(z_in) as z_in, max(z_out) as z_out, round(exp(sum(ln(a))), 6) as a, count(*) as k from g group by l_partkey, run""")
def q_fold_touching(spark, d):
    x = fold.fold_touching(_spans(spark, d), ["l_partkey"], ["l_orderkey", "l_linenumber", "l_suppkey"])
    return x.select("l_partkey", "run", "z_in", "z_out", _r("a").alias("a"), "k")


# one-step rules on linear media beta = b0 + b1 x, gamma = g0 + g1 x over [0, h]
def _linear(spark, d):
    k = F.coalesce(F.get_json_object("props", "$.k").cast("double"), F.lit(0.0))
    return _t(spark, d, "events").select("event_id", (0.2 + F.col("value") / 500).alias("b0"), (k / 20).alias("b1"), (1 + k / 10).alias("g0"), (F.col("value") / 1000).alias("g1"), (0.1 + F.col("value") / 1000).alias("h"))


_LIN = "(select event_id, 0.2 + value / 500 as b0, coalesce(cast(json_extract_string(props, '$.k') as double), 0) / 20 as b1, 1 + coalesce(cast(json_extract_string(props, '$.k') as double), 0) / 10 as g0, value / 1000 as g1, 0.1 + value / 1000 as h from events)"


def _rule(method, sql_inner):
    def run(spark, d):
        be, ga = (lambda x: F.col("b0") + F.col("b1") * x), (lambda x: F.col("g0") + F.col("g1") * x)
        a, b = quadrature.step(method, be, ga, F.lit(0.0), F.col("h"))
        return _linear(spark, d).select("event_id", _r(a, 10).alias("a"), _r(b, 10).alias("b"))

    _q(f"select event_id, round(a, 10) as a, round(b, 10) as b from ({sql_inner})", f"q_step_{method}")(run)


_rule("euler", f"select event_id, 1 - h * b0 as a, h * g0 as b from {_LIN}")
_rule("heun2", f"select event_id, 1 - h / 2 * (b0 + (b0 + b1 * h) * (1 - h * b0)) as a, h / 2 * (g0 + g0 + g1 * h - (b0 + b1 * h) * h * g0) as b from {_LIN}")
_rule("heun3", f"select event_id, 1 - h * (b0 / 4 + 3 * p2 * (1 - 2 * h / 3 * p1 * (1 - h / 3 * b0)) / 4) as a, h * (g0 / 4 + 3 * (q2 - p2 * 2 * h / 3 * (q1 - p1 * h / 3 * g0)) / 4) as b from (select *, b0 + b1 * h / 3 as p1, b0 + b1 * 2 * h / 3 as p2, g0 + g1 * h / 3 as q1, g0 + g1 * 2 * h / 3 as q2 from {_LIN})")
_rule("rk4", f"""select event_id, 1 + h * (k1 + 2 * k2 + 2 * k3 + k4) / 6 as a, h * (m1 + 2 * m2 + 2 * m3 + m4) / 6 as b from (
  select *, -be * (1 + h * k3) as k4, ge - be * h * m3 as m4 from (select *, -bm * (1 + h / 2 * k2) as k3, gm - bm * h / 2 * m2 as m3 from (
  select *, -bm * (1 + h / 2 * k1) as k2, gm - bm * h / 2 * m1 as m2 from (select *, -b0 as k1, g0 as m1, b0 + b1 * h / 2 as bm, g0 + g1 * h / 2 as gm, b0 + b1 * h as be, g0 + g1 * h as ge from {_LIN}))))""")
_rule("gauss", f"""select event_id, (1 - a1 + a2) / (1 + a1 + a2) as a, (h * (s0 + s1) / 2 + h * h * (p0 * s1 - p1 * s0) * sqrt(3) / 12) / (1 + a1 + a2) as b from (select *, h * (p0 + p1) / 4 as a1, h * h * p0 * p1 / 12 as a2 from (
  select *, b0 + b1 * h * (0.5 - sqrt(3) / 6) as p0, b0 + b1 * h * (0.5 + sqrt(3) / 6) as p1, g0 + g1 * h * (0.5 - sqrt(3) / 6) as s0, g0 + g1 * h * (0.5 + sqrt(3) / 6) as s1 from {_LIN}))""")
_rule("simpson", f"select event_id, exp(-t) as a, h / 6 * (exp(-t) * g0 + 4 * exp(-t / 2) * (g0 + g1 * h / 2) + g0 + g1 * h) as b from (select *, h * b0 + b1 * h * h / 2 as t from {_LIN})")
_rule("simpson_half", f"select event_id, exp(-t) as a, h / 6 * (exp(-t) * g0 + 4 * exp(-u) * (g0 + g1 * h / 2) + g0 + g1 * h) as b from (select *, h * b0 + b1 * h * h / 2 as t, h / 2 * b0 + b1 * 3 * h * h / 8 as u from {_LIN})")


@_q("""with d as (select event_id, value / 100 as b, case when value / 100 <= 0.1 then 0 else ceil(log2(value / 100 / 0.1))::bigint end as depth from events), n as (select *, power(2.0, depth) as n, b / power(2.0, depth) as z from d),
  s as (select *, 1 - z + z * z / 2 - z * z * z / 6 + z * z * z * z / 24 as a1, (1 - z / 2 + z * z / 6 - z * z * z / 24) / n as b1 from n)
  select event_id, depth, round(power(a1, n), 7) as a, round(case when a1 = 1 then b1 * n else b1 * (1 - power(a1, n)) / (1 - a1) end, 7) as b from s""")
def q_adaptive_depth(spark, d):
    """The recursion with RK4 on one medium an event: halvings, and the segment that the equal pieces fold to."""
    x = _t(spark, d, "events").select(F.col("event_id").alias("id"), F.lit(0.0).alias("x1"), F.lit(1.0).alias("x2"), (F.col("value") / 100).alias("b0"), F.lit(0.0).alias("z"), F.lit(1.0).alias("g0"))
    return quadrature.adaptive(x, "rk4", 0.1, ["b0", "z", "g0", "z"]).select(F.col("id").alias("event_id"), "depth", _r("a", 7).alias("a"), _r("b", 7).alias("b"))


def _cells(spark, d):
    e = _t(spark, d, "embeddings").select("vec_id", *[sfc.cell(F.element_at("embedding", i + 1).cast("double") + 0.5, TOP).alias(c) for i, c in enumerate("xyz")])
    return e.select("vec_id", F.lit(0).alias("tree"), sfc.morton3(F.col("x"), F.col("y"), F.col("z")).alias("key"))


_BITS = " + ".join(f"(((x >> {i}) & 1) << {3 * i}) + (((y >> {i}) & 1) << {3 * i + 1}) + (((z >> {i}) & 1) << {3 * i + 2})" for i in range(TOP))
_KEYS = f"(select vec_id, {_BITS} as key from (select vec_id, " + ", ".join(f"least(1023, greatest(0, floor((embedding[{i + 1}]::double + 0.5) * 1024)))::bigint as {c}" for i, c in enumerate("xyz")) + " from embeddings))"


@_q(f"select vec_id, key, key >> 21 as p3, (key >> 21) & 7 as child from {_KEYS}")
def q_morton(spark, d):
    return _cells(spark, d).select("vec_id", "key", sfc.prefix(F.col("key"), 3, TOP).alias("p3"), sfc.child_id(F.col("key"), 3, TOP).alias("child"))


_LEAVES = f"""with p as {_KEYS}, u as (select l.level, key >> (3 * ({TOP} - l.level))::int as p, count(*) as n from p, (select unnest(range(0, {TOP + 1})) as level) l group by 1, 2),
  leaf as (select u.level, u.p, u.n from u left join u o on o.level = u.level - 1 and o.p = u.p >> 3 where (u.n <= 8 or u.level = {TOP}) and (u.level = 0 or o.n > 8))"""


def _leaves(spark, d, cap=8):
    return forest.from_points(_cells(spark, d), cap, TOP)


@_q(_LEAVES + f" select level, p << (3 * ({TOP} - level))::int as key, n from leaf")
def q_from_points(spark, d):
    return _leaves(spark, d).select(F.col("level").cast("bigint").alias("level"), "key", "n")


_FULL = _LEAVES + """, anc as (select distinct a.level, leaf.p >> (3 * (leaf.level - a.level))::int as p from leaf, (select unnest(range(0, 11)) as level) a where a.level < leaf.level),
  kid as (select level + 1 as level, p * 8 + c.c as p from anc, (select unnest(range(0, 8)) as c) c),
  fill as (select * from kid k where not exists (select 1 from anc where anc.level = k.level and anc.p = k.p) and not exists (select 1 from leaf where leaf.level = k.level and leaf.p = k.p)),
  full_ as (select level, p, false as filled from leaf union all select level, p, true from fill)"""


@_q(_FULL + f" select level, p << (3 * ({TOP} - level))::int as key, filled from full_")
def q_complete(spark, d):
    return forest.complete(_leaves(spark, d), TOP).select(F.col("level").cast("bigint").alias("level"), "key", "filled")


@_q(_FULL + " select 0 as tree, 1.0::double as volume, 0::bigint as overlaps, count(*) as leaves from full_")
def q_check_volume(spark, d):
    return forest.check(forest.complete(_leaves(spark, d), TOP), TOP)


@_q(_FULL + f""", fam as (select level, p >> 3 as q from full_ where level > 0 group by 1, 2 having count(*) = 8)
  select level - 1 as level, q << (3 * ({TOP} + 1 - level))::int as key, true as merged from fam
  union all select f.level, p << (3 * ({TOP} - f.level))::int, false from full_ f where not exists (select 1 from fam where fam.level = f.level and fam.q = f.p >> 3)""")
def q_coarsen(spark, d):
    full = forest.complete(_leaves(spark, d), TOP).select("tree", "level", "key")
    return forest.coarsen(full, TOP).select(F.col("level").cast("bigint").alias("level"), "key", "merged")


@_q(_LEAVES + f" select vec_id, leaf.level as leaf_level, leaf.p << (3 * ({TOP} - leaf.level))::int as leaf_key from p join leaf on p.key >> (3 * ({TOP} - leaf.level))::int = leaf.p")
def q_locate(spark, d):
    return forest.locate(_cells(spark, d), _leaves(spark, d), TOP).select("vec_id", F.col("leaf_level").cast("bigint").alias("leaf_level"), "leaf_key")


_PID = _LEAVES + f""", w as (select p << (3 * ({TOP} - level))::int as key, n, coalesce(sum(n) over (order by p << (3 * ({TOP} - level))::int rows between unbounded preceding and 1 preceding), 0) as before, sum(n) over () as total from leaf),
  own as (select key, n, least(7, (before * 8) // total)::int as pid from w)"""


@_q(_PID + " select key, n, pid from own")
def q_weighted_partition(spark, d):
    return forest.with_owner(_leaves(spark, d), "n", 8).select("key", "n", "pid")


@_q(_PID + " select pid, 0 as tree, min(key) as key from own group by pid")
def q_markers(spark, d):
    return forest.markers(forest.with_owner(_leaves(spark, d), "n", 8))


@_q(_PID + " select round(max(s) * 8.0 / sum(s), 6) as imbalance, sum(s)::bigint as total from (select sum(n) as s from own group by pid)")
def q_imbalance(spark, d):
    s = forest.with_owner(_leaves(spark, d), "n", 8).groupBy("pid").agg(F.sum("n").alias("s"))
    return s.agg(_r(F.max("s") * 8.0 / F.sum("s")).alias("imbalance"), F.sum("s").alias("total"))


_SPLIT = ", ".join(f"({' + '.join(f'(((p >> {3 * i + a}) & 1) << {i})' for i in range(TOP))})::bigint as {c}" for a, c in enumerate("xyz"))


@_q(_LEAVES.replace("with p as", "with recursive p as", 1) + f""", anc as (select distinct a.level, leaf.p >> (3 * (leaf.level - a.level))::int as p from leaf, (select unnest(range(0, 11)) as level) a where a.level < leaf.level),
  split as (select level, {_SPLIT} from anc union select level - 1, (x + i.i) >> 1, (y + j.j) >> 1, (z + k.k) >> 1 from split, range(-1, 2) i(i), range(-1, 2) j(j), range(-1, 2) k(k)
    where level > 0 and x + i.i between 0 and (1 << level::int) - 1 and y + j.j between 0 and (1 << level::int) - 1 and z + k.k between 0 and (1 << level::int) - 1),
  kid as (select level + 1 as level, 2 * x + i.i as x, 2 * y + j.j as y, 2 * z + k.k as z from split, range(2) i(i), range(2) j(j), range(2) k(k))
  select level, x, y, z from kid where not exists (select 1 from split t where t.level = kid.level and t.x = kid.x and t.y = kid.y and t.z = kid.z)""")
def q_balance(spark, d):
    """The leaves of the balanced tree, as level and place; its twin closes the split nodes under neighbours of the parents."""
    full = forest.complete(_leaves(spark, d), TOP)
    x = forest.balance(full, TOP).withColumn("p", F.call_function("shiftright", F.col("key"), F.expr(f"cast(3 * ({TOP} - level) as int)")))
    return x.select(F.col("level").cast("bigint").alias("level"), *[sfc.coordinate(F.col("p"), a, TOP).alias(c) for a, c in enumerate("xyz")])


@_q(_FULL + " select level, count(*) as leaves, sum(case when filled then 1 else 0 end)::bigint as filled from full_ group by rollup(level)")
def q_tree_census_rollup(spark, d):
    x = forest.complete(_leaves(spark, d), TOP).select(F.col("level").cast("bigint").alias("level"), "filled")
    return x.rollup("level").agg(F.count("*").alias("leaves"), F.sum(F.when(F.col("filled"), 1).otherwise(0)).alias("filled"))


_SPH = "(select p_partkey, " + ", ".join(f"((p_partkey * 2654435761 + {s} * 40503) % 4294967296) / 4294967296.0 as c{c}" for s, c in zip((1, 2, 3), "xyz")) + ", sqrt(0.001 * power(100.0, (p_size - 0.5) / 50) / pi()) as r from part)"


def _spheres(spark, d):
    r = F.sqrt(scenes.section((F.col("p_size") - 0.5) / 50) / F.pi())
    return _t(spark, d, "part").select("p_partkey", *[scenes.uniform01(F.col("p_partkey"), s).alias(f"c{c}") for s, c in zip((1, 2, 3), "xyz")], r.alias("r"))


@_q(f"select p_partkey, round(cx, 6) as cx, round(r, 6) as r from {_SPH}")
def q_spheres_size(spark, d):
    return _spheres(spark, d).select("p_partkey", _r("cx").alias("cx"), _r("r").alias("r"))


@_q(f"""select p_partkey, round(-b - sqrt(b * b - k), 6) as near, round(-b + sqrt(b * b - k), 6) as far from (select p_partkey, -(cz + 1) as b, (0.5 - cx) * (0.5 - cx) + (0.5 - cy) * (0.5 - cy) + (cz + 1) * (cz + 1) - r * r as k from {_SPH}) where b * b - k >= 0""")
def q_hit_sphere(spark, d):
    n, f = G.hit_sphere([F.col("cx"), F.col("cy"), F.col("cz")], F.col("r"), [F.lit(0.5), F.lit(0.5), F.lit(-1.0)], [F.lit(0.0), F.lit(0.0), F.lit(1.0)])
    return _spheres(spark, d).select("p_partkey", _r(n).alias("near"), _r(f).alias("far")).filter("near is not null")


@_q(f"""with c as (select x.x, y.x as y, z.x as z from range(8) x(x), range(8) y(x), range(8) z(x)),
  h as (select c.x, c.y, c.z, r, power(greatest(c.x / 8.0 - cx, cx - (c.x + 1) / 8.0, 0), 2) + power(greatest(c.y / 8.0 - cy, cy - (c.y + 1) / 8.0, 0), 2) + power(greatest(c.z / 8.0 - cz, cz - (c.z + 1) / 8.0, 0), 2) as near,
    power(greatest(abs(cx - c.x / 8.0), abs(cx - (c.x + 1) / 8.0)), 2) + power(greatest(abs(cy - c.y / 8.0), abs(cy - (c.y + 1) / 8.0)), 2) + power(greatest(abs(cz - c.z / 8.0), abs(cz - (c.z + 1) / 8.0)), 2) as far from c, {_SPH})
  select x, y, z, count(*) as spheres from h where near <= power(r * 1.05, 2) and far >= power(r * 0.95, 2) group by x, y, z""")
def q_shell_refine(spark, d):
    """Elements of an 8 x 8 x 8 mesh that shells of spheres meet: candidate cells from each sphere's
    bounds, then the exact test."""
    s = _spheres(spark, d)
    ends = {c: F.sequence(F.greatest(F.floor((F.col(f"c{c}") - F.col("r") * 1.05) * 8), F.lit(0)), F.least(F.floor((F.col(f"c{c}") + F.col("r") * 1.05) * 8), F.lit(7))) for c in "xyz"}
    for c in "xyz":
        s = s.withColumn(c, F.explode(ends[c]))
    meets = scenes.shell_meets_box([F.col("cx"), F.col("cy"), F.col("cz")], F.col("r"), [F.col(c) / 8 for c in "xyz"], [(F.col(c) + 1) / 8 for c in "xyz"], 0.05)
    return s.filter(meets).groupBy("x", "y", "z").agg(F.count("*").alias("spheres"))


@_q("""with recursive c as (select distinct (l_quantity - 1) / 49 * 3.6 - 2.3 as cr, floor((l_extendedprice - 900) / 104100 * 64) / 64 * 3.6 - 1.8 as ci from lineitem),
  z as (select cr, ci, 0.0::double as x, 0.0::double as y, 0 as n, false as out from c union all
    select cr, ci, case when x * x + y * y > 4 then x else x * x - y * y + cr end, case when x * x + y * y > 4 then y else 2 * x * y + ci end, n + 1, x * x + y * y > 4 from z where n < 30)
  select round(cr, 6) as cre, round(ci, 6) as cim, sum(case when n > 0 and not out then 1 else 0 end)::int as steps from z group by cr, ci""")
def q_fractal_iter(spark, d):
    c = _t(spark, d, "lineitem").select(((F.col("l_quantity") - 1) / 49 * 3.6 - 2.3).alias("cr"), (F.floor((F.col("l_extendedprice") - 900) / 104100 * 64) / 64 * 3.6 - 1.8).alias("ci")).distinct()
    return c.select(_r("cr").alias("cre"), _r("ci").alias("cim"), scenes.escape_steps(F.col("cr"), F.col("ci")).cast("int").alias("steps"))


def _pixels(spark, d):
    x = F.least(F.lit(63), F.floor((F.col("l_quantity") - 1) / 49 * 64)).cast("long")
    y = F.least(F.lit(63), F.floor((F.col("l_extendedprice") - 900) / 104100 * 64)).cast("long")
    return _t(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", x.alias("i"), y.alias("j"), sfc.morton2(x, y).alias("pix"), F.exp(-F.col("l_quantity") / 50).alias("a"), F.col("l_discount").alias("b"))


@_q(f"select {L4}, i, j, round(0.1 + (i - 31.5) / 16, 6) as rx, round((j - 31.5) / 16, 6) as ry, 1.0::double as rz from (select *, least(63, floor((l_quantity - 1) / 49 * 64))::bigint as i, least(63, floor((l_extendedprice - 900) / 104100 * 64))::bigint as j from lineitem)")
def q_ray_dir(spark, d):
    """The direction of each line item's ray, by its pixel."""
    r = G.ray_dir(F.col("i"), F.col("j"), 64, 64, 1 / 16, (0.1, 0.0, 1.0), (1, 0, 0), (0, 1, 0))
    return _pixels(spark, d).select(*L5[:4], "i", "j", *[_r(x).alias(n) for x, n in zip(r, ("rx", "ry", "rz"))])


_P2 = " + ".join(f"(((i >> {k}) & 1) << {2 * k}) + (((j >> {k}) & 1) << {2 * k + 1})" for k in range(6))
_PIX = f"(select *, {_P2} as pix from (select *, exp(-l_quantity / 50) as a, l_discount as b, least(63, floor((l_quantity - 1) / 49 * 64))::bigint as i, least(63, floor((l_extendedprice - 900) / 104100 * 64))::bigint as j from lineitem))"


@_q(f"select pix >> 8 as tile, count(distinct pix) as pixels, count(*) as segments from {_PIX} group by 1")
def q_tile_counts(spark, d):
    x = _pixels(spark, d).withColumn("tile", imagetree.tile_of(F.col("pix"), 4)).groupBy("tile", "pix").agg(F.count("*").alias("n"))
    return x.groupBy("tile").agg(F.count("*").alias("pixels"), F.sum("n").alias("segments"))


_PIXFOLD = f"""select pix, exp(sum(ln(a))) as a, sum(t * b) as b from (select *, exp(coalesce(sum(ln(a)) over (partition by pix order by l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate
  rows between unbounded preceding and 1 preceding), 0)) as t from {_PIX}) group by pix"""


@_q(f"select pix >> 8 as tile, pix, round(a, 6) as a, round(b, 6) as b from ({_PIXFOLD})")
def q_final_composite(spark, d):
    x = _pixels(spark, d).withColumn("tile", imagetree.tile_of(F.col("pix"), 4))
    return fold.composite(x, ["tile", "pix"], L5).select("tile", "pix", _r("a").alias("a"), _r("b").alias("b"))


@_q(f"""select g.i, g.j, round(coalesce(a, 1) * case when (g.i // 8 + g.j // 8) % 2 = 0 then 0.25 else 0.75 end + coalesce(b, 0), 6) as v from
  (select i, j, {_P2} as pix from range(64) x(i), range(64) y(j)) g left join ({_PIXFOLD}) f on g.pix = f.pix""")
def q_skybox(spark, d):
    """All pixels; those without segments show the checkerboard sky."""
    g = spark.range(4096).select((F.col("id") % 64).alias("i"), F.floor(F.col("id") / 64).alias("j"))
    f = fold.composite(_pixels(spark, d), ["pix"], L5)
    x = g.withColumn("pix", sfc.morton2(F.col("i"), F.col("j"))).join(f, "pix", "left")
    return x.select("i", "j", _r(F.coalesce("a", F.lit(1.0)) * pipeline.checkerboard(F.col("i"), F.col("j")) + F.coalesce("b", F.lit(0.0))).alias("v"))


@_q(f"select pix >> 8 as tile, count(distinct pix)::int as pixels, count(*)::int as segments, round(sum(a), 4) as total from {_PIX} group by 1")
def q_pixel_pack(spark, d):
    x = _pixels(spark, d).select(imagetree.tile_of(F.col("pix"), 4).alias("tile"), "pix", F.col("l_orderkey").cast("double").alias("z"), "a", "b")
    p = imagetree.pack(x, ["tile"])
    return p.select("tile", F.size("pix").alias("pixels"), F.element_at("offs", -1).alias("segments"), _r(F.aggregate("a", F.lit(0.0), lambda s, v: s + v), 4).alias("total"))


def _scene(spark, d):
    p = _cells(spark, d).join(_t(spark, d, "embeddings").select("vec_id", F.col("label").cast("double").alias("label")), "vec_id")
    leaves = _leaves(spark, d)
    at = forest.locate(p, leaves, TOP).groupBy("tree", F.col("leaf_level").alias("level"), F.col("leaf_key").alias("key"))
    return at.agg((F.avg("label") / 3 + 0.5).alias("beta"), F.avg(F.col("label") / 9).alias("gamma"))


@_q()
def q_render_pipeline(spark, d):
    """The flagship: points to forest to pixels of two cameras, by all phases: descent, culling, transfer by pixels, rendering,
    condensing, tiles."""
    x = pipeline.render_pipeline(_scene(spark, d), pipeline.front_cameras(2), TOP, depth=2, parts=8)
    return x.select("inst", "tile", "pix", _r("a").alias("a"), _r("b").alias("b"))


def q_condense_lossless(spark, d):
    """Pixels whose composite after three condense cycles is off that of the raw segments by more than roundoff."""
    cams = pipeline.front_cameras(2, 32)
    raw = forest.cut(pipeline.render(pipeline.visible_leaves(_scene(spark, d), cams, TOP), cams))
    x = pipeline.image(raw)
    y = pipeline.image(pipeline.condense(raw, TOP, 3)).select("inst", "pix", F.col("a").alias("a2"), F.col("b").alias("b2"))
    j = x.join(y, ["inst", "pix"], "full")
    off = (F.abs(F.col("a") - F.col("a2")) > 1e-9) | (F.abs(F.col("b") - F.col("b2")) > 1e-9) | F.col("a").isNull() | F.col("a2").isNull()
    return j.agg(F.count("*").alias("pixels"), F.coalesce(F.sum(F.when(off, 1).otherwise(0)), F.lit(0)).cast("int").alias("differ"))


@_q("""select user_id, time_bucket(interval 30 days, ts, timestamp '1970-01-01') as start, round(exp(sum(ln(a))), 6) as a, round(sum(t * b), 6) as b, count(*) as k from (select *, exp(coalesce(sum(ln(a)) over
  (partition by user_id, time_bucket(interval 30 days, ts, timestamp '1970-01-01') order by ts, event_id rows between unbounded preceding and 1 preceding), 0)) as t from (select *, exp(-value / 500) as a, (1 - exp(-value / 500)) / 2 as b from events)) group by 1, 2""")
def q_window_tumbling(spark, d):
    """The batch twin of the streaming window composite."""
    from .streaming.composite import windowed

    x = _events(spark, d).withColumn("ts", F.col("ts").cast("timestamp")).withColumnRenamed("event_id", "tie")
    w = windowed(x, ["user_id"], "ts", "30 days", "1 hour")
    return w.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), _r("a").alias("a"), _r("b").alias("b"), "k")
