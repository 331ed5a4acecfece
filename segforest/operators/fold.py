"""Ordered folds of segments along rays. Input has columns ``rays`` + ``order`` + a, b."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.algebra import seg, seg_combine, seg_identity


def _log(a: Column) -> Column:
    return F.when(a > 0, F.ln(F.nullif(a, F.lit(0.0)))).otherwise(0.0)


def composite(df: DataFrame, rays: list[str], order: list[str], how: str = "scan", levels: list[str] | None = None, extra: dict[str, Column] | None = None) -> DataFrame:
    """One segment per ray: rays, a, b, k (segments folded). ``order`` must be total, near first.

    scan: running sums of ln a give the transmittance in front of each segment; one exchange on the rays, spills.
    array: gathers a ray's segments in an array; for short rays.
    levels: ``levels`` are columns, coarse to fine, that cut each ray into contiguous runs (hot rays);
    runs fold first, then the partial segments, so no task holds a whole hot ray.
    ``extra`` (scan only) names further aggregates of a ray.
    Segments with null or negative a are an error of the caller and give null."""
    if how == "array":
        items = F.array_sort(F.collect_list(F.struct(*order, "a", "b")))
        g = df.groupBy(*rays).agg(items.alias("s"))
        f = F.aggregate("s", seg_identity(), lambda acc, s: seg_combine(acc, seg(s["a"], s["b"])))
        return g.select(*rays, f["a"].alias("a"), f["b"].alias("b"), F.size("s").cast("long").alias("k"))
    if how == "levels":
        # one exchange brings the runs of the coarsest level together; finer ones fold inside it, and one more joins its ends
        out, first = df.withColumn("_k", F.lit(1).cast("long")).repartition(*rays, *levels[:1]), order
        for depth in range(len(levels), -1, -1):
            keys = [*rays, *levels[:depth]]
            inner = _scan(out, keys, first, "_k")
            first = [c for c in [f"_z{i}" for i in range(len(order))]]
            out = inner
        return out.select(*rays, "a", "b", F.col("_k").alias("k"))
    return _scan(df.withColumn("_k", F.lit(1).cast("long")), rays, order, "_k", extra).select(*rays, "a", "b", F.col("_k").alias("k"), *(extra or {}))


def _scan(df: DataFrame, keys: list[str], order: list[str], count: str, extra: dict[str, Column] | None = None) -> DataFrame:
    w = Window.partitionBy(*keys).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    front = F.when(F.coalesce(F.sum(F.when(F.col("a") == 0, 1).otherwise(0)).over(w), F.lit(0)) > 0, 0.0).otherwise(F.exp(F.coalesce(F.sum(_log(F.col("a"))).over(w), F.lit(0.0))))
    x = df.withColumn("_t", front)
    whole = F.when(F.min("a") == 0, 0.0).otherwise(F.exp(F.sum(_log(F.col("a")))))
    firsts = F.min(F.struct(*[F.col(c).alias(f"_z{i}") for i, c in enumerate(order)])).alias("_first")
    out = x.groupBy(*keys).agg(whole.alias("_a"), F.sum(F.col("_t") * F.col("b")).alias("_b"), F.sum(count).alias("_n"), firsts, *(c.alias(k) for k, c in (extra or {}).items()))
    return out.select(*keys, F.col("_a").alias("a"), F.col("_b").alias("b"), F.col("_n").alias(count), "_first.*", *(extra or {}))


def running_composite(df: DataFrame, rays: list[str], order: list[str]) -> DataFrame:
    """Each row with the fold of its ray up to it: run_a, run_b."""
    w = Window.partitionBy(*rays).orderBy(*order)
    before, here = w.rowsBetween(Window.unboundedPreceding, -1), w.rowsBetween(Window.unboundedPreceding, 0)
    zero = F.when(F.col("a") == 0, 1).otherwise(0)
    front = F.when(F.coalesce(F.sum(zero).over(before), F.lit(0)) > 0, 0.0).otherwise(F.exp(F.coalesce(F.sum(_log(F.col("a"))).over(before), F.lit(0.0))))
    x = df.withColumn("_t", front)
    whole = F.when(F.sum(zero).over(here) > 0, 0.0).otherwise(F.exp(F.sum(_log(F.col("a"))).over(here)))
    return x.withColumn("run_a", whole).withColumn("run_b", F.sum(F.col("_t") * F.col("b")).over(here)).drop("_t")


def rolling_composite(df: DataFrame, rays: list[str], order: list[str], rows: int, least: float = 1e-6) -> DataFrame:
    """Fold of the last ``rows`` segments of each row's ray: roll_a, roll_b, by the group inverse of the prefix before the window.

    Prefixes start anew at every ``rows`` rows, so that they do not get dark along a ray: a window is the rest of one run
    (its end folded backwards) and the beginning of the next, for which the inverse of that run's prefix suffices. Only where
    that prefix is darker than ``least``, or opaque, is the rest taken from a fold from the run's end."""
    w = Window.partitionBy(*rays).orderBy(*order)
    x = df.withColumn("_n", F.row_number().over(w) - 1)
    x = running_composite(x.withColumn("_run", F.floor(F.col("_n") / rows)), [*rays, "_run"], order)
    # the run's suffix after each row, folded from its end: the same scan backwards
    run = Window.partitionBy(*rays, "_run").orderBy(*order)
    back = run.rowsBetween(1, Window.unboundedFollowing)
    dim = F.when(F.coalesce(F.sum(F.when(F.col("a") == 0, 1).otherwise(0)).over(back), F.lit(0)) > 0, 0.0).otherwise(F.exp(F.coalesce(F.sum(_log(F.col("a"))).over(back), F.lit(0.0))))
    whole = F.last(F.struct("run_a", "run_b")).over(run.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    x = x.withColumn("_rest_a", dim).withColumn("_all", whole)
    # prefix + rest = whole, so rest = inverse(prefix) + whole
    pa = F.nullif(F.col("run_a"), F.lit(0.0))
    x = x.withColumn("_rest_b", F.when(F.col("run_a") >= least, (F.col("_all.run_b") - F.col("run_b")) / pa))
    return _with_dark_rests(x, rays, order, rows).drop("_n", "_run", "_rest_a", "_rest_b", "_all", "run_a", "run_b")


def _with_dark_rests(x: DataFrame, rays: list[str], order: list[str], rows: int) -> DataFrame:
    """roll_a, roll_b from the run's prefix at a row and the rest of the run before; a rest that its dark prefix hides is
    folded from the segments themselves, gathered for those rows alone."""
    w, run = Window.partitionBy(*rays).orderBy(*order), Window.partitionBy(*rays, "_run").orderBy(*order)
    dark = F.max(F.col("_rest_b").isNull()).over(run.rowsBetween(Window.unboundedPreceding, 0))  # here or before, in the run
    x = x.withColumn("_d", F.when(dark, F.struct("a", "b")))
    x = x.withColumn("_w", F.collect_list("_d").over(run.rowsBetween(1, Window.unboundedFollowing)))
    again = F.aggregate("_w", seg_identity(), lambda acc, s: seg_combine(acc, s))
    x = x.withColumn("_rest_b", F.coalesce("_rest_b", again["b"])).drop("_w", "_d")
    rest = F.lag(F.struct(F.col("_rest_a").alias("a"), F.col("_rest_b").alias("b")), rows).over(w)
    s = seg_combine(F.coalesce(rest, seg_identity()), seg(F.col("run_a"), F.col("run_b")))
    return x.withColumn("_s", s).withColumn("roll_a", F.col("_s.a")).withColumn("roll_b", F.col("_s.b")).drop("_s")


def fold_touching(df: DataFrame, rays: list[str], order: list[str], tol: float = 0.0) -> DataFrame:
    """Folds runs of segments that touch (z_in within tol of the end so far): rays, run, z_in, z_out, a, b, k."""
    w = Window.partitionBy(*rays).orderBy("z_in", *order)
    reach = F.max("z_out").over(w.rowsBetween(Window.unboundedPreceding, -1))
    x = df.withColumn("_new", F.when(reach.isNull() | (F.col("z_in") > reach + tol), 1).otherwise(0))
    x = x.withColumn("run", F.sum("_new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    spans = x.groupBy(*rays, "run").agg(F.min("z_in").alias("z_in"), F.max("z_out").alias("z_out"))
    return composite(x, [*rays, "run"], ["z_in", *order]).join(spans, [*rays, "run"])


def resolve_overlaps(df: DataFrame, rays: list[str], mode: str = "printed") -> DataFrame:
    """Cuts segments (z_in < z_out) at all end points of their ray and averages what covers an interval:
    rays, z_in, z_out, a, b, covers. Intervals that nothing covers give no row. ``printed``: geometric mean of A,
    arithmetic of B; ``limit``: mean coefficients."""
    # a ray's span in buckets of about 64 segments: a cell meets the segments of the bucket where it begins, so a hot ray is no one group
    ray = Window.partitionBy(*rays)
    x = df.withColumn("_lo", F.min("z_in").over(ray)).withColumn("_wide", (F.max("z_out").over(ray) - F.col("_lo")) / F.ceil(F.count("*").over(ray) / 64))
    ends = x.select(*rays, "_lo", "_wide", F.explode(F.array("z_in", "z_out")).alias("lo")).distinct()
    w = Window.partitionBy(*rays).orderBy("lo")
    bucket = lambda z: F.floor((F.col(z) - F.col("_lo")) / F.col("_wide"))
    cells = ends.withColumn("hi", F.lead("lo").over(w)).filter("hi is not null").withColumn("_bucket", bucket("lo"))
    s = x.withColumn("_bucket", F.explode(F.sequence(bucket("z_in"), bucket("z_out")))).alias("s")
    same = [F.col(f"s.{r}") == F.col(f"c.{r}") for r in [*rays, "_bucket"]]
    cover = cells.alias("c").join(s, [*same, F.col("s.z_in") < F.col("c.hi"), F.col("s.z_out") > F.col("c.lo")])
    q = (F.col("hi") - F.col("lo")) / (F.col("s.z_out") - F.col("s.z_in"))
    a, b = F.col("s.a"), F.col("s.b")
    pa = F.when(a == 0, 0.0).otherwise(F.pow(a, q))
    pb = F.when(a == 0, b).when(a == 1, b * q).otherwise(b * (1 - pa) / F.nullif(1 - a, F.lit(0.0)))
    x = cover.select(*[F.col(f"c.{r}").alias(r) for r in rays], "lo", "hi", pa.alias("a"), pb.alias("b"))
    if mode == "printed":
        agg = [F.when(F.min("a") == 0, 0.0).otherwise(F.exp(F.avg(_log(F.col("a"))))).alias("a"), F.avg("b").alias("b")]
    else:
        length = F.col("hi") - F.col("lo")
        beta = -_log(F.col("a")) / length
        gamma = F.when(F.col("a") == 1, F.col("b") / length).otherwise(beta * F.col("b") / F.nullif(1 - F.col("a"), F.lit(0.0)))
        x = x.withColumn("_be", beta).withColumn("_ga", gamma)
        be, ga, ln = F.avg("_be"), F.avg("_ga"), F.first(length)
        agg = [F.exp(-be * ln).alias("a"), F.when(be == 0, ga * ln).otherwise(-ga * F.expm1(-be * ln) / F.nullif(be, F.lit(0.0))).alias("b")]
    g = x.groupBy(*rays, "lo", "hi").agg(*agg, F.count("*").alias("covers"))
    return g.withColumnRenamed("lo", "z_in").withColumnRenamed("hi", "z_out")


def classic_composite(df: DataFrame, rays: list[str], order: list[str], background: str) -> DataFrame:
    """The baseline: each ray alone, far to near, from its background intensity: rays, i."""
    items = F.reverse(F.array_sort(F.collect_list(F.struct(*order, "a", "b"))))
    g = df.groupBy(*rays).agg(items.alias("s"), F.first(background).alias("_ib"))
    return g.select(*rays, F.aggregate("s", F.col("_ib").cast("double"), lambda i, s: s["a"] * i + s["b"]).alias("i"))


def composite_channels(df: DataFrame, rays: list[str], order: list[str], channels: list[str]) -> DataFrame:
    """One segment per ray and channel from columns a_c, b_c: rays, a_c, b_c, k. All channels share one exchange and one sort."""
    w = Window.partitionBy(*rays).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    x, aggs = df, []
    for c in channels:
        a = F.col(f"a_{c}")
        dark = F.coalesce(F.sum(F.when(a == 0, 1).otherwise(0)).over(w), F.lit(0)) > 0
        x = x.withColumn(f"_t_{c}", F.when(dark, 0.0).otherwise(F.exp(F.coalesce(F.sum(_log(a)).over(w), F.lit(0.0)))))
        aggs += [F.when(F.min(a) == 0, 0.0).otherwise(F.exp(F.sum(_log(a)))).alias(f"_a_{c}"), F.sum(F.col(f"_t_{c}") * F.col(f"b_{c}")).alias(f"_b_{c}")]
    g = x.groupBy(*rays).agg(*aggs, F.count("*").alias("k"))
    return g.select(*rays, *[F.col(f"_{s}_{c}").alias(f"{s}_{c}") for c in channels for s in "ab"], "k")


def peel(whole: Column, part: Column, end: str = "near") -> Column:
    """What is left of the fold ``whole`` without the segment ``part`` at its near or far end; null where part is opaque."""
    a = F.nullif(part["a"], F.lit(0.0))
    if end == "near":
        return F.when(part["a"] != 0, seg(whole["a"] / a, (whole["b"] - part["b"]) / a))
    rest = whole["a"] / a
    return F.when(part["a"] != 0, seg(rest, whole["b"] - rest * part["b"]))
