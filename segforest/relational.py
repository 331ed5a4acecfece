"""The relational operators around the methods, on the given tables, each as a query with its SQL twin."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .experiments import _CULLED, _visible
from .functions import algebra as A
from .operators import fold, forest
from .queries import _LEAVES, _RAYS, L4, L5, TOP, _events, _leaves, _q, _r, _rays, _t


@_q(f"select level, count(*) as leaves, sum(n)::bigint as points from ({_LEAVES} select * from leaf) group by level")
def q_sql_views(spark, d):
    """A forest as a view, asked in SQL text."""
    _leaves(spark, d).createOrReplaceTempView("segforest_leaves")
    return spark.sql("select cast(level as bigint) as level, count(*) as leaves, sum(n) as points from segforest_leaves group by level")


@_q("""select event_id, e.user_id, o_orderkey, round(date_diff('second', o_orderdate, ts), 0)::bigint as age from (select event_id, user_id, ts from events) e asof left join
  (select o_custkey, o_orderdate, max(o_orderkey) as o_orderkey from orders group by 1, 2) o on e.user_id = o.o_custkey and e.ts >= o.o_orderdate""")
def q_asof_order(spark, d):
    """Each event with its user's last order before it: both in one sort by user and time, the last order carried on."""
    o = _t(spark, d, "orders").groupBy(F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("ts")).agg(F.max("o_orderkey").alias("o"))
    o = o.select("user_id", "ts", F.lit(None).cast("long").alias("event_id"), F.struct(F.col("o").alias("o_orderkey"), F.col("ts").alias("at")).alias("last"))
    e = _t(spark, d, "events").select("user_id", "ts", "event_id").withColumn("last", F.lit(None).cast(o.schema["last"].dataType))
    w = Window.partitionBy("user_id").orderBy("ts", F.col("event_id").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    x = o.unionByName(e).withColumn("last", F.last("last", ignorenulls=True).over(w)).filter("event_id is not null")
    return x.select("event_id", "user_id", "last.o_orderkey", F.expr("timestampdiff(second, last.at, ts)").alias("age"))


@_q(_LEAVES + f" select level + 1 as level, (p * 8 + c.c) << (3 * ({TOP} - 1 - level))::int as key from leaf, range(8) c(c) where level < {TOP} and n > 2")
def q_lateral_children(spark, d):
    """Children of leaves by a table function that SQL text joins laterally."""
    spark.sql(f"create or replace temporary function children(node_level int, node_key bigint) returns table (level int, key bigint) return select node_level + 1, node_key + c * cast(power(2, 3 * ({TOP} - node_level - 1)) as bigint) from (select explode(sequence(0, 7)) as c)")
    x = _leaves(spark, d).filter((F.col("level") < TOP) & (F.col("n") > 2)).select(F.col("level").cast("int").alias("l"), F.col("key").alias("k"))
    return spark.sql("select cast(c.level as bigint) as level, c.key from {x} x, lateral children(x.l, x.k) c", x=x)


@_q("select l_returnflag, count(distinct l_partkey) as parts, true as near from lineitem group by 1")
def q_approx_distinct(spark, d):
    """Distinct parts by flag, and whether the sketch comes within a tenth."""
    g = _t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.approx_count_distinct("l_partkey", 0.02).alias("about"))
    return g.select("l_returnflag", "parts", (F.abs(F.col("about") - F.col("parts")) <= 0.1 * F.col("parts")).alias("near"))


@_q(_CULLED + " select inst, level, count(*) as leaves, sum(npix)::bigint as pixels, grouping(inst)::int as all_inst, grouping(level)::int as all_levels from v group by cube (inst, level)")
def q_visible_cube(spark, d):
    """Visible leaves and pixels by camera, by level, by both and in all."""
    g = _visible(spark, d).select("inst", F.col("level").cast("bigint").alias("level"), "npix").cube("inst", "level")
    return g.agg(F.count("*").alias("leaves"), F.sum("npix").alias("pixels"), F.grouping("inst").cast("int").alias("all_inst"), F.grouping("level").cast("int").alias("all_levels"))


@_q("select l_returnflag, l_linestatus, count(*) as k, round(sum(l_quantity), 2) as total from lineitem group by grouping sets ((l_returnflag), (l_linestatus), ())")
def q_grouping_sets(spark, d):
    x = _t(spark, d, "lineitem")
    return spark.sql("select l_returnflag, l_linestatus, count(*) as k, round(sum(l_quantity), 2) as total from {x} group by grouping sets ((l_returnflag), (l_linestatus), ())", x=x)


@_q("select l_returnflag, round(quantile_cont(l_extendedprice, 0.25), 4) as q1, round(quantile_cont(l_extendedprice, 0.5), 4) as q2, true as near from lineitem group by 1")
def q_percentiles(spark, d):
    """Exact quartiles of prices, and whether the sketch's median is between the exact 0.45 and 0.55 quantiles."""
    p = lambda v: F.percentile("l_extendedprice", v)
    g = _t(spark, d, "lineitem").groupBy("l_returnflag").agg(p(0.25).alias("q1"), p(0.5).alias("q2"), p(0.45).alias("lo"), p(0.55).alias("hi"), F.percentile_approx("l_extendedprice", 0.5).alias("about"))
    return g.select("l_returnflag", _r("q1", 4).alias("q1"), _r("q2", 4).alias("q2"), F.col("about").between(F.col("lo"), F.col("hi")).alias("near"))


@_q(f"select {L4}, rank() over w as r, dense_rank() over w as dr, ntile(3) over (partition by l_orderkey order by l_quantity, l_linenumber, l_partkey, l_suppkey, l_shipdate) as third from lineitem window w as (partition by l_orderkey order by l_quantity)")
def q_ranks(spark, d):
    """Ranks of segments within their ray, with ties."""
    w = Window.partitionBy("l_orderkey").orderBy("l_quantity")
    own = Window.partitionBy("l_orderkey").orderBy("l_quantity", *L5[1:])
    return _t(spark, d, "lineitem").select(*L5[:4], F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(3).over(own).cast("long").alias("third"))


@_q("""select 'intersect' as op, count(*) as rows from (select c_custkey from customer intersect select o_custkey from orders) union all select 'except', count(*) from (select c_custkey from customer except select o_custkey from orders)
  union all select 'intersect all', count(*) from (select l_suppkey from lineitem where l_returnflag = 'A' intersect all select l_suppkey from lineitem where l_returnflag = 'R') union all select 'except all', count(*) from (select l_suppkey from lineitem where l_returnflag = 'A' except all select l_suppkey from lineitem where l_returnflag = 'R')""")
def q_set_operations(spark, d):
    c, o = _t(spark, d, "customer").select("c_custkey"), _t(spark, d, "orders").select("o_custkey")
    p, q = (_t(spark, d, "lineitem").filter(F.col("l_returnflag") == f).select("l_suppkey") for f in "AR")
    out = None
    for name, x in (("intersect", c.intersect(o)), ("except", c.subtract(o)), ("intersect all", p.intersectAll(q)), ("except all", p.exceptAll(q))):
        row = x.agg(F.lit(name).alias("op"), F.count("*").alias("rows"))
        out = row if out is None else out.unionByName(row)
    return out


@_q("select event_id, cast(json_extract_string(props, '$.k') as int) as k, 'k' as name, lpad(hex(event_id), 8, '0') as label, strftime(date_trunc('month', ts), '%Y-%m') as month, split_part(event_type, '_', 1) as kind from events")
def q_json_text_dates(spark, d):
    """Channels out of JSON as a map, hexadecimal labels, months."""
    m = F.from_json("props", "map<string,int>")
    x = _t(spark, d, "events").withColumn("m", m)
    return x.select("event_id", F.col("m")["k"].alias("k"), F.map_keys("m")[0].alias("name"), F.lpad(F.hex("event_id"), 8, "0").alias("label"), F.date_format(F.date_trunc("month", "ts"), "yyyy-MM").alias("month"), F.split_part("event_type", F.lit("_"), F.lit(1)).alias("kind"))


@_q("select count(*) as leaves, sum(npix)::bigint as pixels from (" + _CULLED + " select * from v where ((key // 64) * 2654435761 % 4294967296) < 1073741824)")
def q_preview_sample(spark, d):
    """A quarter of the visible leaves for a preview, chosen by a hash of the key: the same leaves on every run (a sampling operator)."""
    x = forest.preview(_visible(spark, d), 0.25)
    return x.agg(F.count("*").alias("leaves"), F.sum("npix").alias("pixels"))


@_q("select r.r_regionkey as inst, i, j, round((i - 1.5) / 4, 4) as x from region r, range(4) a(i), range(4) b(j)")
def q_ray_grid(spark, d):
    """Pixels of each camera by a Python table function joined laterally."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="i bigint, j bigint, x double")
    class Grid:
        def eval(self, size: int):
            for i in range(size):
                for j in range(size):
                    yield i, j, (i - (size - 1) / 2) / size

    spark.udtf.register("ray_grid", Grid)
    r = _t(spark, d, "region")
    return spark.sql("select r_regionkey as inst, i, j, round(x, 4) as x from {r}, lateral ray_grid(4)", r=r)


@_q("select c_nationkey as tree, round(min(c_acctbal), 2) as least, round(max(c_acctbal), 2) as most, count(*) as rows from customer group by 1")
def q_partitioned_sink(spark, d):
    """A forest's payload written by tree in curve order and read back one tree at a time (partition pruning)."""
    from .sources.mesh import read_forest, write_forest

    x = _t(spark, d, "customer").select(F.col("c_nationkey").cast("int").alias("tree"), F.lit(TOP).alias("level"), F.col("c_custkey").alias("key"), "c_acctbal")
    path = write_forest(x)
    back = read_forest(spark, path, x.schema)
    return back.groupBy(F.col("tree").cast("int").alias("tree")).agg(_r(F.min("c_acctbal"), 2).alias("least"), _r(F.max("c_acctbal"), 2).alias("most"), F.count("*").alias("rows"))


_SLIDE = """with w as (select *, unnest(generate_series(time_bucket(interval 10 days, ts, timestamp '1970-01-01') - interval 20 days, time_bucket(interval 10 days, ts, timestamp '1970-01-01'), interval 10 days)) as start from (select *, exp(-value / 500) as a, (1 - exp(-value / 500)) / 2 as b from events)),
  t as (select *, exp(coalesce(sum(ln(a)) over (partition by user_id, start order by ts, event_id rows between unbounded preceding and 1 preceding), 0)) as t from w)
  select user_id, start, round(exp(sum(ln(a))), 6) as a, round(sum(t * b), 6) as b, count(*) as k from t group by 1, 2"""


@_q(_SLIDE)
def q_window_sliding(spark, d):
    """The batch twin of the sliding window composite."""
    from .streaming.composite import windowed

    x = _events(spark, d).withColumn("ts", F.col("ts").cast("timestamp")).withColumnRenamed("event_id", "tie")
    w = windowed(x, ["user_id"], "ts", "30 days", "1 hour", slide="10 days")
    return w.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), _r("a").alias("a"), _r("b").alias("b"), "k")


@_q(f"select l_orderkey, round(exp(sum(ln(a))), 6) as a, round(exp(sum(ln(a))) * any_value(o_totalprice) / 500000 + sum(t * b), 6) as i from (select r.*, exp(coalesce(sum(ln(a)) over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_shipdate rows between unbounded preceding and 1 preceding), 0)) as t from {_RAYS} r) join orders on l_orderkey = o_orderkey group by l_orderkey")
def q_bucketed_headers(spark, d):
    """Rays with their headers' background, both written in buckets by ray: the join and the fold need no exchange."""
    from .sources.mesh import bucketed

    x = bucketed(_rays(spark, d), "segforest_rays", ["l_orderkey"], 8)
    h = bucketed(_t(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), (F.col("o_totalprice") / 500000).alias("ib")), "segforest_headers", ["l_orderkey"], 8)
    f = fold.composite(x, ["l_orderkey"], L5[1:]).join(h, "l_orderkey")
    return f.select("l_orderkey", _r("a").alias("a"), _r(A.apply_background(F.struct("a", "b"), F.col("ib"))).alias("i"))
