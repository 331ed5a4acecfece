"""Linear forests: leaves (tree, level, key) in curve order; key is the Morton number of the lower corner
at TOP levels, a leaf of level l covers 2 ** (d * (TOP - l)) keys."""

from __future__ import annotations

from bisect import bisect_right

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def shared_folder(spark) -> str:
    """The folder that driver and executors share (spark.checkpoint.dir); one under /tmp only where the session names none."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        base = "file:///tmp/checkpoints/segforest"
        spark.sparkContext.setCheckpointDir(base)
    return base.rstrip("/")


def cut(df: DataFrame) -> DataFrame:
    """A checkpoint in the folder that all executors share."""
    spark = df.sparkSession
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(shared_folder(spark))
    return df.checkpoint()


def uniform(spark, trees: int, level: int, top: int, d: int = 3) -> DataFrame:
    n = 1 << (d * level)
    return spark.range(trees * n).select(F.floor(F.col("id") / n).cast("int").alias("tree"), F.lit(level).alias("level"), F.shiftleft(F.col("id") % n, d * (top - level)).alias("key"))


def children(leaves: DataFrame, top: int, d: int = 3) -> DataFrame:
    step = F.expr(f"cast(power(2, {d} * ({top} - level - 1)) as bigint)")
    x = leaves.select("tree", "level", "key", F.explode(F.sequence(F.lit(0), F.lit((1 << d) - 1))).alias("c"))
    return x.select("tree", (F.col("level") + 1).alias("level"), (F.col("key") + F.col("c") * step).alias("key"))


def refine(leaves: DataFrame, keep, top: int, d: int = 3) -> DataFrame:
    """Leaves for which ``keep`` holds become their children; one round."""
    three = leaves.select("tree", "level", "key")
    return leaves.filter(~keep).select("tree", "level", "key").unionByName(children(leaves.filter(keep).select(*three.columns), top, d))


def from_points(points: DataFrame, capacity: int, top: int, d: int = 3) -> DataFrame:
    """Leaves with n from points (tree, key): the coarsest prefixes with at most ``capacity`` points.

    One aggregation counts finest cells; all coarser counts come from it. A parent that is over capacity
    makes its child cells candidates; cells of the finest level may hold more."""
    cells = points.groupBy("tree", "key").agg(F.count("*").alias("n"))
    up = cells.select("tree", "n", "key", F.explode(F.sequence(F.lit(0), F.lit(top))).alias("level"))
    shift = F.expr(f"{d} * ({top} - level)")
    up = up.withColumn("p", F.call_function("shiftright", F.col("key"), shift.cast("int")))
    sums = up.groupBy("tree", "level", "p").agg(F.sum("n").alias("n"))
    over = sums.filter(F.col("n") > capacity).select("tree", (F.col("level") + 1).alias("level"), F.col("p").alias("parent"))
    fit = sums.filter((F.col("n") <= capacity) | (F.col("level") == top)).withColumn("parent", F.shiftright("p", d))
    leaves = fit.filter("level > 0").join(over, ["tree", "level", "parent"], "left_semi").unionByName(fit.filter("level = 0"))
    return leaves.select("tree", "level", F.call_function("shiftleft", F.col("p"), shift.cast("int")).alias("key"), "n")


def ancestors(leaves: DataFrame, top: int, d: int = 3) -> DataFrame:
    """Distinct proper ancestors (tree, level, p: prefix number)."""
    x = leaves.filter("level > 0").select("tree", "key", F.explode(F.expr("sequence(0, level - 1)")).alias("level"))
    return x.select("tree", "level", F.call_function("shiftright", F.col("key"), F.expr(f"cast({d} * ({top} - level) as int)")).alias("p")).distinct()


def complete(leaves: DataFrame, top: int, d: int = 3) -> DataFrame:
    """``leaves`` plus the fewest coarse leaves that fill their trees; column filled tells them apart."""
    a = ancestors(leaves, top, d)
    kids = a.select("tree", "level", "p", F.explode(F.sequence(F.lit(0), F.lit((1 << d) - 1))).alias("c"))
    kids = kids.select("tree", (F.col("level") + 1).alias("level"), (F.shiftleft("p", d) + F.col("c")).alias("p"))
    own = leaves.select("tree", F.col("level").cast("int").alias("level"), F.call_function("shiftright", F.col("key"), F.expr(f"cast({d} * ({top} - level) as int)")).alias("p"))
    fill = kids.join(a, ["tree", "level", "p"], "left_anti").join(own, ["tree", "level", "p"], "left_anti")
    key = F.call_function("shiftleft", F.col("p"), F.expr(f"cast({d} * ({top} - level) as int)"))
    return leaves.select("tree", "level", "key", F.lit(False).alias("filled")).unionByName(fill.select("tree", "level", key.alias("key"), F.lit(True).alias("filled")))


def coarsen(leaves: DataFrame, top: int, d: int = 3) -> DataFrame:
    """Complete families of equal level become their parent; one round. Column ``merged``."""
    up = F.call_function("shiftright", F.col("key"), F.expr(f"cast({d} * ({top} - level + 1) as int)"))
    x = leaves.filter("level > 0").withColumn("parent", up)
    full = x.groupBy("tree", "level", "parent").agg(F.count("*").alias("c"), F.min("key").alias("key")).filter(F.col("c") == 1 << d)
    rest = x.join(full.select("tree", "level", "parent"), ["tree", "level", "parent"], "left_anti").select("tree", "level", "key")
    root = leaves.filter("level = 0").select("tree", "level", "key")
    return full.select("tree", (F.col("level") - 1).alias("level"), "key", F.lit(True).alias("merged")).unionByName(rest.unionByName(root).withColumn("merged", F.lit(False)))


def check(leaves: DataFrame, top: int, d: int = 3) -> DataFrame:
    """Per tree: volume (1 for a complete tree) and overlaps (0)."""
    size = F.expr(f"cast(power(2, {d} * ({top} - level)) as bigint)")
    w = Window.partitionBy("tree").orderBy("key", "level")
    x = leaves.withColumn("_s", size).withColumn("_next", F.lead("key").over(w))
    return x.groupBy("tree").agg((F.sum("_s") / float(1 << (d * top))).alias("volume"), F.sum(F.when(F.col("_next") < F.col("key") + F.col("_s"), 1).otherwise(0)).cast("long").alias("overlaps"), F.count("*").alias("leaves"))


def neighbours(leaves: DataFrame, top: int, d: int = 3, across: str = "full") -> DataFrame:
    """(tree, level, p) of the equal-level neighbours of each leaf inside its tree: all faces, edges and
    corners (``full``), or faces only."""
    import itertools

    from ..functions.sfc import coordinate

    moves = [m for m in itertools.product((-1, 0, 1), repeat=d) if any(m) and (across == "full" or sum(map(abs, m)) == 1)]
    own = leaves.select("tree", F.col("level").cast("int").alias("level"), F.call_function("shiftright", F.col("key"), F.expr(f"cast({d} * ({top} - level) as int)")).alias("p"))
    x = own.select("tree", "level", *[coordinate(F.col("p"), a, top, d).alias(f"x{a}") for a in range(d)])
    x = x.select("tree", "level", *[f"x{a}" for a in range(d)], F.explode(F.array(*[F.struct(*[F.lit(v).alias(f"m{a}") for a, v in enumerate(m)]) for m in moves])).alias("m"))
    moved = [(F.col(f"x{a}") + F.col(f"m.m{a}")).alias(f"x{a}") for a in range(d)]
    edge = F.expr("cast(power(2, level) as bigint)")
    y = x.select("tree", "level", *moved)
    for a in range(d):
        y = y.filter((F.col(f"x{a}") >= 0) & (F.col(f"x{a}") < edge))
    from ..functions.sfc import morton2, morton3

    key = morton3(F.col("x0"), F.col("x1"), F.col("x2")) if d == 3 else morton2(F.col("x0"), F.col("x1"))
    return y.select("tree", "level", key.alias("p")).distinct()


def unbalanced(leaves: DataFrame, top: int, d: int = 3, across: str = "full") -> DataFrame:
    """Leaves that are two or more levels coarser than a neighbour."""
    n = neighbours(leaves, top, d, across).filter("level >= 2")
    up = n.select("tree", "p", F.col("level").alias("fine"), F.explode(F.expr("sequence(0, level - 2)")).alias("level"))
    up = up.select("tree", "level", F.call_function("shiftright", F.col("p"), F.expr(f"cast({d} * (fine - level) as int)")).alias("p")).distinct()
    own = leaves.withColumn("p", F.call_function("shiftright", F.col("key"), F.expr(f"cast({d} * ({top} - level) as int)")))
    return own.join(up, ["tree", "level", "p"], "left_semi").select("tree", "level", "key")


def _parents_beside(nodes: DataFrame, level: int, d: int, across: str) -> DataFrame:
    """(tree, p) at ``level`` - 1: the parents of the neighbours of ``nodes`` (tree, p) at ``level``, inside their trees."""
    import itertools

    from ..functions.sfc import coordinate, morton2, morton3

    moves = [m for m in itertools.product((-1, 0, 1), repeat=d) if any(m) and (across == "full" or sum(map(abs, m)) == 1)]
    x = nodes.select("tree", *[coordinate(F.col("p"), a, level, d).alias(f"x{a}") for a in range(d)])
    x = x.withColumn("m", F.explode(F.array(*[F.struct(*[F.lit(v).alias(f"m{a}") for a, v in enumerate(m)]) for m in moves])))
    x = x.select("tree", *[(F.col(f"x{a}") + F.col(f"m.m{a}")).alias(f"x{a}") for a in range(d)])
    for a in range(d):
        x = x.filter((F.col(f"x{a}") >= 0) & (F.col(f"x{a}") < (1 << level)))
    half = [F.shiftright(f"x{a}", 1) for a in range(d)]
    return x.select("tree", (morton3(*half) if d == 3 else morton2(*half)).alias("p")).distinct()


def balance(leaves: DataFrame, top: int, d: int = 3, across: str = "full") -> DataFrame:
    """The coarsest refinement of whole trees in which no leaf is two levels coarser than a neighbour. A node that is split needs the
    parents of its neighbours to be split, which concerns one level at a time: one sweep from the finest level up, over split nodes
    only (an eighth or a quarter of the leaves), finds them all. Each level is written to the checkpoint folder."""
    own = cut(leaves.select("tree", F.col("level").cast("int").alias("level"), "key"))
    split = cut(ancestors(own, top, d))
    deepest = split.agg(F.max("level")).first()[0]
    if deepest is None:
        return own
    here, out = None, []
    for level in range(deepest, -1, -1):
        more = split.filter(F.col("level") == level).select("tree", "p")
        if here is not None:
            more = more.unionByName(_parents_beside(here, level + 1, d, across)).distinct()
        here = cut(more)
        out.append(here.select("tree", F.lit(level).alias("level"), "p"))
    whole = out[0]
    for x in out[1:]:
        whole = whole.unionByName(x)
    kids = whole.select("tree", (F.col("level") + 1).alias("level"), F.explode(F.sequence(F.shiftleft("p", d), F.shiftleft("p", d) + ((1 << d) - 1))).alias("p"))
    kept = kids.join(whole, ["tree", "level", "p"], "left_anti")
    new = kept.select("tree", "level", F.call_function("shiftleft", F.col("p"), F.expr(f"cast({d} * ({top} - level) as int)")).alias("key"))
    return new.unionByName(own.filter("level = 0"))


def with_owner(leaves: DataFrame, weight: str, parts: int) -> DataFrame:
    """Adds pid: an even cut of the whole-number ``weight`` along the curve (tree, key), so that loads exceed
    total / parts by less than the largest weight. Leaves go into ranges of the curve that hold about as many each, however unevenly
    a tree is refined; prefix sums come from one sum a range and a scan inside each."""
    x = cut(leaves.repartitionByRange("tree", "key").withColumn("_range", F.spark_partition_id()))
    sums = x.groupBy("_range").agg(F.sum(weight).alias("_s"))
    total = sums.agg(F.sum("_s")).first()[0] or 1
    before = F.coalesce(F.sum("_s").over(Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))  # one row a range
    offs = sums.select("_range", before.alias("_off"))
    inside = F.coalesce(F.sum(weight).over(Window.partitionBy("_range").orderBy("tree", "key").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    y = x.withColumn("_in", inside).join(F.broadcast(offs), "_range")
    pid = F.least(F.lit(parts - 1), F.expr(f"((_off + _in) * {parts}) div {total}")).cast("int")
    return y.withColumn("pid", pid).drop("_range", "_in", "_off")


def markers(owned: DataFrame) -> DataFrame:
    return owned.groupBy("pid").agg(F.min(F.struct("tree", "key")).alias("m")).select("pid", "m.tree", "m.key")


def owner_of(points: DataFrame, marks: DataFrame, top: int, d: int = 3, bits: int = 12) -> DataFrame:
    """``points`` (tree, key, ...) with the pid of the owner whose range holds them: an as-of join. Markers and points go through one sort
    in curve order, in 2 ** ``bits`` ranges of each tree's curve; the last marker of each range is carried into the next."""
    cols = points.columns
    both = points.withColumn("_m", F.lit(None).cast("struct<tree:int,key:bigint,pid:int>")).unionByName(
        marks.select(F.col("tree").cast("int").alias("tree"), F.col("key").cast("long").alias("key"), F.struct(F.col("tree").cast("int").alias("tree"), F.col("key").cast("long").alias("key"), F.col("pid").cast("int").alias("pid")).alias("_m")), allowMissingColumns=True
    )
    # a range's first rows may need the last marker before it
    both = both.withColumn("_blk", F.struct("tree", F.shiftright("key", max(0, d * top - bits)).alias("b")))
    w = Window.partitionBy("_blk").orderBy("key", F.col("_m").isNull()).rowsBetween(Window.unboundedPreceding, 0)
    blocks = both.groupBy("_blk").agg(F.max("_m").alias("_top"))
    carried = blocks.withColumn("_before", F.last("_top", ignorenulls=True).over(Window.orderBy("_blk").rowsBetween(Window.unboundedPreceding, -1))).select("_blk", "_before")
    x = both.withColumn("_own", F.last("_m", ignorenulls=True).over(w)).filter("_m is null").join(carried, "_blk")
    return x.select(*cols, F.coalesce("_own.pid", "_before.pid").alias("pid"))


class Owners:
    """First (tree, key) of every owner; which owners a node's range of keys touches."""

    def __init__(self, rows: list[tuple[int, int, int]]):
        rows = sorted((t, k, p) for p, t, k in rows)
        self.at, self.pid = [(t, k) for t, k, _ in rows], [p for *_, p in rows]

    def of(self, tree: int, first: int, last: int) -> range:
        lo = max(0, bisect_right(self.at, (tree, first)) - 1)
        return range(lo, max(lo, bisect_right(self.at, (tree, last)) - 1) + 1)

    def receivers(self, tree: int, touches, top: int, d: int = 3) -> set[int]:
        """Owners whose leaves may touch a tile: top-down over nodes that are never built. ``touches``
        (level, key) says whether a node's box meets the tile."""
        out, todo = set(), [(0, 0)]
        while todo:
            level, key = todo.pop()
            if not touches(level, key):
                continue
            size = 1 << (d * (top - level))
            own = self.of(tree, key, key + size - 1)
            if len(own) == 1 or level == top:
                out.update(self.pid[i] for i in own)
            else:
                todo += [(level + 1, key + i * (size >> d)) for i in range(1 << d)]
        return out


def locate(points: DataFrame, leaves: DataFrame, top: int, d: int = 3) -> DataFrame:
    """``points`` (tree, key, ...) with leaf_level and leaf_key of the leaf that holds them. A point looks for its
    prefix at each level that occurs (at most top + 1), by an equi join."""
    shift = F.expr(f"cast({d} * ({top} - level) as int)")
    own = leaves.select(F.col("tree").alias("_t"), F.col("level").cast("int").alias("leaf_level"), F.call_function("shiftright", F.col("key"), shift).alias("_p"), F.col("key").alias("leaf_key"))
    levels = sorted(r.level for r in leaves.select(F.col("level").cast("int").alias("level")).distinct().collect())
    x = points.withColumn("level", F.explode(F.array(*map(F.lit, levels)) if levels else F.array().cast("array<int>"))).withColumn("_q", F.call_function("shiftright", F.col("key"), shift))
    j = x.join(own, (F.col("tree") == F.col("_t")) & (F.col("level") == F.col("leaf_level")) & (F.col("_q") == F.col("_p")))
    return j.select(*points.columns, "leaf_level", "leaf_key")


def vertices(leaves: DataFrame, top: int) -> DataFrame:
    """Quadtree vertices (tree, vx, vy in finest units): leaves around each, and whether it hangs (fewer than four
    corners meet there though it is inside the tree)."""
    from ..functions.sfc import coordinate

    edge = F.expr(f"cast(power(2, {top} - level) as bigint)")
    x, y = coordinate(F.col("key"), 0, top, 2), coordinate(F.col("key"), 1, top, 2)
    c = leaves.select("tree", x.alias("x"), y.alias("y"), edge.alias("e"), F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in (0, 1) for j in (0, 1)])).alias("c"))
    v = c.select("tree", (F.col("x") + F.col("c.i") * F.col("e")).alias("vx"), (F.col("y") + F.col("c.j") * F.col("e")).alias("vy"))
    end = 1 << top
    g = v.groupBy("tree", "vx", "vy").agg(F.count("*").alias("corners"))
    inner = lambda k: (F.col(k) > 0) & (F.col(k) < end)
    want = F.when(inner("vx"), 2).otherwise(1) * F.when(inner("vy"), 2).otherwise(1)
    return g.withColumn("hanging", F.col("corners") < want)


def preview(leaves: DataFrame, share: float) -> DataFrame:
    """A ``share`` of the leaves by a hash of their key, the same on every run; a sampling operator for quick looks."""
    return leaves.filter(F.expr(f"(key div 64) * 2654435761 % 4294967296 < {int(share * (1 << 32))}"))
