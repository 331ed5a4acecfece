"""Which owner of leaves sends pixels to which image tile: from the leaves (senders), from the markers alone
(receivers), and the all-pairs baseline. A tile is a square of 2 ** t pixels, numbered row by row."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def tiles_across(size: int, t: int) -> int:
    return -(-size // (1 << t))


def senders(visible: DataFrame, w: int, t: int) -> DataFrame:
    """Distinct (inst, pid, tile) over visible leaves (inst, pid, i0..j1). Each task reduces its pairs before the
    exchange, which so carries at most owners x tiles rows a task."""
    across = tiles_across(w, t)
    side = lambda c: F.shiftright(c, t)
    x = visible.select("inst", "pid", F.explode(F.sequence(side("i0"), side("i1"))).alias("tx"), "j0", "j1")
    x = x.select("inst", "pid", "tx", F.explode(F.sequence(side("j0"), side("j1"))).alias("ty"))
    return x.select("inst", "pid", (F.col("ty") * across + F.col("tx")).alias("tile")).distinct()


def senders_all_pairs(visible: DataFrame, w: int, h: int, t: int) -> DataFrame:
    """The baseline: every visible leaf against every tile of the image."""
    across, down, edge = tiles_across(w, t), tiles_across(h, t), 1 << t
    x = visible.select("inst", "pid", "i0", "i1", "j0", "j1", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(across * down - 1).cast("long"))).alias("tile"))
    x0, y0 = F.col("tile") % across * edge, F.floor(F.col("tile") / across) * edge
    meets = (F.col("i0") < x0 + edge) & (F.col("i1") >= x0) & (F.col("j0") < y0 + edge) & (F.col("j1") >= y0)
    return x.filter(meets).select("inst", "pid", "tile").distinct()


def receivers(spark: SparkSession, marks: DataFrame, cams: list, t: int, top: int) -> DataFrame:
    """(inst, pid, tile) that may occur, from the marker table alone: each tile descends nodes that are never built,
    as far as one owner has all of a node. A superset of ``senders``: markers do not tell leaf sizes.

    The markers go to every task once, sorted: one row an owner, so as many as there are partitions. A tile looks at the roots
    of all trees and goes on below those that it meets."""
    from .forest import Owners

    rows = [(r.pid, r.tree, r.key) for r in marks.collect()]
    shared, trees = spark.sparkContext.broadcast(Owners(rows)), sorted({r[1] for r in rows})
    frames = {c.inst: c for c in cams}
    grid = None
    for c in cams:
        n = tiles_across(c.w, t) * tiles_across(c.h, t)
        g = spark.range(n).select(F.lit(c.inst).alias("inst"), F.col("id").alias("tile"))
        grid = g if grid is None else grid.unionByName(g)

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            out: list[list[int]] = [[], [], []]
            for inst, tile in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                cam = frames[inst]
                across = tiles_across(cam.w, t)
                x0, y0 = tile % across << t, tile // across << t
                touches = lambda level, key: _meets(cam, level, key, top, x0, y0, 1 << t)  # noqa: B023, E731
                for pid in sorted(set().union(*[shared.value.receivers(tree, touches, top) for tree in trees])):
                    out[0].append(inst)
                    out[1].append(pid)
                    out[2].append(tile)
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int32()), pa.array(out[1], pa.int32()), pa.array(out[2], pa.int64())], names=["inst", "pid", "tile"])

    return grid.mapInArrow(run, "inst int, pid int, tile long")


def _meets(cam, level: int, key: int, top: int, x0: int, y0: int, edge: int) -> bool:
    """Whether the pixel rectangle of a node's box meets the tile at x0, y0."""
    from math import ceil, floor

    low = [0, 0, 0]
    for b in range(top):
        for a in range(3):
            low[a] |= ((key >> (3 * b + a)) & 1) << b
    lo = [v / (1 << top) for v in low]
    hi = [v + 2.0**-level for v in lo]

    def bound(axis, least):
        return sum(e * ((lo if (e > 0) == least else hi)[a] - cam.o[a]) for a, e in enumerate(axis))

    view = tuple(x / cam.n for x in cam.v)
    z0, z1 = max(bound(view, True), cam.n), min(bound(view, False), cam.far)
    if z0 >= z1:
        return False
    for axis, size, first in ((cam.t, cam.w, x0), (cam.u, cam.h, y0)):
        a, b = bound(axis, True), bound(axis, False)
        p = max(ceil((size - 1) / 2 + a / (z1 if a >= 0 else z0) * cam.n / cam.ell), 0)
        q = min(floor((size - 1) / 2 + b / (z0 if b >= 0 else z1) * cam.n / cam.ell), size - 1)
        if p > q or p >= first + edge or q < first:
            return False
    return True


def false_pairs(sent: DataFrame, expected: DataFrame) -> DataFrame:
    """One row: pairs sent, pairs expected, expected but not sent, sent but not expected (0 for a right routing)."""
    keys = ["inst", "pid", "tile"]
    x = sent.select(*keys, F.lit(1).alias("s"), F.lit(0).alias("e")).unionByName(expected.select(*keys, F.lit(0).alias("s"), F.lit(1).alias("e")))
    g = x.groupBy(*keys).agg(F.max("s").alias("s"), F.max("e").alias("e"))
    total = lambda c: F.coalesce(F.sum(c.cast("int")), F.lit(0)).cast("long")
    s, e = F.col("s") == 1, F.col("e") == 1
    return g.agg(total(s).alias("sent"), total(e).alias("expected"), total(e & ~s).alias("false_pairs"), total(s & ~e).alias("missed"))
