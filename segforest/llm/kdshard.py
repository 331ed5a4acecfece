"""Sharding by a k-d tree over document metadata, with DataFrame functions only.

A node of the tree is cut at the weighted (by bytes) median along the dimension in which its
rows spread widest, until each leaf has its share of the bytes. Dimensions are whole
numbers of 15 bits: logarithm of the size, hashes of source and lang.

What is cut are units: all rows of one text (which take the least source and lang of them) are a unit, so equal
texts share a shard. Only a group of more bytes than ``whole`` of a leaf becomes several units, of consecutive rows. There are at
most leaves / whole such groups, and 32 leaves / whole such units, whatever the number of rows. Units that are equal in a dimension are ordered by the text's
checksum, then by a hash.

The medians are found by descent: one pass sums the bytes of each (node, dimension, number), which tells the widest dimension
and the number at which the wanted sum falls; the units of that number are summed by 15 bits of their order,
then by the next 15, until what is left matters little.
All nodes of a level share these passes over a narrow table (no text), and a window over a node has at most 2 ** 8
sums. The driver holds one small row per node.
"""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ._common import drop_path, pick, scratch, with_positions

STEP, TIE_BITS = 15, 60  # a dimension has STEP bits
OVERHEAD = 16


def _literal(spark, rows: list[dict], schema: str) -> DataFrame:
    return spark.range(1).select(F.explode(F.from_json(F.lit(json.dumps(rows)), f"array<struct<{schema}>>")).alias("r")).select("r.*")


def _store(df: DataFrame, what: str) -> tuple[DataFrame, str]:
    path = scratch(df.sparkSession, what)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path), path


#: What names a unit: checksum, size and a second hash of the text, and the part of a large group.
UNIT = ["text_crc32", "size", "name", "chunk"]


def metadata(docs: DataFrame, carry: dict[str, str] | None = None) -> DataFrame:
    """doc_id, size, text_crc32, name (a hash of the text), source and lang as numbers, and the columns ``carry`` (name:
    type). A null text has no bytes, a null source or lang the smallest number. Columns source and lang may be missing."""
    have = {c.lower() for c in docs.columns}
    extra = {k: "string" for k in ("source", "lang") if k in have}
    base, _ = pick(docs, {"doc_id": "long", "text": "string"} | extra | (carry or {}))
    text = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    size = (F.octet_length(text) + OVERHEAD).cast("long")
    top = (1 << STEP) - 1
    dims = [F.floor(F.coalesce(F.crc32(F.col(k).cast("binary")), F.lit(0)) / float(1 << 32) * top).cast("long") if k in extra else F.lit(0).cast("long") for k in ("source", "lang")]
    return base.select("doc_id", size.alias("size"), F.crc32(text).alias("text_crc32"), F.xxhash64(text).alias("name"), dims[0].alias("d_source"), dims[1].alias("d_lang"), *(carry or {}))


def with_units(rows: DataFrame, leaves: int, whole: float) -> DataFrame:
    """``rows`` with chunk: 0, but for groups of equal texts of more bytes than ``whole`` of a leaf, whose rows (in an order of
    doc_id hashes) are numbered in runs of a sixteenth of that."""
    spark, group = rows.sparkSession, UNIT[:3]
    total = rows.agg(F.sum("size")).first()[0] or 0
    most = max(1.0, total / leaves * whole)
    large = rows.groupBy(*group).agg(F.count("*").alias("n")).filter((F.col("n") > 1) & (F.col("n") * F.col("size") > most)).collect()
    if not large:
        return rows.withColumn("chunk", F.lit(0).cast("long"))
    table = _literal(spark, [{"_c": r.text_crc32, "_s": r["size"], "_m": r.name, "_g": str(i), "_per": max(1, int(most / 16 / r["size"]))} for i, r in enumerate(large)], "_c long, _s long, _m long, _g string, _per long")
    j = rows.join(F.broadcast(table), (F.col("text_crc32") == F.col("_c")) & (F.col("size") == F.col("_s")) & (F.col("name") == F.col("_m")), "left")
    hot, _ = _store(j.filter("_g is not null").drop("_c", "_s", "_m"), "kd-large")
    at = with_positions(hot, "_g", ["doc_id", "d_source", "d_lang"], "_at").withColumn("chunk", F.expr("_at div _per").cast("long"))
    return j.filter("_g is null").select(*rows.columns, F.lit(0).cast("long").alias("chunk")).unionByName(at.select(*rows.columns, "chunk"))


def units(rows: DataFrame) -> DataFrame:
    """The units of with_units()'s rows: their names, size as weight (``bytes``), p (array of the dimensions' numbers), tie."""
    top = (1 << STEP) - 1
    g = rows.groupBy(*UNIT).agg(F.sum("size").alias("bytes"), F.min("d_source").alias("d_source"), F.min("d_lang").alias("d_lang"))
    log = F.least(F.floor(F.log2(F.col("size").cast("double")) / 40.0 * top), F.lit(top)).cast("long")
    tie = F.col("text_crc32") * F.lit(1 << 28) + F.pmod(F.xxhash64("name", "chunk"), F.lit(1 << 28))
    return g.select(*UNIT, "bytes", F.array(log, "d_source", "d_lang").alias("p"), tie.alias("tie"))


def _reached(sums: DataFrame, goal) -> DataFrame:
    """Of ``sums`` (node, b, s, ...) the bucket of each node in which the running sum reaches the goal, with the sum before it. The running sum goes over
    sums of 2 ** 8 buckets first, then over the buckets of one of them, so no window has more than 2 ** 8 rows a node."""
    x = sums.withColumn("goal", goal).withColumn("_c", F.shiftright("b", 8))

    def crossing(rows, by, size, before):
        rows = rows.withColumn("run", before + F.sum(size).over(Window.partitionBy("node").orderBy(by)))
        return rows.filter((F.col("run") >= F.col("goal")) & (F.col("run") - F.col(size) < F.col("goal"))).withColumn("before", F.col("run") - F.col(size))

    coarse = crossing(x.groupBy("node", "_c").agg(F.sum("s").alias("_s"), F.max("goal").alias("goal")), "_c", "_s", F.lit(0))
    at = F.broadcast(coarse.select(F.col("node").alias("_node"), F.col("_c").alias("_at"), F.col("before").alias("_before")))  # one row a node
    return crossing(x.join(at, (F.col("node") == F.col("_node")) & (F.col("_c") == F.col("_at"))), "b", "s", F.col("_before"))


def _widest(live: DataFrame, share: DataFrame) -> list:
    """For each node of ``share`` (node, part of its bytes that goes left): its widest dimension, the number there at which
    the part is reached, the bytes before and at that number, and all its bytes."""
    hist = live.select("node", "bytes", F.posexplode("p").alias("dim", "b")).groupBy("node", "dim", "b").agg(F.sum("bytes").alias("s"))
    spans = hist.groupBy("node", "dim").agg((F.max("b") - F.min("b")).alias("spread"), F.sum("s").alias("w"))
    best = spans.groupBy("node").agg(F.max(F.struct("spread", (-F.col("dim")).alias("d"), "w")).alias("m")).select(F.col("node").alias("_n"), (-F.col("m.d")).alias("_d"), F.col("m.w").alias("w"))
    own = hist.join(best, (F.col("node") == F.col("_n")) & (F.col("dim") == F.col("_d"))).join(F.broadcast(share), "node")
    return _reached(own, F.col("w") * F.col("share")).select("node", "dim", "b", "before", "s", "w", "goal").collect()


def kd_tree(rows: DataFrame, leaves: int, tolerance: float = 0.0005) -> DataFrame:
    """``rows`` (units()) with ``shard``, 0 to leaves - 1, of near equal bytes: each cut is off its goal by
    less than ``tolerance`` of a leaf or by half a unit. An empty leaf occurs only with fewer units than leaves."""
    spark = rows.sparkSession
    rows, path = _store(rows.withColumn("node", F.lit(0)), "kd-units")
    nodes = {0: (0, leaves)}  # node: its first shard and number of shards
    total = rows.agg(F.sum("bytes")).first()[0] or 0
    small = max(total / leaves * tolerance, 1)
    while any(k > 1 for _, k in nodes.values()) and total:
        open_ = [n for n, (_, k) in nodes.items() if k > 1]
        share = _literal(spark, [{"node": n, "share": (nodes[n][1] // 2) / nodes[n][1]} for n in open_], "node int, share double")
        cut, todo = {}, {}  # todo: what is wanted of the units at the border's number
        live = rows.join(F.broadcast(share.select("node")), "node", "left_semi")
        for r in _widest(live, share):
            last = r.s <= small
            cut[r.node] = {"node": r.node, "dim": r.dim + 1, "value": r.b + (1 if last and (r.goal - r.before) * 2 > r.s else 0), "tie": 0, "left": 2 * r.node + 1}
            if not last:
                todo[r.node] = r.goal - r.before
        for done in range(0, TIE_BITS, STEP):
            if not todo:
                break
            at = _literal(spark, [{"n": n, "dim": cut[n]["dim"], "value": cut[n]["value"], "tie": cut[n]["tie"], "goal": g} for n, g in todo.items()], "n int, dim int, value long, tie long, goal double").toDF("_n", "_dim", "_v", "_t", "goal")
            here = rows.join(F.broadcast(at), F.col("node") == F.col("_n")).filter((F.element_at("p", F.col("_dim")) == F.col("_v")) & (F.shiftright("tie", TIE_BITS - done) == F.shiftright("_t", TIE_BITS - done)))
            shift = TIE_BITS - done - STEP
            sums = here.groupBy("node", "goal", F.shiftright("tie", shift).alias("b")).agg(F.sum("bytes").alias("s"), F.count("*").alias("n"))
            for r in _reached(sums, F.col("goal")).select("node", "b", "before", "s", "n", "goal").collect():
                # units below (value, tie) go left; the border moves past the bucket if that is nearer
                last = r.s <= small or r.n == 1 or shift == 0
                cut[r.node]["tie"] = r.b + (1 if last and (r.goal - r.before) * 2 > r.s else 0) << shift
                if last:
                    todo.pop(r.node)
                else:
                    todo[r.node] = r.goal - r.before
        bounds = _literal(spark, list(cut.values()), "node int, dim int, value long, tie long, left int").toDF("_n", "_dim", "_value", "_tie", "_left")
        v = F.element_at("p", F.col("_dim"))
        below = (v < F.col("_value")) | ((v == F.col("_value")) & (F.col("tie") < F.col("_tie")))
        moved = rows.join(F.broadcast(bounds), F.col("node") == F.col("_n"), "left")
        moved = moved.withColumn("node", F.when(F.col("_n").isNull(), F.col("node")).when(below, F.col("_left")).otherwise(F.col("_left") + 1)).select(rows.columns)
        old = path
        rows, path = _store(moved, "kd-units")
        drop_path(spark, old)
        for n in open_:
            first, k = nodes.pop(n)
            nodes[2 * n + 1], nodes[2 * n + 2] = (first, k // 2), (first + k // 2, k - k // 2)
    names = _literal(spark, [{"n": n, "shard": f} for n, (f, _) in nodes.items()], "n int, shard int").toDF("_n", "shard")
    return rows.join(F.broadcast(names), F.col("node") == F.col("_n")).drop("_n", "node")


def sharded(docs: DataFrame, shards: int | None = 40, target_bytes: int | None = None, order: str | None = None, whole: float = 0.25, rest: bool = False) -> DataFrame:
    """doc_id, size, text_crc32, shard, slot of each row of ``docs`` (doc_id, text; source and lang if it has them); with
    ``rest`` all columns of ``docs`` instead of doc_id, but those of the new names and ``order``.
    Give the number of ``shards``, or ``target_bytes`` (with shards=None) for the least number of shards with that
    mean size. size is the text's UTF-8 bytes (null: 0) plus 16. Rows of equal texts share a shard unless together they have more
    than ``whole`` of a shard's bytes. Slots count from 0 without gaps, in the order of
    a hash of doc_id and text or, with ``order``, of that column (whole numbers from 0, one a row, such as places in a mix), whatever the
    layout of the files. Repeated rows have slots of their own; a null doc_id is a value like others. An empty
    table gives an empty result."""
    new = ["size", "text_crc32", "shard", "slot"]
    columns, inner, row = docs.columns, [f"_c{i}" for i in range(len(docs.columns))], "_row"
    while row in (c.lower() for c in columns):
        row += "_"
    if rest:  # rows get a number, by which their columns come back
        held, _ = _store(docs.toDF(*inner).withColumn(row, F.monotonically_increasing_id()), "kd-documents")
        docs = held.toDF(*columns, row)
    rows, _ = _store(metadata(docs, ({order: "long"} if order else {}) | ({row: "long"} if rest else {})), "kd-metadata")
    if shards is None:
        shards = max(1, -(-(rows.agg(F.sum("size")).first()[0] or 0) // target_bytes))
    rows, _ = _store(with_units(rows, shards, whole), "kd-rows")
    leaf = kd_tree(units(rows), shards).select(*UNIT, "shard")
    out, _ = _store(rows.join(leaf, UNIT), "kd-shards")
    ordered = [*([order] if order else []), "doc_id", "text_crc32", "name"]
    out = with_positions(out, "shard", ordered, "slot", ranges=bool(order))
    if not rest:
        return out.select("doc_id", *new)
    found = out.select(F.col(row).alias("_of"), *[F.col(c).alias(f"_new_{c}") for c in new])
    keep = [F.col(x).alias(c) for x, c in zip(inner, columns) if c.lower() not in new and c != order]
    return held.join(found, F.col(row) == F.col("_of")).select(*keep, *[F.col(f"_new_{c}").alias(c) for c in new])
