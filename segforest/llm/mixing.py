"""Mixing sources to target weights by Pfair scheduling, with DataFrame functions only.

The rows of a source form blocks. With weight w (a share of 1), its block i (from 0)
may run from slot floor(i / w) on and must end by slot ceil((i + 1) / w);
of the blocks whose time has come, the one with the earliest deadline takes the next
slot. All slots are used, and after any number of slots each source's blocks differ from
weight * slots by less than one. When a source has no more blocks the others begin a
new phase with their weights scaled to 1, so every row keeps a place.

Weights are kept as exact fractions, so the bound holds for the weights as given, over any number of
slots. As whole numbers without a common divisor, of sum Q, they give a schedule that repeats after Q slots. The plan has
one period for each phase, or the whole phase where that is shorter; Spark joins it to the rows. It has at most
one row a block, and at most sources * Q rows however many rows there are; the driver holds it and one count a source.
"""

from __future__ import annotations

import heapq
import json
from bisect import bisect_left
from fractions import Fraction
from functools import reduce
from math import gcd, lcm

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import pick, restored, with_positions, written

OTHER = "(other)"
#: The column that carries a row's place in the mix to later stages.
POSITION = "mix_position"


#: Rows of a plan that are sent to every task; a longer plan is joined by an exchange.
BROADCAST_ROWS = 100_000


def whole_weights(weights: dict) -> dict[str, int]:
    """The same proportions, exactly, as whole numbers without a common divisor. A float counts as the decimal
    number that it prints as."""
    if not weights or not all(0 < v < float("inf") for v in weights.values()):
        raise ValueError("weights must be positive")
    exact = {k: v if isinstance(v, Fraction) else Fraction(str(v)) for k, v in weights.items()}
    up = lcm(*(v.denominator for v in exact.values()))
    whole = {k: int(v * up) for k, v in exact.items()}
    down = gcd(*whole.values())
    return {k: v // down for k, v in whole.items()}


def period(weights: dict[str, int], blocks: dict[str, int] | None = None) -> tuple[dict[str, list[int]], int]:
    """Earliest deadline first over one period of sum(weights) slots, or until a source has placed all its
    ``blocks``: the slots of each source's blocks, and the slots used. Ties go to the smaller name."""
    q, ready, later, t = sum(weights.values()), [], [(0, name, 0) for name in weights], 0
    heapq.heapify(later)
    slots: dict[str, list[int]] = {k: [] for k in weights}
    while t < q:
        while later and later[0][0] <= t:
            _, name, i = heapq.heappop(later)
            heapq.heappush(ready, (-(-(i + 1) * q // weights[name]), name, i))
        _, name, i = heapq.heappop(ready)
        slots[name].append(t)
        t += 1
        if blocks is not None and i + 1 == blocks[name]:
            break
        if i + 1 < weights[name]:
            heapq.heappush(later, ((i + 1) * q // weights[name], name, i + 1))
    return slots, t


def plan(blocks: dict[str, int], weights: dict[str, int]) -> tuple[list[dict], list[dict]]:
    """Phases (source, phase, first and end block, blocks and slots after which the schedule repeats, first slot) and
    periods (source, phase, block within the period, its slot, release and deadline)."""
    left = {k: n for k, n in blocks.items() if n > 0}
    done, base, phase = dict.fromkeys(left, 0), 0, 0
    phases, periods = [], []
    while left:
        w = whole_weights({k: weights[k] for k in sorted(left)})
        q = sum(w.values())
        slots, used = period(w, left)
        again = used == q  # a whole period: it repeats until the first source ends
        length = min((n - 1) // w[k] * q + slots[k][(n - 1) % w[k]] + 1 for k, n in left.items()) if again else used
        for k in w:
            n = length // q * w[k] + bisect_left(slots[k], length % q) if again else len(slots[k])
            if n:
                phases.append({"source": k, "phase": phase, "first": done[k], "end": done[k] + n, "w": w[k] if again else n, "q": q if again else 0, "base": base})
                periods += [{"source": k, "phase": phase, "j": j, "at": s, "rel": j * q // w[k], "due": -(-(j + 1) * q // w[k])} for j, s in enumerate(slots[k][: min(n, w[k])])]
            done[k] += n
            left[k] -= n
        left = {k: n for k, n in left.items() if n}
        base, phase = base + length, phase + 1
    return phases, periods


def _table(spark, rows: list[dict], schema: str, chunk: int = 20_000) -> DataFrame:
    """Plan rows as literals, without Python on executors; more than one literal's rows are written first."""
    parts = [spark.range(1).select(F.explode(F.from_json(F.lit(json.dumps(rows[i : i + chunk])), f"array<struct<{schema}>>")).alias("r")).select("r.*") for i in range(0, max(1, len(rows)), chunk)]
    return parts[0] if len(parts) == 1 else written(reduce(DataFrame.unionByName, parts), "mix-plan")


def default_weights(counts: dict[str, int]) -> dict[str, int]:
    """The target weights where none are given: the square root of a source's rows, as a whole number of thousandths
    (of 4 * sources parts, if that is more) of all roots, at least 1."""
    roots = {k: n**0.5 for k, n in counts.items() if n}
    total, parts = sum(roots.values()), max(1000, 4 * len(roots))
    return {k: max(1, round(r / total * parts)) for k, r in roots.items()}


def mixed(docs: DataFrame, weights: dict | None = None, block_rows: int = 64, rest: bool = False) -> DataFrame:
    """Each row of ``docs`` (doc_id, source) with its place in the mix: stream, block, release and
    deadline (slots within the phase's clock, added to its first slot), slot, place (within the block).

    ``weights`` names target weights (numbers or fractions); sources that it does not name, and null, share the stream
    ``(other)``, whose weight is weights["(other)"] or else the mean weight. Without ``weights`` every
    source is a stream (null: ``(other)``) with its default_weights(); the driver holds one count a source.
    No row is dropped or repeated: rows within a source are ordered by a hash of doc_id (rows that repeat a doc_id stand
    together), the last block of a source may be short. An empty table gives an empty result. Other columns are
    ignored, whatever their names."""
    spark = docs.sparkSession
    base, inner = pick(docs, {"doc_id": "long", "source": "string"}, rest)
    named = None if weights is None else [k for k in weights if k != OTHER]
    stream = F.coalesce("source", F.lit(OTHER)) if named is None else F.when(F.col("source").isin(named), F.col("source")).otherwise(OTHER) if named else F.lit(OTHER)
    base = base.withColumn("stream", stream)
    rows = {r.stream: r["count"] for r in base.groupBy("stream").count().collect()}
    if weights is None:
        targets = default_weights(rows)
    else:
        targets = {k: v if isinstance(v, Fraction) else Fraction(str(v)) for k, v in weights.items()}
        targets.setdefault(OTHER, sum(targets.values()) / len(targets) if targets else Fraction(1))
    phases, periods = plan({k: -(-n // block_rows) for k, n in rows.items()}, {k: targets[k] for k in rows}) if rows else ([], [])
    put = with_positions(base, "stream", ["doc_id"], "_at", least=256)
    put = put.withColumn("block", F.floor(F.col("_at") / block_rows)).withColumn("place", (F.col("_at") % block_rows).cast("int"))
    p = _table(spark, phases, "source string, phase int, first long, end long, w long, q long, base long").withColumnRenamed("source", "_s")
    q = _table(spark, periods, "source string, phase int, j long, at long, rel long, due long").toDF("_qs", "_qp", "_qj", "_qat", "_rel", "_due")
    small = lambda df, n: F.broadcast(df) if n <= BROADCAST_ROWS else df
    x = put.join(small(p, len(phases)), (F.col("stream") == F.col("_s")) & (F.col("block") >= F.col("first")) & (F.col("block") < F.col("end")))
    x = x.withColumn("_i", F.col("block") - F.col("first")).withColumn("_j", F.col("_i") % F.col("w"))
    x = x.join(small(q, len(periods)), (F.col("stream") == F.col("_qs")) & (F.col("phase") == F.col("_qp")) & (F.col("_j") == F.col("_qj")))
    turn = F.col("base") + F.expr("_i div w") * F.col("q")
    names = [*(inner if rest else []), "doc_id", "source", "stream", "phase", "block", "place"]
    return x.select(*names, (turn + F.col("_rel")).alias("release"), (turn + F.col("_due")).alias("deadline"), (turn + F.col("_qat")).alias("slot"))


def in_mixed_order(docs: DataFrame, block_rows: int = 64, position: str | None = None, **how) -> DataFrame:
    """The rows of ``docs``, all of them with their columns, laid out by slot: written as
    files and read in file order, they come in the mix's order. ``position`` names one more column, slot *
    block_rows + place, by which later stages can keep that order; a column of that name is replaced."""
    if position is not None:
        docs = docs.drop(position)
    _, inner = pick(docs, {"doc_id": "long", "source": "string"}, rest=True)
    x = mixed(docs, rest=True, block_rows=block_rows, **how).repartitionByRange("slot", "place").sortWithinPartitions("slot", "place")
    if position is None:
        return restored(x, inner, docs)
    at = (F.col("slot") * block_rows + F.col("place")).alias("_at")
    return restored(x.select(*inner, at), [*inner, "_at"], docs.withColumn(position, F.lit(0)))
