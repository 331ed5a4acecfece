"""Chat logs: collapse of cumulative snapshots, then rendering.

A chat service that logs the whole dialogue at each turn leaves conversations that are
prefixes of longer ones. Each turn is hashed with its place, role and text; running sums of
these hashes name every prefix of every conversation. A conversation whose full name is that of a
proper prefix of another is covered; an anti join keeps the others, and of equal ones the smallest
conv_id. Sums of two hashes, in halves of 32 bits, make 128-bit names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ._common import pick, written

_SUMS = ["a_hi", "a_lo", "b_hi", "b_lo"]
START, MIDDLE, END = "<|im_start|>", "\n", "<|im_end|>\n"


def prefixes(conversations: DataFrame) -> DataFrame:
    """conv_id, role, text, n (turns up to this one), total, and the prefix name of each turn.

    Turns are ordered by turn, then role, then text, null turns first; null roles and texts read as empty; rows that repeat are turns of their own.
    A row with a null conv_id is a conversation of one turn. Extra columns are ignored, whatever their names."""
    rows, _ = pick(conversations, {"conv_id": "long", "turn": "long", "role": "string", "text": "string"})
    rows = rows.withColumn("role", F.coalesce("role", F.lit(""))).withColumn("text", F.coalesce("text", F.lit("")))
    w = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    known = rows.filter("conv_id is not null").withColumn("n", F.row_number().over(w).cast("long"))
    single = rows.filter("conv_id is null").withColumn("n", F.lit(1).cast("long"))
    a, b = F.xxhash64("n", "role", "text"), F.xxhash64(F.lit("b"), "text", "role", "n")
    halves = {"a_hi": F.shiftright(a, 32), "a_lo": a.bitwiseAND(F.lit(0xFFFFFFFF)), "b_hi": F.shiftright(b, 32), "b_lo": b.bitwiseAND(F.lit(0xFFFFFFFF))}
    run = w.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    known = known.withColumns(halves).withColumns({k: F.sum(k).over(run) for k in halves})
    known = known.withColumn("total", F.max("n").over(Window.partitionBy("conv_id")))
    return known.unionByName(single.withColumns(halves).withColumn("total", F.lit(1).cast("long")))


def maximal(conversations: DataFrame) -> DataFrame:
    """conv_id, n_turns, n_copies (equal conversations, itself included) and full name of the conversations that stay."""
    marked = written(prefixes(conversations).select("conv_id", "n", "total", *_SUMS), "prefixes")
    full = marked.filter("n = total").groupBy("n", *_SUMS).agg(F.min("conv_id").alias("conv_id"), F.count("*").alias("n_copies"))
    inside = marked.filter("n < total").select("n", *_SUMS).distinct()
    return full.join(inside, ["n", *_SUMS], "left_anti").select("conv_id", F.col("n").alias("n_turns"), "n_copies", *_SUMS)


def rendered(conversations: DataFrame, start: str = START, middle: str = MIDDLE, end: str = END) -> DataFrame:
    """conv_id, n_turns, n_copies and the text of each conversation that stays. A
    conversation's turns are gathered to one row, as its text is one value."""
    turns = prefixes(conversations)
    stay = maximal(conversations)
    rows = turns.select("conv_id", "n", "role", "text").join(stay.filter("conv_id is not null"), "conv_id")
    said = F.transform(F.array_sort(F.collect_list(F.struct("n", "role", "text"))), lambda t: F.concat(F.lit(start), t["role"], F.lit(middle), t["text"], F.lit(end)))
    out = rows.groupBy("conv_id", "n_turns", "n_copies").agg(F.array_join(said, "").alias("rendered"))
    # a conversation all of whose copies have no conv_id: one turn, found again by its name
    lone = turns.filter("conv_id is null").dropDuplicates(_SUMS).join(stay.filter("conv_id is null"), _SUMS).select(turns["conv_id"], "n_turns", "n_copies", F.concat(F.lit(start), "role", F.lit(middle), "text", F.lit(end)).alias("rendered"))
    return out.unionByName(lone)


SQL = f"""
with t as (
  select conv_id, coalesce(role, '') as role, coalesce(text, '') as text, row_number() over () as line,
    case when conv_id is null then 1 else row_number() over (partition by conv_id order by turn nulls first, coalesce(role, ''), coalesce(text, '')) end as n
  from conversations),
p as (
  select conv_id, n, max(n) over (partition by conv_id) as total,
    string_agg('{START}' || role || chr(10) || text || '{END[:-1]}' || chr(10), '') over (partition by conv_id, case when conv_id is null then line end order by n) as said
  from t),
f as (select said, n as n_turns, min(conv_id) as conv_id, count(*) as n_copies from p where n = total group by said, n)
select conv_id, n_turns, n_copies, said as rendered from f
where not exists (select 1 from p where p.said = f.said and p.n < p.total)
"""
