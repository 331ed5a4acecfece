"""The segment algebra for SQL text: temporary SQL functions, inlined by the optimizer."""

from __future__ import annotations

from pyspark.sql import SparkSession

SEG = "struct<a: double, b: double>"
ITEM = "struct<z: double, a: double, b: double>"
FUNCTIONS = {
    "seg_const(beta double, gamma double, dx double)": "named_struct('a', exp(-beta * dx), 'b', case when beta = 0 then gamma * dx else -gamma * expm1(-beta * dx) / beta end)",
    f"seg_combine(near {SEG}, far {SEG})": "named_struct('a', near.a * far.a, 'b', near.a * far.b + near.b)",
    f"seg_inverse(s {SEG})": "case when s.a <> 0 then named_struct('a', 1 / s.a, 'b', -s.b / s.a) end",
    "seg_surface(a double, i double)": "named_struct('a', a, 'b', i * (1 - a))",
    f"seg_fold(items array<{ITEM}>)": "aggregate(array_sort(items), named_struct('a', 1d, 'b', 0d), (f, s) -> named_struct('a', f.a * s.a, 'b', f.a * s.b + f.b))",
    f"seg_split(s {SEG}, part double)": "case when s.a = 0 then s when s.a = 1 then named_struct('a', 1d, 'b', s.b * part) else named_struct('a', power(s.a, part), 'b', s.b * (1 - power(s.a, part)) / (1 - s.a)) end",
}
SCALARS = {
    f"seg_apply(s {SEG}, ib double)": ("double", "s.a * ib + s.b"),
    "seg_item(z double, a double, b double)": (ITEM, "named_struct('z', z, 'a', a, 'b', b)"),
    "to_rgb(i double)": ("int", "cast(least(greatest(floor(i * 255 + 0.5), 0), 255) as int)"),
}


def register(spark: SparkSession) -> None:
    """Adds seg_const, seg_combine, seg_inverse, seg_surface, seg_split, seg_apply, to_rgb and the aggregate
    seg_fold(collect_list(seg_item(z, a, b))) to the session: near first, rows of equal z in order of a and b. A group's segments are
    one array, and no row leaves the JVM; hot rays want ``composite``."""
    for head, body in FUNCTIONS.items():
        spark.sql(f"create or replace temporary function {head} returns {SEG} return {body}")
    for head, (kind, body) in SCALARS.items():
        spark.sql(f"create or replace temporary function {head} returns {kind} return {body}")
