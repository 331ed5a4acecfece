"""Cost and accuracy measures of the pipeline's phases, images and partitions."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def load_balance(owned: DataFrame, weight: str, parts: int) -> DataFrame:
    """One row: heaviest part over the mean of all ``parts`` (1 is even), and the total."""
    s = owned.groupBy("pid").agg(F.sum(weight).alias("s"))
    return s.agg((F.max("s") * float(parts) / F.sum("s")).alias("imbalance"), F.sum("s").alias("total"))


def image_error(image: DataFrame, reference: DataFrame, keys: list[str], value: str = "v") -> DataFrame:
    """One row: greatest and root mean square difference over the pixels of both; a pixel of one alone counts as 0 in the other."""
    j = image.select(*keys, F.col(value).alias("_x")).join(reference.select(*keys, F.col(value).alias("_y")), keys, "full")
    d = F.coalesce("_x", F.lit(0.0)) - F.coalesce("_y", F.lit(0.0))
    return j.agg(F.max(F.abs(d)).alias("max_error"), F.sqrt(F.avg(d * d)).alias("rmse"), F.count("*").alias("pixels"))


def reduction(stages: dict[str, DataFrame], **extra: Column) -> DataFrame:
    """Segments, elements and bytes (six 8-byte columns a segment) of each stage in one row each; ``extra`` names further aggregates."""
    out = None
    for name, df in stages.items():
        row = df.agg(F.lit(name).alias("stage"), F.count("*").alias("segments"), F.countDistinct("tree", "level", "key").alias("elements"), (F.count("*") * 48).alias("bytes"), *(c.alias(k) for k, c in extra.items()))
        out = row if out is None else out.unionByName(row)
    return out


def timed(phases: dict[str, Callable[[], DataFrame]], sink: Callable[[DataFrame], DataFrame]) -> list[tuple[str, float, int]]:
    """Wall-clock seconds and rows of each phase. ``sink`` writes a phase's rows (a checkpoint or a table) and
    returns them to be read by the next."""
    out = []
    for name, make in phases.items():
        start = time.time()
        rows = sink(make())
        took = time.time() - start
        out.append((name, took, rows.count()))
    return out


def observed_order(errors: DataFrame, keys: list[str]) -> DataFrame:
    """Rows (keys, n, err) with log2 of the error's fall against the row of half as many steps."""
    half = errors.select(*keys, (F.col("n") * 2).alias("n"), F.col("err").alias("_before"))
    return errors.join(half, [*keys, "n"]).select(*keys, "n", "err", F.log2(F.col("_before") / F.nullif(F.col("err"), F.lit(0.0))).alias("order"))


def weighted_pixels(npix, length, beta, c: float):
    """Work of a leaf under adaptive integration: pixels times the pieces a ray is expected to be cut in."""
    return npix * F.greatest(F.lit(1.0), F.pow(F.lit(2.0), F.ceil(F.log2(F.greatest(length * F.abs(beta) / c, F.lit(1e-12))))))
