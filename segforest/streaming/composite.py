"""Composites over streams of segments: per window in event time, and a running one per ray."""

from __future__ import annotations

from bisect import bisect_left

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.algebra import seg, seg_combine, seg_identity


def windowed(stream: DataFrame, rays: list[str], time: str, size: str, late: str, slide: str | None = None, gap: str | None = None) -> DataFrame:
    """Composite of each (ray, window) in time order, near = earliest; rows later than ``late`` are dropped by the
    watermark. ``gap`` gives session windows, ``slide`` sliding ones. Columns: rays, start, end, a, b, k."""
    win = F.session_window(time, gap) if gap else F.window(time, size, slide) if slide else F.window(time, size)
    items = F.array_sort(F.collect_list(F.struct(F.col(time).alias("z"), "tie", "a", "b")))
    g = stream.withWatermark(time, late).groupBy(*rays, win.alias("w")).agg(items.alias("s"))
    f = F.aggregate("s", seg_identity(), lambda acc, s: seg_combine(acc, seg(s["a"], s["b"])))
    return g.select(*rays, F.col("w.start").alias("start"), F.col("w.end").alias("end"), f["a"].alias("a"), f["b"].alias("b"), F.size("s").cast("long").alias("k"))


RUNNING = "ray long, a double, b double, k long, late long"
_STATE = "a double, b double, k long, late long, sealed long, z array<long>, pa array<double>, pb array<double>"


def running(stream: DataFrame, late: str) -> DataFrame:
    """Running composite per ray over all accepted segments (ray, z timestamp, a, b), in update mode. Segments below the
    watermark fold into a sealed prefix; the rest waits, sorted, so rows may come in any order within
    ``late``; rows older than the sealed prefix are counted as late and left out."""
    import pandas as pd

    def step(key, frames, state):
        a, b, k, lates, sealed, z, pa, pb = state.get if state.exists else (1.0, 0.0, 0, 0, -(1 << 62), [], [], [])
        pend = list(zip(z, pa, pb))
        for f in frames:
            for t, x, y in zip(f["z"].astype("int64") // 1000 if str(f["z"].dtype).endswith("[ns]") else f["z"].astype("int64"), f["a"], f["b"]):
                if t < sealed:
                    lates += 1
                else:
                    pend.append((int(t), float(x), float(y)))
                    k += 1
        pend.sort()
        mark = state.getCurrentWatermarkMs() * 1000
        done = bisect_left(pend, (mark,))
        for _, x, y in pend[:done]:
            a, b = a * x, a * y + b
        pend = pend[done:]
        sealed = max(sealed, mark)
        state.update((a, b, k, lates, sealed, [p[0] for p in pend], [p[1] for p in pend], [p[2] for p in pend]))
        for _, x, y in pend:
            a, b = a * x, a * y + b
        yield pd.DataFrame({"ray": [key[0]], "a": [a], "b": [b], "k": [k], "late": [lates]})

    return stream.withWatermark("z", late).groupBy("ray").applyInPandasWithState(step, RUNNING, _STATE, "update", "NoTimeout")


def once(stream: DataFrame, keys: list[str], time: str, late: str) -> DataFrame:
    """Drops segments that were sent again within ``late``."""
    return stream.withWatermark(time, late).dropDuplicatesWithinWatermark(keys)


def with_headers(stream: DataFrame, headers: DataFrame, key: str) -> DataFrame:
    """Segments with their ray's static header (background, say); rays without one keep nulls."""
    return stream.join(headers, key, "left")


def with_live_headers(stream: DataFrame, headers: DataFrame, key: str, time: str, header_time: str, within: str, late: str) -> DataFrame:
    """Segments with the headers of their ray that arrive as a stream of their own, not more than ``within`` before a segment or
    after it. Both sides wait for ``late``; segments without a header then come with nulls. The headers' key is ``key`` too."""
    h = headers.withColumnRenamed(key, "_key").withWatermark(header_time, late)
    near = (F.col(header_time) >= F.col(time) - F.expr(f"interval {within}")) & (F.col(header_time) <= F.col(time) + F.expr(f"interval {within}"))
    return stream.withWatermark(time, late).join(h, (F.col(key) == F.col("_key")) & near, "left").drop("_key")


def image_writer(path: str, w: int, h: int):
    """For ``foreachBatch``: each batch of pixels (x, y, r, g, b) becomes the file ``path``-<batch>.ppm; a batch that is run
    again writes the same file again."""

    def write(batch: DataFrame, number: int) -> None:
        from ..sources.ppm import PpmSource

        batch.sparkSession.dataSource.register(PpmSource)
        batch.write.format("ppm").option("path", f"{path}-{number}.ppm").option("width", w).option("height", h).mode("append").save()

    return write
