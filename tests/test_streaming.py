import numpy as np
from pyspark.sql import functions as F

from segforest import queries as Q
from segforest.operators.fold import composite
from segforest.sources.ppm import PpmSource
from segforest.streaming.composite import running, windowed

DATA = "/root/testdata/sf0.001"


def files(spark, tmp_path):
    """Events as three files in any order of time."""
    x = Q._events(spark, DATA).withColumn("ts", F.col("ts").cast("timestamp"))
    x.repartition(3).write.parquet(str(tmp_path / "in"))
    return x, spark.readStream.schema(x.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))


def drain(df, name, mode):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(60)
    return df.sparkSession.table(name)


def test_windowed_equals_batch(spark, tmp_path):
    batch, stream = files(spark, tmp_path)
    make = lambda df: windowed(df.withColumnRenamed("event_id", "tie"), ["user_id"], "ts", "30 days", "400 days")
    keys = ["user_id", "start"]
    got = drain(make(stream), "tumbling", "complete").toPandas().sort_values(keys)
    want = make(batch).toPandas().sort_values(keys)
    assert len(got) == len(want) and np.allclose(got[["a", "b", "k"]], want[["a", "b", "k"]])


def test_running_equals_batch(spark, tmp_path):
    batch, stream = files(spark, tmp_path)
    out = drain(running(stream.select(F.col("user_id").alias("ray"), F.col("ts").alias("z"), "a", "b"), "400 days"), "running", "update").toPandas()
    got = out.sort_values("k").groupby("ray").last().sort_index()
    want = composite(batch, ["user_id"], ["ts", "event_id"]).toPandas().set_index("user_id").sort_index()
    assert (got.late == 0).all() and (got.k == want.k).all() and np.allclose(got[["a", "b"]], want[["a", "b"]])


def test_late_rows_are_counted(spark, tmp_path):
    """Files in a row: day 100, day 50 (not sealed yet: taken in order), day 101 (seals up to day 99), day 20 (late)."""
    schema = "ray long, z timestamp, a double, b double"
    for k, (day, b) in enumerate(((100, 1.0), (50, 2.0), (101, 4.0), (20, 8.0))):
        x = spark.range(1).select(F.lit(1).cast("long").alias("ray"), F.timestamp_seconds(F.lit(day * 86400)).alias("z"), F.lit(0.5).alias("a"), F.lit(b).alias("b"))
        x.coalesce(1).write.parquet(str(tmp_path / f"f{k}"))
    (tmp_path / "in").mkdir()
    import time

    for k in range(4):
        f = next((tmp_path / f"f{k}").glob("*.parquet"))
        f.rename(tmp_path / "in" / f"{k}.parquet")
        import os

        os.utime(tmp_path / "in" / f"{k}.parquet", (time.time() - 100 + 10 * k,) * 2)
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    out = drain(running(stream, "1 day"), "late", "update").toPandas().sort_values(["k", "late"]).iloc[-1]
    assert (out.k, out.late) == (3, 1)
    assert np.isclose(out.a, 0.125) and np.isclose(out.b, 2.0 + 0.5 * 1.0 + 0.25 * 4.0)


def test_dedup_headers_and_images(spark, tmp_path):
    from segforest.streaming.composite import image_writer, once, with_headers

    rows = [(k % 3, k % 3) for k in range(6)]
    x = spark.createDataFrame(rows, "x int, y int").select("x", "y", F.timestamp_seconds(F.lit(1000)).alias("z"))
    x.coalesce(1).write.parquet(str(tmp_path / "px"))
    heads = spark.createDataFrame([(0, 9), (1, 8)], "x int, r int")
    stream = with_headers(once(spark.readStream.schema(x.schema).parquet(str(tmp_path / "px")), ["x", "y"], "z", "1 hour"), heads, "x")
    pix = stream.select("x", "y", F.coalesce("r", F.lit(7)).alias("r"), F.lit(1).alias("g"), F.lit(2).alias("b"))
    pix.writeStream.foreachBatch(image_writer(str(tmp_path / "i"), 3, 3)).option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start().awaitTermination(60)
    spark.dataSource.register(PpmSource)
    got = spark.read.format("ppm").option("path", str(tmp_path / "i-0.ppm")).load().filter("r > 0").collect()
    assert sorted(map(tuple, got)) == [(0, 0, 9, 1, 2), (1, 1, 8, 1, 2), (2, 2, 7, 1, 2)]


def test_sliding_and_session_windows_on_a_stream(spark, tmp_path):
    batch, stream = files(spark, tmp_path)
    for name, how in (("sliding", {"slide": "10 days"}), ("session", {"gap": "10 days"})):
        make = lambda df: windowed(df.withColumnRenamed("event_id", "tie"), ["user_id"], "ts", "30 days", "400 days", **how)  # noqa: B023, E731
        got = drain(make(stream), name, "complete").toPandas().sort_values(["user_id", "start"])
        want = make(batch).toPandas().sort_values(["user_id", "start"])
        assert len(got) == len(want) and np.allclose(got[["a", "b", "k"]], want[["a", "b", "k"]])


def test_headers_that_arrive_as_a_stream(spark, tmp_path):
    from segforest.streaming.composite import with_live_headers

    at = lambda c: F.timestamp_seconds(F.col(c)).alias(c)
    seg = spark.createDataFrame([(1, 1000, 0.5), (1, 9000, 0.6), (2, 1000, 0.7), (3, 90_000_000, 0.1)], "ray int, z long, a double").select("ray", at("z"), "a")
    head = spark.createDataFrame([(1, 1010, 7.0), (2, 5000, 8.0), (9, 90_000_000, 0.0)], "ray int, sent long, sky double").select("ray", at("sent"), "sky")
    for n, x in (("seg", seg), ("head", head)):
        x.orderBy(x.columns[1]).coalesce(1).write.parquet(str(tmp_path / n))
    s, h = (spark.readStream.schema(x.schema).parquet(str(tmp_path / n)) for n, x in (("seg", seg), ("head", head)))
    got = drain(with_live_headers(s, h, "ray", "z", "sent", "1 minute", "1 minute"), "live", "append").collect()
    assert {(r.ray, r.a, r.sky) for r in got} >= {(1, 0.5, 7.0), (1, 0.6, None), (2, 0.7, None)}
