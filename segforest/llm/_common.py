"""Helpers that the operators of this subpackage share: the shared folder, tables
written to cut lineage, gapless positions without a global window, and byte
views of Arrow text columns."""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

_WRITTEN: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share (``spark.checkpoint.dir``); a
    folder under /tmp/checkpoints is set only where the session names none."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        base = f"file:///tmp/checkpoints/segforest-{os.getuid()}"
        spark.sparkContext.setCheckpointDir(base)
    return base.rstrip("/")


def scratch(spark: SparkSession, what: str) -> str:
    """A new path below the shared folder; it is deleted when Python ends."""
    path = f"{shared_dir(spark)}/segforest/{what}-{uuid.uuid4().hex}"
    if not _WRITTEN:
        atexit.register(_clean)
    _WRITTEN.append((spark, path))
    return path


def drop_path(spark: SparkSession, path: str) -> None:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def _clean() -> None:
    for spark, path in _WRITTEN:
        if getattr(spark.sparkContext, "_jsc", None) is None:
            return
        try:
            drop_path(spark, path)
        except Exception as e:  # the JVM may already be gone when Python ends
            print(f"left behind: {path} ({type(e).__name__})")
            return


def written(df: DataFrame, what: str) -> DataFrame:
    """``df`` written as Parquet in the shared folder and read back: lineage ends
    there, and a lost executor costs no recomputation of what stands above."""
    path = scratch(df.sparkSession, what)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def pick(docs: DataFrame, wanted: dict[str, str], rest: bool = False) -> tuple[DataFrame, list[str]]:
    """``docs`` with the ``wanted`` columns (name: type) first, found by exact name, else
    by the first that differs in case only; with ``rest`` all columns follow
    under neutral names (returned), so that no other column's name can clash."""
    inner = [f"_c{i}" for i in range(len(docs.columns))]
    lower = [c.lower() for c in docs.columns]
    at = {w: docs.columns.index(w) if w in docs.columns else lower.index(w.lower()) for w in wanted}
    renamed = docs.toDF(*inner)
    chosen = [F.col(inner[at[w]]).cast(t).alias(w) for w, t in wanted.items()]
    return renamed.select(*chosen, *(inner if rest else [])), inner


def restored(df: DataFrame, inner: list[str], docs: DataFrame) -> DataFrame:
    """The columns of ``docs`` under their own names, from pick(..., rest=True)."""
    return df.select(*[F.col(x).alias(c) for x, c in zip(inner, docs.columns)])


DOC = {"doc_id": "long", "text": "string"}


def label_sample(labels: DataFrame, name: str, keep, per_class: int) -> DataFrame:
    """doc_id, label: at most ``per_class`` labelled rows of each class 0 and 1 (rows with
    ``keep`` only), chosen by a hash of doc_id. A doc_id with several labels has their
    largest; null ids and labels are left out."""
    two, _ = pick(labels, {"doc_id": "long", name: "int"})
    one = two.filter(F.col("doc_id").isNotNull() & F.col(name).isin(0, 1) & keep).groupBy("doc_id").agg(F.max(name).alias("label"))
    parts = [one.filter(F.col("label") == k).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class) for k in (0, 1)]
    return parts[0].union(parts[1])


def crc_mod(n: int):
    """crc32 of doc_id as text, modulo n."""
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % n


def with_positions(df: DataFrame, key: str, order: list[str], out: str, rows_per_bucket: int = 50_000, least: int = 64, ranges: bool = False) -> DataFrame:
    """Adds ``out``: gapless positions from 0 within each ``key`` (no nulls in it).
    They follow a hash of ``order``; with ``ranges``, whose order[0] is a whole number from 0 that hardly two rows
    share, they follow ``order`` itself.

    Rows of a key are dealt into hash buckets, numbered inside the bucket and
    shifted by the bucket's offset, so a hot key is never sorted in one task. The
    broadcast table has one row per (key, bucket), a number that the code computes
    from the row count: rows / rows_per_bucket + keys * least. ``df`` is read
    twice and should be cheap to read."""
    if ranges:
        end = (df.agg(F.max(order[0])).first()[0] or 0) + 1
        width = max(1, min(rows_per_bucket, -(-end // least)))
        bucket = F.floor(F.col(order[0]) / width)
    else:
        top = df.groupBy(key).count().agg(F.max("count")).first()[0] or 0
        bucket = F.pmod(F.xxhash64(*order), F.lit(max(least, -(-top // rows_per_bucket))))
    df = df.withColumn("_b", bucket)
    sizes = df.groupBy(key, "_b").agg(F.count("*").alias("_n"))
    w = Window.partitionBy(key).orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sizes.select(F.col(key).alias("_k"), F.col("_b").alias("_bb"), F.coalesce(F.sum("_n").over(w), F.lit(0)).alias("_off"))
    here = df.withColumn("_r", F.row_number().over(Window.partitionBy(key, "_b").orderBy(*order)))
    j = here.join(F.broadcast(offsets), (F.col(key) == F.col("_k")) & (F.col("_b") == F.col("_bb")))
    return j.withColumn(out, (F.col("_off") + F.col("_r") - 1).cast("long")).drop("_b", "_r", "_k", "_bb", "_off")


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a string column (null: empty) and its int64 offsets."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    n = len(column)
    _, offs, data = column.buffers()
    if n == 0 or data is None:
        return np.zeros(0, np.uint8), np.zeros(n + 1, np.int64)
    offsets = np.frombuffer(offs, np.int64)[column.offset : column.offset + n + 1]
    buf = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]]
    return buf, offsets - offsets[0]


def pieces(batches, column: str = "text", limit: int = 3 << 19):
    """Cuts record batches into slices of about ``limit`` text bytes (a longer
    single text is its own slice), which bounds the size of work arrays."""
    for batch in batches:
        n = batch.num_rows
        if not n:
            continue
        _, offsets = text_bytes(batch.column(batch.schema.get_field_index(column)))
        lo = 0
        while lo < n:
            hi = int(np.searchsorted(offsets, offsets[lo] + limit, "right")) - 1
            hi = min(n, max(hi, lo + 1))
            yield batch.slice(lo, hi - lo)
            lo = hi


def col(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finalizer."""
    x = x ^ (x >> np.uint64(30))
    x = x * _M1
    x = x ^ (x >> np.uint64(27))
    x = x * _M2
    return x ^ (x >> np.uint64(31))


_POW: list[np.ndarray] = []
_P = 0x9E3779B97F4A7C15 | 1
_PINV = pow(_P, -1, 1 << 64)


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _POW or len(_POW[0]) < n:
        size = max(1 << (n - 1).bit_length(), 1 << 14)
        out = []
        for base in (_P, _PINV):
            p = np.ones(size, np.uint64)
            k = 1
            while k < size:  # doubling
                step = np.uint64(pow(base, k, 1 << 64))
                m = min(k, size - k)
                p[k : k + m] = p[:m] * step
                k += m
            out.append(p)
        _POW[:] = out
    return _POW[0], _POW[1]


def word_spans(buf: np.ndarray, offsets: np.ndarray, is_word: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Runs of bytes marked in the 256-entry table ``is_word``, never across texts:
    first byte, end byte, and for each text the number of runs before it (n + 1)."""
    n = len(buf)
    if n == 0:
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(len(offsets), np.int64)
    w = is_word[buf]
    head = np.zeros(n + 1, bool)
    head[offsets] = True
    begins = w.copy()
    begins[1:] &= ~w[:-1] | head[1:n]
    ends = w.copy()
    ends[:-1] &= ~w[1:] | head[1:n]
    starts, stops = np.flatnonzero(begins), np.flatnonzero(ends) + 1
    return starts, stops, np.searchsorted(starts, offsets)


def span_hashes(values: np.ndarray, starts: np.ndarray, stops: np.ndarray) -> np.ndarray:
    """64-bit hashes of byte runs from one running sum; ``values`` are uint8."""
    p, inv = _powers(len(values) + 1)
    run = np.zeros(len(values) + 1, np.uint64)
    np.cumsum((values.astype(np.uint64) + np.uint64(1)) * p[: len(values)], out=run[1:])
    h = (run[stops] - run[starts]) * inv[starts]
    return mix(h + (stops - starts).astype(np.uint64) * _M1)


LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
