"""Document fingerprints from closed syncmers.

A k-gram of bytes is chosen when the smallest hash among its s-grams stands at its first
or last place. That depends on the k-gram alone, so an edit changes only the anchors that it
touches. A fingerprint is all anchor hashes of a text (by occurrence), each with its place, so
it grows with the text (about one anchor to 4.5 bytes, 12 characters each); two fingerprints
are compared on all of them, and the common anchors count that lie on the longest chain of
places that increase in both texts.
"""

from __future__ import annotations

import base64
import hashlib
from bisect import bisect_left

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import DOC, col, mix, pick, text_bytes

K, S = 12, 4


def syncmers(buf: np.ndarray, offsets: np.ndarray, k: int = K, s: int = S) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes, texts and places of all closed syncmers; a text of fewer than k bytes (but
    not none) has one anchor of all its bytes."""
    size = np.diff(offsets)
    h = mix(_grams(buf, s) * np.uint64(0x9E3779B97F4A7C15)) if len(buf) >= k else np.zeros(0, np.uint64)
    n, w = len(buf) - k + 1, k - s + 1
    if n > 0:
        least, have = h, 1
        while have < w:
            step = min(have, w - have)
            least = np.minimum(least[: len(least) - step], least[step:])
            have += step
        at = np.flatnonzero((least[:n] == h[:n]) | (least[:n] == h[w - 1 : w - 1 + n]))
        text = np.searchsorted(offsets, at, "right") - 1
        whole = at + k <= offsets[text + 1]
        at, text = at[whole], text[whole]
        value = h[at]
        for j in range(s, k - s + 1, s):
            value = mix(value * np.uint64(0xD6E8FEB86659FD93) + h[at + j])
        if k % s:
            value = mix(value * np.uint64(0xD6E8FEB86659FD93) + h[at + k - s])
    else:
        at, text, value = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64)
    short = np.flatnonzero((size > 0) & (size < k))
    if len(short):
        own = np.array([int.from_bytes(hashlib.blake2b(buf[offsets[t] : offsets[t + 1]].tobytes(), digest_size=8).digest(), "little") for t in short], np.uint64)
        value, text, at = np.append(value, own), np.append(text, short), np.append(at, offsets[short])
        order = np.argsort(text, kind="stable")
        value, text, at = value[order], text[order], at[order]
    return value, text, at - offsets[text]


def _grams(buf: np.ndarray, s: int) -> np.ndarray:
    n = len(buf) - s + 1
    h = np.zeros(max(0, n), np.uint64)
    for j in range(s):
        h = (h << np.uint64(8)) ^ buf[j : j + n]
    return h


def fingerprints(texts: list[str], k: int = K, s: int = S) -> list[tuple[int, np.ndarray, np.ndarray]]:
    """(number of anchors, their hashes ascending, their places) of each text. The second and
    later occurrences of an anchor have hashes of their own, so repetition counts."""
    buf, offsets = text_bytes(pa.array(texts, pa.large_string()))
    value, text, place = syncmers(buf, offsets, k, s)
    cut = np.searchsorted(text, np.arange(len(texts) + 1))
    out = []
    for t in range(len(texts)):
        v, p = value[cut[t] : cut[t + 1]], place[cut[t] : cut[t + 1]]
        order = np.argsort(v, kind="stable")
        v, p = v[order], p[order]
        new = np.concatenate([[True], v[1:] != v[:-1]]) if len(v) else np.zeros(0, bool)
        index = np.arange(len(v))
        nth = index - np.maximum.accumulate(np.where(new, index, 0)) if len(v) else index
        if nth.any():
            v = np.where(nth > 0, mix(v + nth.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)), v)
            order = np.argsort(v)
            v, p = v[order], p[order]
        out.append((len(v), v, p.astype(np.int64)))
    return out


def encode(fp: tuple[int, np.ndarray, np.ndarray]) -> str:
    """As a string: the count, then in base 64 the hashes (8 bytes each) in order of place, and
    the steps from place to place (all of 1, 2, 4 or 8 bytes, the least that holds them)."""
    n, v, p = fp
    order = np.argsort(p)
    steps = np.diff(p[order], prepend=0)
    return f"{n}:" + base64.b64encode(v[order].astype("<u8").tobytes() + steps.astype(np.min_scalar_type(steps.max(initial=0))).tobytes()).decode()


def decode(text: str) -> tuple[int, np.ndarray, np.ndarray]:
    n, _, body = text.partition(":")
    n, raw = int(n), base64.b64decode(body)
    if not n:
        return 0, np.zeros(0, np.uint64), np.zeros(0, np.int64)
    v = np.frombuffer(raw, "<u8", n)
    p = np.cumsum(np.frombuffer(raw, f"<u{len(raw) // n - 8}", n, 8 * n).astype(np.int64))
    order = np.argsort(v)
    return n, v[order].astype(np.uint64), p[order]


def chain(p: np.ndarray, q: np.ndarray) -> int:
    """The most pairs (p[i], q[i]) that can be kept so that both places increase; no place occurs twice in
    p or in q. Pairs next to each other in both orders go together, so only blocks of them are searched."""
    if not len(p):
        return 0
    rank = np.empty(len(q), np.int64)
    rank[np.argsort(q)] = np.arange(len(q))
    rank = rank[np.argsort(p)]
    first = np.flatnonzero(np.diff(rank, prepend=-2) != 1)
    ends, best = [], []  # last block of a chain and the chain's pairs, both ascending
    for r, w in zip(rank[first].tolist(), np.diff(first, append=len(rank)).tolist()):
        at = bisect_left(ends, r)
        total = w + (best[at - 1] if at else 0)
        worse = bisect_left(best, total + 1, at)
        ends[at:worse], best[at:worse] = [r], [total]
    return best[-1]


def likeness(x: tuple, y: tuple) -> float:
    """Share of common anchors in the union (Jaccard) of two fingerprints, over all anchors. Common
    anchors count if they are on the longest chain that has the same order in both texts, whatever
    was put in or taken out between them; the n-th occurrence of an anchor meets the n-th. Two
    empty texts are alike (1), an empty and another are not (0)."""
    (n, u, p), (m, v, q) = x, y
    if not n or not m:
        return float(n == m)
    at = np.minimum(np.searchsorted(v, u), m - 1)
    both = v[at] == u
    return float(chain(p[both], q[at[both]]) / (n + m - both.sum()))


_COLUMNS = [("n_chars", pa.int64()), ("edited_sha256", pa.string()), ("fingerprint", pa.string()), ("edited_fingerprint", pa.string()), ("near_edited", pa.float64()), ("near_next", pa.float64())]


def _judged(ids: list, texts: list[str], following: list[str]) -> pa.RecordBatch:
    """One output row for each text; following[i] is texts[i + 1], then the last one's next."""
    edited = []
    for t, nxt in zip(texts, following):
        m = len(t) // 3
        edited.append(t[: len(t) - m] + nxt[:m])
    own, other = fingerprints([*texts, following[-1]]), fingerprints(edited)
    after = own[1:]
    rows = [(i, len(t), hashlib.sha256(e.encode("utf-8", "surrogatepass")).hexdigest(), encode(a), encode(b), likeness(a, b), likeness(a, c)) for i, t, e, a, b, c in zip(ids, texts, edited, own, other, after)]
    cols = list(zip(*rows))
    return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), *(pa.array(c, t) for c, (_, t) in zip(cols[1:], _COLUMNS))], names=["doc_id", *(n for n, _ in _COLUMNS)])


_OUT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def _borders(ids: DataFrame, parts: int) -> list[int]:
    """The greatest doc_id of each of at most ``parts`` ranges, descending; Spark's range exchange of the ids alone finds them."""
    ranged = ids.filter("doc_id is not null").repartitionByRange(parts, F.desc("doc_id")).select(F.spark_partition_id().alias("p"), "doc_id")
    return sorted((r.m for r in ranged.groupBy("p").agg(F.max("doc_id").alias("m")).collect()), reverse=True)


def edit_fingerprints(docs: DataFrame, part_bytes: int = 8 << 20, slice_chars: int = 1 << 20) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next.

    The edited text of a document replaces its last floor(n_chars / 3) code points by the
    first as many (or all) of the next document in descending doc_id; after the last
    comes the first. Null texts count as empty. Null doc_ids come last; equal doc_ids are ordered by
    text, and rows that are equal in both follow each other. A single row is its own next. Other columns are ignored.

    Texts move once: rows are dealt into ranges of doc_id of about ``part_bytes`` of text, and the first row of each range
    goes to the range before it as well, as the next of its last row. Every task and the driver hold two ids a range, as they
    hold something for each partition of any exchange."""
    spark = docs.sparkSession
    two, _ = pick(docs, DOC)
    two = two.withColumn("text", F.coalesce("text", F.lit("")))
    parts = max(1, -(-(two.agg(F.sum(F.octet_length("text") + 16)).first()[0] or 0) // part_bytes))
    heads = _borders(two.select("doc_id"), parts)[1:] if parts > 1 else []  # range k has the ids that k of these reach
    parts, shared = len(heads) + 1, spark.sparkContext.broadcast(np.sort(np.array(heads, np.int64)))

    @F.pandas_udf("int")
    def place(ids: pd.Series) -> pd.Series:
        """Ranges in descending order."""
        return pd.Series((len(shared.value) - np.searchsorted(shared.value, ids.to_numpy(np.int64), "left")).astype(np.int32))

    # nulls stand below all ids, so they are in the last range
    placed = two.withColumn("part", place(F.coalesce("doc_id", F.lit(-(1 << 63)))))
    firsts = placed.select("part", "doc_id").groupBy("part").agg(F.max("doc_id").alias("head")).collect()
    heads = sorted((r.part, r.head) for r in firsts)
    before = [(head, part, heads[k - 1][0]) for k, (part, head) in enumerate(heads)]
    guests = F.broadcast(spark.createDataFrame(before, "head long, head_part int, host int"))
    same = F.col("doc_id").eqNullSafe(F.col("head")) & (F.col("part") == F.col("head_part"))
    own = F.struct(F.col("part").alias("part"), F.lit(0).alias("guest"))
    also = F.struct(F.col("host").alias("part"), F.lit(1).alias("guest"))
    dealt = placed.join(guests, same, "left").select("doc_id", "text", F.explode(F.when(F.col("host").isNull(), F.array(own)).otherwise(F.array(own, also))).alias("at"))
    dealt = dealt.select("doc_id", "text", "at.part", "at.guest").repartitionById(parts, "part")
    dealt = dealt.sortWithinPartitions("part", "guest", F.desc_nulls_last("doc_id"), "text")

    def run(batches):
        ids, texts, size, part, met = [], [], 0, None, False
        for b in batches:
            for i, t, p, g in zip(*(col(b, n).to_pylist() for n in ("doc_id", "text", "part", "guest"))):
                if p != part:
                    part, met, ids, texts, size = p, False, [], [], 0
                if met:
                    continue  # only the first guest is the next row
                ids.append(i)
                texts.append(t)
                size += len(t)
                met = g == 1
                if len(texts) > 1 and (met or size >= slice_chars):
                    yield _judged(ids[:-1], texts[:-1], texts[1:])
                    ids, texts, size = ids[-1:], texts[-1:], len(t)

    return dealt.mapInArrow(run, _OUT)
