"""Quality by a Gaussian kernel machine over document statistics.

Random Fourier features cos(w.x + b), w normal with the kernel's width, approximate
the kernel; their ridge weights solve normal equations that partitions sum; and an isotonic
fit on labelled rows of its own turns ridge values into probabilities.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import DOC, LOWER, col, crc_mod, label_sample, pick, pieces, span_hashes, text_bytes, word_spans
from .decontam import shingle_hashes
from .neardup import IS_WORD

STATISTICS = ("log_bytes", "log_words", "word_length", "upper", "digit", "space", "stop", "exclaim", "symbol", "pipe", "quote", "high", "line_words", "short_words", "long_words", "unlike_words", "unlike_triples", "symbol_words", "upper_words", "entropy")


def _class(chars: str) -> np.ndarray:
    out = np.zeros(256, np.float32)
    out[[ord(c) for c in chars]] = 1
    return out


_UPPER, _DIGIT = _class("ABCDEFGHIJKLMNOPQRSTUVWXYZ"), _class("0123456789")
_SYMBOL = _class("#$%&*+<=>@\\^_`{|}~")
_HIGH = np.zeros(256, np.float32)
_HIGH[128:] = 1
_CLASSES = [_UPPER, _DIGIT, _class(" \t\r\n\v\f"), _class(".,;:"), _class("!?"), _SYMBOL, _class("|"), _class("\"'()[]"), _HIGH]


def statistics(column: pa.Array) -> np.ndarray:
    """float64 [texts, len(STATISTICS)] from whole texts; an empty text has zeros."""
    buf, offsets = text_bytes(column)
    n, size = len(offsets) - 1, np.diff(offsets)
    out = np.zeros((n, len(STATISTICS)))
    starts, stops, first = word_spans(buf, offsets, IS_WORD)
    words = np.diff(first)
    full = np.flatnonzero(size)
    if not len(full):
        return out
    hist = np.bincount(buf.astype(np.int64) + np.repeat(np.arange(n) * 256, size), minlength=n * 256).reshape(n, 256)
    share = hist / np.maximum(1, size)[:, None]
    logs = np.log2(share, out=np.zeros_like(share), where=share > 0)
    out[:, 0], out[:, 1] = np.log1p(size), np.log1p(words)
    out[:, 3:12] = share @ np.stack(_CLASSES, 1)
    out[:, 12] = np.log1p(words / (1 + hist[:, 10]))
    out[:, 19] = -(share * logs).sum(1)
    some = np.flatnonzero(words)
    if len(some):
        length, cut, w = stops - starts, first[:-1][some], words[some]
        mean = lambda x: np.add.reduceat(x.astype(np.float64), cut) / w
        out[some, 2], out[some, 13], out[some, 14] = mean(length), mean(length <= 2), mean(length >= 12)
        out[some, 17], out[some, 18] = mean(_SYMBOL[buf[stops - 1]]), mean(_UPPER[buf[starts]] * _UPPER[buf[stops - 1]])
        h = span_hashes(LOWER[buf], starts, stops)
        triples = shingle_hashes(h, 3)
        for t in some:
            a, b = first[t], first[t + 1]
            out[t, 15] = _kinds(h[a:b]) / (b - a)
            out[t, 16] = _kinds(triples[a : b - 2]) / (b - a - 2) if b - a > 2 else 1
    return out


def _kinds(h: np.ndarray) -> int:
    h = np.sort(h)
    return 1 + int((h[1:] != h[:-1]).sum())


@dataclass
class QualityModel:
    mean: np.ndarray
    scale: np.ndarray
    w: np.ndarray
    b: np.ndarray
    ridge: np.ndarray
    knots: np.ndarray
    values: np.ndarray

    def features(self, x: np.ndarray) -> np.ndarray:
        return fourier((np.clip((x - self.mean) / self.scale, -6, 6)), self.w, self.b)

    def raw(self, x: np.ndarray) -> np.ndarray:
        return self.features(x) @ self.ridge

    def score(self, x: np.ndarray) -> np.ndarray:
        return np.interp(self.raw(x), self.knots, self.values)


def fourier(x: np.ndarray, w: np.ndarray, b: np.ndarray) -> np.ndarray:
    z = np.cos(x @ w + b) * np.sqrt(2 / len(b))
    return np.concatenate([z, np.ones((len(x), 1))], 1)


def isotonic(x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pooled adjacent violators: knots and rising values; equal x are pooled first."""
    x, inverse = np.unique(x, return_inverse=True)
    y = np.bincount(inverse, y * weight) / np.bincount(inverse, weight)
    weight = np.bincount(inverse, weight)
    blocks: list[list[float]] = []  # mean, weight, first, last
    for i in range(len(x)):
        blocks.append([y[i], weight[i], i, i])
        while len(blocks) > 1 and blocks[-2][0] >= blocks[-1][0]:
            m, w, _, last = blocks.pop()
            p = blocks[-1]
            p[0], p[1], p[3] = (p[0] * p[1] + m * w) / (p[1] + w), p[1] + w, last
    knots = np.array([v for m, w, a, b in blocks for v in ((x[a], x[b]) if b > a else (x[a],))])
    values = np.array([v for m, w, a, b in blocks for v in ((m, m) if b > a else (m,))])
    return knots, np.clip(values, 0, 1)


def fit(docs: DataFrame, labels: DataFrame, keep=None, per_class: int = 20_000, features: int = 384, width: float = 3.0, l2: float = 1e-4, seed: int = 5, partitions: int = 4) -> QualityModel:
    """Fits on at most ``per_class`` labelled rows of each class whose labels ``keep``
    allows, each class weighted to its share of all those labels. One row in five (by hash) calibrates.
    ``partitions`` partitions of the sample's statistics (few numbers a row) send sums of (features + 1) ** 2 numbers. With labels of one
    class only every text scores that class; with none 0.5."""
    rows, _ = pick(docs, DOC)
    keep = F.lit(True) if keep is None else keep
    share = {r.label: r.n for r in pick(labels, {"doc_id": "long", "quality": "int"})[0].filter(keep & F.col("quality").isin(0, 1)).groupBy(F.col("quality").alias("label")).agg(F.count("*").alias("n")).collect()}
    d, total = len(STATISTICS), max(1, sum(share.values()))
    rng = np.random.default_rng(seed)
    w, b = rng.normal(size=(d, features)) / width, rng.uniform(0, 2 * np.pi, features)
    p = share.get(1, 0) / total if share else 0.5
    flat = QualityModel(np.zeros(d), np.ones(d), w, b, np.zeros(features + 1), np.array([0.0]), np.array([p]))
    chosen = label_sample(labels, "quality", keep, per_class)

    def stats(batches):
        for s in pieces(batches):
            x = statistics(col(s, "text"))
            yield pa.RecordBatch.from_arrays([col(s, "label"), col(s, "part"), pa.FixedSizeListArray.from_arrays(pa.array(x.ravel()), d).cast(pa.list_(pa.float64()))], names=["label", "part", "x"])

    part = F.pmod(F.xxhash64(F.lit(3), "doc_id"), F.lit(5)).cast("int").alias("part")
    sample = rows.join(F.broadcast(chosen), "doc_id").select("label", part, "text").mapInArrow(stats, "label int, part int, x array<double>")
    from ._common import written

    sample = written(sample, "quality-sample").repartition(partitions)
    sizes = {r.label: r.n for r in sample.groupBy("label").agg(F.count("*").alias("n")).collect()}
    if not sizes.get(0) or not sizes.get(1):
        return flat
    per = {k: share[k] / total / sizes[k] * sum(sizes.values()) for k in sizes}

    def moments(batches):
        n, s1, s2 = 0, np.zeros(d), np.zeros(d)
        for batch in batches:
            x = np.array(col(batch, "x").flatten()).reshape(-1, d)
            n, s1, s2 = n + len(x), s1 + x.sum(0), s2 + (x**2).sum(0)
        yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([s1.tolist()]), pa.array([s2.tolist()])], names=["n", "s1", "s2"])

    m = sample.mapInArrow(moments, "n long, s1 array<double>, s2 array<double>").collect()
    n = sum(r.n for r in m)
    mean = np.sum([r.s1 for r in m], 0) / n
    scale = np.sqrt(np.maximum(np.sum([r.s2 for r in m], 0) / n - mean**2, 1e-8))

    def normal(batches):
        a, c, have = np.zeros((features + 1, features + 1)), np.zeros(features + 1), False
        for batch in batches:
            fit_ = np.flatnonzero(col(batch, "part").to_numpy() != 0)
            x, y = np.array(col(batch, "x").flatten()).reshape(-1, d)[fit_], col(batch, "label").to_numpy()[fit_]
            z = fourier(np.clip((x - mean) / scale, -6, 6), w, b)
            zw = z * np.where(y == 1, per[1], per[0])[:, None]
            a, c, have = a + zw.T @ z, c + zw.T @ y, True
        if have:
            yield pa.RecordBatch.from_arrays([pa.array([a.tobytes()]), pa.array([c.tobytes()])], names=["a", "c"])

    sums = sample.mapInArrow(normal, "a binary, c binary").collect()
    a = sum(np.frombuffer(r.a).reshape(features + 1, -1) for r in sums)
    c = sum(np.frombuffer(r.c) for r in sums)
    ridge = np.linalg.solve(a + l2 * n * np.eye(features + 1) / features, c)
    model = QualityModel(mean, scale, w, b, ridge, np.array([0.0]), np.array([p]))
    rest = sample.filter("part = 0").toArrow()
    if rest.num_rows:
        x, y = np.array(rest.column("x").combine_chunks().flatten()).reshape(-1, d), rest.column("label").to_numpy()
        model.knots, model.values = isotonic(model.raw(x), y.astype(float), np.where(y == 1, per[1], per[0]))
    return model


def scored(docs: DataFrame, model: QualityModel) -> DataFrame:
    """doc_id and score of each row, from the text alone (null: empty)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        for s in pieces(batches):
            yield pa.RecordBatch.from_arrays([col(s, "doc_id"), pa.array(m.score(statistics(col(s, "text"))))], names=["doc_id", "score"])

    return pick(docs, DOC)[0].mapInArrow(run, "doc_id long, score double")


def quality(docs: DataFrame, labels: DataFrame, threshold: float = 0.7, **how) -> DataFrame:
    """doc_id, held_out, score, predicted of every row; labels of held-out rows are not used.

    Each row is scored by its whole text alone: repeated rows and equal texts score alike, a null text scores as an empty one
    (all statistics 0). A null doc_id is not held out and no label is its. Of several labels of a doc_id the largest
    counts. Columns other than doc_id and text are ignored, whatever their names; an empty table gives an empty result."""
    out = scored(docs, fit(docs, labels, F.coalesce(crc_mod(4) != 2, F.lit(False)), **how))
    return out.select("doc_id", F.coalesce(crc_mod(4) == 2, F.lit(False)).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
