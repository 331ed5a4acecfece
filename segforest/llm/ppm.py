"""Language identification by prediction by partial matching.

For each language a tree of byte contexts of up to ``order`` bytes is counted once and
then frozen. A byte's code length in a context is -log2 n / (total + distinct); a byte new to
the context costs the escape -log2 distinct / (total + distinct) and is coded in the next
shorter context, down to 1/256. A text's language is the one whose tree codes all its bytes
in the fewest bits.

The trees are stored as arrays: for each order the grams (context and byte) that any
language has seen, with one code length per language, escapes included; and the
contexts' escape costs, for grams that no language has seen.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ._common import DOC, col, crc_mod, pick, pieces, text_bytes

PAD = 10  # texts are read as if line feeds came before them


class GramTable:
    """uint64 keys to row numbers by hashing in a few levels: a key goes to the first level where
    its slot is free, so a lookup ends at a free slot."""

    def __init__(self, keys: np.ndarray):
        self.levels, left, rows = [], keys, np.arange(len(keys))
        bits = max(8, int(4 * max(1, len(keys))).bit_length())
        odd = 0x9E3779B97F4A7C15
        while len(left):
            slot = ((left * np.uint64(odd)) >> np.uint64(64 - bits)).astype(np.int64)
            held, row = np.zeros(1 << bits, np.uint64), np.full(1 << bits, -1, np.int32)
            _, first = np.unique(slot, return_index=True)
            held[slot[first]], row[slot[first]] = left[first], rows[first]
            self.levels.append((np.uint64(odd), np.uint64(64 - bits), held, row))
            rest = np.ones(len(left), bool)
            rest[first] = False
            left, rows, odd, bits = left[rest], rows[rest], odd * 0xD6E8FEB86659FD93 % (1 << 64) | 1, max(8, bits - 2)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Row numbers, -1 for unknown keys."""
        out = np.full(len(keys), -1, np.int32)
        todo = None
        for odd, shift, held, row in self.levels:
            k = keys if todo is None else keys[todo]
            slot = (k * odd) >> shift
            r = row[slot]
            same = held[slot] == k
            hit = same & (r >= 0)
            if todo is None:
                out = np.where(hit, r, out)
                todo = np.flatnonzero(~same & (r >= 0))
            else:
                out[todo[hit]] = r[hit]
                todo = todo[~same & (r >= 0)]
            if not len(todo):
                break
        return out


def padded(buf: np.ndarray, offsets: np.ndarray, order: int) -> tuple[np.ndarray, np.ndarray]:
    """All texts, ``order`` PAD bytes before each, and where each text's own bytes begin (plus the end)."""
    n = len(offsets) - 1
    size = np.diff(offsets)
    begin = offsets[:-1] + order * np.arange(1, n + 1)
    out = np.full(len(buf) + order * n, PAD, np.uint8)
    out[np.arange(len(buf)) + np.repeat(order * np.arange(1, n + 1), size)] = buf
    return out, np.append(begin, len(out) + order)


def grams(bytes_: np.ndarray, length: int, order: int) -> np.ndarray:
    """For each own position p >= order, the ``length`` bytes that end there, as a number."""
    n = len(bytes_) - order
    h = np.zeros(max(0, n), np.uint64)
    for j in range(length):
        at = order - length + 1 + j
        h = (h << np.uint64(8)) | bytes_[at : at + n]
    return h


@dataclass
class ContextTrees:
    languages: list[str]
    order: int
    keys: list[np.ndarray]  # by order: grams, sorted
    costs: list[np.ndarray]  # float32 [grams, languages], bits
    contexts: list[np.ndarray]  # by order >= 1: contexts, sorted
    escapes: list[np.ndarray]  # float32 [contexts, languages], bits; 0 where a language has not seen it

    @classmethod
    def of(cls, languages: list[str], order: int, counts: list[dict]) -> ContextTrees:
        """counts[k]: (language number, gram of k + 1 bytes) arrays 'l', 'g', 'c'."""
        n, zero = len(languages), np.array([0], np.uint64)
        keys, costs, contexts, escapes = [], [], [], [np.zeros((1, n), np.float32)]
        for k in range(order + 1):
            lang, g, c = counts[k]["l"], counts[k]["g"], counts[k]["c"].astype(float)
            own = np.arange(256, dtype=np.uint64) if k == 0 else np.unique(g)
            ctx = zero if k == 0 else np.unique(g >> np.uint64(8))
            where = np.zeros(len(g), np.int64) if k == 0 else np.searchsorted(ctx, g >> np.uint64(8))
            total, kinds = np.zeros((len(ctx), n)), np.zeros((len(ctx), n))
            np.add.at(total, (where, lang), c)
            np.add.at(kinds, (where, lang), 1)
            with np.errstate(divide="ignore", invalid="ignore"):
                esc = np.where(total > 0, -np.log2(kinds / (total + kinds)), 0.0)
            if k == 0:
                shorter = np.full((256, n), 8.0)
            else:
                low = own & np.uint64((1 << (8 * k)) - 1)
                shorter = costs[k - 1][np.searchsorted(keys[k - 1], low)]
            cost = shorter + esc[np.zeros(len(own), np.int64) if k == 0 else np.searchsorted(ctx, own >> np.uint64(8))]
            cost[np.searchsorted(own, g), lang] = -np.log2(c / (total[where, lang] + kinds[where, lang]))
            keys.append(own)
            costs.append(cost.astype(np.float32))
            contexts.append(ctx)
            if k:
                escapes.append(esc.astype(np.float32))
        return cls(languages, order, keys, costs, contexts, escapes)

    def prepare(self) -> None:
        self._grams = [None, *(GramTable(k) for k in self.keys[1:])]
        self._contexts = [None, *(GramTable(c) for c in self.contexts[1:])]

    def lengths(self, buf: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Code lengths in bits [texts, languages], over all bytes of each text."""
        n, m = len(offsets) - 1, len(self.languages)
        out = np.zeros((n, m))
        if not len(buf) or not m:
            return out
        own, begin = padded(buf, offsets, self.order)
        full = np.flatnonzero(np.diff(offsets))
        real = np.zeros(len(own) - self.order, bool)
        real[np.arange(len(buf)) + np.repeat(self.order * np.arange(n), np.diff(offsets))] = True
        keys = grams(own, self.order + 1, self.order)[real]
        rows = self._grams[self.order].find(keys) if self.order else (keys & np.uint64(255)).astype(np.int32)
        missing = np.flatnonzero(rows < 0)
        extra = np.zeros((len(missing), m), np.float32)
        todo, g = np.arange(len(missing)), keys[missing]
        for k in range(self.order, 0, -1):  # unseen by all languages: escape and shorten
            ctx = self._contexts[k].find(g >> np.uint64(8))
            ok = ctx >= 0
            extra[todo[ok]] += self.escapes[k][ctx[ok]]
            g = g & np.uint64((1 << (8 * k)) - 1)
            r = self._grams[k - 1].find(g) if k > 1 else g.astype(np.int32)
            extra[todo[r >= 0]] += self.costs[k - 1][r[r >= 0]]
            todo, g = todo[r < 0], g[r < 0]
        at = offsets[full]
        rows[missing] = 0
        for l in range(m):
            cost = np.ascontiguousarray(self.costs[self.order][:, l])[rows]
            cost[missing] = extra[:, l]
            out[full, l] = np.add.reduceat(cost, at, dtype=np.float64)
        return out


def fit(docs: DataFrame, keep=None, order: int = 3, per_language: int = 400, max_languages: int = 1024) -> ContextTrees:
    """Trees from at most ``per_language`` documents of each language (those with the smallest
    hashes of doc_id) among the rows that ``keep`` allows with non-null text and lang.
    The driver holds the trees: distinct grams of languages * per_language texts. More than
    ``max_languages`` values of lang are an error, as lang is then not a language."""
    if not 0 <= order <= 5:
        raise ValueError("order must be 0 to 5")
    rows = pick(docs, DOC | {"lang": "string"})[0].filter("lang is not null and text is not null")
    rows = rows if keep is None else rows.filter(keep)
    sizes = rows.groupBy("lang").count().orderBy("lang").limit(max_languages + 1).collect()
    if len(sizes) > max_languages:
        raise ValueError(f"more than {max_languages} languages")
    languages = [r.lang for r in sizes]
    if not languages:
        return ContextTrees.of([], order, [{"l": np.zeros(0, np.int64), "g": np.zeros(0, np.uint64), "c": np.zeros(0)} for _ in range(order + 1)])
    spark = docs.sparkSession
    # a hash bound leaves about twice the wanted rows of each language; then the exact choice
    table = spark.createDataFrame([(r.lang, i, min(1.0, (2 * per_language + 50) / r["count"])) for i, r in enumerate(sizes)], "_lang string, l int, part double")
    h = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30))
    near = rows.join(F.broadcast(table), F.col("lang") == F.col("_lang")).withColumn("_h", h).filter(F.col("_h") < F.col("part") * (1 << 30))
    first = F.row_number().over(Window.partitionBy("l").orderBy("_h", "doc_id", F.xxhash64("text")))
    sample = near.withColumn("_n", first).filter(F.col("_n") <= per_language).select("l", "text")

    def count(batches):
        for s in pieces(batches):
            buf, offsets = text_bytes(col(s, "text"))
            own, _ = padded(buf, offsets, order)
            real = np.zeros(len(own) - order, bool)
            real[np.arange(len(buf)) + np.repeat(order * np.arange(s.num_rows), np.diff(offsets))] = True
            lang = np.repeat(col(s, "l").to_numpy(), np.diff(offsets)).astype(np.uint64)
            for k in range(order + 1):
                key, c = np.unique((lang << np.uint64(8 * (k + 1))) | grams(own, k + 1, order)[real], return_counts=True)
                shift = np.uint64(8 * (k + 1))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(key), k, np.int32)), pa.array((key >> shift).astype(np.int32)), pa.array((key & np.uint64((1 << int(shift)) - 1)).view(np.int64)), pa.array(c)], names=["k", "l", "g", "c"])

    found = sample.mapInArrow(count, "k int, l int, g long, c long").groupBy("k", "l", "g").agg(F.sum("c").alias("c")).toArrow()
    k = found.column("k").to_numpy()
    parts = {n: found.column(n).to_numpy() for n in ("l", "g", "c")}
    counts = [{"l": parts["l"][k == i].astype(np.int64), "g": parts["g"][k == i].astype(np.uint64), "c": parts["c"][k == i]} for i in range(order + 1)]
    return ContextTrees.of(languages, order, counts)


def identified(docs: DataFrame, trees: ContextTrees) -> DataFrame:
    """doc_id, lang_pred, score, bits_per_byte of each row. score is the share of the chosen language when
    each has weight 2 ** -(code length). ``und``, with score 0, for null texts and texts without
    a letter, and where no language was learned; of equal code lengths the first name wins."""
    shared = docs.sparkSession.sparkContext.broadcast(trees)  # bounded by languages * per_language texts

    def run(batches):
        t = shared.value
        t.prepare()
        names = pa.array([*t.languages, "und"], pa.string())
        for s in pieces(batches):
            text = col(s, "text")
            buf, offsets = text_bytes(text)
            bits = t.lengths(buf, offsets)
            letters = pc.match_substring_regex(text.fill_null(""), r"\pL").to_numpy(zero_copy_only=False)
            known = letters if t.languages else np.zeros(s.num_rows, bool)
            if t.languages:
                best = bits.argmin(1)
                least = bits[np.arange(len(best)), best]
                share = 1 / np.exp2(np.maximum(least[:, None] - bits, -1000)).sum(1)
            else:
                best, least, share = np.zeros(s.num_rows, np.int64), np.zeros(s.num_rows), np.zeros(s.num_rows)
            size = np.maximum(1, np.diff(offsets))
            pred = names.take(pa.array(np.where(known, best, len(t.languages))))
            yield pa.RecordBatch.from_arrays([col(s, "doc_id"), pred, pa.array(np.where(known, share, 0.0)), pa.array(np.where(known, least / size, 0.0))], names=["doc_id", "lang_pred", "score", "bits_per_byte"])

    return pick(docs, DOC)[0].mapInArrow(run, "doc_id long, lang_pred string, score double, bits_per_byte double")


def language_id(docs: DataFrame, **how) -> DataFrame:
    """doc_id, held_out, lang_pred, score; nothing is learned from held-out rows.

    Each row is judged by its whole text alone: repeated rows and equal texts get one answer, null texts and texts without a letter
    ``und`` with score 0, of equal code lengths the first name wins. A null doc_id is not learned from and not held out. Columns
    other than doc_id, text and lang are ignored, whatever their names; an empty table gives an empty result."""
    out = identified(docs, fit(docs, F.coalesce(crc_mod(4) != 2, F.lit(False)), **how))
    return out.select("doc_id", F.coalesce(crc_mod(4) == 2, F.lit(False)).alias("held_out"), "lang_pred", "score", "bits_per_byte")
