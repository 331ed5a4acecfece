"""Toxicity behind a noisy channel.

Writers hide words by look-alike characters (1d10t), spacing (i d i o t, i.d.i.o.t) and
repetition (idiooot). Each suspicious stretch becomes a lattice of what the
characters may stand for, with channel costs, and Viterbi search finds the best
path under a character trigram model counted over all texts. The restored
text, lower-cased, is scored by a logistic model on the presence of character 5-grams, which
is fitted on a bounded sample of labelled rows.

Text without such stretches has a lattice of a single path and is left as it is.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import DOC, col, crc_mod, label_sample, mix, pick, pieces, restored
from .decontam import Probe

# What characters may stand for.
LOOKS_LIKE = {
    "0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "gb", "7": "t", "8": "b", "9": "g",
    "@": "a", "$": "s", "!": "il", "|": "il", "+": "t", "(": "c", "€": "e", "£": "l", "¥": "y", "µ": "u", "*": "aeiou",
}
_LEET = "".join(re.escape(c) for c in LOOKS_LIKE)
#: What may stand between spaced characters, in any length. "*" and "|" are separators and look-alikes: between characters the
#: decoder chooses, at the start they are characters.
_SEPARATORS = r"\s.\-_*/~,|"
_SYMBOLS = "".join(re.escape(c) for c in LOOKS_LIKE if not c.isalnum() and c not in "*|")
_CHAR = rf"(?:[^\W_]|[{_SYMBOLS}])"
_SPACED = re.compile(rf"(?<![^\W_])(?:({_CHAR})(?:\1\1+)?|[*|])(?:[{_SEPARATORS}]+({_CHAR})(?:\2\2+)?){{2,}}(?<!!)(?![^\W_])")
_REPEATED = re.compile(rf"({_CHAR})\1*(?:[{_SEPARATORS}]+\1+){{2,}}")
_SUSPECT = re.compile(rf"[^\W\d_][{_LEET}]|[{_LEET}][^\W\d_]|([^\W\d_])\1\1", re.I)
_TAIL = re.compile(r"[!.,;:?)*&%#\]}\"']+$|\${3,}$")
#: Texts that do not match, and have no letter three times in a row (thrice()), have nothing to restore.
_GATE = rf"\pL[{_LEET}]|[{_LEET}]\pL"
_UNIT = rf"(?:[\pL\pN{_SYMBOLS}]|" + "|".join(f"{re.escape(c)}{{3,}}" for c in LOOKS_LIKE) + ")"
_GATE += rf"|(?:^|[^\pL\pN])(?:{_UNIT}|[*|])(?:[{_SEPARATORS}\pZ\x0b\x1c-\x1f\x{{85}}]+{_UNIT}){{2,}}(?:[^\pL\pN]|$)"
# Channel costs in nats: a substitution, a symbol that stands for itself, a run shortened to one or two, a separator kept or dropped.
SUBSTITUTE, ITSELF, TO_ONE, TO_TWO, KEEP_GAP, DROP_GAP = 1.0, 6.0, 1.0, 1.5, 4.0, 0.5

#: Symbols of the character model: boundary, a-z, the letters from U+00DF to U+00FF, any other letter.
_LETTERS = "abcdefghijklmnopqrstuvwxyz" + "".join(chr(c) for c in range(0xDF, 0x100) if c != 0xF7)
SYMBOLS = len(_LETTERS) + 2
GRAM = 5


@cache
def fold_table() -> np.ndarray:
    """Lower-case letter of each code point; 0 for what is not a letter."""
    out = np.zeros(0x110000, np.uint32)
    for c in range(0x110000):
        ch = chr(c)
        if ch.isalpha():
            low = ch.lower()
            out[c] = ord(low) if len(low) == 1 else c
    return out


@cache
def symbol_table() -> np.ndarray:
    fold = fold_table()
    known = np.full(0x110000, SYMBOLS - 1, np.uint8)
    known[0] = 0
    for i, ch in enumerate(_LETTERS):
        known[ord(ch)] = i + 1
    return known[fold]


def code_points(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of all texts, with one 0 before each, and where each text's 0 is."""
    at = np.cumsum([0, *(len(t) + 1 for t in texts)])
    return np.frombuffer(("\0" + "\0".join(texts)).encode("utf-32-le", "surrogatepass"), "<u4"), at


def thrice(texts: list[str]) -> np.ndarray:
    """Which texts have one letter of any alphabet, in either case, three times in a row."""
    points, at = code_points(texts)
    c = fold_table()[points]
    hit = np.flatnonzero((c[2:] == c[1:-1]) & (c[1:-1] == c[:-2]) & (c[2:] != 0))
    out = np.zeros(len(texts), bool)
    out[np.searchsorted(at, hit, "right") - 1] = True
    return out


def trigram_counts(docs: DataFrame) -> np.ndarray:
    """Counts [SYMBOLS]*3 over the letters and word boundaries of all texts. A task sends
    at most SYMBOLS ** 3 rows; Spark sums them."""

    def count(batches):
        sums, table = np.zeros(SYMBOLS**3, np.int64), symbol_table()
        for s in pieces(batches):
            points, _ = code_points(col(s, "text").fill_null("").to_pylist())
            c = table[points]
            c = c[np.concatenate([[True], (c[1:] != 0) | (c[:-1] != 0)])].astype(np.int32)
            if len(c) > 2:
                sums += np.bincount((c[:-2] * SYMBOLS + c[1:-1]) * SYMBOLS + c[2:], minlength=SYMBOLS**3)
        k = np.flatnonzero(sums)
        yield pa.RecordBatch.from_arrays([pa.array(k), pa.array(sums[k])], names=["k", "c"])

    out = np.zeros(SYMBOLS**3, np.int64)
    for r in docs.select("text").mapInArrow(count, "k long, c long").groupBy("k").agg(F.sum("c").alias("c")).toLocalIterator():
        out[r.k] = r.c
    return out.reshape((SYMBOLS,) * 3)


class CharModel:
    """Trigram model with bigram, unigram and uniform parts mixed in; costs in nats."""

    def __init__(self, counts: np.ndarray):
        c3 = counts.astype(float)
        c2, c1 = c3.sum(0), c3.sum((0, 1))
        p1 = (c1 + 1) / (c1.sum() + SYMBOLS)
        p2 = (c2 + 8 * p1) / (c2.sum(1, keepdims=True) + 8)
        p3 = (c3 + 8 * p2[None]) / (c3.sum(2, keepdims=True) + 8)
        self.cost = -np.log(p3)
        self.rows = self.cost.tolist()
        self.id = {ch: i + 1 for i, ch in enumerate(_LETTERS)}

    def symbol(self, ch: str) -> int:
        return self.id.get(ch, SYMBOLS - 1) if ch.isalpha() else 0

    def decode(self, lattice: list[list[tuple[str, float]]]) -> str:
        """The cheapest reading of ``lattice``: for each position (string, channel cost)
        options; all readings stand between word boundaries."""
        best = {(0, 0): (0.0, None)}
        for options in [*lattice, [(" ", 0.0)]]:
            after: dict = {}
            for (a, b), (cost, path) in best.items():
                for out, extra in options:
                    x, y, total = a, b, cost + extra
                    for ch in out:
                        z = self.symbol(ch)
                        if z == 0 and y == 0:
                            continue
                        total += self.rows[x][y][z]
                        x, y = y, z
                    if (old := after.get((x, y))) is None or total < old[0]:
                        after[x, y] = (total, (path, out))
            best = after
        _, path = min(best.values(), key=lambda v: v[0])
        path, parts = path[0], []
        while path is not None:
            path, out = path
            parts.append(out)
        return "".join(reversed(parts))


def _letters(text: str) -> list[list[tuple[str, float]]]:
    """The lattice of a stretch: runs of a letter, look-alikes, other characters."""
    out = []
    for m in re.finditer(r"(.)\1*", text.lower(), re.S):
        ch, n = m[1], len(m[0])
        if ch in LOOKS_LIKE:
            itself = (" ", ITSELF) if not ch.isdigit() else (ch, ITSELF)
            each = [*((x, SUBSTITUTE) for x in LOOKS_LIKE[ch]), itself]
            out += [each] * n if n < 3 else [[*each, *((x * 2, SUBSTITUTE + TO_TWO) for x in LOOKS_LIKE[ch])]]
        elif ch.isalpha() and n >= 3:
            out.append([(ch, TO_ONE), (ch * 2, TO_TWO)])
        else:
            out += [[(ch, 0.0)]] * n
    return out


class Restorer:
    """Rewrites suspicious stretches; readings of single words are kept in a bounded table."""

    def __init__(self, model: CharModel, most: int = 200_000):
        self.model, self.most, self.known = model, most, {}

    def word(self, w: str) -> str:
        tail = _TAIL.search(w)
        core = w[: tail.start()] if tail else w
        if not _SUSPECT.search(core) or not any(c.isalpha() for c in core):
            return w
        if (out := self.known.get(core)) is None:
            if len(self.known) >= self.most:
                self.known = {}
            out = self.known[core] = self.model.decode(_letters(core))
        return out + w[len(core) :]

    def _spaced(self, m: re.Match) -> str:
        """The reading of a spaced run; without a letter it stays as it is."""
        if not any(c.isalpha() for c in m[0]):
            return m[0]
        lattice = []
        run = _REPEATED.sub(lambda r: r[1] * 3, m[0].lower())
        for part in re.finditer(rf"({_CHAR})\1*|[{_SEPARATORS}]+", run):
            gap, n = part[0], len(part[0])
            if part[1]:
                lattice += _letters(gap)
            elif part.start() == 0:
                lattice.append([(" ", KEEP_GAP), *((x, SUBSTITUTE) for x in LOOKS_LIKE[gap[0]])])
            else:
                both = {x for c in gap if c in LOOKS_LIKE for x in LOOKS_LIKE[c]}
                lattice.append([("", DROP_GAP * n), (" ", KEEP_GAP / n), *((x, SUBSTITUTE + DROP_GAP * (n - 1)) for x in sorted(both))])
        return self.model.decode(lattice)

    def text(self, t: str) -> str:
        t = _SPACED.sub(self._spaced, t)
        return re.sub(r"\S+", lambda m: self.word(m[0]), t)

    def texts(self, column: pa.Array) -> list[str]:
        """All texts (null: empty), those that the gate finds rewritten."""
        column = column.fill_null("")
        texts = column.to_pylist()
        gate = pc.match_substring_regex(column, _GATE).to_numpy(zero_copy_only=False) | thrice(texts)
        return [self.text(t) if g else t for t, g in zip(texts, gate)]


def gram_hashes(texts: list[str], n: int = GRAM) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the n-grams of folded letters (what lies between words is one boundary),
    and the text of each. N-grams stay in one text, which begins and ends with a boundary."""
    points, at = code_points(texts)
    c = fold_table()[points]
    keep = np.concatenate([[True], (c[1:] != 0) | (c[:-1] != 0)])
    keep[at[:-1]] = True
    text = np.repeat(np.arange(len(texts)), np.diff(at))[keep]
    c = c[keep].astype(np.uint64)
    c, text = np.append(c, np.zeros(n, np.uint64)), np.append(text, np.full(n, -1))
    h = np.zeros(len(c) - n + 1, np.uint64)
    for j in range(n):
        h = (h + c[j : len(c) - n + 1 + j]) * np.uint64(0x9E3779B97F4A7C15)
    # the 0 that begins the next text ends this one
    same = text[: len(h)] == text[n - 2 : n - 2 + len(h)]
    same &= text[: len(h)] >= 0
    return mix(h[same]), text[: len(h)][same]


@dataclass
class ToxicityModel:
    trigrams: np.ndarray
    keys: np.ndarray
    weights: np.ndarray
    bias: float

    def score(self, texts: list[str], probe: Probe | None = None) -> np.ndarray:
        h, text = gram_hashes(texts)
        at, key = (probe or Probe(self.keys)).find(h)
        pairs = np.unique(text[at] * len(self.keys) + key) if len(at) else np.zeros(0, np.int64)
        z = self.bias + np.bincount(pairs // max(1, len(self.keys)), self.weights[pairs % max(1, len(self.keys))] if len(pairs) else None, minlength=len(texts))
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _logistic(features: np.ndarray, counts: np.ndarray, y: np.ndarray, k: int, l2: float = 1.0, rounds: int = 200) -> tuple[np.ndarray, float]:
    """Ridge logistic regression on binary features by accelerated gradient steps. ``counts`` says how
    many of the ``features`` each row has."""
    n = len(counts)
    where = np.repeat(np.arange(n, dtype=np.int32), counts)
    w, v, b, vb = np.zeros(k), np.zeros(k), 0.0, 0.0
    curve = np.bincount(features, minlength=k) / 4 * max(1.0, counts.mean()) ** 0.5 + l2
    for t in range(rounds):
        m = t / (t + 3)
        wx, bx = w + m * (w - v), b + m * (b - vb)
        g = 1 / (1 + np.exp(-np.clip(bx + np.bincount(where, wx[features], minlength=n), -30, 30))) - y
        v, vb = w, b
        w, b = wx - (np.bincount(features, g[where], minlength=k) + l2 * wx) / curve / 2, bx - 2 * g.sum() / n
    return w, float(b)


def fit(docs: DataFrame, labels: DataFrame, keep=None, per_class: int = 20_000, features: int = 2048, least_docs: int = 5) -> ToxicityModel:
    """Character counts over all texts of ``docs``, and weights from at most ``per_class``
    rows of each class whose labels ``keep`` allows. The driver holds the
    SYMBOLS ** 3 counts, ``features`` weights, and the chosen features of the sample.
    Without labels of both classes every text scores the share of label 1 (0 without labels)."""
    docs, _ = pick(docs, DOC)
    trigrams = trigram_counts(docs)
    chosen = label_sample(labels, "toxic", F.lit(True) if keep is None else keep, per_class)
    sample = docs.join(F.broadcast(chosen), "doc_id").select("text", "label")  # at most 2 * per_class ids
    share = {r.label: r.n for r in pick(labels, {"doc_id": "long", "toxic": "int"})[0].filter(F.lit(True) if keep is None else keep).groupBy(F.col("toxic").alias("label")).agg(F.count("*").alias("n")).collect()}
    shared = docs.sparkSession.sparkContext.broadcast(trigrams)

    def grams(batches):
        restorer = Restorer(CharModel(shared.value))
        for s in pieces(batches):
            h, text = gram_hashes(restorer.texts(col(s, "text")))
            order = np.lexsort((h, text))
            h, text = h[order], text[order]
            once = np.concatenate([[True], (h[1:] != h[:-1]) | (text[1:] != text[:-1])]) if len(h) else np.zeros(0, bool)
            h, y = h[once], col(s, "label").to_numpy()[text[once]]
            keys, inverse = np.unique(h, return_inverse=True)
            pos = np.bincount(inverse, y, minlength=len(keys)).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(pos), pa.array(np.bincount(inverse, minlength=len(keys)) - pos)], names=["k", "pos", "neg"])

    sizes = {r.label: r.n for r in sample.groupBy("label").agg(F.count("*").alias("n")).collect()}
    n1, n0 = sizes.get(1, 0), sizes.get(0, 0)
    if not n1 or not n0:
        p = share.get(1, 0) / max(1, share.get(0, 0) + share.get(1, 0))
        return ToxicityModel(trigrams, np.zeros(0, np.uint64), np.zeros(0), float(np.log(max(p, 1e-12) / max(1 - p, 1e-12))))
    table = sample.mapInArrow(grams, "k long, pos long, neg long").groupBy("k").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))
    # association of presence with the label: squared difference of rates over its variance
    rate = (F.col("pos") + F.col("neg")) / (n0 + n1)
    z = (F.col("pos") / n1 - F.col("neg") / n0) / F.sqrt(rate * (1 - rate) * (1 / n1 + 1 / n0) + 1e-9)
    top = table.filter(F.col("pos") + F.col("neg") >= least_docs).withColumn("z", F.abs(z)).filter("z > 4").orderBy(F.desc("z"), "k").limit(features).select("k").collect()
    keys = np.sort(np.array([r.k for r in top], np.int64).view(np.uint64))

    def design(batches):
        restorer, probe = Restorer(CharModel(shared.value)), Probe(keys)
        for s in pieces(batches):
            h, text = gram_hashes(restorer.texts(col(s, "text")))
            at, key = probe.find(h)
            pairs = np.unique(text[at] * max(1, len(keys)) + key)
            ends = np.searchsorted(pairs, np.arange(s.num_rows + 1) * max(1, len(keys))).astype(np.int32)
            yield pa.RecordBatch.from_arrays([col(s, "label"), pa.ListArray.from_arrays(pa.array(ends), pa.array((pairs % max(1, len(keys))).astype(np.int32)))], names=["label", "f"])

    rows = sample.mapInArrow(design, "label int, f array<int>").toArrow().combine_chunks()
    lists = rows.column("f").combine_chunks()
    ends = lists.offsets.to_numpy().astype(np.int64)
    w, b = _logistic(lists.values.to_numpy(), np.diff(ends), rows.column("label").to_numpy().astype(float), len(keys))
    b += np.log(share.get(1, 1) / max(1, share.get(0, 1))) - np.log(n1 / n0)  # from the sample's share to the labels'
    return ToxicityModel(trigrams, keys, w, b)


def scored(docs: DataFrame, model: ToxicityModel, rest: bool = False) -> DataFrame:
    """doc_id and score of each row; the score depends on the text alone. Null and empty
    texts have no n-gram and score the bias."""
    base, inner = pick(docs, DOC, rest)
    shared = docs.sparkSession.sparkContext.broadcast(model)  # SYMBOLS ** 3 counts and the features
    names = [*(inner if rest else []), "doc_id"]

    def run(batches):
        m = shared.value
        restorer, probe = Restorer(CharModel(m.trigrams)), Probe(m.keys)
        for s in pieces(batches):
            score = m.score(restorer.texts(col(s, "text")), probe)
            yield pa.RecordBatch.from_arrays([*(col(s, c) for c in names), pa.array(score)], names=[*names, "score"])

    out = base.drop("text").select(*names).schema.add("score", "double")
    return base.mapInArrow(run, out)


def restored_texts(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """doc_id and the restored text of each row (null stays null)."""
    shared = docs.sparkSession.sparkContext.broadcast(model.trigrams)

    def run(batches):
        restorer = Restorer(CharModel(shared.value))
        for s in pieces(batches):
            t = col(s, "text")
            yield pa.RecordBatch.from_arrays([col(s, "doc_id"), pc.if_else(pc.is_valid(t), pa.array(restorer.texts(t), pa.string()), None)], names=["doc_id", "restored"])

    return pick(docs, DOC)[0].mapInArrow(run, "doc_id long, restored string")


def toxicity(docs: DataFrame, labels: DataFrame, per_class: int = 20_000) -> DataFrame:
    """doc_id, held_out, score, predicted of every row; labels of held-out rows are not used.

    Each row is scored by its text alone: repeated rows and equal texts score alike, a null text scores as an empty one, of any
    length the whole text counts. A null doc_id is not held out and no label is its. Of several labels of a doc_id the
    largest counts. Columns other than doc_id and text are ignored, whatever their names; an empty table gives an
    empty result, and without labels of both classes every text scores the share of label 1."""
    mine = (crc_mod(5) != 0) & F.col("doc_id").isNotNull()
    out = scored(docs, fit(docs, labels, mine, per_class))
    return out.select("doc_id", F.coalesce(crc_mod(5) == 0, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def without_toxic(docs: DataFrame, labels: DataFrame, threshold: float = 0.5, per_class: int = 20_000) -> DataFrame:
    """The rows of ``docs`` that score below ``threshold``, with their columns."""
    mine = (crc_mod(5) != 0) & F.col("doc_id").isNotNull()
    _, inner = pick(docs, DOC, rest=True)
    return restored(scored(docs, fit(docs, labels, mine, per_class), rest=True).filter(F.col("score") < threshold), inner, docs)
