"""Benchmark decontamination by a prefix-filtered containment join.

A window is ``window`` consecutive item words (a shorter item is one window). Seen as
a set of positional shingles that a text must contain whole, its necessary prefix is
``len - ceil(1.0 * len) + 1`` = one shingle: the rarest. So the shingles of each window
are ordered by how often they occur in the corpus, the rarest joins with the
texts, position and length bounds drop starts where the window would leave
the text, and the rest is verified word by word.

The benchmark is the stated query set. It is read in blocks of at most ``block_bytes`` of
item text, each small enough to be sent to every task; the texts stay where they are, so
nothing of the corpus is shuffled unless there is more than one block, when the blocks'
hits of a text are merged by doc_id.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import DOC, LOWER, col, mix, pick, pieces, restored, span_hashes, text_bytes, word_spans, written

IS_WORD = np.zeros(256, bool)
IS_WORD[48:58] = IS_WORD[65:91] = IS_WORD[97:123] = IS_WORD[128:] = True
#: Words in an anchor shingle; shorter windows have one shingle of all their words.
ANCHOR_WORDS = 3
_A, _B = np.uint64(0xD6E8FEB86659FD93), np.uint64(0xA0761D6478BD642F)


def shingle_hashes(words: np.ndarray, n: int) -> np.ndarray:
    h = words[: len(words) - n + 1].copy() if len(words) >= n else np.zeros(0, np.uint64)
    for j in range(1, n):
        h = mix(h * _A + words[j : len(words) - n + 1 + j] * _B)
    return h


@dataclass
class Words:
    """The words of a few texts: lower-cased bytes, spans, hashes, first word of each text."""

    low: np.ndarray
    starts: np.ndarray
    stops: np.ndarray
    first: np.ndarray
    hashes: np.ndarray

    @classmethod
    def of(cls, column: pa.Array) -> Words:
        buf, offsets = text_bytes(column)
        low = LOWER[buf]
        starts, stops, first = word_spans(low, offsets, IS_WORD)
        return cls(low, starts, stops, first, span_hashes(low, starts, stops))

    def text(self, k: int) -> bytes:
        return self.low[self.starts[k] : self.stops[k]].tobytes()

    def shingles(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Hashes and first words of the n-word shingles that stay in one text."""
        h = shingle_hashes(self.hashes, n)
        if not len(h):
            return h, np.zeros(0, np.int64)
        whole = np.ones(len(h), bool)
        for j in range(1, n):
            at = self.first[1:-1] - j
            whole[at[(at >= 0) & (at < len(h))]] = False
        # a text boundary at word b spoils the shingles that start at b-1 .. b-n+1
        return h[whole], np.flatnonzero(whole)


class Probe:
    """Which of many 64-bit hashes are in a small sorted table: a bitmap first, then search."""

    def __init__(self, keys: np.ndarray):
        self.keys = keys
        bits = max(16, int(len(keys) * 16).bit_length())
        self.shift = np.uint64(64 - bits)
        self.map = np.zeros(1 << bits, bool)
        self.map[keys >> self.shift] = True

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions in ``h`` and in the table of the equal hashes."""
        near = np.flatnonzero(self.map[h >> self.shift])
        if not len(near) or not len(self.keys):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        k = np.minimum(np.searchsorted(self.keys, h[near]), len(self.keys) - 1)
        ok = self.keys[k] == h[near]
        return near[ok], k[ok]


@dataclass
class Windows:
    """The distinct windows of one block of items, and their items."""

    words: list[tuple[bytes, ...]] = field(default_factory=list)
    items: list[list[int]] = field(default_factory=list)
    item_ids: list[str | None] = field(default_factory=list)

    @classmethod
    def of(cls, rows: list[tuple[str | None, str]], window: int) -> Windows:
        out, known = cls(), {}
        numbers: dict = {}
        for item_id, text in rows:
            if (k := numbers.setdefault(item_id, len(out.item_ids))) == len(out.item_ids):
                out.item_ids.append(item_id)
            w = Words.of(pa.array([text]))
            all_words = [w.text(i) for i in range(len(w.starts))]
            n = min(window, len(all_words))
            for at in range(len(all_words) - n + 1 if n else 0):
                key = tuple(all_words[at : at + n])
                if (j := known.setdefault(key, len(out.words))) == len(out.words):
                    out.words.append(key)
                    out.items.append([])
                if k not in out.items[j][-1:]:
                    out.items[j].append(k)
        return out

    def shingles(self) -> dict[int, np.ndarray]:
        """Sorted distinct shingle hashes by shingle length."""
        out: dict[int, set] = {}
        for w in self.words:
            n = min(ANCHOR_WORDS, len(w))
            out.setdefault(n, set()).update(int(x) for x in shingle_hashes(self._hashes(w), n))
        return {n: np.array(sorted(s), np.uint64) for n, s in out.items()}

    @staticmethod
    def _hashes(words: tuple[bytes, ...]) -> np.ndarray:
        low = np.frombuffer(b"".join(words), np.uint8)
        stops = np.cumsum([len(x) for x in words])
        return span_hashes(low, stops - [len(x) for x in words], stops)


def rarity(docs: DataFrame, tables: dict[int, np.ndarray]) -> dict[int, np.ndarray]:
    """How often each shingle of the block occurs in all texts. A task sends one row
    for each shingle that it met, of at most the block's shingles; Spark sums them."""

    def count(batches):
        probes, sums = {n: Probe(t) for n, t in tables.items()}, {n: np.zeros(len(t), np.int64) for n, t in tables.items()}
        for s in pieces(batches):
            w = Words.of(col(s, "text"))
            for n, p in probes.items():
                sums[n] += np.bincount(p.find(w.shingles(n)[0])[1], minlength=len(p.keys))
        for n, c in sums.items():
            k = np.flatnonzero(c)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(k), n), pa.int32()), pa.array(k, pa.int64()), pa.array(c[k], pa.int64())], names=["n", "k", "c"])

    out = {n: np.zeros(len(t), np.int64) for n, t in tables.items()}
    for r in docs.select("text").mapInArrow(count, "n int, k long, c long").groupBy("n", "k").agg(F.sum("c").alias("c")).toLocalIterator():
        out[r.n][r.k] = r.c
    return out


class Matcher:
    """Finds every occurrence of a block's windows in texts."""

    def __init__(self, windows: Windows, counts: dict[int, np.ndarray], tables: dict[int, np.ndarray]):
        self.w, self.tables, rows = windows, {}, {n: {} for n in tables}
        for j, words in enumerate(windows.words):
            n = min(ANCHOR_WORDS, len(words))
            h = shingle_hashes(windows._hashes(words), n)
            at = min(range(len(h)), key=lambda i: (counts[n][np.searchsorted(tables[n], h[i])], i))
            rows[n].setdefault(int(h[at]), []).append((j, at))
        for n, r in rows.items():
            keys = np.array(sorted(r), np.uint64)
            self.tables[n] = (keys, [r[int(k)] for k in keys])

    def probes(self) -> dict[int, Probe]:
        return {n: Probe(keys) for n, (keys, _) in self.tables.items()}

    def hits(self, w: Words, probes: dict[int, Probe]) -> dict[int, tuple[list[tuple[int, int]], set[int]]]:
        """By text: word ranges covered by windows, and the items' numbers."""
        found: dict[int, tuple[list[tuple[int, int]], set[int]]] = {}
        for n, p in probes.items():
            h, first = w.shingles(n)
            at, key = p.find(h)
            if not len(at):
                continue
            text = np.searchsorted(w.first, first[at], "right") - 1
            for pos, k, t in zip(first[at].tolist(), key.tolist(), text.tolist()):
                for j, offset in self.tables[n][1][k]:
                    words, lo = self.w.words[j], pos - offset
                    if lo < w.first[t] or lo + len(words) > w.first[t + 1]:
                        continue  # the window would begin before or end after the text
                    if all(w.text(lo + i) == x for i, x in enumerate(words)):
                        ranges, items = found.setdefault(t, ([], set()))
                        ranges.append((lo - int(w.first[t]), lo - int(w.first[t]) + len(words)))
                        items.update(self.w.items[j])
        return found


_OUT = "doc_id long, n_words long, spans array<struct<lo:int,hi:int>>, items array<string>"
_ARROW = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("spans", pa.list_(pa.struct([("lo", pa.int32()), ("hi", pa.int32())]))), ("items", pa.list_(pa.string()))])


def _merged(ranges: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for lo, hi in sorted(ranges):
        if out and lo <= out[-1][1]:
            out[-1] = (out[-1][0], max(hi, out[-1][1]))
        else:
            out.append((lo, hi))
    return out


def _blocks(benchmark: DataFrame, block_bytes: int):
    """Lists of (item_id, text) of at most ``block_bytes`` of text; the driver holds one at a
    time, and a single longer item is a block."""
    rows, held = [], 0
    two = pick(benchmark, {"item_id": "string", "text": "string"})[0].select(F.col("item_id").alias("i"), F.coalesce("text", F.lit("")).alias("t"))
    for r in two.orderBy("i", "t").toLocalIterator():
        if rows and held + len(r.t) > block_bytes:
            yield rows
            rows, held = [], 0
        rows.append((r.i, r.t))
        held += len(r.t)
    yield rows


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = 10, block_bytes: int = 4 << 20, rest: bool = False) -> DataFrame:
    """For each row of ``docs`` (doc_id, text): n_words, the merged word ``spans`` that windows
    cover, and the sorted distinct ``items`` whose windows occur; with ``rest`` the columns of
    ``docs`` follow under neutral names. One block needs no join; several merge by a row number.

    Words are lower-cased (A-Z) runs of digits, ASCII letters and bytes above 0x7F. Null and empty texts have
    no words; items without words have no windows. Rows that repeat an item_id are one item, and so are all rows with a null one, which
    stands last in ``items`` and is written as nothing in digest().
    Rows with equal or null doc_ids each keep their own result."""
    base, inner = pick(docs, DOC, rest)
    carry = inner if rest else []
    schema = base.drop("doc_id", "text").schema
    results = []
    blocks = _blocks(benchmark, block_bytes)
    block = next(blocks)
    following = next(blocks, None)
    many = following is not None
    if many:  # rows need a key of their own to be merged by
        base = written(base.withColumn("_row", F.monotonically_increasing_id()), "decontam-rows")
    while block is not None:
        results.append(_one_block(base, block, window, [*carry, *(["_row"] if many else [])]))
        block, following = following, next(blocks, None) if following is not None else None
    if not many:
        return results[0]
    united = results[0]
    for r in results[1:]:
        united = united.unionByName(r)
    keep = [F.first(c, ignorenulls=False).alias(c) for c in ["doc_id", "n_words", *schema.names]]
    g = united.groupBy("_row").agg(*keep, F.flatten(F.collect_list("spans")).alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))
    # unite the blocks' ranges: sorted by start, each either extends the last or begins anew
    fold = F.aggregate(
        F.array_sort("spans"),
        F.array().cast("array<struct<lo:int,hi:int>>"),
        lambda acc, s: F.when((F.size(acc) > 0) & (s["lo"] <= F.try_element_at(acc, F.lit(-1))["hi"]), F.concat(F.slice(acc, 1, F.greatest(F.size(acc) - 1, F.lit(0))), F.array(F.struct(F.try_element_at(acc, F.lit(-1))["lo"].alias("lo"), F.greatest(F.try_element_at(acc, F.lit(-1))["hi"], s["hi"]).alias("hi"))))).otherwise(F.concat(acc, F.array(s))),
    )
    return g.withColumn("spans", fold).drop("_row")


def _one_block(base: DataFrame, block: list[tuple[str, str]], window: int, carry: list[str]) -> DataFrame:
    spark = base.sparkSession
    windows = Windows.of(block, window)
    tables = windows.shingles()
    counts = rarity(base, tables) if tables else {}
    shared = spark.sparkContext.broadcast(Matcher(windows, counts, tables))  # bounded by block_bytes

    def run(batches):
        m = shared.value
        probes = m.probes()
        for s in pieces(batches):
            w = Words.of(col(s, "text"))
            found = m.hits(w, probes)
            spans, items = [[]] * s.num_rows, [[]] * s.num_rows
            for t, (ranges, which) in found.items():
                spans[t] = [{"lo": lo, "hi": hi} for lo, hi in _merged(ranges)]
                items[t] = sorted({m.w.item_ids[k] for k in which}, key=lambda i: (i is None, i or ""))
            arrays = [col(s, "doc_id"), pa.array(np.diff(w.first), pa.int64()), pa.array(spans, _ARROW.field("spans").type), pa.array(items, _ARROW.field("items").type)]
            yield pa.RecordBatch.from_arrays([*arrays, *(col(s, c) for c in carry)], names=[*_ARROW.names, *carry])

    extra = "".join(f", `{f.name}` {f.dataType.simpleString()}" for f in base.schema if f.name in carry)
    return base.mapInArrow(run, _OUT + extra)


def digest(found: DataFrame) -> DataFrame:
    """The contract's columns from contamination()'s."""
    hit = F.aggregate("spans", F.lit(0), lambda a, s: a + s["hi"] - s["lo"]).cast("long")
    return found.select("doc_id", "n_words", hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join(F.array_sort(F.transform("items", lambda i: F.coalesce(i, F.lit("")))), ","), 256).alias("items_sha256"), (F.size("spans") > 0).alias("contaminated"))


def clean(docs: DataFrame, benchmark: DataFrame, window: int = 10) -> DataFrame:
    """The rows of ``docs`` in whose text no window occurs, with their columns."""
    _, inner = pick(docs, DOC, rest=True)
    return restored(contamination(docs, benchmark, window, rest=True).filter(F.size("spans") == 0), inner, docs)


def brute_force(texts: dict[int, str | None], items: dict[str, str | None], window: int = 10) -> dict[int, tuple[int, int, list[str]]]:
    """Words, hit words and items by plain comparison at every position; for tests."""
    import re

    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))
    out = {}
    for d, t in texts.items():
        dw, hit, which = words(t), set(), set()
        for i, it in items.items():
            iw = words(it)
            n = min(window, len(iw))
            for a in range(len(iw) - n + 1 if n else 0):
                for p in range(len(dw) - n + 1):
                    if dw[p : p + n] == iw[a : a + n]:
                        hit.update(range(p, p + n))
                        which.add(i)
        out[d] = (len(dw), len(hit), sorted(which))
    return out


_LETTERS = "abcdefghijklmnopqrstuvwxyz"
_SQL_WORDS = f"regexp_extract_all(translate(coalesce(text, ''), '{_LETTERS.upper()}', '{_LETTERS}'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') as w"
#: digest(contamination()) by an equal join of all runs of as many words as some window has.
SQL = f"""
with d as (select row_number() over () as line, doc_id, {_SQL_WORDS} from documents), b as (select item_id::varchar as item_id, {_SQL_WORDS} from benchmark),
i as (select distinct item_id, n, array_to_string(w[pos : pos + n - 1], ' ') as said from (select *, least(10, len(w)) as n, unnest(range(1, len(w) - least(10, len(w)) + 2)) as pos from b where len(w) > 0)),
g as (select line, pos, n, array_to_string(w[pos : pos + n - 1], ' ') as said from (select line, w, n.n, unnest(range(1, len(w) - n.n + 2)) as pos from d, (select distinct n from i) n where len(w) >= n.n)),
found as (select line, pos, n, item_id from g join i using (n, said)),
words as (select line, count(distinct place) as n_hit from (select line, unnest(range(pos, pos + n)) as place from (select distinct line, pos, n from found)) group by line),
items as (select line, count(*) as n_items, sha256(string_agg(item_id, ',' order by item_id)) as items_sha256 from (select distinct line, item_id from found) group by line)
select doc_id, len(w)::bigint as n_words, coalesce(n_hit, 0)::bigint as n_hit, coalesce(n_items, 0)::bigint as n_items, coalesce(items_sha256, sha256('')) as items_sha256, n_hit is not null as contaminated
from d left join words using (line) left join items using (line)
"""
