"""Near-duplicate groups: MinHash bands, odd sketches, exact confirmation.

1. Each text becomes the set of its word shingles (64-bit hashes), ``samples``
   MinHash values, their odd sketch, and one key per band of ``rows`` values. The
   sketch of ``bits`` bits flips, for every sample, the bit that (sample number, value)
   hashes to; the XOR of two sketches counts (in parity) the samples that differ,
   which tells high similarities apart more finely than the share of equal samples.
2. Equal sets collapse to one representative, so copies cost one row each.
3. Star rounds: in every bucket each member is paired with the bucket's leader of the round
   only (the smallest member, later ones by a hash); length and sketch bounds drop pairs, each
   member keeps its nearest leader, and the pair is confirmed on full sets. Links
   join trees, and rounds go on in the buckets that hold several trees while they find enough.
   From the second round on sketches fold whole sets: their XOR never counts more
   bits than the sets differ in, which makes the bound strict.
4. What is left are trees that share a bucket without a link so far. Members of *different* trees of a
   bucket are compared inside a join, block by block, whose condition is that strict bound, so
   that little more than the links come out; these are confirmed. No pair of a bucket is
   missed, and a large group of near copies never expands into its pairs.

Everything stays distributed: buckets are grouped by partial aggregates and equi joins
(which Spark splits when one key is hot), and each step is written to the shared folder.
"""

from __future__ import annotations

from math import sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ._common import DOC, LOWER, col, mix, pick, pieces, restored, span_hashes, text_bytes, word_spans, written
from .decontam import shingle_hashes

SPACE = np.zeros(256, bool)
SPACE[[32, 9, 10, 11, 12, 13]] = True
IS_WORD = ~SPACE
#: Bits of the sketch of MinHash samples, and of the sketch of a whole set.
BITS, SET_BITS = 512, 2048
#: Star rounds at most; what they leave is compared in blocks, so the bound costs no link.
MOST_ROUNDS = 8
#: Members of one bucket that are compared with as many others in one group of rows.
BLOCK = 512
#: Tasks that share the members of one bucket.
SALTS = 16


def shingle_sets(column: pa.Array, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct hashes of all texts' n-word shingles, and each text's first (n + 1
    offsets). A text of fewer words has one shingle of all its words; none without words."""
    buf, offsets = text_bytes(column)
    low = LOWER[buf]
    starts, stops, first = word_spans(low, offsets, IS_WORD)
    words = span_hashes(low, starts, stops)
    full = shingle_hashes(words, n)
    counts = np.diff(first)
    sets, sizes = [], np.zeros(len(counts), np.int64)
    for t in range(len(counts)):
        c = counts[t]
        if c >= n:
            h = np.sort(full[first[t] : first[t + 1] - n + 1])
            h = h[np.concatenate([[True], h[1:] != h[:-1]])]
        elif c:
            h = mix(shingle_hashes(words[first[t] : first[t + 1]], int(c)) + np.uint64(c))
        else:
            continue
        sets.append(h)
        sizes[t] = len(h)
    at = np.concatenate([[0], np.cumsum(sizes)])
    return (np.concatenate(sets) if sets else np.zeros(0, np.uint64)), at


def minhashes(sets: np.ndarray, at: np.ndarray, samples: int, seed: int = 7) -> np.ndarray:
    """uint32 [non-empty texts, samples]."""
    full = np.flatnonzero(np.diff(at))
    out = np.empty((len(full), samples), np.uint32)
    if not len(full):
        return out
    rng = np.random.default_rng(seed)
    a = rng.integers(0, 1 << 32, samples, np.uint32) | np.uint32(1)
    b = rng.integers(0, 1 << 32, samples, np.uint32)
    x, cut = (sets >> np.uint64(32)).astype(np.uint32), at[full]
    work = np.empty_like(x)
    for m in range(samples):
        np.bitwise_xor(x, b[m], out=work)
        np.multiply(work, a[m], out=work)
        np.bitwise_xor(work, work >> np.uint32(15), out=work)
        np.multiply(work, np.uint32(0x2C1B3C6D), out=work)
        out[:, m] = np.minimum.reduceat(work, cut)
    return out


def odd_sketches(values: np.ndarray, bits: int = BITS) -> np.ndarray:
    """int64 [texts, bits / 64]: parity of how many samples hash to each bit."""
    n, k = values.shape
    h = mix(values.astype(np.uint64) + (np.arange(k, dtype=np.uint64) << np.uint64(32)))
    flat = (h % np.uint64(bits)).astype(np.int64) + np.arange(n)[:, None] * bits
    odd = (np.bincount(flat.ravel(), minlength=n * bits) & 1).astype(np.uint8).reshape(n, bits)
    return np.packbits(odd, axis=1).view(">i8").astype(np.int64)


def sketch_similarity(distance: float, samples: int, bits: int = BITS) -> float:
    """The share of equal samples that an XOR count of ``distance`` bits tells."""
    x = 1 - 2 * distance / bits
    differ = np.log(max(x, 1e-9)) / (2 * np.log(1 - 2 / bits))
    return max(0.0, 1 - differ / samples)


def sketch_bound(threshold: float, samples: int, bits: int = BITS, sigmas: float = 5.5) -> int:
    """The XOR count that a pair at the threshold passes with less than one in a million."""
    size = 2 * samples * (1 - threshold)
    keep = (1 - 2 / bits) ** size
    mean = bits / 2 * (1 - keep)
    own = bits / 4 * (1 - keep * keep)
    drawn = (2 * keep * sqrt(samples * threshold * (1 - threshold))) ** 2
    return int(mean + sigmas * sqrt(own + drawn))


SAMPLED = [f"k{i}" for i in range(BITS // 64)]
WHOLE = [f"q{i}" for i in range(SET_BITS // 64)]


def signatures(docs: DataFrame, shingle: int, samples: int, rows: int) -> DataFrame:
    """One row for each row of ``docs``: _row (a number of its own), doc_id, t (a hash of the text), n_shingles, s1 and s2 (128 bits
    that name the set), sketch words k0.., bands (array of keys; empty for empty sets)."""
    base = pick(docs, DOC)[0].withColumn("_row", F.monotonically_increasing_id()).withColumn("t", F.xxhash64("text"))
    words = BITS // 64

    def run(batches):
        for s in pieces(batches):
            sets, at = shingle_sets(col(s, "text"), shingle)
            n, size = s.num_rows, np.diff(at)
            full = np.flatnonzero(size)
            values = minhashes(sets, at, samples)
            run_ = [np.concatenate([[np.uint64(0)], np.cumsum(mix(sets + np.uint64(k)))]) for k in (11, 13)]
            name = [(r[at[1:]] - r[at[:-1]]).view(np.int64) for r in run_]
            sketch = np.zeros((n, words), np.int64)
            sketch[full] = odd_sketches(values)
            bands = samples // rows
            h = np.full((len(full), bands), 0, np.uint64) + np.arange(bands, dtype=np.uint64)
            for j in range(rows):
                h = mix(h * np.uint64(0x9E3779B97F4A7C15) + values[:, j : bands * rows : rows].astype(np.uint64))
            ends = np.concatenate([[0], np.cumsum((size > 0) * bands)]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(h.ravel().view(np.int64)))
            yield pa.RecordBatch.from_arrays([col(s, "_row"), col(s, "doc_id"), col(s, "t"), pa.array(size), *map(pa.array, name), *(pa.array(sketch[:, i].copy()) for i in range(words)), lists], names=["_row", "doc_id", "t", "n_shingles", "s1", "s2", *(f"k{i}" for i in range(words)), "bands"])

    return base.mapInArrow(run, "_row long, doc_id long, t long, n_shingles long, s1 long, s2 long, " + ", ".join(f"k{i} long" for i in range(words)) + ", bands array<long>")


def _differ(a: str, b: str, words: list[str]) -> Column:
    """Bits in which two sketches differ."""
    return sum((F.bit_count(F.col(f"{a}.{k}").bitwiseXOR(F.col(f"{b}.{k}"))) for k in words), F.lit(0))


def _near(a: str, b: str, per: int, bound: int | None) -> Column:
    """Bounds that every linked pair meets: set sizes within the threshold (``per`` hundredths), sketches
    near. Without ``bound`` the sketches are of whole sets, which differ in at most
    (1 - t) / (1 + t) of their sizes' sum."""
    x, y = F.col(f"{a}.n_shingles"), F.col(f"{b}.n_shingles")
    near = _differ(a, b, SAMPLED) <= bound if bound is not None else _differ(a, b, WHOLE) * (100 + per) <= (x + y) * (100 - per)
    return (F.least(x, y) * 100 >= F.greatest(x, y) * per) & near


def _sets(docs: DataFrame, wanted: DataFrame, shingle: int) -> DataFrame:
    """rep, n_shingles, set (sorted distinct hashes, as signed numbers) and its sketch words q0.. of the representatives in ``wanted`` (rep, doc_id, t, s1, s2).
    A text comes back by its doc_id and hash, so rows that share a doc_id, or have none, meet only their own text."""
    w = wanted.select("rep", F.col("doc_id").alias("w_id"), F.col("t").alias("w_t"), "s1", "s2")
    j = pick(docs, DOC)[0].join(w, F.col("doc_id").eqNullSafe(F.col("w_id")) & (F.xxhash64("text") == F.col("w_t"))).select("rep", "s1", "s2", "text")

    def run(batches):
        for s in pieces(batches):
            sets, at = shingle_sets(col(s, "text"), shingle)
            run_ = [np.concatenate([[np.uint64(0)], np.cumsum(mix(sets + np.uint64(k)))]) for k in (11, 13)]
            ok = np.ones(s.num_rows, bool)
            for name, r in zip(("s1", "s2"), run_):
                ok &= (r[at[1:]] - r[at[:-1]]).view(np.int64) == col(s, name).to_numpy()
            keep = np.flatnonzero(ok)
            lists = pa.ListArray.from_arrays(pa.array(at.astype(np.int32)), pa.array(sets.view(np.int64)))
            flat = (mix(sets ^ np.uint64(17)) % np.uint64(SET_BITS)).astype(np.int64) + np.repeat(np.arange(s.num_rows), np.diff(at)) * SET_BITS
            odd = (np.bincount(flat, minlength=s.num_rows * SET_BITS) & 1).astype(np.uint8).reshape(-1, SET_BITS)
            words = np.packbits(odd, axis=1).view(">i8").astype(np.int64)[keep]
            take = pa.array(keep)
            yield pa.RecordBatch.from_arrays([col(s, "rep").take(take), pa.array(np.diff(at)[keep]), lists.take(take), *(pa.array(words[:, i].copy()) for i in range(words.shape[1]))], names=["rep", "n_shingles", "set", *WHOLE])

    # rows that repeat a doc_id and a text give the same set again
    return j.mapInArrow(run, "rep long, n_shingles long, set array<long>, " + ", ".join(f"{k} long" for k in WHOLE)).dropDuplicates(["rep"])


def _lists(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Values and offsets of a list column without nulls."""
    return column.values.to_numpy(), column.offsets.to_numpy()


def _confirmed(pairs: DataFrame, sets: DataFrame, threshold: float) -> DataFrame:
    """The pairs (a, b) whose full sets have 100 * intersection >= 100 * threshold * union."""
    per = round(threshold * 100)
    x = pairs.join(sets.select(F.col("rep").alias("b"), F.col("set").alias("set_b")), "b")
    x = x.join(sets.select(F.col("rep").alias("a"), F.col("set").alias("set_a")), "a").select("a", "b", "set_a", "set_b")

    def run(batches):
        for batch in batches:
            ok = []
            (x, i), (y, j) = (_lists(col(batch, n)) for n in ("set_a", "set_b"))
            for k in range(batch.num_rows):
                u, v = x[i[k] : i[k + 1]], y[j[k] : j[k + 1]]
                both = len(u) + len(v) - len(np.union1d(u, v))
                ok.append(bool(both) and 100 * both >= per * (len(u) + len(v) - both))
            keep = pa.array(np.flatnonzero(ok))
            yield pa.RecordBatch.from_arrays([col(batch, "a").take(keep), col(batch, "b").take(keep)], names=["a", "b"])

    return x.mapInArrow(run, "a long, b long")


def components(edges: DataFrame) -> DataFrame:
    """node, root of every node of ``edges`` (a, b): root is the smallest node of its component.

    Each round hangs every node below its smallest neighbour and passes its other smaller
    neighbours on to it, until all nodes have one parent; then parents are
    followed by doubling. Groups are by the larger end, so the centre of a
    large star is never a group."""
    e = edges.select(F.least("a", "b").alias("lo"), F.greatest("a", "b").alias("hi")).filter("lo < hi").distinct()
    e = written(e, "links")
    while True:
        least = e.groupBy("hi").agg(F.min("lo").alias("p"), F.count("*").alias("n"))
        if not least.filter("n > 1").limit(1).count():
            break
        many = e.join(least.filter("n > 1"), "hi", "left")
        kept = many.select(F.coalesce("p", "lo").alias("lo"), "hi")
        passed = many.filter("lo > p").select(F.col("p").alias("lo"), F.col("lo").alias("hi"))
        e = written(kept.union(passed).distinct(), "links")
    up = e.select(F.col("hi").alias("node"), F.col("lo").alias("root"))
    while True:
        above = up.select(F.col("node").alias("root"), F.col("root").alias("next"))
        j = written(up.join(above, "root", "left").select("node", F.coalesce("next", "root").alias("root"), F.col("next").isNotNull().alias("moved")), "roots")
        up = j.select("node", "root")
        if not j.filter("moved").limit(1).count():
            break
    return up.union(up.select(F.col("root").alias("node"), "root").distinct())


def near_duplicates(docs: DataFrame, shingle: int = 5, threshold: float = 0.8, samples: int = 128, rows: int = 4) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for each row of ``docs`` (doc_id, text).

    Links are Jaccard similarities of at least ``threshold`` between sets of
    ``shingle``-word shingles of the lower-cased (A-Z) text. With 32 bands of 4 values, a pair at 0.8 shares no
    bucket once in 20 million. Texts without words (null, empty, blank) link with nothing,
    each its own component. component_id is the smallest doc_id of the component;
    null doc_ids take part and name a component only when it has no other. A repeated
    row is a copy. Extra columns are ignored."""
    sig = written(signatures(docs, shingle, samples, rows), "signatures")
    full = sig.filter("n_shingles > 0")
    classes = written(full.groupBy("s1", "s2").agg(F.min("_row").alias("rep"), F.min("doc_id").alias("least_id")), "classes")
    reps = written(full.join(classes.select(F.col("rep").alias("_row"), "least_id"), "_row").withColumnRenamed("_row", "rep"), "representatives")
    small = reps.select("rep", "n_shingles", *SAMPLED)

    # buckets of more than one representative; their members, with the smallest one
    member = reps.select("rep", F.explode("bands").alias("key"))
    leads = member.groupBy("key").agg(F.min("rep").alias("lead"), F.count("*").alias("n")).filter("n > 1").drop("n")
    inside = written(_spread(member, leads), "buckets")

    bound, per = sketch_bound(threshold, samples), round(threshold * 100)
    wanted = inside.select("rep").distinct().join(reps.select("rep", "doc_id", "t", "s1", "s2"), "rep")
    sets = written(_sets(docs, wanted, shingle), "sets")
    whole = sets.select("rep", "n_shingles", *WHOLE)

    def star(pairs: DataFrame, sketches: DataFrame, limit: int | None) -> tuple[DataFrame, int]:
        """Confirmed links of the nearest leader a of each member b, and how many."""
        p = pairs.distinct().join(sketches.alias("y"), F.col("b") == F.col("y.rep")).join(sketches.alias("x"), F.col("a") == F.col("x.rep"))
        p = p.filter(_near("x", "y", per, limit)).groupBy("b").agg(F.min(F.struct(_differ("x", "y", SAMPLED if limit is not None else WHOLE).alias("d"), F.col("a"))).alias("m"))
        links = written(_confirmed(p.select(F.col("m.a").alias("a"), "b"), sets, threshold), "confirmed")
        return links, links.count()

    links, found = star(inside.filter("lead < rep").select(F.col("lead").alias("a"), F.col("rep").alias("b")), small, bound)
    trees = written(components(links), "trees")
    at = written(_mixed(_in_trees(inside.select("key", "rep"), trees)), "mixed-buckets")
    enough = max(20, found // 20)
    for number in range(1, MOST_ROUNDS):
        leader = F.min(F.struct(F.xxhash64("rep", F.lit(number)).alias("h"), F.col("rep").alias("lead"), F.col("tree").alias("lead_tree"))).alias("m")
        pairs = _spread(at, at.groupBy("key").agg(leader).select("key", "m.lead", "m.lead_tree")).filter("tree <> lead_tree")
        links, found = star(pairs.select(F.col("lead").alias("a"), F.col("rep").alias("b")), whole, None)
        if found:
            trees, at = _joined(links, trees, at)
            at = written(_mixed(at), "mixed-buckets")
        if found < enough:
            break

    # trees that share a bucket and are not linked yet, in blocks of the bucket's members
    w = F.pmod(F.xxhash64("rep"), F.col("blocks"))
    sizes = at.groupBy("key").agg(F.ceil(F.count("*") / BLOCK).alias("blocks"))
    rest = written(_spread(at, sizes).withColumn("own", w).join(whole, "rep"), "bucket-sketches")
    p = rest.select("*", F.explode(F.sequence(F.col("own"), F.col("blocks") - 1)).alias("other"))
    q = rest.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.col("own"))).alias("other"))
    same = (F.col("p.key") == F.col("q.key")) & (F.col("p.own") == F.col("q.other")) & (F.col("p.other") == F.col("q.own"))
    once = (F.col("p.own") < F.col("q.own")) | (F.col("p.rep") < F.col("q.rep"))
    late = p.alias("p").join(q.alias("q"), same & once & (F.col("p.tree") != F.col("q.tree")) & _near("p", "q", per, None))
    late = written(_confirmed(late.select(F.col("p.rep").alias("a"), F.col("q.rep").alias("b")).distinct(), sets, threshold), "late-links")
    roots, _ = _joined(late, trees, None)

    ids = classes.join(roots.withColumnRenamed("node", "rep"), "rep", "left").select("s1", "s2", "least_id", F.coalesce("root", "rep").alias("root"))
    ids = written(ids, "rooted")
    named = written(ids.groupBy("root").agg(F.min("least_id").alias("component_id")), "named")
    by_set = written(ids.join(named, "root").select("s1", "s2", "component_id"), "by-set")
    out = sig.select("doc_id", "n_shingles", "s1", "s2").filter("n_shingles > 0").join(by_set, ["s1", "s2"]).select("doc_id", "n_shingles", "component_id")
    alone = sig.filter("n_shingles = 0").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    return out.union(alone).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def _spread(members: DataFrame, buckets: DataFrame) -> DataFrame:
    """``members`` (key, rep, ...) joined with ``buckets`` (one row a key) in SALTS tasks a key, as one bucket may hold a large group of
    near copies."""
    dealt = buckets.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    return members.withColumn("_salt", F.pmod(F.xxhash64("rep"), F.lit(SALTS))).join(dealt, ["key", "_salt"]).drop("_salt")


def _in_trees(members: DataFrame, trees: DataFrame) -> DataFrame:
    """``members`` (rep, ...) with ``tree``: the root of rep, or rep itself."""
    return members.join(trees.select(F.col("node").alias("rep"), F.col("root").alias("tree")), "rep", "left").withColumn("tree", F.coalesce("tree", "rep"))


def _mixed(at: DataFrame) -> DataFrame:
    """The rows (key, rep, tree) of buckets that hold more than one tree."""
    several = at.groupBy("key").agg(F.min("tree").alias("lo"), F.max("tree").alias("hi")).filter("lo < hi").select("key")
    return _spread(at, several)


def _joined(links: DataFrame, trees: DataFrame, at: DataFrame | None) -> tuple[DataFrame, DataFrame | None]:
    """Trees, and the bucket rows ``at``, after ``links`` (a, b) between members of different trees."""
    ends = _in_trees(_in_trees(links.withColumnRenamed("a", "rep"), trees).select(F.col("tree").alias("a"), F.col("b").alias("rep")), trees)
    up = written(components(ends.select("a", F.col("tree").alias("b"))).toDF("tree", "top"), "tree-roots")
    # roots that had no tree of their own yet come in as nodes
    every = trees.select("node", F.col("root").alias("tree")).union(up.select("tree", "tree")).distinct()
    out = written(every.join(up, "tree", "left").select("node", F.coalesce("top", "tree").alias("root")), "trees")
    if at is not None:
        at = written(at.join(up, "tree", "left").select("key", "rep", F.coalesce("top", "tree").alias("tree")), "bucket-trees")
    return out, at


def deduplicated(docs: DataFrame, **how) -> DataFrame:
    """The rows of ``docs`` that stay: of each component the row with the smallest doc_id,
    once, with its columns. A doc_id is taken to name one text; where it does not, its rows with
    different texts stay or go together."""
    stays = near_duplicates(docs, **how).filter("kept").select(F.col("doc_id").alias("_stay")).distinct()
    mine, inner = pick(docs, DOC, rest=True)
    kept = mine.join(stays, F.col("doc_id").eqNullSafe(F.col("_stay")), "left_semi")
    again = F.row_number().over(Window.partitionBy("doc_id", F.xxhash64("text")).orderBy("doc_id"))
    return restored(kept.withColumn("_again", again).filter("_again = 1"), inner, docs)


_LETTERS = "abcdefghijklmnopqrstuvwxyz"
#: near_duplicates(shingle=2) where doc_id is unique and not null: pairs that share one of the rarest shingles that a link must share, their
#: exact similarity, and all that a document reaches.
SQL = f"""
with recursive d as (select doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_LETTERS.upper()}', '{_LETTERS}'), '[^\\x20\\x09-\\x0D]+') as w from documents),
s as (select distinct doc_id, said from (select doc_id, w[pos] || ' ' || w[pos + 1] as said from (select *, unnest(range(1, len(w))) as pos from d where len(w) > 1) union all select doc_id, w[1] from d where len(w) = 1)),
n as (select doc_id, count(*) as n from s group by doc_id),
f as (select said, count(*) as often from s group by said),
r as (select s.doc_id, s.said, n.n, row_number() over (partition by s.doc_id order by often, s.said) as k from s join f using (said) join n using (doc_id)),
p as (select doc_id, said, n from r where k <= n - (80 * n + 99) // 100 + 1),
c as (select distinct x.doc_id as a, y.doc_id as b, x.n as na, y.n as nb from p x join p y on x.said = y.said and x.doc_id < y.doc_id where 100 * least(x.n, y.n) >= 80 * greatest(x.n, y.n)),
e as (select a, b from (select c.a, c.b, c.na, c.nb, count(*) as common from c join s x on x.doc_id = c.a join s y on y.doc_id = c.b and y.said = x.said group by all) where 100 * common >= 80 * (na + nb - common)),
l as (select a, b from e union all select b, a from e),
reach as (select doc_id as a, doc_id as b from d union select reach.a, l.b from reach join l on reach.b = l.a),
g as (select a as doc_id, min(b) as component_id from reach group by a)
select doc_id, coalesce(n.n, 0)::bigint as n_shingles, component_id, doc_id = component_id as kept from g left join n using (doc_id)
"""
