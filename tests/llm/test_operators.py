import hashlib
import itertools
import zlib
from fractions import Fraction
from math import ceil, floor

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import types as T

pytest.importorskip("public_tokenizers")
import public_tokenizers

from segforest.llm import chat, decontam, kdshard, mixing, neardup, ppm, quality, syncmer, tokenfile, toxicity

DOC = "doc_id long, text string, lang string, source string, n_chars long, TEXT string"
LONG = "lorem ipsum dolor sit amet " * 20000


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty, blank and very long texts, repeated rows, a clashing column name."""
    base = "the quick brown fox jumps over the lazy dog and runs far away from all the other animals here"
    rows = [(1, None, None, None, None, "x"), (2, "", "en", "a", 0, "x"), (3, " \n", None, "a", 2, "x"), (4, LONG, "la", None, 5, "x"), (5, base, "en", "a", 9, "x"), (5, base, "en", "a", 9, "x"), (6, base.upper(), "en", "b", 9, "x"), (7, base + " x", "en", "b", 9, "x"), (None, "null id", "en", "b", 1, "x"), (8, "été où ça", "fr", "b", 1, "x")]
    return spark.createDataFrame(rows, DOC), rows


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOC)


def labels(spark, rows=()):
    return spark.createDataFrame(list(rows), "doc_id long, quality int, toxic int")


def test_token_files(spark, odd, empty):
    path = public_tokenizers.path("word_bpe_49k.json")
    got = {(r.doc_id, r.start): r for r in tokenfile.token_files(odd[0], path).collect()}
    enc, at = tokenfile.Encoder(path, by_piece=False), 0
    for doc_id, text in sorted(((r[0], r[1]) for r in odd[1]), key=lambda r: (r[0] is not None, r[0] or 0)):
        ids = np.append(np.frombuffer(enc.encode([text])[0], enc.kind), 1).astype("<u4")
        r = got[doc_id, at]
        assert (r.n_tokens, r.ids_crc32) == (len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)
    assert tokenfile.token_files(empty, path).count() == 0


def test_pieces_equal_whole_texts():
    path = public_tokenizers.path("word_bpe_49k.json")
    texts = ["Hello, World... it's $$$, x\x1cy 12,5 a.b. naïve. ΑΣ, <|endoftext|> don't.,", "é a b, c.\n", "'s 'S,. ½. _a_."]
    assert tokenfile.Encoder(path).encode(texts) == tokenfile.Encoder(path, by_piece=False).encode(texts)


@pytest.mark.parametrize("name", ["word_bpe_49k.json", "byte_bpe_50k.json"])
def test_encoder_equals_the_tokenizer(spark, name):
    from tokenizers import Tokenizer

    path = public_tokenizers.path(name)
    texts = [r.text for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("text").collect()] + ["", "a b  c\n\n", "x.,y ..,", "e\u0301. \u00a0z"]
    enc, tok = tokenfile.Encoder(path), Tokenizer.from_file(path)
    assert enc.by_piece == (name == "word_bpe_49k.json")
    got = [np.frombuffer(b, enc.kind).tolist() for b in enc.encode(texts)]
    assert got == [e.ids for e in tok.encode_batch(texts, add_special_tokens=False)]


def test_items_without_id(spark):
    bench = spark.createDataFrame([(None, "alpha beta"), ("", "gamma delta"), ("b", "alpha beta"), ("b", "epsilon")], "item_id string, text string")
    docs = spark.createDataFrame([(1, "Alpha beta gamma delta"), (2, "alpha beta epsilon"), (3, "beta alpha")], "doc_id long, text string")
    for block in (4 << 20, 12):
        got = {r.doc_id: (r.n_hit, r.n_items, r.items_sha256) for r in decontam.digest(decontam.contamination(docs, bench, block_bytes=block)).collect()}
        sha = lambda *i: hashlib.sha256(",".join(sorted(i)).encode()).hexdigest()
        assert got == {1: (4, 3, sha("", "", "b")), 2: (3, 2, sha("", "b")), 3: (0, 0, sha())}


def test_near_duplicates_with_repeated_ids(spark):
    """Many rows without doc_id, or with one: each meets its own text alone."""
    base = "the quick brown fox jumps over the lazy dog and runs far away from all the other animals here now"
    rows = [(None, base)] * 300 + [(None, base + " x")] * 300 + [(7, f"text number {i} of one id with words {i * 7}") for i in range(200)]
    got = neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), shingle=2).collect()
    assert len(got) == 800 and {(r.doc_id, r.component_id) for r in got} == {(None, None), (7, 7)}


def test_reader_fetches_only_wanted_frames_and_checks_them():
    docs = [(i, np.full(300, i % 7, "<u2").tobytes()) for i in range(400)]
    data, n = tokenfile.pack(docs, 2, frame_bytes=6000)
    r = tokenfile.Reader(tokenfile.InMemory(data))
    before = r.frames_read
    assert n == 120000 and [(d, ids[0]) for _, d, ids in r.documents({17})] == [(17, 3)] and r.frames_read == before + 1
    bad = bytearray(data)
    bad[3 + int(r.at[5])] ^= 0xFF
    with pytest.raises(Exception):
        list(tokenfile.Reader(tokenfile.InMemory(bytes(bad))).documents())


def test_decontamination(spark, odd, empty):
    bench = [("a", "the quick brown fox jumps over the lazy dog and"), ("b", "ipsum dolor"), ("c", None), (None, "null id"), ("d", "...")]
    b = spark.createDataFrame(bench, "item_id string, text string")
    want = decontam.brute_force({i: (t if t != LONG else LONG[:5000]) for i, t in enumerate(r[1] for r in odd[1])}, {i or "": t for i, t in bench})
    for block in (4 << 20, 20):
        got = sorted((r.text_n, r.n_hit, r.items_sha256) for r in decontam.digest(decontam.contamination(odd[0], b, block_bytes=block)).selectExpr("n_words as text_n", "n_hit", "items_sha256").collect() if r.text_n < 5000)
        assert got == sorted((n, h, hashlib.sha256(",".join(i).encode()).hexdigest()) for n, h, i in want.values() if n < 700)
    assert decontam.contamination(empty, b).count() == 0 and decontam.clean(odd[0], b.limit(0)).count() == len(odd[1])


def test_near_duplicates(spark, odd, empty):
    got = sorted(((r.doc_id or 0, r.component_id or 0) for r in neardup.near_duplicates(odd[0], shingle=2).collect()))
    assert got == [(0, 0), (1, 1), (2, 2), (3, 3), (4, 4), (5, 5), (5, 5), (6, 5), (7, 5), (8, 8)]
    assert neardup.near_duplicates(empty).count() == 0
    kept = neardup.deduplicated(odd[0], shingle=2)
    assert kept.columns == odd[0].columns and sorted(r[0] or 0 for r in kept.collect()) == [0, 1, 2, 3, 4, 5, 8]


def test_sketch_tells_similarity():
    rng = np.random.default_rng(0)
    v = rng.integers(0, 1 << 32, (2, 128), np.uint32)
    v[1, :100] = v[0, :100]
    s = neardup.odd_sketches(v)
    d = sum(bin(int(a) ^ int(b) if int(a) ^ int(b) >= 0 else (int(a) ^ int(b)) & (1 << 64) - 1).count("1") for a, b in zip(*s))
    assert abs(neardup.sketch_similarity(d, 128) - 100 / 128) < 0.1


def earliest_deadline(weights, blocks):
    """Pfair slots one by one with fractions: [(stream, block)] in slot order, phases begin when a stream ends."""
    left, done, out = {k: n for k, n in blocks.items() if n}, dict.fromkeys(blocks, 0), []
    while left:
        total, own, t = sum(Fraction(str(weights[k])) for k in left), dict.fromkeys(left, 0), 0
        share = {k: Fraction(str(weights[k])) / total for k in left}
        while all(left.values()):
            ready = [(ceil((own[k] + 1) / share[k]), k) for k in left if floor(own[k] / share[k]) <= t]
            k = min(ready)[1]
            out.append((k, done[k]))
            own[k], done[k], left[k], t = own[k] + 1, done[k] + 1, left[k] - 1, t + 1
            assert all(abs(own[j] - share[j] * t) < 1 for j in left)
        left = {k: n for k, n in left.items() if n}
    return out


def test_mixing(spark, odd, empty):
    rows = [(i, "a" if i % 3 else "b" if i % 2 else None) for i in range(900)]
    df = spark.createDataFrame(rows, "doc_id long, source string")
    for weights in ({"a": 5.0, "b": 3.0, "(other)": 2.0}, {"a": 0.731, "b": 0.1113, "(other)": 0.15}, {"a": 0.9996, "b": 0.0004}):
        got = mixing.mixed(df, weights, block_rows=7).collect()
        assert len(got) == 900 and all(r.release <= r.slot < r.deadline for r in got)
        rows_of = {}
        for r in got:
            rows_of.setdefault((r.stream, r.block), []).append(r.place)
        assert all(sorted(p) == list(range(len(p))) for p in rows_of.values())
        counts = {k: max(b for s, b in rows_of if s == k) + 1 for k in {s for s, _ in rows_of}}
        want = earliest_deadline({"(other)": sum(Fraction(str(w)) for w in weights.values()) / len(weights)} | weights, counts)
        assert [k for k, _ in sorted({(r.stream, r.block): r.slot for r in got}.items(), key=lambda x: x[1])] == want
    assert mixing.mixed(empty).count() == 0 and mixing.in_mixed_order(odd[0]).count() == len(odd[1])
    got = {(r.doc_id, r.source, r.stream) for r in mixing.mixed(odd[0]).collect()}
    assert got == {(r[0], r[3], r[3] or "(other)") for r in odd[1]}


def test_mix_holds_any_weights():
    """Over 100,000 blocks of 12 sources with arbitrary weights, each stays within one block of its target."""
    rng = np.random.default_rng(3)
    weights = {f"s{i}": float(w) for i, w in enumerate(rng.random(12))}
    phases, periods = mixing.plan(dict.fromkeys(weights, 40_000), weights)
    first = [r for r in periods if r["phase"] == 0]
    assert all(r["rel"] <= r["at"] < r["due"] for r in first) and len(first) > 100_000
    total, seen = sum(weights.values()), dict.fromkeys(weights, 0)
    for t, r in enumerate(sorted(first, key=lambda r: r["at"])):
        seen[r["source"]] += 1
        assert t % 101 or all(abs(n - weights[k] / total * (t + 1)) < 1 + 1e-6 for k, n in seen.items())
    many = {f"s{i}": 1 + i % 3 for i in range(600)}
    phases, periods = mixing.plan(dict.fromkeys(many, 2), many)
    assert len({r["source"] for r in phases}) == 600 and sum(r["end"] - r["first"] for r in phases) == 1200


def test_shards(spark, odd, empty):
    assert kdshard.sharded(empty, 4).count() == 0 and kdshard.sharded(odd[0], 4).count() == len(odd[1])
    same = spark.range(400).selectExpr("1L as doc_id", "'same text' as text", "'s' as source")
    got = kdshard.sharded(same, 7).toPandas()
    g = got.groupby("shard")["size"].sum()
    assert len(g) == 7 and g.max() - g.min() <= 2 * 25
    assert all(sorted(x.slot) == list(range(len(x))) for _, x in got.groupby("shard"))


def test_shards_of_repeated_and_odd_rows(spark, odd):
    got = kdshard.sharded(odd[0], 3, rest=True)
    assert got.columns == [*odd[0].columns, "size", "text_crc32", "shard", "slot"]
    assert sorted(map(str, (tuple(r)[:6] for r in got.collect()))) == sorted(map(str, odd[1]))
    # a third of all rows has one text: it is cut, other equal texts are not; slots do not depend on the files
    rows = spark.range(3000).selectExpr("id as doc_id", "if(id % 3 = 0, 'one text', concat('text ', id div 10)) as text", "concat('s', id % 7) as source", "'SHARD' as Shard")
    one, two = (kdshard.sharded(rows.repartition(n), 8).toPandas().sort_values(["doc_id"]).reset_index(drop=True) for n in (1, 5))
    assert one.equals(two)
    size = one.groupby("shard")["size"].sum()
    spread = one.groupby(["text_crc32", "size"]).shard.nunique()
    assert len(size) == 8 and size.max() - size.min() <= size.mean() / 16 and (spread > 1).sum() == 1
    assert kdshard.sharded(rows, None, target_bytes=int(size.sum() / 5) + 1).agg({"shard": "max"}).first()[0] == 4


def test_models(spark, odd, empty):
    words = ["good", "calm", "tree", "river", "stone", "light", "bird", "cloud"]
    text = lambda i: " ".join(words[(i * k + k) % 8] for k in range(1, 30))
    rows = [(i, text(i) + (" you stupid idiot" if i % 4 == 0 else ""), "en", "s", 1, "x") for i in range(400)]
    docs = spark.createDataFrame(rows, DOC)
    lab = labels(spark, [(i, int(i % 2), int(i % 4 == 0)) for i in range(400)] + [(None, 1, 1), (3, None, None)])
    model = toxicity.fit(docs, lab)
    hidden = ["bird st0ne y0u stup1d id10t", "tree s t u p i d cloud", "bird stuuupid idiooot", "calm river stone"]
    r = toxicity.Restorer(toxicity.CharModel(model.trigrams))
    assert [r.text(t) for t in hidden] == ["bird stone you stupid idiot", "tree stupid cloud", "bird stupid idiot", "calm river stone"]
    score = model.score([r.text(rows[4][1].replace("stupid", "stup1d").replace("idiot", "i d i o t")), rows[5][1]])
    assert score[0] > 0.5 > score[1]
    for make in (lambda d, l: toxicity.toxicity(d, l), lambda d, l: quality.quality(d, l)):
        assert make(docs, labels(spark)).count() == 400 and make(empty, lab).count() == 0 and make(odd[0], lab).count() == len(odd[1])


def test_hidden_words_with_several_tricks(spark):
    base = "good calm tree river stone light bird cloud you stupid idiot ass "
    docs = spark.createDataFrame([(1, base * 50)], "doc_id long, text string")
    r = toxicity.Restorer(toxicity.CharModel(toxicity.trigram_counts(docs)))
    read = {"$ t u p ! d": "stupid", "i d ! o t": "idiot", "I d 1 0 t": "idiot", "i\td\ti\to\tt": "idiot", "i   d   i   o   t": "idiot", "i|d|i|o|t": "idiot", "i\nd\ni\no\nt": "idiot", "i d i o o o o t": "idiot", "(i.d.!.o.t)!": " idiot)!", "s - t - u - p - 1 - d": "stupid", "i d | o t": "idiot", "i d i o t !": "idiot !", "i d i 000 t": "idiot", "a s s": "ass", "a $ $": "ass", "@.s.s": "ass"}
    assert r.texts(pa.array([f"bird {t} tree" for t in read])) == [f"bird {t} tree" for t in read.values()]
    plain = ["tree 1 2 3 4", "calm river stone - 5 / 6 / 7", "- - -", "* * *"]
    assert r.texts(pa.array(plain)) == plain


def test_viterbi_finds_the_cheapest_reading(spark):
    docs = spark.createDataFrame([(1, "you stupid idiot calm river stone grass " * 20)], "doc_id long, text string")
    model = toxicity.CharModel(toxicity.trigram_counts(docs))

    def cost(reading):
        x = y = 0
        total = sum(c for _, c in reading)
        for ch in "".join(o for o, _ in reading) + " ":
            z = model.symbol(ch)
            if z or y:
                total += model.rows[x][y][z]
                x, y = y, z
        return total

    for word in ("1d10t", "$tup!d", "r1v3r", "iiid1oot", "5t0ne", "gr@55", "*d*t", "a|"):
        lattice = toxicity._letters(word)
        best = min(map(cost, itertools.product(*lattice)))
        found = model.decode(lattice)
        ways = [r for r in itertools.product(*lattice) if "".join(o for o, _ in r) == found]
        assert min(map(cost, ways)) == pytest.approx(best)


def test_gate_lets_all_through_that_the_decoder_would_change(spark):
    texts = ["дурааак ты", "дурааак 1d10t", "ÄÄÄrger", "aAa", "ßßß ok", "x\u0130\u0130\u0130", "ααα βγ", None, "", "a" * 50_000, "plain words"]
    texts += [r.text for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("text").collect()]
    r = toxicity.Restorer(toxicity.CharModel(toxicity.trigram_counts(spark.createDataFrame([("дурак idiot word",)], "text string"))))
    assert r.texts(pa.array(texts)) == [r.text(t or "") for t in texts]
    assert r.texts(pa.array(["дурааак ты"])) != ["дурааак ты"]


def test_ridge_and_pooling():
    rng = np.random.default_rng(0)
    x, y = rng.normal(size=60).round(1), rng.integers(0, 2, 60).astype(float)
    weight = rng.random(60) + 0.1
    knots, values = quality.isotonic(x, y, weight)
    # least squares over all rising step functions: the largest lower mean of upper sets
    xs = np.unique(x)
    for v in xs:
        mean = lambda a, b: np.average(y[(x >= a) & (x <= b)], weights=weight[(x >= a) & (x <= b)])
        want = max(min(mean(a, b) for b in xs[xs >= v]) for a in xs[xs <= v])
        assert np.interp(v, knots, values) == pytest.approx(want)


def test_quality_fit_is_plain_ridge(spark):
    rng = np.random.default_rng(1)
    good = ["calm river light stone bird tree cloud", "one two three four five six seven"]
    rows = [(i, " ".join(rng.permutation((good[i % 2] + (" !!! $$$ BUY" * 3 if i % 2 else "")).split()))) for i in range(300)]
    docs, lab = spark.createDataFrame(rows, "doc_id long, text string"), labels(spark, [(i, 1 - i % 2, 0) for i in range(300)])
    m = quality.fit(docs, lab, features=20)
    x, y = quality.statistics(pa.array([t for _, t in rows])), np.array([1 - i % 2 for i, _ in rows])
    assert m.mean == pytest.approx(x.mean(0)) and m.scale == pytest.approx(np.sqrt(np.maximum(x.var(0), 1e-8)))
    part = {r.doc_id: r.p for r in docs.selectExpr("doc_id", "pmod(xxhash64(3, doc_id), 5) as p").collect()}
    fit_ = np.array([part[i] != 0 for i, _ in rows])
    z = np.concatenate([np.cos(np.clip((x - m.mean) / m.scale, -6, 6) @ m.w + m.b) * np.sqrt(2 / 20), np.ones((300, 1))], 1)[fit_]
    ridge = np.linalg.lstsq(np.concatenate([z, np.sqrt(1e-4 * 300 / 20) * np.eye(21)]), np.concatenate([y[fit_], np.zeros(21)]), rcond=None)[0]
    assert m.ridge == pytest.approx(ridge, abs=1e-6)
    assert quality.statistics(pa.array([None, ""])).tolist() == [[0.0] * len(quality.STATISTICS)] * 2


def plain_lengths(train, text, order):
    """Code length of ``text`` in bits after ``train`` (texts of one language), by dictionaries."""
    seen = {}
    for t in train:
        b = bytes([ppm.PAD]) * order + t
        for i in range(order, len(b)):
            for k in range(order + 1):
                seen.setdefault(b[i - k : i], {}).setdefault(b[i], 0)
                seen[b[i - k : i]][b[i]] += 1
    bits, b = 0.0, bytes([ppm.PAD]) * order + text
    for i in range(order, len(b)):
        for k in range(order, -1, -1):
            here = seen.get(b[i - k : i])
            if here is None:
                continue  # a context never seen costs nothing to leave
            total = sum(here.values()) + len(here)
            if b[i] in here:
                bits -= np.log2(here[b[i]] / total)
                break
            bits -= np.log2(len(here) / total)
        else:
            bits += 8
    return bits


def test_code_lengths_against_plain_trees(spark):
    train = {"en": ["the cat sat on the mat", "a quick brown fox", "that thing there"], "fr": ["le chat est là", "où est la bibliothèque", "ça va bien"]}
    rows = [(i, t, lang) for i, (lang, t) in enumerate((lang, t) for lang, ts in train.items() for t in ts)]
    trees = ppm.fit(spark.createDataFrame(rows, "doc_id long, text string, lang string"), order=3)
    trees.prepare()
    texts = ["the hat", "la chatte où", "zzz\u4e2d", "", "x" * 3000, "there là"]
    raw = [t.encode() for t in texts]
    got = trees.lengths(np.frombuffer(b"".join(raw), np.uint8), np.cumsum([0, *map(len, raw)]))
    for i, t in enumerate(raw):
        for j, lang in enumerate(trees.languages):
            assert got[i, j] == pytest.approx(plain_lengths([x.encode() for x in train[lang]], t, 3), rel=1e-5)
    new = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    assert [r.lang_pred for r in ppm.identified(new, trees).orderBy("doc_id").collect()][:4] == ["en", "fr", ppm.identified(new, trees).filter("doc_id = 2").first().lang_pred, "und"]


def test_code_lengths_by_hand():
    """One language that has seen "ab": order 0 counts a, b once each."""
    t = ppm.ContextTrees.of(["x"], 0, [{"l": np.array([0, 0]), "g": np.array([97, 98], np.uint64), "c": np.array([1, 1])}])
    t.prepare()
    bits = t.lengths(np.frombuffer(b"abz", np.uint8), np.array([0, 2, 3]))
    assert bits[0, 0] == pytest.approx(4) and bits[1, 0] == pytest.approx(1 + 8)


def test_language(spark, odd, empty):
    got = {r.doc_id: r.lang_pred for r in ppm.language_id(odd[0]).collect()}
    assert got[1] == got[2] == got[3] == "und" and ppm.language_id(empty).count() == 0


def test_syncmers(spark, odd, empty):
    got = syncmer.edit_fingerprints(odd[0], part_bytes=100).collect()
    assert len(got) == len(odd[1]) and syncmer.edit_fingerprints(empty).count() == 0
    x, y = syncmer.fingerprints(["a long enough text about nothing at all " * 5] * 2)
    assert syncmer.encode(x) == syncmer.encode(y) and syncmer.likeness(x, syncmer.decode(syncmer.encode(y))) == 1


def plain_syncmers(raw):
    """(hash, place) of each closed syncmer, from the definition alone."""
    whole = (1 << 64) - 1

    def mixed(x):
        x = (x ^ x >> 30) * 0xBF58476D1CE4E5B9 & whole
        x = (x ^ x >> 27) * 0x94D049BB133111EB & whole
        return x ^ x >> 31

    gram = lambda i: mixed(int.from_bytes(raw[i : i + 4], "big") * 0x9E3779B97F4A7C15 & whole)
    out = []
    for i in range(len(raw) - 11):
        inner = [gram(i + j) for j in range(9)]
        if min(inner) in (inner[0], inner[8]):
            value = inner[0]
            for j in (4, 8):
                value = mixed((value * 0xD6E8FEB86659FD93 + inner[j]) & whole)
            out.append((value, i))
    return out


def test_syncmers_against_the_definition():
    rng = np.random.default_rng(5)
    texts = ["".join(rng.choice(list("abcé "), n)) for n in (0, 3, 11, 12, 13, 200, 700)] + ["aaaa" * 30]
    value, text, place = syncmer.syncmers(*syncmer.text_bytes(pa.array(texts)))
    for t, raw in enumerate(x.encode() for x in texts):
        mine = list(zip(value[text == t].tolist(), place[text == t].tolist()))
        assert mine == plain_syncmers(raw) if len(raw) >= 12 else len(mine) == (len(raw) > 0)


def words(seed, n):
    rng = np.random.default_rng(seed)
    letters = np.array(list("abcdefghijklmnopqrstuvwxyz"))
    return ["".join(letters[rng.integers(0, 26, k)]) for k in rng.integers(2, 9, n)]


def test_syncmers_keep_all_anchors_of_long_texts():
    """Two texts of 20,000 words share a passage of 60 words; any share of anchors is told."""
    for seed in range(4):
        a, b, common = words(3 * seed, 20_000), words(3 * seed + 1, 20_000), words(3 * seed + 2, 60)
        texts = [" ".join([*a[:7000], *common, *a[7000:]]), " ".join([*b[:7100], *common, *b[7100:]])]
        x, y = syncmer.fingerprints(texts)
        value, text, place = syncmer.syncmers(*syncmer.text_bytes(pa.array(texts)))
        assert (len(x[1]), len(y[1])) == tuple(np.bincount(text)) and sorted(x[2]) == place[text == 0].tolist()
        assert len(x[1]) > 20_000 and 40 / (x[0] + y[0]) < syncmer.likeness(x, y) < 130 / (x[0] + y[0])
        n, v, p = syncmer.decode(syncmer.encode(x))
        assert n == x[0] and (v == x[1]).all() and (p == x[2]).all()


def test_syncmers_follow_insertions():
    a, more = words(1, 1000), words(2, 200)
    text, put_in = " ".join(a), " ".join(more)[:300]
    half = len(" ".join(a[:500]))
    edits = [text[:half] + " " + put_in + text[half:], text[:half] + text[half + 300 :], put_in + text[: half // 2] + put_in[::-1] + text[half // 2 :]]
    x, *near = syncmer.fingerprints([text, *edits])
    for y in near:
        common = len(np.intersect1d(x[1], y[1]))
        assert syncmer.likeness(x, y) == pytest.approx(common / (x[0] + y[0] - common), abs=0.01) and common > 0.9 * x[0]
    swapped = syncmer.fingerprints([" ".join(a[700:] + a[:700])])[0]
    assert 0.6 < syncmer.likeness(x, swapped) < 0.75
    rng = np.random.default_rng(0)
    for n in (0, 1, 2, 7, 30):
        p, q = rng.permutation(50)[:n], rng.permutation(50)[:n]
        longest = {}
        for i in np.argsort(p):
            longest[i] = 1 + max((k for j, k in longest.items() if q[j] < q[i]), default=0)
        assert syncmer.chain(p, q) == max(longest.values(), default=0)


def test_chat_against_all_prefixes(spark):
    """Planted snapshots: each conversation's proper prefixes, copies, a different ending, rows without conversation."""
    rng, rows, said = np.random.default_rng(2), [], {}
    for c in range(60):
        turns = [("user" if k % 2 == 0 else "bot", f"w{rng.integers(3)}") for k in range(rng.integers(1, 5))]
        said[c] = turns
        rows += [(c, 10 * k, r, t) for k, (r, t) in enumerate(turns)]
    rows += [(None, 5, "user", "w1"), (None, 5, "user", "w1"), (None, 0, "user", "only here"), (None, 9, None, None)]
    alone = [("user", "w1"), ("user", "w1"), ("user", "only here"), ("", "")]
    every = [*said.values(), *([a] for a in alone)]
    got = sorted((r.conv_id if r.conv_id is not None else -1, r.n_turns, r.n_copies, r.rendered) for r in chat.rendered(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").selectExpr("*", "'x' as CONV_ID_", "1 as n")).collect())
    want = set()
    for t in every:
        if not any(len(o) > len(t) and o[: len(t)] == t for o in every):
            ids = [c for c, o in said.items() if o == t]
            want.add((min(ids, default=-1), len(t), sum(o == t for o in every), "".join(f"<|im_start|>{r}\n{x}<|im_end|>\n" for r, x in t)))
    assert got == sorted(want) and len(got) < 50


def test_chat(spark):
    rows = [(1, 0, "user", "hi"), (1, 1, "bot", "yo"), (2, 0, "user", "hi"), (3, 0, "user", "hi"), (3, 1, "bot", "yo"), (4, 0, None, None), (None, 0, "user", "alone")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = {r.conv_id: (r.n_turns, r.n_copies) for r in chat.rendered(df).collect()}
    assert got == {1: (2, 2), 4: (1, 1), None: (1, 1)} and chat.rendered(df.limit(0)).count() == 0
    assert T.StringType() == chat.rendered(df).schema["rendered"].dataType


def test_words_are_encoded_once_in_lower_case(monkeypatch):
    """Words that differ in case or closing marks only reach the tokenizer once, and texts have the ids of the whole tokenizer."""
    e, seen, joined = tokenfile.Encoder(public_tokenizers.path("word_bpe_49k.json")), [], tokenfile.Encoder._joined
    monkeypatch.setattr(tokenfile.Encoder, "_joined", lambda self, tok, words: (seen.extend(words), joined(self, tok, words))[1])
    texts = ["The THE the. THE., the!! the&&&", "\u00c9t\u00e9 \u00e9t\u00e9? \u00c9T\u00c9***", "don't Don'T X1 a!b \u0130stanbul \u212a e\u0301 E\u0301! \ufb01 q<|endoftext|> endoftext", "", None]
    assert e.encode(texts) == [e._whole(t or "") for t in texts]
    assert seen.count("the") == 1 and seen.count("\u00e9t\u00e9") == 1 and not {"The", "THE"} & set(seen)
    assert e.encode(["THE The tHe"]) == [e._whole("the the the")] and seen.count("the") == 1
