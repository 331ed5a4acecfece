"""The pipeline and whole-table queries against plain Python over the smallest tables, and held-out accuracy."""

import hashlib
import re
import zlib

import pytest

pytest.importorskip("public_tokenizers")
pytest.importorskip("corpus_pipeline")
import corpus_pipeline

from segforest.llm import decontam, queries, syncmer, toxicity

DATA, MORE = "/root/testdata/sf0.001", "/root/testdata/sf0.01"
LOWER = {c: c + 32 for c in range(65, 91)}


def documents(spark, folder=DATA):
    return spark.read.parquet(f"{folder}/documents.parquet")


def shingles(text, n):
    words = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(LOWER))
    return {tuple(words[i : i + n]) for i in range(max(1, len(words) - n + 1))} if words else set()


def classes(texts, n):
    """Smallest id reachable over pairs of similarity 0.8 or more, all pairs compared."""
    sets, ids = {k: shingles(t, n) for k, t in texts.items()}, sorted(texts)
    root = {k: k for k in ids}

    def find(k):
        while root[k] != k:
            k = root[k]
        return k

    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if sets[a] and sets[b] and min(len(sets[a]), len(sets[b])) * 100 >= 80 * max(len(sets[a]), len(sets[b])):
                if 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                    x, y = sorted((find(a), find(b)))
                    root[y] = x
    return {k: find(k) for k in ids}, {k: len(s) for k, s in sets.items()}


@pytest.fixture(scope="module")
def staged(spark):
    """The rows after each stage of one run over the smallest tables."""
    out, write = [], corpus_pipeline.written
    corpus_pipeline.written = lambda df, what: out.append(write(df, what)) or out[-1]
    out.append(write(corpus_pipeline.run(spark, DATA), "test-run"))
    corpus_pipeline.written = write
    return out


def test_pipeline_keeps_what_plain_python_keeps(spark, staged):
    docs = {r.doc_id: r for r in documents(spark).collect()}
    toxic = {r.doc_id for r in toxicity.toxicity(documents(spark), spark.read.parquet(f"{DATA}/labels.parquet")).filter("score >= 0.5").collect()}
    kept = {k: r.text for k, r in docs.items() if k not in toxic}
    ids = lambda df: sorted(r.doc_id for r in df.select("doc_id").collect())
    assert ids(staged[0]) == sorted(kept) and len(kept) > 150
    root, _ = classes(kept, 5)
    kept = {k: t for k, t in kept.items() if root[k] == k}
    assert ids(staged[1]) == sorted(kept)
    bench = {r.item_id: r.text for r in spark.read.parquet(f"{DATA}/benchmark.parquet").collect()}
    hits = decontam.brute_force(kept, bench)
    kept = {k: t for k, t in kept.items() if not hits[k][1]}
    assert ids(staged[2]) == ids(staged[3]) == ids(staged[4]) == sorted(kept)
    for r in staged[4].collect():
        assert all(r[c] == docs[r.doc_id][c] for c in documents(spark).columns) and 0 <= r.shard < 40


def test_every_stage_counts(spark, staged):
    """Without any one stage the result is another."""
    assert staged[0].count() > staged[1].count() > staged[2].count()
    assert corpus_pipeline.toxic_out(spark, documents(spark, MORE), MORE).count() < documents(spark, MORE).count()
    place = lambda df: {r.doc_id: (r.shard, r.slot) for r in df.collect()}
    mixed, unmixed = place(staged[4]), place(corpus_pipeline.shard(spark, staged[2], DATA))
    assert mixed.keys() == unmixed.keys() and mixed != unmixed
    order = {r.doc_id: r.mix_position for r in staged[3].collect()}
    by_slot = {}
    for k, (shard, slot) in mixed.items():
        by_slot.setdefault(shard, []).append((slot, order[k]))
    assert len(by_slot) == 40 and all(sorted(v) == sorted(v, key=lambda x: x[1]) for v in by_slot.values())


def test_token_files_against_the_tokenizer(spark):
    from tokenizers import Tokenizer

    tok, at = Tokenizer.from_file(queries.public_tokenizers.path("word_bpe_49k.json")), 0
    got = {r.doc_id: (r.start, r.n_tokens, r.ids_crc32) for r in queries.op2_token_files(spark, DATA).collect()}
    for r in sorted(documents(spark).collect()):
        ids = [*tok.encode(r.text or "", add_special_tokens=False).ids, 1]
        assert got.pop(r.doc_id) == (at, len(ids), zlib.crc32(b"".join(i.to_bytes(4, "little") for i in ids)))
        at += len(ids)
    assert not got


def test_mix_is_earliest_deadline_first(spark):
    from test_operators import earliest_deadline

    got, rows = {}, {}
    for r in queries.op5_pfair_mix(spark, DATA).collect():
        got[r.stream, r.block] = r.slot
        rows[r.stream] = rows.get(r.stream, 0) + 1
    weights = corpus_pipeline.mixing.default_weights(rows)
    want = earliest_deadline(weights, {k: -(-n // 64) for k, n in rows.items()})
    assert sorted(got, key=got.get) == want and sorted(got.values()) == list(range(len(want)))


def test_near_duplicates_against_all_pairs(spark):
    root, sizes = classes({r.doc_id: r.text for r in documents(spark).collect()}, 2)
    got = queries.op6_odd_sketch_dedup(spark, DATA).collect()
    assert {r.doc_id: (r.component_id, r.n_shingles, r.kept) for r in got} == {k: (c, sizes[k], c == k) for k, c in root.items()}


def test_contamination_against_plain_python(spark):
    docs = {r.doc_id: r.text for r in documents(spark).collect()}
    want = decontam.brute_force(docs, {r.item_id: r.text for r in spark.read.parquet(f"{DATA}/benchmark.parquet").collect()})
    for r in queries.op4_decontamination(spark, DATA).collect():
        n, hit, items = want[r.doc_id]
        assert (r.n_words, r.n_hit, r.n_items, r.contaminated) == (n, hit, len(items), hit > 0)
        assert r.items_sha256 == hashlib.sha256(",".join(sorted(map(str, items))).encode()).hexdigest()


def median_tree(units, leaves):
    """Shards of units (bytes, p, tie) by sorting: cut where the running sum of the widest dimension is nearest its share."""
    out, todo = {}, [(units, 0, leaves)]
    while todo:
        here, first, k = todo.pop()
        if k == 1:
            out |= {u.tie: first for u in here}
            continue
        d = max(range(3), key=lambda i: (max(u.p[i] for u in here) - min(u.p[i] for u in here), -i))
        here = sorted(here, key=lambda u: (u.p[d], u.tie))
        goal, sums = sum(u.bytes for u in here) * (k // 2) / k, [0]
        for u in here:
            sums.append(sums[-1] + u.bytes)
        at = next(i for i, s in enumerate(sums) if s >= goal)
        at -= (goal - sums[at - 1]) * 2 <= sums[at] - sums[at - 1]
        todo += [(here[:at], first, k // 2), (here[at:], first + k // 2, k - k // 2)]
    return out


def test_shards_are_those_of_a_sorted_tree(spark):
    kd = corpus_pipeline.kdshard
    rows = kd.with_units(kd.metadata(documents(spark)), 12, 0.25).cache()
    units = kd.units(rows).collect()
    want = median_tree(units, 12)
    got = {r.tie: r.shard for r in kd.kd_tree(kd.units(rows), 12).collect()}
    assert got == want and len(set(got.values())) == 12


@pytest.mark.parametrize("folder", [DATA, MORE, "/root/testdata/sf0.1"])
def test_shards_hold_the_law(spark, folder):
    docs = {r.doc_id: r.text for r in documents(spark, folder).collect()}
    got = queries.op7_kd_shards(spark, folder).collect()
    assert sorted(r.doc_id for r in got) == sorted(docs)
    slots, size, groups = {}, dict.fromkeys(range(40), 0), {}
    for r in got:
        raw = (docs[r.doc_id] or "").encode()
        assert (r["size"], r.text_crc32) == (len(raw) + 16, zlib.crc32(raw))
        slots.setdefault(r.shard, []).append(r.slot)
        size[r.shard] += r["size"]
        groups.setdefault(raw, []).append(r.shard)
    assert set(slots) <= set(range(40)) and all(sorted(s) == list(range(len(s))) for s in slots.values())
    mean = sum(size.values()) / 40
    # a unit is a text, or a group of equal texts of at most a quarter of a shard
    unit = max([len(t) + 16 for t in groups] + [mean / 4])
    assert max(size.values()) - mean <= unit and mean - min(size.values()) <= unit
    assert all(len(set(s)) == 1 for t, s in groups.items() if len(s) * (len(t) + 16) <= mean / 4)


def test_edited_texts(spark):
    rows = sorted(((r.doc_id, r.text or "") for r in documents(spark).collect()), reverse=True)
    after = {k: rows[(i + 1) % len(rows)][1] for i, (k, _) in enumerate(rows)}
    text, prints = dict(rows), {}
    for r in queries.op9_syncmers(spark, DATA).collect():
        t = text[r.doc_id]
        cut = len(t) // 3
        edited = t[: len(t) - cut] + after[r.doc_id][:cut]
        assert (r.n_chars, r.edited_sha256) == (len(t), hashlib.sha256(edited.encode()).hexdigest())
        own, new, nxt = (syncmer.fingerprints([x])[0] for x in (t, edited, after[r.doc_id]))
        assert (r.near_edited, r.near_next) == (syncmer.likeness(own, new), syncmer.likeness(own, nxt))
        assert (r.fingerprint, r.edited_fingerprint) == (syncmer.encode(own), syncmer.encode(new)) and prints.setdefault(t, r.fingerprint) == r.fingerprint
        assert prints.setdefault(edited, r.edited_fingerprint) == r.edited_fingerprint


def test_held_out_accuracy(spark):
    labels = {r.doc_id: r for r in spark.read.parquet(f"{MORE}/labels.parquet").collect()}
    lang = {r.doc_id: r.lang for r in documents(spark, MORE).collect()}
    tox = [r for r in queries.op1_toxicity(spark, MORE).collect() if r.doc_id in labels and r.held_out and labels[r.doc_id].toxic is not None]
    good = [r for r in queries.op8_quality(spark, MORE).collect() if r.doc_id in labels and r.held_out and labels[r.doc_id].quality is not None]
    said = [r for r in queries.op10_language_id(spark, MORE).collect() if r.held_out and r.lang_pred != "und" and lang[r.doc_id]]
    share = lambda rows, right: sum(map(right, rows)) / len(rows)
    assert share(tox, lambda r: r.predicted == labels[r.doc_id].toxic) > 0.9
    assert share(good, lambda r: r.predicted == labels[r.doc_id].quality) > 0.85
    assert share(said, lambda r: r.lang_pred == lang[r.doc_id]) > 0.95


def test_shards_keep_the_mix(spark):
    """Slots of a shard follow the mix, and its prefixes hold the target weights: sources of 4900 and 100 rows weigh 70 to 10."""
    docs = spark.range(5000).selectExpr("id as doc_id", "'text' as text", "'en' as lang", "if(id % 50 = 7, 'few', 'many') as source", "4L as n_chars")
    mix = {r.doc_id: (r.slot, r.place, r.phase, r.source) for r in corpus_pipeline.mixing.mixed(docs).collect()}
    shards = {}
    for r in corpus_pipeline.shard(spark, corpus_pipeline.mix(spark, docs, DATA), DATA).collect():
        shards.setdefault(r.shard, []).append((r.slot, mix[r.doc_id]))
    assert len(shards) == 40
    early = []
    for rows in shards.values():
        rows = [m for _, m in sorted(rows)]
        assert rows == sorted(rows)
        early += [m[3] for m in rows if m[2] == 0]
    # in the first phase, before a source ends, each has its weight but for one block
    assert abs(early.count("few") - len(early) / 8) <= 64 and early.count("few") > 0.9 * 100 and len(early) < 2500


@pytest.mark.parametrize("name,stage", corpus_pipeline.STAGES)
def test_stages_with_odd_and_empty_tables(spark, name, stage):
    base = documents(spark)
    odd = base.limit(30).unionByName(base.limit(3)).unionByName(spark.createDataFrame([(None, None, None, None, None), (900, "", None, None, 0), (901, None, "en", "s", None)], base.schema)).selectExpr("*", "'x' as shard_", "1 as kept")
    out = stage(spark, odd, DATA)
    assert set(odd.columns) <= set(out.columns)
    assert 0 < out.count() <= 36
    assert stage(spark, odd.limit(0), DATA).count() == 0
