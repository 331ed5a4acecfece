"""Token ids in seekable files: independent zstandard frames, a table of documents,
and a trailing seek table with a checksum per frame.

File layout, all little-endian: data frames (each a whole number of documents, ids of
``width`` bytes); one more frame with the table of documents (``doc_id`` int64,
token count uint32); a skippable frame with the seek table. The
seek table follows zstandard's published seekable format: magic 0x184D2A5E, then
for each frame compressed size, decompressed size and the low 32 bits of XXH64 of
the content, then frame count, descriptor 0x80 (checksums present) and magic 0x8F92EAB1.
A reader fetches the tail, then the document table, then only the frames that hold
wanted documents."""

from __future__ import annotations

import gc
import json
import re
import struct
import zlib
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession

from ._common import DOC, col, pick, scratch, written

SKIPPABLE, SEEKABLE, FOOTER = 0x184D2A5E, 0x8F92EAB1, 9
#: Pieces whose ids a worker keeps, at about 200 bytes each.
CACHE_PIECES = 1_000_000
# Fixed value: a splitting pattern whose pieces hold no white space, and no letter beside a mark.
_WORDS_ONLY = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
_ODD_SPACE = re.compile("[\x1c-\x1f]")
_CLOSED = re.compile(r"([A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+)([.,!?:;#$%&*]*)")


class CorruptFrame(ValueError):
    """A frame's content does not match its checksum in the seek table."""


class _Known(dict):
    """Pieces and their ids; pieces beyond CACHE_PIECES live in ``passing`` for one batch only."""

    passing: dict[str, bytes] = {}

    def __missing__(self, piece: str) -> bytes:
        return self.passing[piece]


def cuts_at_space(settings: dict) -> bool:
    """Whether a tokenizer's file says that white space always ends a token and has none itself: its normalizer works on single
    words, its splitting pattern is _WORDS_ONLY, no added token has white space, and encoding is not random."""

    def steps(part, inside):
        return [] if part is None else [y for x in part[inside] for y in steps(x, inside)] if part["type"] == "Sequence" else [part]

    space = {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}
    words = [x["type"] in ("NFC", "Lowercase") or x == space for x in steps(settings.get("normalizer"), "normalizers")]
    split = steps(settings.get("pre_tokenizer"), "pretokenizers")
    first = {"type": "Split", "pattern": {"Regex": _WORDS_ONLY}, "behavior": "Removed", "invert": True}
    later = {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False}
    model = settings["model"]
    whole = model["type"] == "BPE" and not model.get("dropout") and model.get("end_of_word_suffix") == "</w>" and not model.get("ignore_merges")
    plain = not any(re.search(r"\s", t["content"]) or t["lstrip"] or t["rstrip"] for t in settings.get("added_tokens") or [])
    return all(words) and split[:1] == [first] and split[1:] in ([], [later]) and whole and plain


class Encoder:
    """Token ids of whole texts as bytes of ``width``-byte integers.

    Where the tokenizer's file says that it never joins text across white space, which it drops (cuts_at_space()), a text's ids
    are those of its pieces in order, cut at white space, and a word's closing marks are apart. Pieces repeat, so the
    ids of CACHE_PIECES of them are kept; the others are encoded once a batch. A text with one of the four
    control characters that Python but not the tokenizer calls white space is encoded whole,
    as is every text of any other tokenizer, and with ``by_piece=False``."""

    def __init__(self, path: str, width: int | None = None, by_piece: bool | None = None, special_as_text: bool = False):
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.tok.encode_special_tokens = special_as_text
        self.width = width or (2 if self.tok.get_vocab_size() <= 1 << 16 else 4)
        self.kind = np.dtype(f"<u{self.width}")
        if by_piece is None:
            with open(path, encoding="utf-8") as f:
                by_piece = cuts_at_space(json.load(f))
        self.by_piece, self.known, self.plain = by_piece, _Known(), None
        if by_piece:
            self.plain, self.lowers, self.special = self._plain(path)
        vocab = self.tok.get_vocab()
        self.ends = np.zeros(max(vocab.values()) + 1, bool)
        self.ends[[i for k, i in vocab.items() if k.endswith("</w>")]] = True

    @staticmethod
    def _plain(path: str):
        """The tokenizer without its normalizer and splitting pattern, which makes of Latin words in lower case between blanks what the
        whole one makes of them; whether that lowers them; and its added tokens, which only the whole one knows."""
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            settings = json.load(f)
        lowers = '"Lowercase"' in json.dumps(settings.get("normalizer"))
        special = [t["content"] for t in settings.get("added_tokens") or []]
        split = settings["pre_tokenizer"]
        later = [x for x in split.get("pretokenizers", []) if x["type"] == "ByteLevel"]
        split = {"type": "Sequence", "pretokenizers": [{"type": "WhitespaceSplit"}, *later]}
        settings |= {"normalizer": None, "pre_tokenizer": split, "post_processor": None, "added_tokens": []}
        return Tokenizer.from_str(json.dumps(settings)), lowers, special

    def _whole(self, text: str) -> bytes:
        return np.array(self.tok.encode(text, add_special_tokens=False).ids, self.kind).tobytes()

    def _pieces(self, pieces: list[str]) -> dict[str, bytes]:
        """Ids of distinct pieces. Latin words, without the marks that close
        them, go many in one text and in lower case, where each ends in its one token with the
        end-of-word mark; should the counts not agree they go one by one like all other pieces."""
        out: dict[str, bytes] = {}
        closed, latin, rest = [], [], []
        for p in pieces:
            if p.isalpha() and p.isascii():
                latin.append(p)
            elif m := _CLOSED.fullmatch(p):
                closed.append((p, m[1], m[2]))
            else:
                rest.append(p)
        words = dict.fromkeys(latin)
        words.update(dict.fromkeys(w for _, w, _ in closed))
        known = self.known
        new = [w for w in words if w not in known]
        own = [w for w in new if w not in self.special]
        # words that differ in case only are encoded once
        low = [w.lower() for w in own] if self.lowers else own
        ids = self._joined(self.plain, [w for w in dict.fromkeys(low) if w not in known])
        out |= {w: ids[x] if x in ids else known[x] for w, x in zip(own, low)}
        out |= self._joined(self.tok, [w for w in new if w not in out])
        marks = self._singly(list({m for _, _, m in closed if m}))
        for p, w, m in closed:
            if m:
                out[p] = (out[w] if w in out else known[w]) + marks[m]
        return out | self._singly(rest)

    def _joined(self, tok, words: list[str]) -> dict[str, bytes]:
        """Ids of words that are each one piece of the splitting pattern, many in one text."""
        out: dict[str, bytes] = {}
        for k in range(0, len(words), 500):
            part = words[k : k + 500]
            ids = np.array(tok.encode_batch_fast([" ".join(part)], add_special_tokens=False)[0].ids, self.kind)
            cut = (np.flatnonzero(self.ends[ids]) + 1).tolist()
            if len(cut) != len(part) or cut[-1] != len(ids):
                out |= self._singly(part)
                continue
            raw, w, at = ids.tobytes(), self.width, 0
            for p, c in zip(part, cut):
                out[p] = raw[at * w : c * w]
                at = c
        return out

    def _singly(self, pieces: list[str]) -> dict[str, bytes]:
        return {p: np.array(e.ids, self.kind).tobytes() for p, e in zip(pieces, self.tok.encode_batch_fast(pieces, add_special_tokens=False))}

    def encode(self, texts: list[str | None]) -> list[bytes]:
        if not self.by_piece:
            return [self._whole(t or "") for t in texts]
        split = [None if _ODD_SPACE.search(t) else t.split() for t in (x or "" for x in texts)]
        new = self._pieces(list(set().union(*(s for s in split if s)) - self.known.keys()))
        if len(new) + len(self.known) <= CACHE_PIECES:
            self.known.update(new)
        else:
            self.known.passing = new
        get = self.known.__getitem__
        return [self._whole(t) if s is None else b"".join(map(get, s)) for s, t in zip(split, texts)]


def pack(docs, width: int, frame_bytes: int = 1 << 18, level: int = 1) -> tuple[bytes, int]:
    """The file of ``docs`` = (doc_id, ids as bytes) in the given order; also the id count."""
    c = zstandard.ZstdCompressor(level=level, write_content_size=True)
    out, table, ids, counts, part, held, first = [], [], [], [], [], 0, []

    def close(content: bytes) -> None:
        z = c.compress(content)
        table.append(struct.pack("<III", len(z), len(content), xxhash.xxh64_intdigest(content) & 0xFFFFFFFF))
        out.append(z)

    for doc_id, raw in docs:
        ids.append(doc_id)
        counts.append(len(raw) // width)
        if not part:
            first.append(len(ids) - 1)
        part.append(raw)
        held += len(raw)
        if held >= frame_bytes:
            close(b"".join(part))
            part, held = [], 0
    if part:
        close(b"".join(part))
    head = json.dumps({"width": width, "docs": len(ids), "first": first}).encode()
    known = np.array([x is not None for x in ids], np.uint8).tobytes()
    close(struct.pack("<I", len(head)) + head + np.array([x or 0 for x in ids], "<i8").tobytes() + np.array(counts, "<u4").tobytes() + known)
    body = b"".join(table) + struct.pack("<IBI", len(table), 0x80, SEEKABLE)
    return b"".join(out) + struct.pack("<II", SKIPPABLE, len(body)) + body, sum(counts)


class Reader:
    """Random access to one file; ``source`` has read(offset, length) and ``size``."""

    def __init__(self, source):
        self.source, self.frames_read = source, 0
        n, descriptor, magic = struct.unpack("<IBI", source.read(source.size - FOOTER, FOOTER))
        if magic != SEEKABLE or not descriptor & 0x80:
            raise CorruptFrame("no seek table with checksums")
        raw = source.read(source.size - FOOTER - 12 * n, 12 * n)
        self.table = np.frombuffer(raw, "<u4").reshape(n, 3).astype(np.int64)
        self.at = np.concatenate([[0], np.cumsum(self.table[:, 0])])
        meta = self._frame(n - 1)
        (h,) = struct.unpack_from("<I", meta)
        head = json.loads(meta[4 : 4 + h])
        d, p = head["docs"], 4 + h
        self.width, self.first = head["width"], [*head["first"], d]
        self.doc_ids = np.frombuffer(meta, "<i8", d, p)
        self.counts = np.frombuffer(meta, "<u4", d, p + 8 * d).astype(np.int64)
        self.known = np.frombuffer(meta, np.uint8, d, p + 12 * d).astype(bool)

    def _frame(self, k: int) -> bytes:
        content = zstandard.ZstdDecompressor().decompress(self.source.read(int(self.at[k]), int(self.table[k, 0])), max_output_size=int(self.table[k, 1]))
        if xxhash.xxh64_intdigest(content) & 0xFFFFFFFF != self.table[k, 2]:
            raise CorruptFrame(f"frame {k}")
        self.frames_read += 1
        return content

    def documents(self, wanted=None):
        """(index, doc_id or None, ids as uint32) in file order; only frames with a
        wanted doc_id are fetched and decompressed."""
        for k in range(len(self.first) - 1):
            lo, hi = self.first[k], self.first[k + 1]
            mine = range(lo, hi) if wanted is None else [i for i in range(lo, hi) if self.known[i] and int(self.doc_ids[i]) in wanted]
            if not mine:
                continue
            content, ends = self._frame(k), np.concatenate([[0], np.cumsum(self.counts[lo:hi])]) * self.width
            for i in mine:
                raw = content[ends[i - lo] : ends[i - lo + 1]]
                yield i, int(self.doc_ids[i]) if self.known[i] else None, np.frombuffer(raw, f"<u{self.width}").astype("<u4")


class Stored:
    """A file in any store that Arrow's file systems reach, by its URI."""

    def __init__(self, uri: str):
        fs, path = _fs(uri)
        self.file = fs.open_input_file(path)
        self.size = self.file.size()

    def read(self, offset: int, length: int) -> bytes:
        return self.file.read_at(length, offset)


class InMemory:
    def __init__(self, data: bytes):
        self.data, self.size = data, len(data)

    def read(self, offset: int, length: int) -> bytes:
        return self.data[offset : offset + length]


def _fs(uri: str):
    return pafs.FileSystem.from_uri(uri if "://" in uri else f"file://{uri[5:] if uri.startswith('file:') else uri}")


def _store(uri: str, data: bytes) -> None:
    """Written under another name first, then moved: a retried or doubled task leaves
    one whole file."""
    import uuid

    fs, path = _fs(uri)
    fs.create_dir(path.rpartition("/")[0], recursive=True)
    part = f"{path}.{uuid.uuid4().hex}.part"
    with fs.open_output_stream(part) as f:
        f.write(data)
    fs.move(part, path)


@cache
def _encoder(path: str, special_as_text: bool) -> Encoder:
    return Encoder(path, special_as_text=special_as_text)


_MANIFEST = "part int, file int, uri string, first_id long, docs long, ids long"


def write_files(docs: DataFrame, out_uri: str, tokenizer_path: str, end_id: int | None = 1, parts: int | None = None, file_bytes: int = 64 << 20, special_as_text: bool = False) -> DataFrame:
    """Encodes ``docs`` (doc_id, text) in ascending doc_id order into files below ``out_uri``
    and returns their manifest (one row a file, in ``part``, ``file`` order).

    Null or empty texts have only the end id. Rows with a null doc_id come first;
    equal doc_ids stay next to each other, ordered by text. Extra columns are ignored."""
    two, _ = pick(docs, DOC)
    ranged = two.repartitionByRange(parts, "doc_id") if parts else two.repartitionByRange("doc_id")
    ranged = ranged.sortWithinPartitions("doc_id", "text")

    def run(batches):
        from pyspark import TaskContext

        part, file, docs_, held = TaskContext.get().partitionId(), 0, [], 0
        enc = _encoder(tokenizer_path, special_as_text)
        end = b"" if end_id is None else np.array([end_id], enc.kind).tobytes()

        def close():
            data, ids = pack(docs_, enc.width)
            uri = f"{out_uri}/tokens-{part:06d}-{file:04d}.zst"
            _store(uri, data)
            return pa.RecordBatch.from_pylist([{"part": part, "file": file, "uri": uri, "first_id": docs_[0][0], "docs": len(docs_), "ids": ids}], schema=pa.schema([("part", pa.int32()), ("file", pa.int32()), ("uri", pa.string()), ("first_id", pa.int64()), ("docs", pa.int64()), ("ids", pa.int64())]))

        for b in batches:
            for lo in range(0, b.num_rows, 4096):
                s = b.slice(lo, 4096)
                gc.disable()  # millions of strings, and no cycles among them
                try:
                    raws = enc.encode(col(s, "text").to_pylist())
                finally:
                    gc.enable()
                docs_ += zip(col(s, "doc_id").to_pylist(), (r + end for r in raws))
                held += sum(map(len, raws))
                if held >= file_bytes:
                    yield close()
                    file, docs_, held = file + 1, [], 0
        if docs_:
            yield close()

    return written(ranged.mapInArrow(run, _MANIFEST), "token-manifest")


def read_files(spark: SparkSession, manifest: DataFrame, wanted: list[int] | None = None) -> DataFrame:
    """Documents of the files: doc_id, start, n_tokens, ids_crc32 and ids. ``start`` counts
    the ids before a document over all files. The driver holds one small row a file."""
    files, before = [], 0
    for r in manifest.orderBy("part", "file").toLocalIterator():
        files.append((r.uri, before))
        before += r.ids
    plan = spark.createDataFrame(files, "uri string, start long")
    plan = plan.repartition(max(1, len(files)))

    def run(batches):
        keep = None if wanted is None else set(wanted)
        for b in batches:
            for uri, base in zip(col(b, "uri").to_pylist(), col(b, "start").to_pylist()):
                r = Reader(Stored(uri))
                starts = base + np.concatenate([[0], np.cumsum(r.counts)])
                rows = []

                def flush():
                    cols = list(zip(*rows))
                    return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.int64()), pa.array(cols[3], pa.int64()), pa.array(cols[4], pa.list_(pa.int32()))], names=["doc_id", "start", "n_tokens", "ids_crc32", "ids"])

                for i, doc_id, ids in r.documents(keep):
                    rows.append((doc_id, int(starts[i]), len(ids), zlib.crc32(ids.tobytes()), ids.astype(np.int32)))
                    if len(rows) >= 256:
                        yield flush()
                        rows = []
                if rows:
                    yield flush()

    return plan.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long, ids array<int>")


def document_digests(spark: SparkSession, manifest: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens and ids_crc32 of every document, read back from the files."""
    files, before = [], 0
    for r in manifest.orderBy("part", "file").toLocalIterator():
        files.append((r.uri, before))
        before += r.ids
    plan = spark.createDataFrame(files, "uri string, start long").repartition(max(1, len(files)))

    def run(batches):
        for b in batches:
            for uri, base in zip(col(b, "uri").to_pylist(), col(b, "start").to_pylist()):
                r = Reader(Stored(uri))
                crc = [zlib.crc32(ids.tobytes()) for _, _, ids in r.documents()]
                starts = base + np.concatenate([[0], np.cumsum(r.counts)])[:-1]
                ids = pa.array(r.doc_ids, pa.int64(), mask=~r.known)
                yield pa.RecordBatch.from_arrays([ids, pa.array(starts, pa.int64()), pa.array(r.counts, pa.int64()), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return plan.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_files(docs: DataFrame, tokenizer_path: str, end_id: int | None = 1, parts: int | None = None) -> DataFrame:
    """Writes the files in the shared folder and returns the digests read back from them.
    An empty table gives an empty result and no file."""
    spark = docs.sparkSession
    return document_digests(spark, write_files(docs, scratch(spark, "tokens"), tokenizer_path, end_id, parts))
