r"""Token-id files: one zstandard frame for each document, a document index and a seek table at the end.

File layout (little-endian throughout):
  frames        one independent zstandard frame for each document, holding its ids as unsigned 32-bit integers
  index frame   a skippable frame with the documents' ids as signed 64-bit integers, in frame order, then a bit for each (most significant first) that marks a null id
  seek table    a skippable frame in the public seekable layout: for each frame its compressed size, its decompressed size
                and the low 32 bits of the XXH64 of its decompressed bytes; then the number of frames, a descriptor byte and a magic number.
A reader loads the tail, finds a document's frame by prefix sums, and decompresses only that frame, checking its checksum.

Files are written under a temporary name and renamed when whole, one for each range of documents, so a lost executor's task is simply run again.

Defined results: null or empty text gives the end id alone; null ids come first; equal doc_ids are kept, ordered by a hash of the text, then the text; a very long text is one frame; an empty table gives no
files and an empty result; only the id and text columns are read, so other columns may have any name.
"""

from __future__ import annotations

import io
import json
import re
import struct
import uuid
import zlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyarrow import fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .common import docs_view, scratch

# Fixed values of the public seekable layout: skippable frame numbers, flag for checksums, end-of-file number.
INDEX_MAGIC = 0x184D2A5D
SEEK_MAGIC = 0x184D2A5E
CHECKSUMS = 0x80
END_MAGIC = 0x8F92EAB1
NO_ID = -(1 << 63)  # what stands in the index for a null id, which its bit tells from this number

_TOKENIZERS: dict[str, object] = {}


def tokenizer(path: str):
    """One tokenizer for each worker process."""
    if path not in _TOKENIZERS:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        _TOKENIZERS[path] = Tokenizer.from_file(path)
    return _TOKENIZERS[path]


def default_tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


#: White space as the pre-tokenizer's pattern means it (the Unicode property); Python's own class also has U+001C to U+001F.
_WS = r"\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
#: Pieces at whose ends the byte-level pattern always ends a match, so that each can be encoded alone.
_PIECES = re.compile(f" ?[^{_WS}]+|[{_WS}]+(?![^{_WS}])|[{_WS}]+")


class Encoder:
    """Encodes with the tokenizers library, each distinct piece once while it stays in a cache of bounded size.

    Pieces are used only for a byte-level model without a normalizer, and not for texts that hold one of its added tokens;
    other texts and models are encoded whole. Values are the ids as little-endian bytes, so a text is one join.
    Where single blanks and line feeds are the only white space, words are found by split(): `spaced` has them with the blank before them.
    """

    def __init__(self, path: str, cache_entries: int = 600_000):
        self.tok, self.limit = tokenizer(path), cache_entries
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        pre, added = spec.get("pre_tokenizer") or {}, spec.get("added_tokens", [])
        self.added = [t["content"] for t in added]
        self.pieces = pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True) and not spec.get("normalizer") and not any(t.get("lstrip") or t.get("rstrip") for t in added)
        vocab = self.tok.get_vocab()
        self.opens = np.zeros(max(vocab.values()) + 1, dtype=bool)  # ids whose piece begins with a blank
        self.opens[[i for t, i in vocab.items() if t.startswith("\u0120")]] = True
        self.spaced: tuple[dict[str, bytes], dict[str, bytes]] = ({}, {})  # young and old generation
        self.plain: tuple[dict[str, bytes], dict[str, bytes]] = ({}, {})

    def _missing(self, kind: str, wanted: set[str]) -> list[str]:
        young, old = getattr(self, kind)
        if len(young) > self.limit:
            young, old = {}, young
            setattr(self, kind, (young, old))
        new = wanted.difference(young)
        if old:
            young.update([(p, old[p]) for p in new if p in old])
            new = new.difference(young)
        return list(new)

    def _ids(self, text: str) -> np.ndarray:
        """The library's fast form leaves out the offsets in the text, which nothing here reads."""
        return np.array(self.tok.encode_batch_fast([text], add_special_tokens=False)[0].ids, dtype="<u4")

    def _one_by_one(self, cache: dict[str, bytes], keys: list[str], texts: list[str]) -> None:
        for k, e in zip(keys, self.tok.encode_batch_fast(texts, add_special_tokens=False)):
            cache[k] = np.array(e.ids, dtype="<u4").tobytes()

    def _fill_plain(self, wanted: set[str]) -> None:
        new = self._missing("plain", wanted)
        self._one_by_one(self.plain[0], new, new)

    def _fill_spaced(self, wanted: set[str]) -> None:
        new = self._missing("spaced", wanted)
        cache = self.spaced[0]
        for lo in range(0, len(new), 20_000):
            part = new[lo : lo + 20_000]
            ids = self._ids(" " + " ".join(part))
            cuts = np.flatnonzero(self.opens[ids])
            if len(cuts) == len(part):
                raw, at = ids.tobytes(), [*(4 * cuts).tolist(), 4 * len(ids)]
                for k, w in enumerate(part):
                    cache[w] = raw[at[k] : at[k + 1]]
            else:  # a token that holds a blank inside: its words one by one
                self._one_by_one(cache, part, [" " + w for w in part])

    def raw(self, texts: list[str]) -> Iterator[bytes]:
        group: list = []
        size = 0
        for k, text in enumerate(texts):
            if not self.pieces or any(a in text for a in self.added):
                group.append(text)
            else:
                lines = [x.split(" ") for x in text.split("\n")]
                if list(chain.from_iterable(lines)) == text.split():
                    group.append((lines, None))
                    size += len(text) // 6
                else:
                    group.append((None, got := _PIECES.findall(text)))
                    size += len(got)
            if size >= 200_000 or k == len(texts) - 1:  # for some texts at a time: the cache holds at least what they need
                mid, first = set(), {"\n"}
                for x in group:
                    if isinstance(x, tuple):
                        if x[0] is None:
                            first.update(x[1])
                        else:
                            for line in x[0]:
                                first.add(line[0])
                                mid.update(line[1:])
                self._fill_spaced(mid)
                self._fill_plain(first)
                plain, spaced = self.plain[0].__getitem__, self.spaced[0].__getitem__
                feed = plain("\n")
                for x in group:
                    if not isinstance(x, tuple):
                        yield self._ids(x).tobytes()
                    elif x[0] is None:
                        yield b"".join(map(plain, x[1]))
                    else:
                        yield feed.join([plain(line[0]) + b"".join(map(spaced, line[1:])) for line in x[0]])
                group, size = [], 0


_ENCODERS: dict[str, Encoder] = {}


def encode(texts: list[str | None], path: str | None = None, end_id: int = 0) -> Iterator[np.ndarray]:
    path = path or default_tokenizer_path()
    if path not in _ENCODERS:
        _ENCODERS[path] = Encoder(path)
    end = np.array([end_id], dtype="<u4").tobytes()
    for raw in _ENCODERS[path].raw([t or "" for t in texts]):
        yield np.frombuffer(raw + end, dtype="<u4")


class Writer:
    """Appends documents to a binary stream and closes it with the index and the seek table."""

    def __init__(self, out, level: int = 3):
        self.out, self.coder = out, zstandard.ZstdCompressor(level=level, write_checksum=False)
        self.entries: list[tuple[int, int, int]] = []
        self.ids: list[int | None] = []

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        raw = ids.astype("<u4", copy=False).tobytes()
        frame = self.coder.compress(raw)
        self.out.write(frame)
        self.entries.append((len(frame), len(raw), xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF))
        self.ids.append(doc_id)

    def close(self) -> None:
        none = np.array([k is None for k in self.ids], dtype=bool)
        index = np.array([NO_ID if k is None else k for k in self.ids], dtype="<i8").tobytes() + np.packbits(none).tobytes()
        self.out.write(struct.pack("<II", INDEX_MAGIC, len(index)) + index)
        table = np.array(self.entries, dtype="<u4").tobytes()
        self.out.write(struct.pack("<II", SEEK_MAGIC, len(table) + 9) + table + struct.pack("<IBI", len(self.entries), CHECKSUMS, END_MAGIC))


class Reader:
    """Random access to the documents of one file."""

    def __init__(self, source, size: int):
        self.source = source
        tail = self._at(size - 17, 17) if size >= 17 else b""
        if len(tail) < 9 or struct.unpack("<I", tail[-4:])[0] != END_MAGIC:
            raise ValueError("no seek table at the end of the file")
        n = struct.unpack("<I", tail[-9:-5])[0]
        start = size - 9 - 12 * n - 8
        magic, length = struct.unpack("<II", self._at(start, 8))
        if magic != SEEK_MAGIC or length != 12 * n + 9:
            raise ValueError("the seek table is damaged")
        self.entries = np.frombuffer(self._at(start + 8, 12 * n), dtype="<u4").reshape(n, 3)
        self.starts = np.concatenate([[0], np.cumsum(self.entries[:, 0], dtype=np.int64)])
        magic, length = struct.unpack("<II", self._at(int(self.starts[-1]), 8))
        if magic != INDEX_MAGIC or length != 8 * n + (n + 7) // 8:
            raise ValueError("the document index is damaged")
        self.doc_ids = np.frombuffer(self._at(int(self.starts[-1]) + 8, 8 * n), dtype="<i8")
        self.none = np.unpackbits(np.frombuffer(self._at(int(self.starts[-1]) + 8 + 8 * n, (n + 7) // 8), dtype=np.uint8), count=n).astype(bool)
        self.decoder = zstandard.ZstdDecompressor()

    def _at(self, start: int, n: int) -> bytes:
        self.source.seek(start)
        return self.source.read(n)

    def ids(self, k: int) -> np.ndarray:
        frame = self._at(int(self.starts[k]), int(self.entries[k, 0]))
        raw = self.decoder.decompress(frame, max_output_size=int(self.entries[k, 1]))
        if len(raw) != self.entries[k, 1] or xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF != self.entries[k, 2]:
            raise ValueError(f"checksum of frame {k} differs")
        return np.frombuffer(raw, dtype="<u4")

    def of(self, doc_id: int | None) -> list[np.ndarray]:
        if doc_id is None:
            return [self.ids(int(k)) for k in np.flatnonzero(self.none)]
        lo, hi = np.searchsorted(self.doc_ids, doc_id, "left"), np.searchsorted(self.doc_ids, doc_id, "right")
        return [self.ids(int(k)) for k in range(lo, hi) if not self.none[k]]


def opened(uri: str) -> tuple[pafs.FileSystem, str]:
    """The file system of a URI and the path in it; hdfs, s3 and gs URIs work as file ones do."""
    return pafs.FileSystem.from_uri(uri if "://" in uri else uri.replace("file:", "file://", 1))


MANIFEST = "part int, file string, first_id long, last_id long, n_docs long, n_tokens long"


def write_tokens(docs: DataFrame, out: str, tokenizer_path: str | None = None, end_id: int = 0, level: int = 3, id_col: str = "doc_id", text_col: str = "text", partitions: int | None = None) -> DataFrame:
    """Writes the files in ascending order of doc_id and returns the manifest, one row for each file."""
    view = docs_view(docs, id_col, text_col).withColumn("text", F.coalesce("text", F.lit("")))
    args = [F.col("doc_id"), F.xxhash64("text")]
    ranged = (view.repartitionByRange(partitions, *args) if partitions else view.repartitionByRange(*args)).sortWithinPartitions(*args, "text")
    ranged = ranged.select(F.spark_partition_id().alias("part"), "doc_id", "text")
    schema = to_arrow_schema(T._parse_datatype_string(MANIFEST))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        writer = stream = None
        tokens = 0
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                keys = part.column(1).to_pylist()
                if writer is None:
                    number = part.column(0)[0].as_py()
                    fs, folder = opened(out)
                    fs.create_dir(folder, recursive=True)
                    name = f"tokens-{number:06d}.zst"
                    temp = f"{folder}/.{name}.{uuid.uuid4().hex}"
                    stream = fs.open_output_stream(temp)
                    writer = Writer(stream, level)
                for key, ids in zip(keys, encode(part.column(2).to_pylist(), tokenizer_path, end_id)):
                    writer.add(key, ids)
                    tokens += len(ids)
        if writer is not None:
            writer.close()
            stream.close()
            fs.move(temp, f"{folder}/{name}")
            yield pa.RecordBatch.from_pylist([{"part": number, "file": f"{out}/{name}", "first_id": writer.ids[0], "last_id": writer.ids[-1], "n_docs": len(writer.ids), "n_tokens": tokens}], schema=schema)

    from .common import stored

    return stored(ranged.mapInArrow(run, MANIFEST), "manifest")  # written once: reading it never writes the files again


READ = "doc_id long, start long, n_tokens long, ids_crc32 long, ids binary"


def read_tokens(manifest: DataFrame, ids: bool = True) -> DataFrame:
    """Every document of the files, with the number of ids before it; the files' totals (a row for each file) are summed on the driver."""
    spark = manifest.sparkSession
    files = sorted(manifest.collect(), key=lambda r: r.part)
    starts, total = [], 0
    for r in files:
        starts.append((r.file, total))
        total += r.n_tokens
    if not files:
        return spark.createDataFrame([], READ)
    listed = spark.createDataFrame(starts, "file string, before long").repartition(len(files), "file")
    arrow = to_arrow_schema(T._parse_datatype_string(READ))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for file, at in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                fs, path = opened(file)
                with fs.open_input_file(path) as source:
                    reader = Reader(source, source.size())
                    rows, held = [], 0
                    for k, (doc_id, none) in enumerate(zip(reader.doc_ids.tolist(), reader.none.tolist())):
                        got = reader.ids(k)
                        raw = got.tobytes()
                        rows.append({"doc_id": None if none else doc_id, "start": at, "n_tokens": len(got), "ids_crc32": zlib.crc32(raw), "ids": raw if ids else None})
                        at += len(got)
                        held += len(raw) if ids else 64
                        if held > 4 << 20:
                            yield pa.RecordBatch.from_pylist(rows, schema=arrow)
                            rows, held = [], 0
                    if rows:
                        yield pa.RecordBatch.from_pylist(rows, schema=arrow)

    return listed.mapInArrow(run, READ)


def lookup(manifest: DataFrame, doc_ids: list[int | None]) -> dict[int | None, list[np.ndarray]]:
    """The ids of a few documents, decompressing no other frame; None asks for those without an id."""
    out: dict[int | None, list[np.ndarray]] = {k: [] for k in doc_ids}
    known = sorted(k for k in out if k is not None)
    asked = F.lit(False)
    if known:
        asked = asked | (F.col("last_id") >= known[0]) & (F.coalesce("first_id", F.lit(NO_ID)) <= known[-1])
    if None in out:
        asked = asked | F.col("first_id").isNull()
    for r in manifest.where(asked).orderBy("part").collect():
        fs, path = opened(r.file)
        with fs.open_input_file(path) as source:
            reader = Reader(source, source.size())
            for k in out:
                out[k] += reader.of(k)
    return out


def to_bytes(items: list[tuple[int | None, np.ndarray]], level: int = 3) -> bytes:
    buffer = io.BytesIO()
    w = Writer(buffer, level)
    for key, ids in items:
        w.add(key, ids)
    w.close()
    return buffer.getvalue()


def token_rows(spark: SparkSession, docs: DataFrame, tokenizer_path: str | None = None, **kw) -> DataFrame:
    """Write docs to fresh files, then read them back: doc_id, start, n_tokens, ids_crc32."""
    manifest = write_tokens(docs, scratch(spark, "tokens"), tokenizer_path, **kw)
    return read_tokens(manifest, ids=False).drop("ids")
