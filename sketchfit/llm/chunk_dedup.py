r"""Substring deduplication by content-defined chunks.

A gear hash over the last 16 bytes marks cut candidates, so cuts depend on content alone and the chunks behind an insertion are found again. Chunks have a least and a largest size, and
never cut a UTF-8 character. Chunks with equal 128-bit digests are one; the occurrence in the least document (id, then hash of the text, then place) stays, the others go where they form a
run of at least `min_run` bytes of removable chunks, so a chance repeat of a few words stays.

Defined results: null or empty text has no chunks; of rows with one id and text, null ids among them, one is judged as above and every other one is a copy whose chunks all go; null ids sort
first; only id and text are read; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from bisect import bisect_left
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .common import docs_view, stored, with_totals
from .packed import Batches, repeated

MASK = 0xF800  # five bits that depend on the last 16 bytes
NO_ID = -(1 << 63)
_rng = np.random.Generator(np.random.Philox(20))
GEAR = _rng.integers(0, 1 << 16, size=256, dtype=np.uint16)


def gear(data: np.ndarray) -> np.ndarray:
    """The low 16 bits of the gear hash at each byte: the sum of table values shifted left by their age."""
    h = GEAR[data]
    for step in (1, 2, 4, 8):
        shifted = h.copy()
        shifted[step:] += h[:-step] << np.uint16(step)
        h = shifted
    return h


def cuts(data: bytes, least: int = 32, most: int = 128) -> list[int]:
    """Ends of the chunks of a text, the last one its length."""
    n = len(data)
    if not n:
        return []
    raw = np.frombuffer(data, dtype=np.uint8)
    start = np.ones(n + 1, dtype=bool)
    start[:n] = (raw & 0xC0) != 0x80
    ok = np.flatnonzero(((gear(raw) & MASK) == 0) & start[1:]) + 1
    points, out, at = ok.tolist(), [], 0
    while n - at > least:
        i = bisect_left(points, at + least)
        end = points[i] if i < len(points) else n
        if end > at + most:
            end = at + most
            while end < n and not start[end]:
                end += 1
        out.append(min(end, n))
        at = out[-1]
    if at < n:
        out.append(n)
    return out


CHUNKS = "keys binary, doc_id long, k2 long, d2 binary, place binary"


def chunk_rows(least: int, most: int) -> Callable[[Batches], Batches]:
    """From doc_id, k2, text the chunks of each document. place: start (32 bits), size (12 bits)."""
    arrow = to_arrow_schema(T._parse_datatype_string(CHUNKS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        digest = xxhash.xxh3_128_digest
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                rows = []
                for doc_id, k2, text in zip(*(c.slice(lo, 500).to_pylist() for c in batch.columns)):
                    data = text.encode("utf-8", "surrogatepass")
                    ends = cuts(data, least, most)
                    begins = [0, *ends[:-1]] if ends else []
                    both = np.frombuffer(b"".join([digest(data[a:b]) for a, b in zip(begins, ends)]), dtype=">u8").reshape(-1, 2).astype(np.uint64)
                    a, b = np.array(begins, dtype=np.int64), np.array(ends, dtype=np.int64)
                    rows.append((both[:, 0].tobytes(), doc_id, k2, both[:, 1].tobytes(), (a << 12 | (b - a)).tobytes()))
                yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), arrow)], schema=arrow)

    return run


def removable(docs: DataFrame, least: int, most: int) -> DataFrame:
    """doc_id, k2, spans: array of (start, stop, first) of the chunks that occur elsewhere; first: this is the place that stays."""
    spark = docs.sparkSession
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), int((docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0) // (750_000 * least)) + 1)
    dups = stored(repeated(docs, ["doc_id", "k2", "d2", "place"], parts, chunk_rows(least, most)), "chunks")
    heads = dups.groupBy("key", "d2").agg(F.min(F.struct("doc_id", "k2", "place")).alias("head"), F.count("place").alias("c")).where("c > 1")
    told = with_totals(dups, stored(heads, "heads"), ["key", "d2"])
    here = F.struct("doc_id", "k2", "place")
    start = F.shiftright("place", 12)
    span = F.struct(start.cast("int").alias("start"), (start + F.col("place").bitwiseAND(0xFFF)).cast("int").alias("stop"), (here == F.col("head")).alias("first"))
    return told.groupBy("doc_id", "k2").agg(F.collect_set(span).alias("spans"))


DONE = "n_bytes long, n_dup_chunks long, n_removed long, spans array<struct<start:int,stop:int>>, kept binary"


def chunk_dedup(docs: DataFrame, least: int = 32, most: int = 128, min_run: int = 64, id_col: str = "doc_id", text_col: str = "text", broadcast_rows: int = 1_000_000) -> DataFrame:
    """doc_id, n_bytes, n_dup_chunks, n_removed, spans (removed runs), kept (remaining bytes)."""
    view = docs_view(docs, id_col, text_col).select(F.coalesce("doc_id", F.lit(NO_ID)).alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).withColumn("k2", F.xxhash64("text"))
    found = stored(removable(view.select("doc_id", "k2", "text"), least, most), "removable")
    schema = f"doc_id long, {DONE}"
    arrow = to_arrow_schema(T._parse_datatype_string(schema))

    # rows with one id and text: one of each is the first, which only a written table can tell for good
    twins = stored(view.groupBy("doc_id", "k2").agg(F.count("text").alias("c")).where("c > 1"), "twins")
    if twins.limit(1).count():
        twin = stored(with_totals(view, twins, ["doc_id", "k2"]).select("doc_id", "k2", "text", F.monotonically_increasing_id().alias("row")), "copies")
        firsts = stored(twin.groupBy("doc_id", "k2").agg(F.min("row").alias("least"), F.count("row").alias("c")), "firsts")
        few = twins.count() <= broadcast_rows
        view = view.join(F.broadcast(twins) if few else twins, ["doc_id", "k2"], "left_anti").select("doc_id", "k2", "text", F.lit(False).alias("copy"))
        view = view.unionByName(with_totals(twin, firsts, ["doc_id", "k2"]).select("doc_id", "k2", "text", (F.col("row") > F.col("least")).alias("copy")))
    else:
        view = view.withColumn("copy", F.lit(False))
    rows = view.join(found, ["doc_id", "k2"], "left").select("doc_id", "text", "copy", "spans")

    def each(doc_id, text, copy, spans):
        data = text.encode("utf-8", "surrogatepass")
        runs: list[list[int]] = []
        for s in sorted((x["start"], x["stop"]) for x in spans or () if copy or not x["first"]):
            if runs and runs[-1][1] == s[0]:
                runs[-1][1] = s[1]
            else:
                runs.append(list(s))
        runs = [r for r in runs if r[1] - r[0] >= min_run]
        out, at = [], 0
        for a, b in runs:
            out.append(data[at:a])
            at = b
        out.append(data[at:])
        kept = b"".join(out)
        return (None if doc_id == NO_ID else doc_id), len(data), len(spans or ()), len(data) - len(kept), [{"start": a, "stop": b} for a, b in runs], kept

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                got = [each(*row) for row in zip(*(c.slice(lo, 1000).to_pylist() for c in batch.columns))]
                yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*got), arrow)], schema=arrow)

    return rows.mapInArrow(run, schema)


def digest(kept: bytes) -> str:
    return hashlib.sha256(kept).hexdigest()
