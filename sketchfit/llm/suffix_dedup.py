r"""Exact removal of repeated byte strings by bucket-pointer refinement.

Every string of `length` bytes (a window) is reached from one place in it, its anchor: the start of the q-gram with the least hash among its first `reach` bytes, so equal windows have
equal anchors at equal offsets. Anchors are put into buckets by their q-gram; buckets of one are dropped. A bucket is then refined by identifiers of the text at later and earlier
offsets: a block of offsets has the identifier of what all its windows share (the intersection of their bytes) and of all they cover (the union).
  equal unions:         all windows of the block occur twice; the block is settled
  no equal intersection: none occurs twice; the block is settled
  otherwise:            the block is cut into smaller ones, whose identifiers refine the bucket again, down to single windows.
Of entries with one union a single one goes on, as the partner of those that are not settled. Each level sorts the entries on the identifiers in the packed
exchange, whose tasks hold a distinct key once, so copies of one text cost their number and no more. Unions are compared by 128-bit digests; the 64-bit keys only gate.
An entry carries the offsets it serves, so later levels slice the text and hash no q-gram again. Documents are told apart by id and the whole 64-bit hash of the text.

Removal is exact and judged on the input: overlapping repeats within one document count. n_repeat_grams counts the document's anchors whose q-gram occurs elsewhere: any passage of at
least `reach` bytes that repeats has one, though it may be too short to be removed. Defined results: null or empty text has no bytes and nothing removed; texts shorter than
`length` stay whole; rows with one id and text count as two documents with the same result, and n_repeat_grams is of all of them; null ids are ordinary; only id and text are read; an
empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .common import docs_view, release, stored, with_totals
from .near_duplicates import mix
from .packed import Batches, parts_for, repeated

U = np.uint64
NO_ID = -(1 << 63)
SEGMENT = 1 << 19
BASE = 0x9E3779B97F4A7C15 | 1
INVERSE = pow(BASE, -1, 1 << 64)
TABLE = np.random.Generator(np.random.Philox(7)).integers(0, 1 << 63, size=256, dtype=np.int64).astype(U)
_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = 1 << max(12, (n - 1).bit_length())
    if size not in _POWERS:
        up, down = np.full(size, BASE, dtype=U), np.full(size, INVERSE, dtype=U)
        up[0] = down[0] = 1
        _POWERS[size] = np.cumprod(up), np.cumprod(down)
    a, b = _POWERS[size]
    return a[:n], b[:n]


def gram_hashes(raw: np.ndarray, q: int) -> np.ndarray:
    """A hash of each q-gram that depends on its bytes alone."""
    n = len(raw)
    up, down = powers(n + 1)
    sums = np.zeros(n + 1, dtype=U)
    np.cumsum(TABLE[raw] * up[:n], out=sums[1:])
    return mix((sums[q:] - sums[:-q]) * down[: n - q + 1], 31)


def anchors(raw: np.ndarray, length: int, q: int, segment: int = SEGMENT) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(place, least offset, largest offset, q-gram hash), each place once: the windows that start at place - offset have their anchor at place.

    Texts are read `segment` windows at a time; an anchor with windows on both sides of a cut is one entry.
    """
    out = []
    w = length - q + 1
    for base in range(0, len(raw) - length + 1, segment):
        part = raw[base : base + segment + length - 1]
        h = gram_hashes(part, q)
        best = (h & U(0xFFFFFFFFFFF00000)) | np.arange(len(h), dtype=U)  # the low 20 bits are the place: of equal ones the first
        span = 1
        while span * 2 <= w:
            best = np.minimum(best[:-span], best[span:])
            span *= 2
        if w > span:
            best = np.minimum(best[: len(best) - (w - span)], best[w - span :])
        at = (best & U(0xFFFFF)).astype(np.int64)
        first = np.flatnonzero(np.diff(at, prepend=-1))
        last = np.append(first[1:], len(at)) - 1
        place = at[first]
        out.append((place + base, place - last, place - first, h[place]))
    place, low, high, h = (np.concatenate(x) for x in zip(*out))
    first = np.flatnonzero(np.diff(place, prepend=-1))  # places never fall from window to window
    return place[first], np.minimum.reduceat(low, first), np.maximum.reduceat(high, first), h[first]


ROWS = "keys binary, doc_id long, k2 long, place binary, u1 binary, u2 binary"
PAYLOAD = ["doc_id", "k2", "place", "u1", "u2"]
NO_PLACE = -1
SLICE = 200  # documents in Python at a time
HELD = 100_000  # entries before a batch goes out


def digests(parts: list[bytes]) -> np.ndarray:
    """128-bit digests as two columns of signed longs; the second is never 0, which stands for none."""
    u = np.frombuffer(b"".join([xxhash.xxh3_128_digest(x) for x in parts]), dtype="<i8").reshape(-1, 2).copy()
    u[u[:, 1] == 0, 1] = 1
    return u


def packed_place(a, low, high, b0, partner):
    """Anchor (31 bits), least and largest offset served (10 each), first offset of the block (10), partner mark (1)."""
    return a << 31 | low << 21 | high << 11 | b0 << 1 | partner


def anchor_of(place):
    return F.shiftright(place, 31)


def first_offset(place):
    return F.shiftright(place, 1).bitwiseAND(0x3FF)


def batched(rows: list[tuple], arrow: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), arrow)] if rows else [pa.array([], type=f.type) for f in arrow], schema=arrow)


def first_level(length: int, q: int, reach: int) -> Callable[[Batches], Batches]:
    """From doc_id, k2, text the entries of all anchors: the bucket is the q-gram, the union is everything that any window with this anchor could cover."""
    arrow = to_arrow_schema(T._parse_datatype_string(ROWS))
    far = reach - q

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, held = [], 0
        for batch in batches:
            for lo in range(0, batch.num_rows, SLICE):
                for doc_id, k2, text in zip(*(c.slice(lo, SLICE).to_pylist() for c in batch.columns)):
                    data = text.encode("utf-8", "surrogatepass")
                    n = len(data)
                    if n < reach:
                        continue
                    at, low, high, h = anchors(np.frombuffer(data, dtype=np.uint8), reach, q)
                    low = np.maximum(low, at + length - n)  # offsets whose window ends within the text
                    place = np.where(low <= high, packed_place(at, low, high, 0, 0), NO_PLACE)
                    u = np.zeros((len(at), 2), dtype=np.int64)
                    inner = (at >= far) & (at + length <= n)
                    u[inner] = digests([data[a - far : a + length] for a in at[inner].tolist()])
                    h = mix(h, 32)  # an anchor's is the least of many and so a small number, and the exchange deals by the high bits
                    rows.append((h.tobytes(), doc_id, k2, place.tobytes(), u[:, 0].tobytes(), u[:, 1].tobytes()))
                    held += len(at)
                    if held > HELD:
                        yield batched(rows, arrow)
                        rows, held = [], 0
        if rows:
            yield batched(rows, arrow)

    return run


def next_level(theirs: DataFrame, parent: int, size: int, length: int, far: int) -> DataFrame:
    """Entries of the blocks of `size` offsets within the open blocks of `parent` offsets; theirs: doc_id, k2, text, open (array of place)."""
    arrow = to_arrow_schema(T._parse_datatype_string(ROWS))

    def entries(data: bytes, todo: list[int]) -> tuple[list, list, list]:
        n = len(data)
        keys, places, unions = [], [], []
        for x in todo:
            a, low, high, start = x >> 31, x >> 21 & 0x3FF, x >> 11 & 0x3FF, x >> 1 & 0x3FF
            for b0 in range(start, min(start + parent, far + 1), size):
                b1 = min(b0 + size, far + 1) - 1
                if b1 >= low and b0 <= high:
                    keys.append(xxhash.xxh3_64_intdigest(data[a - b0 : a - b1 + length], seed=b0 * 1024 + b1))
                    places.append(packed_place(a, low, high, b0, x & 1))
                    unions.append(data[a - b1 : a - b0 + length] if a >= b1 and a - b0 + length <= n else b"")
        return keys, places, unions

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, held = [], 0
        for batch in batches:
            for lo in range(0, batch.num_rows, SLICE):
                for doc_id, k2, text, todo in zip(*(c.slice(lo, SLICE).to_pylist() for c in batch.columns)):
                    data = text.encode("utf-8", "surrogatepass")
                    for x in range(0, len(todo), 5000):
                        keys, places, unions = entries(data, todo[x : x + 5000])
                        u = digests(unions)
                        u[[not x for x in unions]] = 0
                        rows.append((np.array(keys, dtype=U).tobytes(), doc_id, k2, np.array(places, dtype=np.int64).tobytes(), u[:, 0].tobytes(), u[:, 1].tobytes()))
                        held += len(keys)
                        if held > HELD:
                            yield batched(rows, arrow)
                            rows, held = [], 0
        if rows:
            yield batched(rows, arrow)

    return theirs.select("doc_id", "k2", "text", "open").mapInArrow(run, ROWS)


def settle(entries: DataFrame, size: int, length: int, last: bool, far: int) -> tuple[DataFrame, DataFrame | None, DataFrame]:
    """(spans: doc_id, k2, start, stop; open: doc_id, k2, place; a table that both read) of one level."""
    place = F.col("place")
    own = place.bitwiseAND(1) == 0
    kinds = entries.where("u2 <> 0").groupBy("key", "u1", "u2").agg(F.count("place").alias("c"), *[F.first(x).alias(x) for x in ("doc_id", "k2", "place")])
    kinds = stored(kinds, "kinds")  # which entry stands for its union is settled here
    a, b0 = anchor_of(place), first_offset(place)
    many = kinds.where("c > 1").select("key", "u1", "u2", "c")
    twice = with_totals(entries.where(own & (F.col("u2") != 0)), many, ["key", "u1", "u2"])
    b1 = F.least(b0 + F.lit(size - 1), F.lit(far))
    spans = twice.select("doc_id", "k2", (a - b1).alias("start"), (a - b0 + F.lit(length)).alias("stop"))
    if last:
        return spans, None, kinds
    # buckets with something open: an entry that stands at an edge of its text, or is the only one of its union
    edges = entries.where("u2 = 0").select("key", "doc_id", "k2", "place", own.alias("open"))
    mark = place.bitwiseOR(F.when(F.col("c") > 1, 1).otherwise(0))
    going = edges.union(kinds.select("key", "doc_id", "k2", mark.alias("place"), ((F.col("c") == 1) & own).alias("open")))
    live = stored(going.groupBy("key").agg(F.count("place").alias("c"), F.max("open").alias("any")).where("any").select("key", "c"), "live")
    return spans, with_totals(going, live, ["key"]).select("doc_id", "k2", "place"), kinds


def repeated_spans(docs: DataFrame, length: int, q: int, reach: int, levels: tuple[int, ...], broadcast_rows: int) -> tuple[DataFrame, DataFrame]:
    """(doc_id, k2, start, stop: bytes that lie in a window which occurs more than once; doc_id, k2, n_repeat_grams). docs: doc_id, k2, text."""
    if levels[-1] != 1 or any(a % b for a, b in zip(levels, levels[1:])):
        raise ValueError("each level must divide the one before it, and the last be 1")
    if not q <= reach <= length or reach - q > 0x3FE:
        raise ValueError("a q-gram must fit into the reach, that into a window, and at most 1023 offsets into both")
    spark = docs.sparkSession
    far = reach - q
    n_bytes = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), int(n_bytes * 2 // ((far + 2) * 500_000)) + 1)
    entries = stored(repeated(docs, PAYLOAD, parts, first_level(length, q, reach)), "entries")
    grams = stored(entries.groupBy("doc_id", "k2").agg(F.count("key").alias("n_repeat_grams")), "grams")
    spans, todo, kinds = settle(entries.where(F.col("place") != NO_PLACE), far + 1, length, False, far)
    found = [stored(spans, "spans")]
    parent = far + 1
    for i, size in enumerate(levels):
        todo = stored(todo.groupBy("doc_id", "k2").agg(F.collect_set("place").alias("open")), "open")
        release(entries, kinds)
        n = todo.count()
        if not n:
            break
        few = F.broadcast(todo.select("doc_id").distinct()) if n <= broadcast_rows else todo.select("doc_id").distinct()
        theirs = docs.join(few, "doc_id", "left_semi").join(todo, ["doc_id", "k2"])
        made = stored(next_level(theirs, parent, size, length, far), "blocks")
        entries = stored(repeated(made, PAYLOAD, parts_for(made, "keys")), "entries")
        release(made, todo)
        spans, todo, kinds = settle(entries, size, length, i == len(levels) - 1, far)
        found.append(stored(spans, "spans"))
        parent = size
    out = found[0]
    for x in found[1:]:
        out = out.union(x)
    return out, grams


def remove_repeats(docs: DataFrame, length: int = 400, q: int = 128, reach: int = 250, id_col: str = "doc_id", text_col: str = "text", levels: tuple[int, ...] = (48, 8, 1), broadcast_rows: int = 1_000_000) -> DataFrame:
    """doc_id, n_bytes, n_repeat_grams, spans (maximal removed runs, sorted), kept (remaining bytes) for every row."""
    view = docs_view(docs, id_col, text_col).select(F.coalesce("doc_id", F.lit(NO_ID)).alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    view = view.withColumn("k2", F.xxhash64("text")).select("doc_id", "k2", "text")
    found, grams = repeated_spans(view, length, q, reach, levels, broadcast_rows)
    found = found.groupBy("doc_id", "k2").agg(F.collect_set(F.struct(F.col("start").cast("int").alias("start"), F.col("stop").cast("int").alias("stop"))).alias("spans"))
    found = stored(grams.join(found, ["doc_id", "k2"], "left"), "spans")
    schema = "doc_id long, n_bytes long, n_repeat_grams long, spans array<struct<start:int,stop:int>>, kept binary"
    arrow = to_arrow_schema(T._parse_datatype_string(schema))

    def each(doc_id, text, grams, spans):
        data = text.encode("utf-8", "surrogatepass")
        runs: list[list[int]] = []
        for a, b in sorted((s["start"], s["stop"]) for s in spans or ()):
            if runs and a <= runs[-1][1]:
                runs[-1][1] = max(runs[-1][1], b)
            else:
                runs.append([a, b])
        out, at = [], 0
        for a, b in runs:
            out.append(data[at:a])
            at = b
        out.append(data[at:])
        return (None if doc_id == NO_ID else doc_id), len(data), grams or 0, [{"start": a, "stop": b} for a, b in runs], b"".join(out)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, SLICE):
                yield batched([each(*row) for row in zip(*(c.slice(lo, SLICE).to_pylist() for c in batch.columns))], arrow)

    rows = view.join(found, ["doc_id", "k2"], "left").select("doc_id", "text", "n_repeat_grams", "spans")
    return rows.mapInArrow(run, schema)
