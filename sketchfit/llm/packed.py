"""Which 64-bit keys occur more than once, and with what: an exchange of keys packed into binary columns.

Rows of one part hold many keys, so a shuffle moves some bytes for each key instead of a row. Entries that repeat a key within a flush of a task are known to be repeated at once:
they go to any part as finished, and one of them stands for the flush in the key's own part. So a key's own task gets at most one entry from each flush, however frequent the key is, and
holds each distinct key of its share once.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

U = np.uint64
FLUSH = 400_000  # entries of a flush at most
FLUSH_VALUES = 1_200_000  # and their numbers: rows with a wide payload go out sooner
SINGLE, FIRST, DONE = 0, 1, 2


def parts_for(df: DataFrame, keys: str, per_part: int = 750_000) -> int:
    spark = df.sparkSession
    total = df.select(F.sum(F.octet_length(keys) / 8)).first()[0] or 0
    return int(max(int(spark.conf.get("spark.sql.shuffle.partitions")), total // per_part + 1))


def home(keys: np.ndarray, parts: int) -> np.ndarray:
    """The part of each key, rising with the key."""
    return ((keys >> U(32)) * U(parts)) >> U(32)


Batches = Iterator[pa.RecordBatch]


def give_back() -> None:
    """Freed memory goes back to the system: workers wait between tasks, and theirs counts as the executor's."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


def repeated(df: DataFrame, payload: list[str], parts: int, make: Callable[[Batches], Batches] | None = None) -> DataFrame:
    """df: `keys` (binary, unsigned 64-bit values) and for each payload name either a long or a binary of as many 64-bit values; or with `make` the rows
    from which it makes such batches (columns `keys`, then the payload), in the same worker process.

    Returns (key, *payload) as longs for every entry whose key occurs at least twice.
    """
    width = len(payload)
    most = min(FLUSH, FLUSH_VALUES // (width + 1))
    fields = ", ".join(f"b{i} binary" for i in range(width + 1))
    packed_schema = f"part int, kind int, {fields}"
    out_schema = "key long, " + ", ".join(f"{p} long" for p in payload)
    packed_arrow, out_arrow = (to_arrow_schema(T._parse_datatype_string(x)) for x in (packed_schema, out_schema))

    def pack(batches: Batches) -> Batches:
        batches = make(batches) if make else batches
        held: list[list[np.ndarray]] = [[] for _ in range(width + 1)]
        size, turn = 0, 104_729 * TaskContext.get().partitionId()  # tasks begin apart, and a repeated task as it did

        def flush() -> pa.RecordBatch:
            """The held entries as rows; a column at a time, so that little more than the result is held at once."""
            nonlocal size, turn
            size = 0
            keys = np.concatenate(held[0])
            order = np.argsort(keys, kind="stable")
            keys = keys[order]
            begin = np.diff(keys, prepend=keys[:1] ^ U(1)) != 0
            alone = begin & np.append(begin[1:], True)
            chosen, starts, part_of, kind_of, at = [], [], [], [], 0
            for kind, which in ((SINGLE, alone), (FIRST, begin & ~alone), (DONE, ~begin)):
                some = np.flatnonzero(which)
                if not len(some):
                    continue
                if kind == DONE:  # wherever there is room
                    cuts = np.arange(0, len(some), 20_000)
                    part = (turn + np.arange(len(cuts))) * 7919 % parts
                    turn += len(cuts)
                else:
                    part = home(keys[some], parts)
                    cuts = np.flatnonzero(np.diff(part.astype(np.int64), prepend=-1))
                    part = part[cuts]
                chosen.append(order[some])
                starts.append(cuts + at)
                part_of.append(part.astype(np.int32))
                kind_of.append(np.full(len(cuts), kind, dtype=np.int32))
                at += len(some)
            del keys, order, begin, alone
            chosen = np.concatenate(chosen)
            ends = pa.py_buffer((np.concatenate([*starts, [at]]) * 8).astype(np.int32))
            cols = [pa.array(np.concatenate(part_of)), pa.array(np.concatenate(kind_of))]
            for i in range(width + 1):
                values = np.concatenate(held[i])
                held[i] = []
                cols.append(pa.Array.from_buffers(pa.binary(), len(cols[0]), [None, ends, pa.py_buffer(values[chosen])]))
            return pa.RecordBatch.from_arrays(cols, schema=packed_arrow)

        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                for row in zip(*(c.to_pylist() for c in batch.slice(lo, 500).columns)):
                    keys = np.frombuffer(row[0], dtype=U)
                    for a in range(0, len(keys), most):
                        held[0].append(keys[a : a + most])
                        for h, v in zip(held[1:], row[1:]):
                            h.append(np.frombuffer(v, dtype=np.int64)[a : a + most] if isinstance(v, bytes) else np.full(len(held[0][-1]), v, dtype=np.int64))
                        size += len(held[0][-1])
                        if size >= most:
                            yield flush()
        if size:
            yield flush()
        held.clear()
        give_back()

    def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first = [np.zeros(0, dtype=U)] + [np.zeros(0, dtype=np.int64) for _ in range(width)]
        many = told = np.zeros(0, dtype=bool)  # of the keys in first: known to be repeated, and already given out
        wait: list[list[np.ndarray]] = [[] for _ in range(width + 2)]
        waiting = 0

        def out(cols: list[np.ndarray]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(cols[0].view(np.int64)), *[pa.array(c) for c in cols[1:]]], schema=out_arrow)

        def settle() -> pa.RecordBatch:
            nonlocal first, many, told, wait, waiting
            n = len(told)
            sure = np.concatenate([many, *wait.pop()])
            cols = []
            for i in range(width + 1):
                cols.append(np.concatenate([first[i], *wait[i]]))
                first[i] = wait[i] = None
            wait, waiting = [[] for _ in range(width + 2)], 0
            old = np.concatenate([told, np.zeros(len(sure) - n, dtype=bool)])
            order = np.argsort(cols[0], kind="stable")
            for i in range(width + 1):
                cols[i] = cols[i][order]
            old, sure = old[order], sure[order]
            starts = np.flatnonzero(np.diff(cols[0], prepend=cols[0][:1] ^ U(1)) != 0)
            sizes = np.diff(np.append(starts, len(sure)))
            sure = np.maximum.reduceat(sure, starts) | (sizes > 1)
            tell = np.repeat(sure, sizes) & ~old
            first, many, told = [c[starts] for c in cols], sure, sure
            return out([c[tell] for c in cols])

        for batch in batches:
            for lo in range(0, batch.num_rows, 200):
                for kind, *row in zip(*(c.to_pylist() for c in batch.slice(lo, 200).columns[1:])):
                    cols = [np.frombuffer(v, dtype=t) for v, t in zip(row, [U] + [np.int64] * width)]
                    if kind == DONE:
                        yield out(cols)
                        continue
                    for w, c in zip(wait, cols):
                        w.append(c)
                    wait[-1].append(np.full(len(cols[0]), kind == FIRST))
                    waiting += len(cols[0])
                    if waiting >= max(500_000, len(first[0]) // 2):
                        yield settle()
        if waiting:
            yield settle()
        first.clear()
        give_back()

    rows = df if make else df.select("keys", *payload)
    return rows.mapInArrow(pack, packed_schema).repartitionById(parts, F.col("part")).mapInArrow(unpack, out_schema)
