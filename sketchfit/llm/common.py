"""Shared plumbing: table access, scratch folders every executor can reach, Arrow helpers."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: The six ASCII separators of the word pattern [^\x20\x09-\x0D]+; bytes.split() uses exactly these.
ASCII_SPACE = b" \t\n\r\x0b\x0c"
UPPER_TO_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir; where it is unset, a temporary one, on a single machine only."""
    sc = spark.sparkContext
    where = spark.conf.get("spark.checkpoint.dir", None)
    if where is None:
        held = sc._jsc.sc().getCheckpointDir()
        if held.isDefined():
            where = held.get()
        elif re.fullmatch(r"local(\[.*\])?", sc.master):
            where = tempfile.mkdtemp(prefix="sketchfit-")
        else:
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        sc.setCheckpointDir(where)
    return where.rstrip("/")


def scratch(spark: SparkSession, kind: str) -> str:
    """A fresh folder name below the shared folder, as a URI."""
    base = shared_dir(spark)
    if "://" not in base and not base.startswith("file:"):
        base = f"file://{base}"
    return f"{base}/{kind}-{uuid.uuid4().hex}"


#: With this setting Spark removes a plan's shuffle files as its execution ends; a written table needs them no more.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def stored(df: DataFrame, kind: str, **options: str) -> DataFrame:
    """Write df once below the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = scratch(spark, kind)
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        writer = df.write.option("compression", "zstd")
        for k, v in options.items():
            writer = writer.option(k, v)
        writer.parquet(path)
    finally:
        if before is None:
            spark.conf.unset(CLEANUP)
        else:
            spark.conf.set(CLEANUP, before)
    out = spark.read.schema(df.schema).parquet(path)
    out.stored_at = path
    return out


def release(*tables: DataFrame) -> None:
    """Delete the files of stored() tables that no later step reads."""
    for df in tables:
        spark = df.sparkSession
        p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(df.stored_at)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


#: A key is hot beyond this many rows, or a hundred-thousandth of all: so there are at most 100,000 hot keys, whatever the input.
HOT_ROWS, HOT_SHARE = 1000, 100_000


def with_totals(df: DataFrame, totals: DataFrame, keys: list[str], count: str = "c") -> DataFrame:
    """df joined with totals (one row for each key; `count`: the rows that df has of it), without bringing the rows of a hot key into one task.

    Hot keys are broadcast, of which there are at most HOT_SHARE; the others meet in a shuffle.
    """
    n = totals.agg(F.sum(count)).first()[0] or 0
    limit = max(HOT_ROWS, n // HOT_SHARE)
    hot = totals.where(F.col(count) > limit)
    if not hot.limit(1).count():
        return df.join(totals, keys)
    cold = df.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(totals.where(F.col(count) <= limit), keys)
    return cold.unionByName(df.join(F.broadcast(hot), keys))


def docs_view(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Only the two columns that an operator reads, under fixed names, whatever else the table holds."""
    return df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def over_rows(df: DataFrame, schema: str | T.StructType, each: Callable[..., tuple]) -> DataFrame:
    """Apply each(*row values) -> output values to every row, Arrow batch by batch; the order of rows stays."""
    want = T._parse_datatype_string(schema) if isinstance(schema, str) else schema
    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(want)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cols = [c.to_pylist() for c in batch.columns]
            out = [each(*row) for row in zip(*cols)] if cols else []
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], type=f.type) for i, f in enumerate(arrow)], schema=arrow)

    return df.mapInArrow(run, want)
