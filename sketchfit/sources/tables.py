"""Scans of the given tables, file round trips, and the store of sketches."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession, kind: str) -> str:
    """A fresh folder below spark.checkpoint.dir, which all executors reach; where that is unset, a temporary one, on a single machine only."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base is None:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        base = tempfile.mkdtemp(prefix="sketchfit-")
    return f"{base.rstrip('/')}/{kind}-{uuid.uuid4().hex}"


def written(df: DataFrame, kind: str) -> DataFrame:
    """Write df and read it back: a cut in the lineage that survives lost executors."""
    spark = df.sparkSession
    path = shared_folder(spark, kind)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def round_trip(df: DataFrame, fmt: str, kind: str = "roundtrip") -> DataFrame:
    spark = df.sparkSession
    path = shared_folder(spark, kind)
    df.write.format(fmt).option("header", "true").save(path)
    return spark.read.format(fmt).option("header", "true").schema(df.schema).load(path)


def save_sketches(sk: DataFrame, path: str, by: str | None = None, mode: str = "overwrite") -> None:
    """Parquet partitioned by map (and `by`, such as a day); overwriting replaces only the partitions that sk holds."""
    parts = ["map_id"] + ([by] if by else [])
    sk.write.mode(mode).option("partitionOverwriteMode", "dynamic").partitionBy(*parts).parquet(path)


def load_sketches(spark: SparkSession, path: str, map_id: str | None = None) -> DataFrame:
    """With a map the scan reads its partitions alone."""
    df = spark.read.parquet(path)
    return df if map_id is None else df.where(F.col("map_id") == map_id)


def event_stream(spark: SparkSession, sf_dir: str, rows_per_trigger: int | None = None) -> DataFrame:
    """`events` as a file stream with a proper timestamp (watermarks refuse zoneless ones)."""
    static = spark.read.parquet(f"{sf_dir}/events.parquet")
    reader = spark.readStream.schema(static.schema)
    if rows_per_trigger:
        reader = reader.option("maxFilesPerTrigger", 1)
    return reader.parquet(f"{sf_dir}/events*.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
