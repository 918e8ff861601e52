"""Sketches of streams: windows, late rows, retractions, a store that batches update once, alarms on drift, and decoding every few batches."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..functions import vectors as V
from ..operators.maps import FeatureMap
from ..sources.tables import shared_folder


def windowed(stream: DataFrame, fm: FeatureMap, window: Column, watermark: str = "1 hour", keys: tuple[str, ...] = ()) -> DataFrame:
    """Sums of each window (tumbling, sliding or session) as exact integers; native sums, so the state of a window is m numbers."""
    cols = fm.columns(F.col("features"))
    rows = stream.withWatermark("ts", watermark)
    return rows.groupBy(window.alias("w"), *keys).agg(F.count(F.lit(1)).alias("n"), F.array(*[F.sum(V.fixed(c)) for c in cols]).alias("acc_fx"))


@contextmanager
def rocksdb_state(spark: SparkSession) -> Iterator[None]:
    """Streams started within keep their state in RocksDB, on disk and outside the heap."""
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key, None)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(key)
        else:
            spark.conf.set(key, before)


def drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what is there and read what it wrote, always Parquet written by the tasks: nothing of a result is held on the driver.
    complete: the last batch's rows; update: those of all batches."""
    spark = df.sparkSession
    out = shared_folder(spark, "sink")
    if mode == "append":
        q = df.writeStream.format("parquet").option("path", out).option("checkpointLocation", shared_folder(spark, "stream")).outputMode(mode).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(df.schema).parquet(out)
    batches: dict[int, str] = {}

    def each(batch: DataFrame, batch_id: int) -> None:
        batches[batch_id] = f"{out}/b{batch_id}"
        batch.write.mode("overwrite").parquet(batches[batch_id])

    q = df.writeStream.foreachBatch(each).option("checkpointLocation", shared_folder(spark, "stream")).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    if not batches:
        return spark.createDataFrame([], df.schema)
    return spark.read.schema(df.schema).parquet(*([batches[max(batches)]] if mode == "complete" else batches.values()))


class SketchStore:
    """A running total kept in one Parquet folder for each version. A batch is applied once, however often it is tried and by whichever driver: its id is the
    version's name, and a new store on the same path goes on from the newest version that was written whole."""

    def __init__(self, spark: SparkSession, fm: FeatureMap, path: str | None = None):
        self.spark, self.fm = spark, fm
        self.path = path or shared_folder(spark, "totals")
        self.version = self.newest()

    def newest(self) -> int | None:
        """The largest version whose folder holds the mark that Spark's writer leaves when it has ended."""
        jvm, conf = self.spark.sparkContext._jvm, self.spark.sparkContext._jsc.hadoopConfiguration()
        marks = jvm.org.apache.hadoop.fs.Path(f"{self.path}/v*/_SUCCESS")
        found = marks.getFileSystem(conf).globStatus(marks)
        return max((int(x.getPath().getParent().getName()[1:]) for x in found or ()), default=None)

    def state(self) -> DataFrame | None:
        return None if self.version is None else self.spark.read.parquet(f"{self.path}/v{self.version}")

    def update(self, batch: DataFrame, batch_id: int, by: str | None = None) -> None:
        from ..operators.sketch import mean_sketch, merge

        if self.version is not None and batch_id <= self.version:
            return
        new = mean_sketch(batch, self.fm, by)
        old = self.state()
        (new if old is None else merge(old, new)).write.mode("overwrite").parquet(f"{self.path}/v{batch_id}")
        self.version = batch_id

    def run(self, stream: DataFrame, by: str | None = None, decode_every: int = 0, decode: Callable[[DataFrame], object] | None = None) -> list:
        """Apply a stream; with decode_every, decode the total each so many batches. Returns what the decoder gave."""
        out: list = []

        def each(batch: DataFrame, batch_id: int) -> None:
            self.update(batch, batch_id, by)
            if decode is not None and decode_every and (batch_id + 1) % decode_every == 0:
                out.append(decode(self.state()))

        q = stream.writeStream.foreachBatch(each).option("checkpointLocation", f"{self.path}/checkpoint").trigger(availableNow=True).start()
        q.awaitTermination()
        return out


class DriftAlarm(StatefulProcessor):
    """Per key: the running mean of the features; a row goes out when a batch's mean is farther from it than the limit. State expires with the TTL."""

    def __init__(self, limit: float, ttl_ms: int | None = None):
        self.limit, self.ttl = limit, ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("sums", "n long, acc array<double>", self.ttl)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        n, acc = 0, 0.0
        for pdf in rows:
            if len(pdf):
                acc = acc + np.stack(pdf["features"].to_numpy()).sum(0)
                n += len(pdf)
        if not n:
            return
        old = self.state.get() if self.state.exists() else None
        drift = 0.0 if old is None else float(np.linalg.norm(acc / n - np.array(old[1]) / old[0]))
        total, sums = (n, acc) if old is None else (old[0] + n, np.array(old[1]) + acc)
        self.state.update((int(total), [float(x) for x in sums]))
        yield pd.DataFrame({"key": [str(key[0])], "n": [int(total)], "drift": [drift], "alarm": [drift > self.limit]})

    def close(self) -> None:
        pass


def drift_alarms(stream: DataFrame, key: str, limit: float, ttl_ms: int | None = None) -> DataFrame:
    return stream.select(key, "features").groupBy(key).transformWithStateInPandas(DriftAlarm(limit, ttl_ms), "key string, n long, drift double, alarm boolean", "Update", "ProcessingTime" if ttl_ms else "None")
