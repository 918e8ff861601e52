"""The long result form of a workload."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession

RESULT = "method string, param double, dataset_id string, metric string, value_micro long"


def result(spark: SparkSession, rows: Iterable[tuple]) -> DataFrame:
    """rows: (method, param, dataset_id, metric, value); values that are not finite are left null."""
    out = []
    for method, param, dataset, metric, value in rows:
        v = float(value)
        out.append((method, float(param), str(dataset), metric, int(round(v * 1e6)) if abs(v) < 1e12 else None))
    return spark.createDataFrame(out, RESULT)
