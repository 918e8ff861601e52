"""Generated datasets with known parameters, as a Spark data source and as arrays. All numbers come from md5 keys, so every reader sees the same rows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.keyed_random import fast_normals, fast_uniforms


def planted_mixture(k: int, d: int, n: int, seed: int = 0, spread: float = 0.03) -> tuple[np.ndarray, np.ndarray]:
    """(rows, centroids) in [0, 1]: k normals whose centres keep apart."""
    rng = np.random.Generator(np.random.Philox([seed, k, d]))
    best, far = None, -1.0
    for _ in range(50):
        c = 0.15 + 0.7 * rng.random((k, d))
        gap = min((np.linalg.norm(c[i] - c[j]) for i in range(k) for j in range(i)), default=1.0)
        if gap > far:
            best, far = c, gap
    which = rng.integers(k, size=n)
    return np.clip(best[which] + spread * rng.standard_normal((n, d)), 0, 1), best


def planted_lowrank(r: int, d: int, n: int, seed: int = 0, noise: float = 0.02) -> np.ndarray:
    rng = np.random.Generator(np.random.Philox([seed, r, d]))
    return rng.standard_normal((n, r)) @ rng.standard_normal((r, d)) / np.sqrt(d) + noise * rng.standard_normal((n, d))


def planted_linear(q: int, n: int, seed: int = 0, noise: float = 0.1) -> tuple[np.ndarray, np.ndarray]:
    """(rows with the target first, weights)."""
    rng = np.random.Generator(np.random.Philox([seed, q]))
    theta, x = rng.standard_normal(q), rng.random((n, q))
    return np.column_stack([x @ theta + noise * rng.standard_normal(n), x]), theta


class PlantedSource(DataSource):
    """spark.read.format("sketchfit_planted") with options datasets, rows, k, d, seed: dataset_id, row_key, cls, features."""

    @classmethod
    def name(cls) -> str:
        return "sketchfit_planted"

    def schema(self) -> str:
        return "dataset_id string, row_key string, cls string, features array<double>"

    def reader(self, schema) -> DataSourceReader:
        return PlantedReader(self.options)


class PlantedReader(DataSourceReader):
    def __init__(self, options):
        get = lambda k, v: int(options.get(k, v))
        self.datasets, self.rows, self.k, self.d, self.seed = get("datasets", 4), get("rows", 200), get("k", 3), get("d", 2), get("seed", 0)

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.datasets)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        i = partition.value
        centres = 0.15 + 0.7 * fast_uniforms(self.seed * 1000 + i, self.k, self.d)
        noise = fast_normals(self.seed * 1000 + i + 500, self.rows, self.d)
        for r in range(self.rows):
            c = r % self.k
            yield f"planted{i}", f"{i}-{r}", str(c), [float(v) for v in np.clip(centres[c] + 0.03 * noise[r], 0, 1)]


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PlantedSource)
