"""Registry of queries and of the SQL that checks them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .plans.registry import Query, Registry


def registries() -> list[Registry]:
    from .plans import relational, sketch_queries
    from .streaming import queries as streaming
    from .workloads import autoencoder, clusters, moments, privacy

    return [relational.R, sketch_queries.R, streaming.R, moments.R, privacy.R, clusters.R, autoencoder.R]


def queries() -> dict[str, Query]:
    return {k: v for r in registries() for k, v in r.queries.items()}


def oracle_sql() -> dict[str, str]:
    return {k: v for r in registries() for k, v in r.sql.items()}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .workloads.moments import slice_query

    return slice_query(spark, sf_dir)
