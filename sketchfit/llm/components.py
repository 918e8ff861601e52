"""Connected components of a distributed edge list: minimum labels with pointer jumping, one written table for each round."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import HOT_ROWS, HOT_SHARE, release, stored


def components(edges: DataFrame) -> DataFrame:
    """(id, comp) for every end of an edge (a, b); comp is the least id reachable. An empty edge list gives an empty result."""
    both = edges.select("a", "b").union(edges.select(F.col("b"), F.col("a"))).where("a <> b").distinct()
    both = stored(both, "edges")
    ends = both.groupBy("b").count()
    hubs = stored(ends.where(F.col("count") > max(HOT_ROWS, both.count() // HOT_SHARE)).select("b"), "hubs")  # at most HOT_SHARE of them
    rays, rest = both.join(F.broadcast(hubs), "b", "left_semi"), both.join(F.broadcast(hubs), "b", "left_anti")
    labels = stored(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("id"), F.least("a", "m").alias("comp")), "labels")
    while True:
        named = labels.select(F.col("id").alias("b"), "comp")
        told = rest.join(named, "b").unionByName(rays.join(F.broadcast(named.join(F.broadcast(hubs), "b", "left_semi")), "b"))
        near = told.groupBy("a").agg(F.min("comp").alias("m"))
        step = labels.join(near.select(F.col("a").alias("id"), "m"), "id", "left").select("id", F.col("comp").alias("old"), F.least("comp", F.coalesce("m", "comp")).alias("comp"))
        up = labels.select(F.col("id").alias("comp"), F.col("comp").alias("up"))
        jumped = step.join(up, "comp", "left").select("id", "old", F.least("comp", F.coalesce("up", "comp")).alias("comp"))
        new = stored(jumped, "labels")
        release(labels)
        moved = new.where("old <> comp").limit(1).count()
        labels = new.drop("old")
        labels.stored_at = new.stored_at
        if not moved:
            return labels
