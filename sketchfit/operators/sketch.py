"""Mean sketches: built by one scan with partial sums on the map side, merged, rolled up, extended and reduced without touching rows again.

A sketch row is (dataset_id, map_id, n, acc, acc_fx, max_norm): the signed count, the sum of the features (not the mean), in exact mode also the sum of
the features in units of 2^-20 as whole numbers, and the largest feature norm seen (an upper bound after removals).
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..functions import vectors as V
from ..plans.engine import pick_engine
from .maps import FeatureMap, identity_map, outer_lt_map

STATE = "dataset_id string, map_id string, n long, acc array<double>, acc_fx array<decimal(38,0)>, max_norm double"
BITS = 20


def _keyed(df: DataFrame, by: Column | str | None) -> DataFrame:
    """dataset_id, features, op (+1 or -1)."""
    key = F.lit("all") if by is None else (F.col(by) if isinstance(by, str) else by)
    sign = F.col("op").cast("int") if "op" in df.columns else F.lit(1)
    return df.select(key.cast("string").alias("dataset_id"), V.as_doubles(F.col("features")).alias("features"), sign.alias("op"))


def partials(rows: DataFrame, fm: FeatureMap, clip: float | None = None, budget_numbers: int = 8_000_000) -> DataFrame:
    """Sums for each dataset within a task. The accumulators of a task are given out and dropped when they reach `budget_numbers`."""
    schema = "dataset_id string, n long, acc array<double>, fx array<long>, top double"
    arrow = to_arrow_schema(T._parse_datatype_string(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str | None, list] = {}

        def flush() -> pa.RecordBatch:
            rows = list(held.items())
            out = pa.RecordBatch.from_arrays([pa.array([k for k, _ in rows], pa.string()), pa.array([v[0] for _, v in rows], pa.int64()), pa.array([v[1] for _, v in rows], arrow.field(2).type), pa.array([v[2] for _, v in rows], arrow.field(3).type), pa.array([v[3] for _, v in rows], pa.float64())], schema=arrow)
            held.clear()
            return out

        for batch in batches:
            if not batch.num_rows:
                continue
            flat = batch.column(1).flatten().to_numpy(zero_copy_only=False)
            z = fm.batch(flat.reshape(batch.num_rows, -1))
            length = np.linalg.norm(z, axis=1)
            if clip is not None:
                z = z * np.minimum(1.0, clip / np.maximum(length, 1e-300))[:, None]
                length = np.minimum(length, clip)
            op = batch.column(2).to_numpy(zero_copy_only=False).astype(np.int64)
            whole = np.floor(z * (1 << BITS) + 0.5).astype(np.int64) * op[:, None]
            signed = z * op[:, None]
            coded = batch.column(0).dictionary_encode()
            code, names = coded.indices.to_numpy(zero_copy_only=False), coded.dictionary.to_pylist()
            order = np.argsort(code, kind="stable")
            cut = np.flatnonzero(np.diff(code[order], prepend=-1))
            sums, fxs = np.add.reduceat(signed[order], cut), np.add.reduceat(whole[order], cut)
            ns, tops = np.add.reduceat(op[order], cut), np.maximum.reduceat(length[order], cut)
            for i, c in enumerate(code[order][cut]):
                got = held.get(names[c])
                if got is None:
                    held[names[c]] = [int(ns[i]), sums[i], fxs[i], float(tops[i])]
                else:
                    got[0] += int(ns[i])
                    got[1] = got[1] + sums[i]
                    got[2] = got[2] + fxs[i]
                    got[3] = max(got[3], float(tops[i]))
            if len(held) * fm.m >= budget_numbers:
                yield flush()
        if held:
            yield flush()

    return rows.mapInArrow(run, schema)


def gathered(parts: DataFrame, map_id: str) -> DataFrame:
    """Partial sums to states: the coordinates of all partials meet by (dataset, coordinate), so one dataset's final sum is spread over many tasks."""
    heads = parts.groupBy("dataset_id").agg(F.sum("n").alias("n"), F.max("top").alias("max_norm"))
    long = parts.select("dataset_id", F.posexplode(F.arrays_zip("acc", "fx")).alias("j", "v"))
    summed = long.groupBy("dataset_id", "j").agg(F.sum("v.acc").alias("s"), F.sum(F.col("v.fx").cast("decimal(38,0)")).cast("decimal(38,0)").alias("x"))
    wide = summed.groupBy("dataset_id").agg(F.array_sort(F.collect_list(F.struct("j", "s", "x"))).alias("c"))
    out = heads.join(wide, F.expr("1=1") & heads["dataset_id"].eqNullSafe(wide["dataset_id"])).select(heads["dataset_id"], "n", "max_norm", "c")
    return out.select("dataset_id", F.lit(map_id).alias("map_id"), "n", F.col("c.s").alias("acc"), F.col("c.x").alias("acc_fx"), "max_norm")


def mean_sketch(df: DataFrame, fm: FeatureMap, by: Column | str | None = None, engine: str = "auto", clip: float | None = None) -> DataFrame:
    """The sketch of every dataset of df (column `features`; `op` of -1 takes rows away). One scan, one small shuffle."""
    rows = _keyed(df, by)
    engine = pick_engine(fm, engine, clip)
    if engine == "arrow":
        return gathered(partials(rows, fm, clip), fm.map_id)
    if engine == "summarizer":
        return _summarizer(rows, fm)
    cols = fm.columns(F.col("features"))
    z = F.array(*cols)
    if clip is not None:
        z = V.clip_norm(z, clip)
    # features once per row, then plain sums: partial aggregation before the exchange, all in generated code
    flat = rows.select("dataset_id", "op", z.alias("z")).select("dataset_id", "op", *[F.get("z", F.lit(j)).alias(f"z{j}") for j in range(fm.m)], V.norm(F.col("z")).alias("len"))
    agg = [F.sum(F.col("op").cast("long")).alias("n"), F.max("len").alias("max_norm")]
    agg += [F.sum(F.col(f"z{j}") * F.col("op")).alias(f"s{j}") for j in range(fm.m)]
    agg += [F.sum((V.fixed(F.col(f"z{j}"), BITS) * F.col("op")).cast("decimal(20,0)")).cast("decimal(38,0)").alias(f"x{j}") for j in range(fm.m)]
    out = flat.groupBy("dataset_id").agg(*agg)
    return out.select("dataset_id", F.lit(fm.map_id).alias("map_id"), "n", F.array(*[f"s{j}" for j in range(fm.m)]).alias("acc"), F.array(*[f"x{j}" for j in range(fm.m)]).alias("acc_fx"), "max_norm")


def _summarizer(rows: DataFrame, fm: FeatureMap) -> DataFrame:
    """Vector sums by the summarizer of the ML library: partial sums in the JVM, no exact mode."""
    from pyspark.ml.functions import array_to_vector, vector_to_array
    from pyspark.ml.stat import Summarizer

    z = F.array(*fm.columns(F.col("features")))
    prepared = rows.select("dataset_id", "op", z.alias("z"))
    summed = prepared.groupBy("dataset_id").agg(F.sum(F.col("op").cast("long")).alias("n"), Summarizer.sum(array_to_vector(V.scale(F.col("z"), F.col("op").cast("double")))).alias("v"), F.max(V.norm(F.col("z"))).alias("max_norm"))
    return summed.select("dataset_id", F.lit(fm.map_id).alias("map_id"), "n", vector_to_array("v").alias("acc"), F.lit(None).cast("array<decimal(38,0)>").alias("acc_fx"), "max_norm")


def mean(sk: DataFrame) -> DataFrame:
    """dataset_id, map_id, n, z: the sums divided by the count."""
    return sk.select("dataset_id", "map_id", "n", V.scale(F.col("acc"), F.lit(1.0) / F.col("n")).alias("z"))


def long_form(sk: DataFrame, keys: Sequence[str] = ("dataset_id",)) -> DataFrame:
    """keys, n, j, acc_fx as a whole number: the comparable form of exact sketches."""
    return sk.select(*keys, "n", F.posexplode("acc_fx").alias("j", "fx")).select(*keys, "n", "j", F.col("fx").cast("bigint").alias("acc_fx"))


def rollup(sk: DataFrame, keys: Sequence[Column | str] = ()) -> DataFrame:
    """Sketches added up by coarser keys, without a scan of rows: the keys must be columns of sk; sketches of different maps stay apart."""
    names = [k if isinstance(k, str) else f"k{i}" for i, k in enumerate(keys)]
    cols = [F.col(k) if isinstance(k, str) else k for k in keys]
    base = sk.select(*[c.alias(n) for c, n in zip(cols, names)], "map_id", "n", "acc", "acc_fx", "max_norm")
    heads = base.groupBy(*names, "map_id").agg(F.sum("n").alias("n"), F.max("max_norm").alias("max_norm"))
    long = base.select(*names, "map_id", F.posexplode(F.arrays_zip("acc", "acc_fx")).alias("j", "v"))
    summed = long.groupBy(*names, "map_id", "j").agg(F.sum("v.acc").alias("s"), F.sum("v.acc_fx").cast("decimal(38,0)").alias("x"))
    wide = summed.groupBy(*names, "map_id").agg(F.array_sort(F.collect_list(F.struct("j", "s", "x"))).alias("c"))
    return heads.join(wide, [*names, "map_id"]).select(*names, "map_id", "n", F.col("c.s").alias("acc"), F.col("c.x").alias("acc_fx"), "max_norm")


def merge(a: DataFrame, b: DataFrame, mode: str = "sum") -> DataFrame:
    """Sketches of the union of two datasets. mode `average` is the plain mean of the two means, right for equal counts only."""
    if mode == "average":
        x, y = mean(a), mean(b)
        both = x.join(y.select("dataset_id", "map_id", F.col("n").alias("n2"), F.col("z").alias("z2")), ["dataset_id", "map_id"])
        return both.select("dataset_id", "map_id", (F.col("n") + F.col("n2")).alias("n"), F.zip_with("z", "z2", lambda p, q: (p + q) / 2).alias("z"))
    return rollup(a.unionByName(b), ["dataset_id"])


def negate(sk: DataFrame) -> DataFrame:
    return sk.select("dataset_id", "map_id", (-F.col("n")).alias("n"), V.scale(F.col("acc"), -1.0).alias("acc"), F.transform("acc_fx", lambda x: (-x).cast("decimal(38,0)")).alias("acc_fx"), "max_norm")


def subtract(a: DataFrame, b: DataFrame) -> DataFrame:
    """The sketch of a without b's rows, which a must hold."""
    return rollup(a.unionByName(negate(b)), ["dataset_id"])


def add_rows(sk: DataFrame, df: DataFrame, fm: FeatureMap, by: Column | str | None = None, engine: str = "auto") -> DataFrame:
    return merge(sk, mean_sketch(df, fm, by, engine))


def remove_rows(sk: DataFrame, df: DataFrame, fm: FeatureMap, by: Column | str | None = None, engine: str = "auto") -> DataFrame:
    return subtract(sk, mean_sketch(df, fm, by, engine))


def sketch_sites(sites: Sequence[DataFrame], fm: FeatureMap, by: Column | str | None = None) -> DataFrame:
    """Each site builds its own sketches; only those meet."""
    out = mean_sketch(sites[0], fm, by)
    for s in sites[1:]:
        out = out.unionByName(mean_sketch(s, fm, by))
    return rollup(out, ["dataset_id"])


def collected(sk: DataFrame) -> dict[str, tuple[int, np.ndarray]]:
    """Sketches on the driver: n and z of each dataset. For collections whose sketches fit there; decode larger ones with decode_all."""
    return {r.dataset_id: (r.n, np.array(r.acc) / r.n) for r in sk.orderBy("dataset_id").collect()}


def second_moment(df: DataFrame, d: int, by: Column | str | None = None, center: bool = False, engine: str = "auto") -> DataFrame:
    """dataset_id, n, v: the lower triangle of X'X / n, less the outer product of the mean where centred. One scan."""
    if not center:
        return mean(mean_sketch(df, outer_lt_map(d), by, engine)).select("dataset_id", "n", F.col("z").alias("v"))
    from .maps import concat_maps

    both = mean(mean_sketch(df, concat_maps(identity_map(d), outer_lt_map(d)), by, "arrow"))
    mu = F.slice("z", 1, d)
    return both.select("dataset_id", "n", F.zip_with(F.slice("z", d + 1, d * (d + 1) // 2), V.outer_lt(mu, d), lambda a, b: a - b).alias("v"))


def unpack_lt(v: np.ndarray, d: int) -> np.ndarray:
    r = np.zeros((d, d))
    a, b = np.tril_indices(d)
    r[a, b] = v
    r[b, a] = v
    return r


def pack_lt(r: np.ndarray, layout: str = "lt") -> np.ndarray:
    a, b = np.tril_indices(len(r))
    if layout == "full":
        return r.ravel()
    v = r[a, b]
    return np.where(a == b, v, v * np.sqrt(2)) if layout == "lt_iso" else v


def moment_sketch(df: DataFrame, a: np.ndarray, d: int, by: Column | str | None = None, rewrite: str = "auto", engine: str = "auto") -> DataFrame:
    """dataset_id, n, z = A vec(R) (lower-triangle layout). The map is linear, so by default R is built first and A applied to it (`gram`)."""
    from .maps import outer_linear_map

    if rewrite == "auto":
        rewrite = "gram" if d * (d + 1) // 2 <= 8_000_000 else "per_row"
    if rewrite == "per_row":
        return mean(mean_sketch(df, outer_linear_map(a, np.zeros(len(a)), d), by, "arrow")).select("dataset_id", "n", "z")
    r = second_moment(df, d, by, engine=engine)
    arrow = to_arrow_schema(T._parse_datatype_string("dataset_id string, n long, z array<double>"))

    def project(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            v = np.array(batch.column(2).to_pylist(), dtype=float).reshape(batch.num_rows, -1)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(list(v @ a.T) if len(v) else [], arrow.field(2).type)], schema=arrow)

    return r.mapInArrow(project, "dataset_id string, n long, z array<double>")


def sketch_drift(sk: DataFrame, order_by: str) -> DataFrame:
    """Distance of each sketch's mean from the one before it."""
    from pyspark.sql import Window

    z = mean(sk)
    before = F.lag("z").over(Window.partitionBy("map_id").orderBy(order_by))
    return z.withColumn("before", before).select(order_by, "n", F.sqrt(V.norm2(V.subtract(F.col("z"), F.col("before")))).alias("drift"))
