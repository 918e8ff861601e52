"""Cost and accuracy measures, bounds, and reports of them."""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Iterable

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vectors as V
from .moment_decoders import full_size


def sketch_pct(m: int, d: int) -> float:
    return 100.0 * m / full_size(d)


def sketch_numbers(fm) -> int:
    """Numbers that a sketch costs: its features, and the coordinates of the landmarks its map needs."""
    return fm.numbers


def size_grid(d: int, percents: tuple[float, ...] = (0.01, 0.1, 1, 5, 10, 20, 40, 60, 80, 100)) -> list[int]:
    return sorted({max(1, round(full_size(d) * p / 100)) for p in percents})


def balanced_accuracy(df: DataFrame, truth: Column | str, pred: Column | str, by: Column | str | None = None, per_feature: bool = False) -> DataFrame:
    """dataset_id (and j), ba, defined: arrays of bits; rates without cases are left out and counted in `defined`."""
    key = F.lit("all") if by is None else (F.col(by) if isinstance(by, str) else by)
    zipped = F.arrays_zip(F.col(truth).alias("t") if isinstance(truth, str) else truth.alias("t"), F.col(pred).alias("p") if isinstance(pred, str) else pred.alias("p"))
    bits = df.select(key.cast("string").alias("dataset_id"), F.posexplode(zipped).alias("j", "b")).select("dataset_id", "j", F.col("b").getField("t").cast("int").alias("t"), F.col("b").getField("p").cast("int").alias("p"))
    keys = ["dataset_id", "j"] if per_feature else ["dataset_id"]
    c = bits.groupBy(*keys).agg(*[F.count_if((F.col("t") == t) & (F.col("p") == p)).alias(n) for n, t, p in (("tp", 1, 1), ("fn", 1, 0), ("tn", 0, 0), ("fp", 0, 1))])
    tpr, tnr = F.try_divide(F.col("tp"), F.col("tp") + F.col("fn")), F.try_divide(F.col("tn"), F.col("tn") + F.col("fp"))
    both = F.array_compact(F.array(tpr, tnr))
    return c.select(*keys, (V.total(both) / F.nullif(F.size(both), F.lit(0))).alias("ba"), F.size(both).alias("defined"))


def rank_models(df: DataFrame, column: str = "test_set", model: str = "model", value: str = "value") -> DataFrame:
    """Rank of every model in its column of the table, 1 the best; ties share a rank."""
    return df.withColumn("rank", F.dense_rank().over(Window.partitionBy(column).orderBy(F.col(value).desc()))).select(column, model, value, "rank")


def row_average(df: DataFrame, model: str = "model", value: str = "value") -> DataFrame:
    return df.groupBy(model).agg(F.avg(value).alias("average"), F.count(value).alias("n"))


def moment_l1(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.abs(x - y)), F.lit(0.0), lambda s, x: s + x)


def sketch_distance(a: Column, b: Column) -> Column:
    return V.norm2(V.subtract(a, b))


def compression_ratio(df: DataFrame, m: int, d: int, by: Column | str | None = None) -> DataFrame:
    """dataset_id, n, raw and sketch numbers, their ratio."""
    key = F.lit("all") if by is None else (F.col(by) if isinstance(by, str) else by)
    return df.groupBy(key.cast("string").alias("dataset_id")).agg(F.count(F.lit(1)).alias("n")).select("dataset_id", "n", (F.col("n") * d).alias("raw_numbers"), F.lit(m).cast("long").alias("sketch_numbers"), (F.col("n") * d / F.lit(float(m))).alias("ratio"))


def timed(action: Callable[[], object]) -> tuple[object, float]:
    start = time.perf_counter()
    out = action()
    return out, time.perf_counter() - start


def growth_exponent(df: DataFrame, by: str = "method", n: str = "n", seconds: str = "seconds") -> DataFrame:
    """Slope of log seconds over log n."""
    return df.groupBy(by).agg(F.regr_slope(F.ln(seconds), F.ln(n)).alias("exponent"))


def privacy_curve(error_of: Callable[[float, int], float], eps_grid: Iterable[float], repeats: int, quantiles: tuple[float, ...] = (0.1, 0.5, 0.9)) -> list[tuple[float, float, float]]:
    """(eps, quantile, error) over `repeats` draws of the noise; error_of(eps, draw) releases once and measures."""
    out = []
    for eps in eps_grid:
        errs = [error_of(eps, r) for r in range(repeats)]
        out += [(eps, q, float(np.quantile(errs, q))) for q in quantiles]
    return out


def cost_report(df: DataFrame) -> dict[str, int]:
    """Scans, exchanges and Python nodes of the plan that would run."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    lines = [x.lstrip(" :+-*()0123456789") for x in plan.split("\n")]
    count = lambda *names: sum(x.startswith(names) for x in lines)
    return {"scans": count("FileScan", "Scan "), "exchanges": count("Exchange"), "broadcasts": count("BroadcastExchange"), "python": count("MapInArrow", "MapInPandas", "FlatMapGroups", "ArrowEvalPython", "BatchEvalPython")}


# stability and generalisation -----------------------------------------------------------------------------------------


def beta_bound(fm, x: np.ndarray | None = None) -> float:
    return fm.bound if fm.bound is not None else float(np.linalg.norm(fm.batch(x), axis=1).max())


def replace_one_gap(z: np.ndarray) -> float:
    """The largest change of the mean when one row is replaced by another of the given rows' features."""
    sq = (z**2).sum(1)
    d2 = sq[:, None] + sq[None] - 2 * z @ z.T
    return float(math.sqrt(max(d2.max(), 0)) / len(z))


def leave_one_out_gap(z: np.ndarray) -> float:
    n = len(z)
    mean = z.mean(0)
    return float(np.linalg.norm((mean - z) / (n - 1), axis=1).max())


def stability(beta: float, rho_decoder: float, rho_loss: float, n: int, constant: str = "printed") -> float:
    """printed: beta * rho * rho / n; strict: twice that, which leave-one-out with a divisor of n - 1 needs."""
    return {"printed": 1.0, "strict": 2.0}[constant] * beta * rho_decoder * rho_loss / n


def generalization_bound(empirical: float, beta: float, rho_decoder: float, rho_loss: float, top: float, n: int, delta: float, constant: str = "printed") -> float:
    g = stability(beta, rho_decoder, rho_loss, n, constant)
    return empirical + 2 * g + (4 * n * g + top) * math.sqrt(math.log(1 / delta) / (2 * n))


def lipschitz_upper(net) -> float:
    return net.lipschitz()
