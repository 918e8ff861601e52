"""Principal components and regression against sketch size, on unseen datasets; fixed-width preparation."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import features as X
from ..functions import vectors as V
from ..functions.keyed_random import uniform_col
from ..meta.train import augment_bank, bank_scale, train_moment_pair
from ..operators import baselines as B
from ..operators import moment_decoders as D
from ..operators import sketch as S
from ..operators import tasks as T
from ..operators.maps import random_projection
from ..operators.measures import size_grid
from ..plans.registry import Registry
from ..sources.tables import written
from .common import result

R = Registry()


def slice_query(spark: SparkSession, sf_dir: str, share: float = 0.2) -> DataFrame:
    """The smallest whole path: one scan of `embeddings`, random unit-radius sketch of a fifth of the moment's size, pseudo-inverse, components, errors."""
    d = 64
    m = round(D.full_size(d) * share)
    rows = []
    for r in S.second_moment(X.emb64(spark, sf_dir), d, "dataset_id").orderBy("dataset_id").collect():
        v = np.array(r.v)
        got = D.random_pair(v, d, m, "unit", 1)
        exact = S.unpack_lt(v, d)
        err = T.pca_error_profile(exact, T.pca_from_moment(got.r))[:-1].mean()
        ref = T.pca_error_profile(exact, T.pca_from_moment(exact))[:-1].mean()
        rows.append((r.dataset_id, m, float(err), int(round(T.lre(err, ref) * 1e6))))
    return spark.createDataFrame(rows, "dataset_id string, m int, rank_avg_error double, lre_micro long")


def moments_of(df: DataFrame, d: int) -> dict[str, tuple[int, np.ndarray]]:
    """n and triangle of every dataset: one scan, d(d+1)/2 numbers for each."""
    return {r.dataset_id: (r.n, np.array(r.v)) for r in S.second_moment(df, d, "dataset_id").collect()}


def rank_mean_error(exact: np.ndarray, r: np.ndarray) -> float | np.ndarray:
    """Of one dataset, or of each of many (n x d x d)."""
    if exact.ndim == 2:
        return float(T.pca_error_profile(exact, T.pca_from_moment(r))[:-1].mean())
    return T.pca_mean_errors(exact, r)


def decoders(z: np.ndarray, a: np.ndarray, d: int, quick: bool) -> dict[str, np.ndarray]:
    steps = 150 if quick else 1000
    return {"robust": D.robust_all(z, a, d, max(1, d // 4), steps), "accelerated": D.accelerated_all(z, a, d, steps), "expgrad": D.expgrad_all(z, a, d, steps), "gradient": D.gradient_all(z, a, d, steps)}


SCORE = "method string, param double, dataset_id string, value double"


def held_out() -> Column:
    """Whether a dataset is of the test half."""
    return uniform_col("split0", F.col("dataset_id")) >= 0.5


def halves(moments: DataFrame) -> tuple[np.ndarray, DataFrame]:
    """The bank of the training half (all its datasets, d(d+1)/2 numbers for each, collected in the order of their ids' md5) and the moments of all datasets of the other half."""
    bank = moments.where(~held_out()).orderBy(F.md5(F.col("dataset_id").cast("binary")), "dataset_id").select("v").toArrow().column(0).combine_chunks()
    return bank.flatten().to_numpy(zero_copy_only=False).reshape(len(bank), -1), moments.where(held_out())


def rows_of_budgets(sizes: list[int], d: int) -> list[int]:
    return sorted({B.rows_for_budget(m, d) for m in sizes})


def row_moments(rows: DataFrame, d: int, sizes: list[int]) -> DataFrame:
    """dataset_id, method, m, r: moments that the row sketches and the row sample estimate, over all rows of every dataset, at equal budgets of numbers. One scan."""
    return estimates_of(B.states(rows, rows_of_budgets(sizes, d), d, 3), d, sizes)


def estimates_of(states: DataFrame, d: int, sizes: list[int]) -> DataFrame:
    """The estimates of `row_moments` from the states of its scan."""
    counts = rows_of_budgets(sizes, d)
    head, total = 1 + D.full_size(d), sum(counts)
    starts = dict(zip(counts, np.cumsum([0, *counts])))

    def run(pdfs):
        for pdf in pdfs:
            acc = np.stack(pdf["acc"].to_numpy())
            n, kinds = acc[:, 0], acc[:, head:].reshape(len(acc), 2, total, d)
            most = max(len(x) for x in pdf["least"])
            x = np.zeros((len(acc), most, d))
            held = np.array([len(one) for one in pdf["least"]])
            x[np.arange(most) < held[:, None]] = np.concatenate([np.stack(one) for one in pdf["least"]])
            for m in sizes:
                s = B.rows_for_budget(m, d)
                gauss, sparse = (kinds[:, i, starts[s] : starts[s] + s] for i in (0, 1))
                for method, y, count in (("row_gaussian", gauss, n * s), ("row_sparse", sparse, n), ("row_sample", x[:, :s], np.minimum(held, s))):
                    r = D.pack_all(y.transpose(0, 2, 1) @ y) / count[:, None]
                    yield pd.DataFrame({"dataset_id": pdf["dataset_id"], "method": method, "m": m, "r": list(r)})

    return states.select("dataset_id", "acc", "least").mapInPandas(run, "dataset_id string, method string, m int, r array<double>")


def sweep(moments: DataFrame, rows: DataFrame | None, d: int, sizes: list[int], error, quick: bool = True, steps: int = 150, rate: float = 1e-3, states: DataFrame | None = None) -> DataFrame:
    """method, param (the size), dataset_id, value (log error ratio against the exact moment) of every method on every dataset of the test half. The datasets are spread over tasks.

    moments: dataset_id, v. rows: all rows, for the row-sketch baselines. error: takes exact moments and estimates, n x d x d each; or several by name, which then
    stands before the method's: all of them score the same fitted pairs and estimates. states: what one scan made of the rows (`scanned`), in place of `rows`.
    """
    errors = {f"{name}:": e for name, e in error.items()} if isinstance(error, dict) else {"": error}
    bank, test = halves(moments)
    mean, more = bank.mean(0), augment_bank(bank / bank_scale(bank), d, 8, 1)
    pairs = {m: train_moment_pair(bank, d, m, steps=steps, rate=rate, seed=1, augmented=more) for m in sizes}
    maps = {m: {law: random_projection(d, m, "rank_one", law, "lt", 2) for law in ("chi", "unit")} for m in sizes}
    back = {m: {law: np.linalg.pinv(a) for law, a in of.items()} for m, of in maps.items()}

    def estimates(v: np.ndarray, m: int) -> dict[str, np.ndarray]:
        out = {"learned": pairs[m].decode(pairs[m].encode(v)), **{law: v @ a.T @ back[m][law].T for law, a in maps[m].items()}}
        out["random_offset"] = mean + (v - mean) @ maps[m]["chi"].T @ back[m]["chi"].T
        return {method: D.unpack_all(r, d) for method, r in out.items()}

    def iterated(v: np.ndarray, m: int) -> dict[str, np.ndarray]:
        return decoders(v @ maps[m]["chi"].T, maps[m]["chi"], d, quick)

    def ratios(exact: np.ndarray, found: list[tuple[object, object, np.ndarray]], names: np.ndarray) -> Iterator[pd.DataFrame]:
        """found: method, size and estimates of all datasets; method and size may be columns."""
        for label, one in errors.items():
            ref = np.maximum(one(exact, exact), 1e-300)
            for method, m, r in found:
                value = np.log10(np.maximum(one(exact, r), 1e-300) / ref)
                yield pd.DataFrame({"method": label + method, "param": m, "dataset_id": names, "value": value}).astype({"param": float})

    def blocks(pdfs: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        many = max(1, 250_000 // d**2)
        for pdf in pdfs:
            for lo in range(0, len(pdf), many):
                yield pdf.iloc[lo : lo + many]

    def from_moments(found):
        def run(pdfs):
            for pdf in blocks(pdfs):
                v = np.stack(pdf["v"].to_numpy())
                for m in sizes:
                    yield from ratios(D.unpack_all(v, d), [(method, m, r) for method, r in found(v, m).items()], pdf["dataset_id"].to_numpy())

        return run

    def from_rows(pdfs):
        for pdf in blocks(pdfs):
            exact, r = (D.unpack_all(np.stack(pdf[c].to_numpy()), d) for c in ("v", "r"))
            yield from ratios(exact, [(pdf["method"].to_numpy(), pdf["m"].to_numpy(), r)], pdf["dataset_id"].to_numpy())

    spread = int(moments.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    spread_out = test.select("dataset_id", "v").repartition(spread, "dataset_id")
    more_scores = []
    if rows is not None:
        more_scores.append(row_moments(rows.where(held_out()), d, sizes))
    if states is not None:
        more_scores.append(estimates_of(states.where(held_out()), d, sizes))
    more_scores = [one.join(test.select("dataset_id", "v"), "dataset_id").select("dataset_id", "v", "method", "m", "r").mapInPandas(from_rows, SCORE) for one in more_scores]
    if not quick or d <= 10:
        more_scores.append(spread_out.mapInPandas(from_moments(iterated), SCORE))
    out = spread_out.mapInPandas(from_moments(estimates), SCORE)
    for one in more_scores:
        out = out.unionByName(one)
    return out


def means(scores: list[tuple[str, DataFrame]], metric: str = "lre") -> DataFrame:
    """The long result form: averages over datasets, the collection's name (if it has one) before the method's. A value that is not finite or beyond 1e12 leaves its average null."""
    out = None
    for name, df in scores:
        one = df.groupBy(F.concat(F.lit(f"{name}:" if name else ""), "method").alias("method"), "param").agg(F.avg("value").alias("value"))
        out = one if out is None else out.unionByName(one)
    v = F.col("value")
    return out.select("method", "param", F.lit("mean").alias("dataset_id"), F.lit(metric).alias("metric"), F.when(F.abs(v) < 1e12, F.floor(v * 1e6 + 0.5)).cast("long").alias("value_micro"))


def collection(rows: DataFrame, d: int, kind: str) -> DataFrame:
    """The moments (dataset_id, n, v) of all datasets, written once and read by every method."""
    return written(S.second_moment(rows, d, "dataset_id"), f"{kind}-moments")


def scanned(rows: DataFrame, d: int, sizes: list[int], kind: str) -> tuple[DataFrame, DataFrame]:
    """One scan of the rows, which are not stored: the moments of all datasets, and the states of those of the test half for `estimates_of`."""
    states = written(B.states(rows, rows_of_budgets(sizes, d), d, 3, keyed=held_out()), f"{kind}-states")
    n = F.element_at("acc", 1)
    return states.select("dataset_id", n.cast("long").alias("n"), F.transform(F.slice("acc", 2, D.full_size(d)), lambda x: x / n).alias("v")), states


@R.add("w01")
def w01(spark: SparkSession, sf_dir: str, quick: bool = True) -> DataFrame:
    """Components against size over all datasets and rows: embeddings by label (d = 64), suppliers' lines (d = 8), documents by source (d = 16; 64 when not quick)."""
    dd = 16 if quick else 64

    def line() -> DataFrame:
        sizes = size_grid(8, (5, 20, 50, 80, 100) if quick else (1, 5, 10, 20, 40, 60, 80, 100))
        moments, states = scanned(X.line_num(spark, sf_dir), 8, sizes, "w01-line")
        return sweep(moments, None, 8, sizes, rank_mean_error, quick, states=states)

    def documents() -> DataFrame:
        moments = collection(X.documents_by(spark, sf_dir, dd), dd, "w01-documents")
        return sweep(moments, None, dd, size_grid(dd, (3, 10, 30, 100)), rank_mean_error, quick)

    def embeddings() -> DataFrame:
        moments = collection(X.emb64(spark, sf_dir), 64, "w01-embeddings")
        return sweep(moments, None, 64, size_grid(64, (1, 5, 20) if quick else (1, 5, 20, 50, 100)), rank_mean_error, True)

    return means([(part.__name__, part()) for part in (line, documents, embeddings)])


def averaged(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    got: dict[tuple, list] = {}
    for method, param, _, metric, value in rows:
        got.setdefault((method, param, metric), []).append(value)
    return result(spark, [(m, p, "mean", metric, float(np.mean(v))) for (m, p, metric), v in sorted(got.items())])


def ridge_error(lam: float):
    """Mean squared error, on the exact moments, of the weights from the estimates (n x d x d each); weights that cannot be solved for are 0."""

    def weights(r: np.ndarray) -> np.ndarray:
        try:
            inner = r[:, 1:, 1:] + lam * np.eye(r.shape[1] - 1)
            if lam == 0:
                return (np.linalg.pinv(inner, rcond=np.finfo(float).eps * inner.shape[1]) @ r[:, 1:, :1])[:, :, 0]
            return np.linalg.solve(inner, r[:, 1:, :1])[:, :, 0]
        except np.linalg.LinAlgError:
            if len(r) == 1:
                return np.zeros((1, r.shape[1] - 1))
            return np.concatenate([weights(one[None]) for one in r])

    def error(exact: np.ndarray, r: np.ndarray) -> np.ndarray:
        w = weights(r)
        return np.maximum(exact[:, 0, 0] - 2 * (w * exact[:, 1:, 0]).sum(1) + np.einsum("ni,nij,nj->n", w, exact[:, 1:, 1:], w), 1e-12)

    return error


@R.add("w02")
def w02(spark: SparkSession, sf_dir: str, quick: bool = True) -> DataFrame:
    """Regression of the charge on price, quantity, discount, tax, retail price and size, over all suppliers and rows; lambda 0, 0.001 and 0.1."""
    keep = [0, 2, 3, 4, 5, 6, 7]  # without the net price, which would give the target away
    line = X.line_num(spark, sf_dir).withColumn("features", F.array(*[F.get("features", F.lit(j)) for j in keep]))
    sizes = size_grid(7, (10, 40, 70, 100))
    moments, states = scanned(line, 7, sizes, "w02")
    return means([("", sweep(moments, None, 7, sizes, {f"lambda={lam:g}": ridge_error(lam) for lam in (0.0, 1e-3, 1e-1)}, quick, states=states))])


@R.add("w04", "SELECT CAST(count(*) AS BIGINT) AS n, CAST(196 AS INTEGER) AS width, CAST(8 AS INTEGER) AS filled FROM lineitem JOIN part ON l_partkey = p_partkey")
def w04(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fixed width 196 by padding: eight features, the rest 0."""
    x = X.line_num(spark, sf_dir).withColumn("features", X.fit_width(F.col("features"), 8, 196))
    tail = F.exists(F.slice("features", 9, 188), lambda v: v != 0)
    return x.agg(F.count(F.lit(1)).alias("n"), F.max(F.size("features")).alias("width"), F.max(F.when(tail, 9).otherwise(8)).alias("filled"))


@R.add("w14", "SELECT 'lineitem' AS collection, count(*) * 8 AS raw_numbers, CAST(36 AS BIGINT) AS sketch_numbers FROM lineitem UNION ALL SELECT 'embeddings', count(*) * 64, 2080 FROM embeddings UNION ALL SELECT 'events', count(*) * 7, 28 FROM events")
def w14(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Raw and sketch numbers of the collections."""
    out = None
    for name, d in (("lineitem", 8), ("embeddings", 64), ("events", X.EVENT_WIDTH)):
        r = spark.read.parquet(f"{sf_dir}/{name}.parquet").agg((F.count(F.lit(1)) * d).alias("raw_numbers")).select(F.lit(name).alias("collection"), "raw_numbers", F.lit(D.full_size(d)).cast("long").alias("sketch_numbers"))
        out = r if out is None else out.unionByName(r)
    return out


def learned_against_random(spark: SparkSession, sf_dir: str, task: str = "pca") -> list[tuple[float, float]]:
    """(learned, best random) mean log error ratio at sizes below the full one, on all unseen datasets."""
    d = 8
    moments = written(S.second_moment(X.line_num(spark, sf_dir), d, "dataset_id"), "moments")
    error = rank_mean_error if task == "pca" else ridge_error(1e-2)
    bank, test = halves(moments)
    models = {m: (train_moment_pair(bank, d, m, steps=150, rate=1e-3, seed=1), *(random_projection(d, m, "rank_one", law, "lt", 2) for law in ("chi", "unit"))) for m in (4, 9, 18)}

    def run(pdfs):
        for pdf in pdfs:
            v = np.stack(pdf["v"].to_numpy())
            exact = D.unpack_all(v, d)
            ref = error(exact, exact)
            for m, (pair, chi, unit) in models.items():
                rs = (pair.decode(pair.encode(v)), *(v @ a.T @ np.linalg.pinv(a).T for a in (chi, unit)))
                yield pd.DataFrame({"m": m} | {c: np.log10(error(exact, D.unpack_all(r, d)) / ref) for c, r in zip(("learned", "chi", "unit"), rs)})

    mean = test.select("v").mapInPandas(run, "m int, learned double, chi double, unit double").groupBy("m").agg(*[F.avg(c).alias(c) for c in ("learned", "chi", "unit")])
    return [(r.learned, min(r.chi, r.unit)) for r in mean.orderBy("m").collect()]
