"""Centroids from sketches: error against size, time against rows, privacy, and the searched choices."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import features as X
from ..meta.train import split_ids, train_unrolled_pair, unrolled_from, unrolled_space
from ..operators import privacy as P
from ..operators import sketch as S
from ..operators.kmeans import decode_greedy, decode_message_passing, decode_unrolled, kmeans_exact, kmeans_mse_local, lloyd_local
from ..operators.maps import FeatureMap, concat_maps, fourier_map, nystrom_map
from ..operators.measures import growth_exponent, privacy_curve
from ..plans.registry import Registry
from ..sources.planted import planted_mixture
from ..sources.tables import written
from .common import result
from .moments import averaged, means

R = Registry()
EFFORT = {"restarts": 3, "ascent": 40, "polish": 60}


def methods(x: np.ndarray, d: int, k: int, m: int, sigma: float, pair=None, quick: bool = True) -> dict[str, tuple[np.ndarray, float]]:
    """Centroids and seconds of each method from the sketch of x; sizes count landmarks too."""
    out: dict[str, tuple[np.ndarray, float]] = {}

    def run(name: str, f) -> None:
        start = time.perf_counter()
        out[name] = (f(), time.perf_counter() - start)

    rff, ada = fourier_map(d, m, sigma, "gaussian", 1), fourier_map(d, m, sigma, "adapted", 1)
    marks = x[np.random.default_rng(4).choice(len(x), max(2, m // (d + 1)))]
    nys = nystrom_map(marks, 1 / (2 * sigma**2))
    effort = EFFORT if quick else {}
    run("lloyd", lambda: lloyd_local(x, k, 20, 1, 3))
    for name, fm in (("fourier_greedy", rff), ("adapted_greedy", ada), ("nystrom_greedy", nys)):
        run(name, lambda fm=fm: decode_greedy(fm.batch(x).mean(0), fm, k, **effort).theta)
    run("fourier_unrolled", lambda: decode_unrolled(rff.batch(x).mean(0), rff, k, 150, starts=3).theta)
    for name, fm in (("message_passing", rff), ("adapted_message_passing", ada)):
        run(name, lambda fm=fm: np.nan_to_num(decode_message_passing(fm.batch(x).mean(0), fm, k, 20).theta, nan=0.5))
    if pair is not None:
        run("learned_unrolled", lambda: pair.decode(pair.fm.batch(x).mean(0), k).theta)
    return out


def sketched_centroids(rows: DataFrame, maps: dict[str, FeatureMap], decode: Callable[[str, np.ndarray], dict[str, np.ndarray]]) -> dict[tuple[str, str], np.ndarray]:
    """(dataset, method) to centroids: one scan builds the sketches of all maps, the datasets' decoders run in tasks. decode gives methods and centroids from a map's name and a sketch."""
    sk = S.mean(S.mean_sketch(rows, concat_maps(*maps.values()), "dataset_id", "arrow")).select("dataset_id", "z")
    ends = np.cumsum([f.m for f in maps.values()])
    places = [(name, int(end - f.m), int(end)) for (name, f), end in zip(maps.items(), ends)]

    def run(pdfs):
        for pdf in pdfs:
            got = [(name, method, theta.ravel()) for name, z in zip(pdf["dataset_id"], pdf["z"]) for which, lo, hi in places for method, theta in decode(which, np.asarray(z)[lo:hi]).items()]
            yield pd.DataFrame(got, columns=["dataset_id", "method", "theta"])

    spread = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    d = next(iter(maps.values())).d
    out = sk.repartition(spread, "dataset_id").mapInPandas(run, "dataset_id string, method string, theta array<double>").collect()  # k x d numbers for a dataset and method
    return {(r.dataset_id, r.method): np.array(r.theta).reshape(-1, d) for r in out}


def near_sums(rows: DataFrame, thetas: dict[tuple[str, str], np.ndarray]) -> DataFrame:
    """dataset_id, method, cid, n, s (sum of rows), e (sum of squared distances) over all rows; partial sums leave the tasks."""
    by: dict[str, list] = {}
    for (name, method), theta in thetas.items():
        by.setdefault(name, []).append((method, theta))

    def run(pdfs):
        held: dict[tuple, list] = {}
        for pdf in pdfs:
            for name, part in pdf.groupby("dataset_id"):
                x = np.stack(part["features"].to_numpy())
                for method, theta in by.get(name, ()):
                    d2 = ((x[:, None] - theta[None]) ** 2).sum(-1)
                    c = d2.argmin(1)
                    for j in np.unique(c):
                        got = held.setdefault((name, method, int(j)), [0, 0.0, 0.0])
                        got[0] += int((c == j).sum())
                        got[1] = got[1] + x[c == j].sum(0)
                        got[2] += float(d2[c == j, j].sum())
        yield pd.DataFrame([(*k, *v) for k, v in held.items()], columns=["dataset_id", "method", "cid", "n", "s", "e"])

    parts = rows.select("dataset_id", "features").mapInPandas(run, "dataset_id string, method string, cid int, n long, s array<double>, e double")
    d = next(iter(thetas.values())).shape[1]
    return parts.groupBy("dataset_id", "method", "cid").agg(F.sum("n").alias("n"), F.array(*[F.sum(F.get("s", F.lit(j))) for j in range(d)]).alias("s"), F.sum("e").alias("e"))


def lloyd_all(rows: DataFrame, pilots: dict[str, np.ndarray], k: int, steps: int = 20, starts: int = 3) -> dict[tuple[str, str], np.ndarray]:
    """Lloyd's algorithm over all rows of all datasets and starts at once, a scan a step; seeded on bounded pilots. It ends early when no centroid moves."""
    thetas = {(name, f"lloyd#{i}"): lloyd_local(x, k, 0, i, 1) for name, x in pilots.items() for i in range(starts)}
    for _ in range(steps):
        moved = 0.0
        for r in near_sums(rows, thetas).collect():  # k rows for a dataset and start
            new = np.array(r.s) / r.n
            moved = max(moved, float(np.abs(thetas[r.dataset_id, r.method][r.cid] - new).max()))
            thetas[r.dataset_id, r.method][r.cid] = new
        if moved < 1e-9:
            break
    return thetas


def document_scores(spark: SparkSession, sf_dir: str, d: int, k: int, sizes: tuple[int, ...], quick: bool) -> DataFrame:
    """method, param, dataset_id, value: mean squared distance over all documents of every test source. The training sources give bounded samples, for the learned pair and the landmarks."""
    rows = written(X.projected_documents(spark, sf_dir, d).select("dataset_id", "row_key", "features"), "w05")
    train, test = split_ids(sorted(r.dataset_id for r in rows.select("dataset_id").distinct().collect()))  # sources
    known = X.bounded_rows(rows.where(F.col("dataset_id").isin(train)), 400)
    unseen = rows.where(F.col("dataset_id").isin(test))
    lloyd = lloyd_all(unseen, X.bounded_rows(unseen, 400), k)
    effort = EFFORT if quick else {}
    out = None
    for m in sizes:
        pair = train_unrolled_pair([known[i] for i in sorted(known)[:4]], k, m, budget=24 if quick else 200, steps=80, seed=1)
        marks = np.vstack([known[i] for i in sorted(known)])
        marks = marks[np.random.default_rng(4).choice(len(marks), max(2, m // (d + 1)))]
        maps = {"fourier": fourier_map(d, m, 0.25, "gaussian", 1), "adapted": fourier_map(d, m, 0.25, "adapted", 1), "nystrom": nystrom_map(marks, 1 / (2 * 0.25**2)), "learned": pair.fm}

        def decode(which: str, z: np.ndarray, maps=maps, pair=pair) -> dict[str, np.ndarray]:
            if which == "learned":
                return {"learned_unrolled": pair.decode(z, k).theta}
            got = {f"{which}_greedy": decode_greedy(z, maps[which], k, **effort).theta}
            if which != "nystrom":
                name = "message_passing" if which == "fourier" else "adapted_message_passing"
                got[name] = np.nan_to_num(decode_message_passing(z, maps[which], k, 20).theta, nan=0.5)
            if which == "fourier":
                got["fourier_unrolled"] = decode_unrolled(z, maps[which], k, 150, starts=3).theta
            return got

        thetas = sketched_centroids(unseen, maps, decode) | lloyd
        mse = near_sums(unseen, thetas).groupBy("dataset_id", "method").agg((F.sum("e") / F.sum("n")).alias("value"))
        best = mse.groupBy("dataset_id", F.substring_index("method", "#", 1).alias("method")).agg(F.min("value").alias("value"))  # of Lloyd's starts
        one = best.select("method", F.lit(float(m)).alias("param"), "dataset_id", "value")
        out = one if out is None else out.unionByName(one)
    return out


@R.add("w05")
def w05(spark: SparkSession, sf_dir: str, quick: bool = True) -> DataFrame:
    """Mean squared distance against sketch size on all documents of the test sources; the other sources train the learned pair. Planted mixtures as a control."""
    d, k = 2, 4
    sizes = (16, 64) if quick else (8, 16, 32, 64, 128, 256)
    documents = means([("documents", document_scores(spark, sf_dir, d, k, sizes, quick))], "mse")
    out = []
    for m in sizes:
        for seed in range(2):
            x, _c = planted_mixture(k, d, 800, seed)
            for method, (theta, _) in methods(x, d, k, m, 0.15, None, quick).items():
                out.append((f"planted:{method}", m, str(seed), "mse", kmeans_mse_local(x, theta)))
    return documents.unionByName(averaged(spark, out))


@R.add("w06")
def w06(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds against rows, and their growth: a scan that sketches, a decoder that does not see rows, and Lloyd's steps that rescan.

    Shares of lineitem by key hash, joined and written once, so that every method scans the same files. The metric `exponent` is the slope of log seconds over log rows (param 0).
    """
    df = written(X.line_num(spark, sf_dir).select("row_key", F.slice("features", 3, 4).alias("features")), "w06")
    fm = fourier_map(4, 64, 0.5, "gaussian", 1)
    S.mean_sketch(df, fm, None, "arrow").first()  # workers and generated code start before the clock
    out = []
    for share in (0.125, 0.375, 1.0):
        part = df if share == 1.0 else df.where(F.conv(F.substring("row_key", 1, 2), 16, 10).cast("int") < int(256 * share))
        start = time.perf_counter()
        sk = S.mean_sketch(part, fm, None, "arrow").first()
        scan = time.perf_counter() - start
        start = time.perf_counter()
        decode_greedy(np.array(sk.acc) / sk.n, fm, 5, restarts=2, ascent=30, polish=40)
        decode = time.perf_counter() - start
        start = time.perf_counter()
        kmeans_exact(part, 4, 5, 3)
        lloyd = time.perf_counter() - start
        out += [("sketch_scan", sk.n, "lineitem", "seconds", scan), ("sketch_decode", sk.n, "lineitem", "seconds", decode), ("lloyd_3_steps", sk.n, "lineitem", "seconds", lloyd)]
    took = spark.createDataFrame([(name, float(n), s) for name, n, _, _, s in out], "method string, n double, seconds double")
    out += [(r.method, 0, "lineitem", "exponent", r.exponent) for r in growth_exponent(took).collect()]  # a row a method
    return result(spark, out)


@R.add("w07")
def w07(spark: SparkSession, sf_dir: str, quick: bool = True) -> DataFrame:
    """Private centroids against eps, trained with and without the noise of (0.01, 0.01). Clip level and clamp range come from the training sets, never from the private rows."""
    d, k, m = 2, 3, 40
    train = [planted_mixture(k, d, 3000, s)[0] for s in range(3)]
    pairs = {"regular": train_unrolled_pair(train, k, m, budget=24, steps=60, seed=2), "privacy_aware": train_unrolled_pair(train, k, m, budget=24, steps=60, seed=2, dp=(0.01, 0.01))}
    out = []
    for name, pair in pairs.items():
        known = pair.fm.batch(np.vstack(train))
        clip, low, high = float(np.linalg.norm(known, axis=1).max()), known.min(0), known.max(0)
        for seed in (10, 11):
            x, _c = planted_mixture(k, d, 3000, seed)
            f = pair.fm.batch(x)
            f = f * np.minimum(1, clip / np.maximum(np.linalg.norm(f, axis=1, keepdims=True), 1e-12))

            def error_of(eps: float, r: int) -> float:
                z = P.privatize(f.sum(0), len(x), eps, 0.01, clip, low, high, seed=r).clamped
                return kmeans_mse_local(x, pair.decode(z, k, seed=r, starts=2).theta)

            grid = (0.001, 0.01, 0.1, 1, 10) if quick else (0.001, 0.003, 0.01, 0.03, 0.1, 0.3, 1, 3, 10, 100)
            out += [(name, eps, str(seed), "mse" if q == 0.5 else f"mse_q{100 * q:g}", err) for eps, q, err in privacy_curve(error_of, grid, 3)]
    return averaged(spark, out)


@R.add("w13")
def w13(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Activation x inner optimiser x rate x spread of starts, on planted mixtures; candidates x datasets are Spark tasks."""
    sets = [planted_mixture(3, 2, 500, s)[0] for s in range(3)]
    base = np.random.Generator(np.random.Philox(3)).standard_normal((20, 2)) * 4
    grid = [(a, i, r, v) for a in ("cos_sin", "tanh", "relu") for i in ("adam", "sgd") for r in (0.01, 0.05) for v in (0.02, 0.1)]
    space = unrolled_space(2, 40)
    jobs = spark.createDataFrame([(c, i) for c in range(len(grid)) for i in range(3)], "c int, i int").repartition(24, "c", "i")

    def work(pdfs):
        for pdf in pdfs:
            loss = []
            for c, i in zip(pdf["c"], pdf["i"]):
                a, inner, rate, var = grid[c]
                pair = unrolled_from({"log_scale": 0.0, "log_alpha": float(np.log(rate)), "log_var": float(np.log(var)), "act": a, "inner": inner, "weighting": space.choices["weighting"][0], "block": np.zeros(0)}, base, 60)
                loss.append(kmeans_mse_local(sets[i], pair.decode(pair.fm.batch(sets[i]).mean(0), 3, starts=1).theta))
            yield pdf.assign(loss=loss)

    got = jobs.mapInPandas(work, "c int, i int, loss double").groupBy("c").agg(F.avg("loss").alias("loss")).collect()
    return result(spark, [(f"{grid[r.c][0]}/{grid[r.c][1]}/var={grid[r.c][3]:g}", grid[r.c][2], "planted", "mse", r.loss) for r in got])
