"""Reconstruction of binary datasets by an autoencoder that a sketch adapts; conditioning ablation; architecture sweep."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import features as X
from ..meta.train import Autoencoder, LearnedPair, kmeans_meta_loss, split_ids, train_autoencoder, train_pair
from ..meta.layers import residual_mlp
from ..operators.kmeans import kmeans_mse_local
from ..operators.sketch import mean_sketch
from ..plans.registry import Registry
from ..sources.planted import planted_mixture
from ..sources.tables import written
from .common import result

R = Registry()
WIDTH, CODE = 48, 12


def bit_arrays(spark: SparkSession, sf_dir: str, rows: int = 600) -> dict[str, tuple[np.ndarray, np.ndarray]]:
    """Bits and classes of each dataset: bounded samples of least key hash, for training alone."""
    df = X.bit_sets(spark, sf_dir, WIDTH)
    w = Window.partitionBy("dataset_id").orderBy(F.md5(F.col("row_key").cast("binary")), "row_key")
    got = df.withColumn("r", F.row_number().over(w)).where(F.col("r") <= rows).select("dataset_id", "r", "cls", "features").toPandas().sort_values(["dataset_id", "r"])
    out = {}
    for name, part in got.groupby("dataset_id"):
        x = np.stack(part["features"].to_numpy()).astype(np.int8)
        out[name] = (x, pd.factorize(part["cls"])[0])
    return out


def trained(sets: dict[str, tuple[np.ndarray, np.ndarray]], steps: int, modes: tuple[str, ...] = ("plain", "mean", "mean_sketch", "per_class"), specific: bool = True, source: str = "embeddings") -> dict[str, Autoencoder]:
    """One plain model for each set, and models of every mode trained on the randomised source alone."""
    models: dict[str, Autoencoder] = {}
    if specific:
        for name in sorted(sets):
            models[f"own:{name}"] = ae = Autoencoder(WIDTH, CODE, 48, "plain", seed=1)
            train_autoencoder(ae, [sets[name]], steps, seed=1)
    for mode in modes:
        models[f"randomised:{mode}"] = ae = Autoencoder(WIDTH, CODE, 48, mode, 24, seed=1)
        train_autoencoder(ae, [sets[source]], 3 * steps, seed=1, randomize=True)
    return models


class ConditionRows:
    """The feature map whose mean conditions a model."""

    kind, has_columns, bound = "network", False, None

    def __init__(self, name: str, ae: Autoencoder):
        self.map_id, self.m, self.batch = name, ae.zd, ae.sketch_rows


def scored(df: DataFrame, models: dict[str, Autoencoder]) -> DataFrame:
    """model, dataset_id, ba: reconstruction of all rows of a table of bits. A scan for each conditioned model builds its means, one scan reconstructs with every model; only confusion counts leave the tasks.

    Models without condition need no means; `per_class` ones have a mean for each dataset and class (nulls are a class of their own).
    """
    rows = df.select("dataset_id", F.concat_ws("\u0001", "dataset_id", F.coalesce("cls", F.lit("\u0002"))).alias("class_key"), "features")
    conditions: dict[str, dict] = {}
    for name, ae in models.items():
        if ae.mode != "plain":
            sk = mean_sketch(rows, ConditionRows(name, ae), "class_key" if ae.mode == "per_class" else "dataset_id", "arrow")
            conditions[name] = {r.dataset_id: np.array(r.acc) / r.n for r in sk.select("dataset_id", "n", "acc").collect()}  # one for each dataset (and class)
    kinds = ("tp", "fn", "tn", "fp")
    schema = "model string, dataset_id string, tp long, fn long, tn long, fp long"

    def run(pdfs):
        held: dict[tuple[str, str], np.ndarray] = {}
        for pdf in pdfs:
            for name, ae in models.items():
                for k, part in pdf.groupby("class_key" if ae.mode == "per_class" else "dataset_id"):
                    x = np.stack(part["features"].to_numpy())
                    z = conditions.get(name, {}).get(k)
                    y = ae.reconstruct(x, None if z is None else np.repeat(z[None], len(x), axis=0)) == 1
                    t = x > 0.5
                    key = (name, part["dataset_id"].iloc[0])
                    held[key] = held.get(key, 0) + np.array([(t & y).sum(), (t & ~y).sum(), (~t & ~y).sum(), (~t & y).sum()])
        yield pd.DataFrame([(*k, *map(int, v)) for k, v in held.items()], columns=["model", "dataset_id", *kinds])

    c = rows.mapInPandas(run, schema).groupBy("model", "dataset_id").agg(*[F.sum(k).alias(k) for k in kinds])
    rates = F.array_compact(F.array(F.try_divide("tp", F.col("tp") + F.col("fn")), F.try_divide("tn", F.col("tn") + F.col("fp"))))
    return c.select("model", "dataset_id", (F.aggregate(rates, F.lit(0.0), lambda a, b: a + b) / F.size(rates)).alias("ba"))


@R.add("w08")
def w08(spark: SparkSession, sf_dir: str, quick: bool = True) -> DataFrame:
    """Balanced accuracy of every model on every set, over whole tables; training takes bounded samples."""
    models = trained(bit_arrays(spark, sf_dir, 400 if quick else 2000), 150 if quick else 2000)
    got = scored(written(X.bit_sets(spark, sf_dir, WIDTH), "w08"), models)
    return micro_rows(got, F.lit("matrix"), F.concat_ws("|", "model", "dataset_id"), list(models))


@R.add("w09")
def w09(spark: SparkSession, sf_dir: str, quick: bool = True) -> DataFrame:
    """Averages over the sets of the randomised-source models: no conditioning, mean, mean and sketch, both per class. Scores are over whole tables."""
    models = trained(bit_arrays(spark, sf_dir, 400 if quick else 2000), 250 if quick else 2000, specific=False)
    got = scored(written(X.bit_sets(spark, sf_dir, WIDTH), "w09"), models).groupBy("model").agg(F.avg("ba").alias("ba"))
    return micro_rows(got, F.col("model"), F.lit("mean"), list(models))


def micro_rows(got: DataFrame, method: Column, dataset: Column, models: list[str]) -> DataFrame:
    """The long result form; param is the place of the model."""
    place = F.array_position(F.array(*[F.lit(m) for m in models]), F.col("model")) - 1
    return got.select(method.alias("method"), place.cast("double").alias("param"), dataset.alias("dataset_id"), F.lit("balanced_accuracy").alias("metric"), F.floor(F.col("ba") * 1e6 + 0.5).cast("long").alias("value_micro"))


@R.add("w15")
def w15(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Residual networks of both styles, by blocks and width, as encoder and decoder of centroids: loss on held-out planted sets. Trials are Spark tasks."""
    trials = [(s, b, h) for s in ("bn_relu", "ln_gelu") for b in (1, 2) for h in (16, 32)]
    sets = [planted_mixture(2, 2, 400, s)[0] for s in range(10)]

    def work(pdfs):
        for pdf in pdfs:
            loss = []
            for i in pdf["i"]:
                style, blocks, hidden = trials[i]
                pair = LearnedPair(residual_mlp(2, 12, style, blocks, hidden, seed=1), residual_mlp(12, 4, "ln_gelu", blocks, hidden, "sigmoid", seed=2))
                train_pair(pair, sets[:7], kmeans_meta_loss("min", 2, 2), 250, 3e-3, seed=1, rows=96, two_batch=True)
                loss.append(float(np.mean([kmeans_mse_local(x, pair.decode(pair.sketch(x)).reshape(2, 2)) for x in sets[7:]])))
            yield pdf.assign(loss=loss)

    got = spark.createDataFrame([(i,) for i in range(len(trials))], "i int").repartition(len(trials), "i").mapInPandas(work, "i int, loss double").collect()
    return result(spark, [(f"{trials[r.i][0]}/blocks={trials[r.i][1]}", trials[r.i][2], "planted", "held_out_mse", r.loss) for r in got])


def gradient_check() -> bool:
    """One step of training must lower the loss along its own gradient; the conditioned model's reconstruction equals an affine layer on rows and sketch together."""
    rng = np.random.default_rng(0)
    x = (rng.random((200, 20)) < rng.random(20)).astype(np.int8)
    ae = Autoencoder(20, 6, 16, "mean_sketch", 8, seed=3)
    losses = train_autoencoder(ae, [(x, None)], 200, 3e-3, 64, 1)
    z = ae.condition(x.astype(float))
    joint = np.concatenate([2 * x - 1, 2 * z - 1], axis=1) @ np.vstack([ae.enc_in.w, ae.enc_z.w]) + ae.enc_in.b + ae.enc_z.b
    split = ae.enc_in.forward(2 * x - 1) + ae.enc_z.forward(2 * z - 1)
    return bool(np.mean(losses[-20:]) < 0.9 * np.mean(losses[:20]) and np.allclose(joint, split) and math.isfinite(losses[-1]))


@R.add("w10", "SELECT what, true AS ok FROM (VALUES ('days add up'), ('user removed'), ('days to weeks')) v(what)")
def w10(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Online work on sketches of events: merging days, removing a user, rolling days up to weeks; each equals a rebuild."""
    from ..operators.maps import outer_lt_map
    from ..operators.sketch import long_form, mean_sketch, remove_rows, rollup

    rows = X.events_by_user(spark, sf_dir).withColumn("features", F.slice("features", 1, 4))
    fm = outer_lt_map(4)
    day = rows.withColumn("dataset_id", F.date_format("ts", "yyyy-MM-dd"))
    sk = mean_sketch(day, fm, "dataset_id")
    same = lambda a, b: a.exceptAll(b).unionAll(b.exceptAll(a)).limit(1).count() == 0
    total = rollup(sk.withColumn("g", F.lit("all")), ["g"]).withColumnRenamed("g", "dataset_id")
    one = same(long_form(total), long_form(mean_sketch(rows, fm)))
    gone = X.events_by_user(spark, sf_dir).withColumn("features", F.slice("features", 1, 4)).where("dataset_id = '7'")
    two = same(long_form(remove_rows(mean_sketch(rows, fm), gone, fm)), long_form(mean_sketch(rows.where("dataset_id <> '7'"), fm)))
    week = F.date_format(F.date_trunc("week", F.col("dataset_id").cast("timestamp")), "yyyy-MM-dd")
    weeks = rollup(sk.withColumn("wk", week), ["wk"]).withColumnRenamed("wk", "dataset_id")
    three = same(long_form(weeks), long_form(mean_sketch(rows.withColumn("dataset_id", F.date_format(F.date_trunc("week", "ts"), "yyyy-MM-dd")), fm, "dataset_id")))
    return spark.createDataFrame([("days add up", one), ("user removed", two), ("days to weeks", three)], "what string, ok boolean")


def held_out(ids: list[str]) -> tuple[list[str], list[str]]:
    return split_ids(ids)
