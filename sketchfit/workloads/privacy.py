"""Private release against eps, convergence with the number of rows, and the bound against the measured gap."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import features as X
from ..functions.keyed_random import uniform_col
from ..meta.train import bank_of, split_ids, train_moment_pair
from ..operators import measures as E
from ..operators import moment_decoders as D
from ..operators import privacy as P
from ..operators import sketch as S
from ..operators import tasks as T
from ..operators.maps import concat_maps, fourier_map, identity_map, outer_lt_map, random_projection
from ..plans.registry import Registry
from .common import result
from .moments import moments_of, rank_mean_error

R = Registry()


@R.add("w03")
def w03(spark: SparkSession, sf_dir: str, quick: bool = True) -> DataFrame:
    """Components of all documents against eps: a clipped sketch released with noise, learned or random, against noise on the moment itself."""
    d, m = 16, 20
    df = X.documents_by(spark, sf_dir, d)
    bank = moments_of(df, d)
    train, _ = split_ids(sorted(bank))
    total = S.mean_sketch(df, outer_lt_map(d), None, clip=1.0).first()  # rows have norm 1, so the clip takes nothing
    acc, n = np.array(total.acc), total.n
    exact = S.unpack_lt(acc / n, d)
    ref = rank_mean_error(exact, exact)
    pair = train_moment_pair(bank_of(bank, train), d, m, steps=100, rate=1e-3, seed=1, dp=(1.0, 1e-5, n))
    a = random_projection(d, m, "rank_one", "unit", "lt", 2)
    out = []
    # the features of one row: W v / scale + b with |v| <= 1 in the triangle's norm; W has orthonormal rows
    clip = float(np.linalg.norm(pair.w, 2) / pair.scale + np.linalg.norm(pair.b))
    low, high = pair.encode(bank_of(bank, train)).min(0), pair.encode(bank_of(bank, train)).max(0)
    for eps in (0.01, 0.1, 1, 10, 100) if quick else (0.01, 0.03, 0.1, 0.3, 1, 3, 10, 30, 100):
        for delta in (1e-5, 1e-2):
            got: dict[str, list] = {"learned": [], "random": [], "naive": []}
            for k in range(10 if quick else 20):
                z = P.privatize(pair.encode(acc / n) * n, n, eps, delta, clip, low - 0.1, high + 0.1, seed=k).clamped
                got["learned"].append(S.unpack_lt(pair.decode(z), d))
                z = P.privatize(a @ acc, n, eps, delta, float(np.sqrt(m)), 0.0, 1.0, seed=k).clamped
                got["random"].append(D.decode_pinv(z, a, d).r)
                got["naive"].append(P.private_moment(exact * n, n, eps, delta, 1.0, seed=k))
            out += [(f"{name}:delta={delta:g}", eps, "documents", "lre_median", T.lre(float(np.median([rank_mean_error(exact, r) for r in rs])), ref)) for name, rs in got.items()]
    return result(spark, out)


def nested(spark: SparkSession, sf_dir: str, parts: int = 5):
    """Sums of clipped features over nested md5 prefixes of the rows, all in one scan: each row goes to one shell, shells are added up on the driver."""
    fm = fourier_map(8, 16, 0.7, "gaussian", 3)
    df = X.line_num(spark, sf_dir)
    u = uniform_col("nest", F.col("row_key"))
    shell = F.lit(parts - 1)
    for k in range(parts - 2, -1, -1):
        shell = F.when(u < F.lit(4.0 ** (k - parts + 1)), k).otherwise(shell)
    got = {int(r.dataset_id): (r.n, np.array(r.acc)) for r in S.mean_sketch(df, fm, shell, "arrow", clip=fm.bound).collect()}
    n, acc, out = 0, np.zeros(fm.m), []
    for k in range(parts):
        if k in got:
            n, acc = n + got[k][0], acc + got[k][1]
        if n:
            out.append((n, acc.copy()))
    return fm, out


def convergence(spark: SparkSession, sf_dir: str, repeats: int = 60) -> list[tuple[int, float]]:
    fm, prefixes = nested(spark, sf_dir)
    out = []
    for n, acc in prefixes:
        err = [np.linalg.norm(P.privatize(acc, n, 1.0, 1e-5, fm.bound, seed=1000 * n % 997 + k).z - acc / n) for k in range(repeats)]
        out.append((n, float(np.median(err))))
    return out


@R.add("w11")
def w11(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distance of the private from the plain sketch against the number of rows."""
    return result(spark, [("private sketch", n, "lineitem", "distortion", e) for n, e in convergence(spark, sf_dir)])


def bound_against_gap(spark: SparkSession, sf_dir: str) -> DataFrame:
    """dataset_id, train, test, printed, strict for every dataset of at least one row in each half: all rows, in halves by key.

    A linear decoder of a Fourier sketch predicts the mean, with its squared error as the loss. The loss of a half needs the half's mean, its mean square and the sketch alone, so one scan gives all of them.
    """
    d = 8
    fm = fourier_map(d, 16, 1.5, "gaussian", 3)
    decoder = np.random.default_rng(0).standard_normal((d, fm.m)) * 0.05
    slope = float(np.linalg.norm(decoder, 2))
    # |x| <= sqrt(d) and |theta| <= |decoder| beta bound the loss and its slope
    top = float((np.sqrt(d) + slope * fm.bound) ** 2)
    rho_l = float(2 * np.sqrt(top))
    df = X.line_num(spark, sf_dir)
    rows = df.withColumn("features", F.transform("features", lambda v: F.least(F.greatest(v, F.lit(0.0)), F.lit(1.0)))).withColumn("half", F.when(uniform_col("half", F.col("row_key")) < 0.5, "a").otherwise("b"))
    both = concat_maps(identity_map(d), outer_lt_map(d), fm)
    sk = S.mean(S.mean_sketch(rows, both, F.concat_ws("\u0001", "half", "dataset_id"), "arrow"))
    half = lambda h: sk.where(F.col("dataset_id").startswith(h + "\u0001")).select(F.substring("dataset_id", 3, 2**31 - 1).alias("dataset_id"), F.col("n").alias(f"n_{h}"), F.col("z").alias(f"z_{h}"))
    square = [k * (k + 3) // 2 + d for k in range(d)]  # places of the squares behind the first d numbers

    def run(pdfs):
        for pdf in pdfs:
            out = []
            for r in pdf.itertuples(index=False):
                theta = decoder @ np.asarray(r.z_a)[-fm.m :]
                train, test = (float(np.asarray(z)[square].sum() - 2 * theta @ np.asarray(z)[:d] + theta @ theta) for z in (r.z_a, r.z_b))
                out.append((r.dataset_id, train, test, *(float(E.generalization_bound(train, fm.bound, slope, rho_l, top, int(r.n_a), 0.05, c)) for c in ("printed", "strict"))))
            yield pd.DataFrame(out, columns=["dataset_id", "train", "test", "printed", "strict"])

    return half("a").join(half("b"), "dataset_id").mapInPandas(run, "dataset_id string, train double, test double, printed double, strict double")


@R.add("w12")
def w12(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Loss on both halves of every dataset and the bound with either constant."""
    kinds = ("train", "test", "printed", "strict")
    got = bound_against_gap(spark, sf_dir)
    long = got.select("dataset_id", F.explode(F.array(*[F.struct(F.lit(k).alias("method"), F.col(k).alias("v")) for k in kinds])).alias("c"))
    return long.select("c.method", F.lit(0.05).alias("param"), "dataset_id", F.lit("loss").alias("metric"), F.floor(F.col("c.v") * 1e6 + 0.5).cast("long").alias("value_micro"))
