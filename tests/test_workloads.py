"""Whole-table scores of the experiments against plain loops over the same rows."""

import hashlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from sketchfit.functions import features as X
from sketchfit.functions.keyed_random import uniform
from sketchfit.meta.train import Autoencoder, augment_bank, balanced_accuracy_local, bank_scale, train_moment_pair
from sketchfit.operators import baselines as B
from sketchfit.operators import moment_decoders as D
from sketchfit.operators import sketch as S
from sketchfit.operators import tasks as T
from sketchfit.operators.kmeans import kmeans_mse_local, lloyd_local
from sketchfit.operators.maps import fourier_map, identity_map
from sketchfit.workloads import autoencoder, clusters, moments, privacy


@pytest.fixture(scope="module")
def sets(spark):
    rng = np.random.default_rng(5)
    local = {"a": rng.random((300, 3)), "b": rng.random((41, 3)) * 2, "one": rng.random((1, 3))}
    rows = [(k, f"{k}{i}", x.tolist()) for k, v in local.items() for i, x in enumerate(v)]
    return local, spark.createDataFrame(rows, "dataset_id string, row_key string, features array<double>").repartition(5)


def test_near_sums_and_lloyd_read_all_rows(sets):
    local, rows = sets
    thetas = {(k, "m"): x[:1].repeat(2, 0) + [[0.0], [0.2]] for k, x in local.items()}
    got = clusters.near_sums(rows, thetas).groupBy("dataset_id").agg((F.sum("e") / F.sum("n")).alias("e"), F.sum("n").alias("n")).collect()
    assert {r.dataset_id: r.n for r in got} == {k: len(x) for k, x in local.items()}
    for r in got:
        assert r.e == pytest.approx(kmeans_mse_local(local[r.dataset_id], thetas[r.dataset_id, "m"]), abs=1e-9)
    pilots = {k: local[k] for k in ("a", "b")}
    done = clusters.lloyd_all(rows.where("dataset_id <> 'one'"), pilots, 2, 6, 2)
    for (name, start), theta in done.items():
        want = lloyd_local(local[name], 2, 6, int(start[-1]), 1)
        assert np.allclose(theta, want, atol=1e-9)


def test_sketched_centroids_sees_each_map(sets):
    local, rows = sets
    maps = {"mean": identity_map(3), "fourier": fourier_map(3, 8, 1.0, "gaussian", 1)}
    got = clusters.sketched_centroids(rows, maps, lambda which, z: {which: z[:3][None]})
    for name, x in local.items():
        assert np.allclose(got[name, "mean"][0], x.mean(0))
        assert np.allclose(got[name, "fourier"][0], maps["fourier"].batch(x).mean(0)[:3])


def test_row_moments_estimate_the_moment(sets):
    local, rows = sets
    got = {(r.dataset_id, r.method, r.m): S.unpack_lt(np.array(r.r), 3) for r in moments.row_moments(rows, 3, [3, 1200]).collect()}
    assert len(got) == 3 * 3 * 2
    for name, x in local.items():
        exact = x.T @ x / len(x)
        assert np.allclose(got[name, "row_sample", 1200], exact)  # the sample holds all rows
        for method in ("row_sparse", "row_gaussian"):
            r = got[name, method, 1200]
            assert np.linalg.norm(r - exact) < 0.5 * np.linalg.norm(exact)
            assert np.linalg.matrix_rank(got[name, method, 3], tol=1e-9) == 1  # one row of three numbers
        g = B.keyed_normals(np.arange(20000, dtype=np.int64) * 7919, 4)
        assert abs(g.mean()) < 0.02 and abs(g.std() - 1) < 0.02 and abs(np.corrcoef(g.T) - np.eye(4)).max() < 0.04


def test_sweep_scores_every_test_dataset(spark):
    rng = np.random.default_rng(1)
    data = {str(i): rng.random((30, 3)) * (1 + i % 3) for i in range(30)}
    rows = spark.createDataFrame([(k, f"{k}-{j}", x.tolist()) for k, v in data.items() for j, x in enumerate(v)], "dataset_id string, row_key string, features array<double>")
    got = moments.sweep(S.second_moment(rows, 3, "dataset_id"), rows, 3, [3, D.full_size(3)], moments.rank_mean_error, steps=20).toPandas()
    test = {i for i in data if uniform(f"split0-{i}") >= 0.5}
    for (_, _), part in got.groupby(["method", "param"]):
        assert sorted(part["dataset_id"]) == sorted(test)
    full = got[(got["param"] == D.full_size(3)) & got["method"].isin(["chi", "unit", "random_offset"])]
    assert full["value"].abs().max() < 1e-6


def test_bound_losses_are_those_of_all_rows(spark, sf):
    got = {r.dataset_id: r for r in privacy.bound_against_gap(spark, sf).collect()}
    rows = X.line_num(spark, sf).select("dataset_id", "row_key", "features").toPandas()
    fm = fourier_map(8, 16, 1.5, "gaussian", 3)
    decoder = np.random.default_rng(0).standard_normal((8, fm.m)) * 0.05
    seen = 0
    for name, part in rows.groupby("dataset_id"):
        x = np.clip(np.stack(part["features"].to_numpy()), 0, 1)
        first = np.array([uniform(f"half-{k}") < 0.5 for k in part["row_key"]])
        if first.all() or not first.any():
            assert name not in got
            continue
        theta = decoder @ fm.batch(x[first]).mean(0)
        for key, y in (("train", x[first]), ("test", x[~first])):
            assert got[name][key] == pytest.approx(((y - theta) ** 2).sum(1).mean(), abs=1e-9)
        seen += 1
    assert seen == len(got) > 0


@pytest.mark.parametrize("mode", ["plain", "mean", "mean_sketch", "per_class"])
def test_scores_of_bits_equal_a_local_pass(spark, mode):
    rng = np.random.default_rng(2)
    local = {k: ((rng.random((n, 8)) < 0.4).astype(np.int8), rng.integers(3, size=n)) for k, n in (("a", 120), ("b", 35))}
    df = spark.createDataFrame([(k, None if c == 0 else str(c), [float(v) for v in r]) for k, (x, cls) in local.items() for r, c in zip(x, cls)], "dataset_id string, cls string, features array<double>").repartition(3)
    ae = Autoencoder(8, 3, 10, mode, 6, seed=1)
    got = {r.dataset_id: r.ba for r in autoencoder.scored(df, {"m": ae, "n": Autoencoder(8, 3, 10, "plain", seed=2)}).where("model = 'm'").collect()}
    for name, (x, cls) in local.items():
        z = ae.condition(x.astype(float), cls if mode == "per_class" else None)
        assert got[name] == pytest.approx(balanced_accuracy_local(x, ae.reconstruct(x.astype(float), z)), abs=1e-9)


def test_the_bank_holds_every_training_dataset(spark):
    made = spark.range(700).selectExpr("cast(id as string) as dataset_id", "1L as n", "array(id + 1.0D, 0.5D, id + 2.0D) as v")
    bank, test = moments.halves(made)
    train = [i for i in range(700) if uniform(f"split0-{i}") < 0.5]
    assert len(train) > 300 and sorted(bank[:, 0]) == [i + 1.0 for i in train]
    assert test.count() == 700 - len(train)


def test_a_large_bank_is_mixed_and_trained_on_whole(monkeypatch):
    bank = np.eye(600)[:, :10] + np.arange(600)[:, None] / 600
    assert len(augment_bank(bank, 4, 3)) == 4 * 600
    seen = set()

    class Spied(np.ndarray):
        def __getitem__(self, key):
            if isinstance(key, np.ndarray) and key.ndim == 1:
                seen.update(key.tolist())
            return super().__getitem__(key)

    train_moment_pair(bank, 4, 3, steps=5, augmented=augment_bank(bank / bank_scale(bank), 4, 8).view(Spied))
    assert seen == set(range(9 * 600))


@pytest.mark.parametrize("m", [1, 5, 10])
def test_decoders_of_many_datasets_equal_those_of_one(m):
    rng = np.random.default_rng(4)
    x = rng.random((12, 20, 4))
    x[3] = 0
    a = rng.standard_normal((m, 10))
    z = D.pack_all(x.transpose(0, 2, 1) @ x / 20) @ a.T
    pairs = [
        (D.robust_all(z, a, 4, 2, 60), lambda q: D.decode_robust(q, a, 4, 2, 60)),
        (D.accelerated_all(z, a, 4, 60), lambda q: D.decode_accelerated(q, a, 4, 60)),
        (D.expgrad_all(z, a, 4, 60), lambda q: D.decode_expgrad(q, a, 4, 60)),
        (D.gradient_all(z, a, 4, 60), lambda q: D.decode_gradient(q, a, 4, 60)),
    ]
    for many, one in pairs:
        assert np.allclose(many, [one(q).r for q in z], atol=1e-8)


def test_row_sketches_of_one_scan_equal_those_made_alone(sets):
    _, rows = sets
    sizes = [1, 2, 20]
    for r in B.rowsketches(rows, sizes, 3, 7).collect():
        kinds, lo = np.array(r.acc[:-1]).reshape(2, -1, 3), 0
        own = rows.where(F.col("dataset_id") == r.dataset_id)
        assert r.acc[-1] == own.count()
        for s in sizes:
            gauss, sparse = np.zeros((s, 3)), np.zeros((s, 3))
            for q in B.rowsketch_gaussian(own, s, 3, 7).collect():
                gauss[q.i] = q.row
            for q in B.rowsketch_sparse(own, s, 3, 7).collect():
                sparse[q.bucket] = q.row
            assert np.allclose(kinds[0, lo : lo + s] / np.sqrt(s), gauss) and np.allclose(kinds[1, lo : lo + s], sparse)
            lo += s
    alone = {(r.dataset_id, s, tuple(r.features)) for s in sizes for r in B.rowsample(rows, s, 7).collect()}
    assert {(r.dataset_id, r.s, tuple(r.features)) for r in B.rowsamples(rows, sizes, 7).collect()} == alone


def test_errors_of_ridge_share_estimates():
    rng = np.random.default_rng(6)
    x = rng.random((5, 30, 4))
    exact = x.transpose(0, 2, 1) @ x / 30
    r = exact + 0.05 * np.eye(4)
    r[2] = 0  # no weights can be solved for
    for lam in (0.0, 0.1):
        want = [max(T.ridge_mse(e, T.ridge_from_moment(q, 1, lam), 1), 1e-12) for e, q in zip(exact, r)]
        assert np.allclose(moments.ridge_error(lam)(exact, r), want)


def test_several_errors_in_one_sweep_are_those_of_each(spark):
    rng = np.random.default_rng(8)
    data = [(str(i), f"{i}-{j}", rng.random(3).tolist()) for i in range(12) for j in range(9)]
    rows = spark.createDataFrame(data, "dataset_id string, row_key string, features array<double>")
    own = {"a": moments.ridge_error(0.0), "b": moments.ridge_error(0.1)}
    v = S.second_moment(rows, 3, "dataset_id")
    key = lambda df: {(r.method, r.param, r.dataset_id): r.value for r in df.collect()}
    got = key(moments.sweep(v, None, 3, [2], own, steps=5))
    for name, error in own.items():
        for (method, param, dataset), value in key(moments.sweep(v, None, 3, [2], error, steps=5)).items():
            assert got.pop((f"{name}:{method}", param, dataset)) == pytest.approx(value, abs=1e-9)
    assert not got


def test_one_scan_gives_moments_of_all_and_sketches_of_the_keyed(sets):
    local, rows = sets
    twice = rows.unionByName(rows.where("dataset_id = 'one'"))  # rows of one key
    got = {r.dataset_id: r for r in B.states(twice, [1, 2], 3, 3, keyed=F.col("dataset_id") != "b").collect()}
    alone = {r.dataset_id: r.acc for r in B.rowsketches(twice, [1, 2], 3, 3).collect()}
    local = local | {"one": local["one"].repeat(2, 0)}
    assert set(got) == set(local)
    for name, x in local.items():
        n, triangle, tail = got[name].acc[0], got[name].acc[1:7], got[name].acc[7:]
        assert n == len(x) and np.allclose(triangle, S.pack_lt(x.T @ x))
        assert np.allclose(tail, [] if name == "b" else alone[name][:-1])
        if name == "b":
            assert got[name].least is None
        else:
            least = sorted(range(len(x)), key=lambda i: hashlib.md5(f"sample3-{name}{i if name != 'one' else 0}".encode()).hexdigest())[:2]
            assert np.allclose(got[name].least, x[least])


def test_sweep_of_scanned_states_equals_that_of_rows(spark):
    rng = np.random.default_rng(3)
    data = [(str(i), f"{i}-{j}", rng.random(3).tolist()) for i in range(14) for j in range(12)]
    rows = spark.createDataFrame(data, "dataset_id string, row_key string, features array<double>")
    key = lambda df: {(r.method, r.param, r.dataset_id): r.value for r in df.collect()}
    want = key(moments.sweep(S.second_moment(rows, 3, "dataset_id"), rows, 3, [6], moments.rank_mean_error, steps=5))
    found, states = moments.scanned(rows, 3, [6], "test")
    got = key(moments.sweep(found, None, 3, [6], moments.rank_mean_error, steps=5, states=states))
    assert got.keys() == want.keys() and {m for m, _, _ in got} >= {"row_gaussian", "row_sparse", "row_sample", "robust", "learned"}
    # the robust decoder's moment has rank 1 here, so its other components are any
    assert {m for m, p, i in want if abs(got[m, p, i] - want[m, p, i]) > 1e-6} <= {"robust"}
