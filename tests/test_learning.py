"""Networks, training, search, decoders and privacy."""

import numpy as np
import pytest

from sketchfit.meta import train as M
from sketchfit.meta.layers import Adam, residual_mlp
from sketchfit.meta.search import STRATEGIES, Space, derivative_free_search
from sketchfit.operators import moment_decoders as D
from sketchfit.operators import privacy as P
from sketchfit.operators.kmeans import decode_unrolled, jacobian_product, kmeans_mse_local, lloyd_local, nnls
from sketchfit.operators.maps import fourier_map, linear_act_map, nystrom_map, random_projection
from sketchfit.operators.sketch import pack_lt
from sketchfit.operators.tasks import NoSurrogateLoss, autoencoder_sketch_loss
from sketchfit.sources.planted import planted_mixture


@pytest.mark.parametrize("style", ["bn_relu", "ln_gelu"])
@pytest.mark.parametrize("training", [True, False])
def test_backward_matches_differences(style, training):
    net = residual_mlp(3, 2, style, 1, 5, "sigmoid", 1)
    x, g = np.random.default_rng(0).standard_normal((7, 3)), np.random.default_rng(1).standard_normal((7, 2))
    net.forward(x, training)
    dx = net.backward(g)
    grads = {k: v.copy() for k, v in net.grads.items()}
    for k, p in net.params().items():
        i = np.unravel_index(p.size // 2, p.shape)
        eps, old = 1e-6, p[i]
        p[i] = old + eps
        up = (net.forward(x, training) * g).sum()
        p[i] = old - eps
        down = (net.forward(x, training) * g).sum()
        p[i] = old
        assert np.isclose(grads[k][i], (up - down) / (2 * eps), atol=1e-5), k
    e = np.zeros_like(x)
    e[2, 1] = 1e-6
    num = ((net.forward(x + e, training) - net.forward(x - e, training)) * g).sum() / 2e-6
    assert np.isclose(dx[2, 1], num, atol=1e-5)


def test_inference_is_row_wise():
    net = residual_mlp(3, 2, "bn_relu", 2, 8, seed=2)
    x = np.random.default_rng(0).standard_normal((10, 3))
    for _ in range(3):
        net.forward(x, True)
    assert np.allclose(net.forward(x), np.vstack([net.forward(x[i : i + 1]) for i in range(10)]))


@pytest.mark.parametrize("fm", [fourier_map(2, 12, 0.5), linear_act_map(np.random.default_rng(0).standard_normal((6, 2)), "tanh"), linear_act_map(np.random.default_rng(0).standard_normal((6, 2)), "cos_sin"), nystrom_map(np.random.default_rng(1).random((5, 2)), 2.0)])
def test_map_gradients(fm):
    th, g = np.random.default_rng(2).random((3, 2)), np.random.default_rng(3).standard_normal(fm.m)
    got = jacobian_product(fm, th, g)
    for i in np.ndindex(3, 2):
        e = np.zeros((3, 2))
        e[i] = 1e-6
        assert np.isclose(got[i], ((fm.batch(th + e) - fm.batch(th - e)) @ g).sum() / 2e-6, atol=1e-5)


def test_nnls_is_optimal():
    rng = np.random.default_rng(0)
    for _ in range(20):
        a, b = rng.standard_normal((12, 4)), rng.standard_normal(12)
        x = nnls(a, b)
        g = a.T @ (a @ x - b)
        assert (x >= 0).all() and (g > -1e-8).all() and abs(g @ x) < 1e-8


def test_decoders_recover_at_full_size():
    x = np.random.default_rng(0).standard_normal((200, 6))
    v = pack_lt(x.T @ x / 200)
    a = random_projection(6, 21, "rank_one", "chi", "lt", 4)
    assert np.allclose(pack_lt(D.decode_pinv(a @ v, a, 6).r), v, atol=1e-8)
    assert np.linalg.eigvalsh(D.psd(np.diag([1.0, -1.0]))).min() >= 0


def test_moment_pair_trains_and_beats_random():
    rng = np.random.default_rng(0)
    base = rng.standard_normal((2, 6))
    bank = np.array([M.moment_of(rng.random((80, 2)) @ (base + 0.1 * rng.standard_normal((2, 6)))) for _ in range(30)])
    pair = M.train_moment_pair(bank[:20], 6, 3, steps=150, rate=1e-3, held=bank[20:])
    assert pair.log[-1][1] <= pair.log[0][1] + 1e-9
    a = random_projection(6, 3, seed=1)
    learned = np.mean([np.abs(pair.decode(pair.encode(v)) - v).sum() for v in bank[20:]])
    random = np.mean([np.abs(pack_lt(D.decode_pinv(a @ v, a, 6).r) - v).sum() for v in bank[20:]])
    assert learned < random


@pytest.mark.parametrize("name", sorted(STRATEGIES))
def test_search_strategies_improve(name):
    space = Space({"a": 0.0, "b": 0.0}, {"a": 1.0, "b": 1.0}, {"c": ("x", "y")})
    point, tool = derivative_free_search(space, lambda p, g: (p["a"] - 1) ** 2 + (p["b"] + 0.5) ** 2 + (p["c"] != "y"), 400, name, seed=1)
    assert tool.best < 0.5 and (np.diff(tool.history) <= 0).all()


def test_unrolled_pair_search_improves():
    sets = [planted_mixture(2, 2, 200, s)[0] for s in range(2)]
    pair = M.train_unrolled_pair(sets, 2, 20, budget=16, steps=40, seed=1)
    assert pair.log[-1] <= pair.log[0]


def test_unrolled_reaches_lloyd_on_planted():
    x, _ = planted_mixture(2, 2, 1500, 3)
    fm = fourier_map(2, 60, 0.4, seed=2)
    got = decode_unrolled(fm.batch(x).mean(0), fm, 2, 300, starts=6, weighting="nnls")
    assert kmeans_mse_local(x, got.theta) < 2 * kmeans_mse_local(x, lloyd_local(x, 2))


def test_meta_loss_trains_a_pair():
    sets = [planted_mixture(2, 2, 300, s)[0] for s in range(4)]
    pair = M.LearnedPair(residual_mlp(2, 8, "ln_gelu", 1, 16, seed=1), residual_mlp(8, 4, "ln_gelu", 1, 16, "sigmoid", 2))
    losses = M.train_pair(pair, sets, M.kmeans_meta_loss("min", 2, 2), 150, 5e-3, two_batch=True)
    assert np.mean(losses[-20:]) < np.mean(losses[:20])


@pytest.mark.parametrize("mode", ["plain", "mean", "sketch", "mean_sketch", "per_class"])
def test_autoencoder_modes_learn(mode):
    rng = np.random.default_rng(0)
    x = (rng.random((300, 16)) < rng.random(16)).astype(np.int8)
    cls = rng.integers(2, size=300)
    ae = M.Autoencoder(16, 6, 16, mode, 6, seed=1)
    losses = M.train_autoencoder(ae, [(x, cls)], 120, 3e-3, 64)
    assert np.mean(losses[-10:]) < np.mean(losses[:10])


def test_autoencoder_gradients():
    rng = np.random.default_rng(0)
    x = (rng.random((64, 8)) < 0.4).astype(np.int8)
    for dynamic in ("bias", "bias+scale"):
        ae = M.Autoencoder(8, 3, 6, "mean_sketch", 4, dynamic, seed=2)
        before = M.train_autoencoder(ae, [(x, None)], 300, 3e-3, 32)
        assert before[-1] < before[0]


def test_no_surrogate_for_autoencoders():
    with pytest.raises(NoSurrogateLoss):
        autoencoder_sketch_loss()


def test_augmentation_is_shared_by_the_batch():
    x = np.eye(6)[:3]
    y = M.augment_permute_negate(x, 1, 2)
    assert y.shape == x.shape and np.array_equal(y, M.augment_permute_negate(x, 1, 2))
    assert {tuple(sorted(c)) for c in np.abs(y - y[0]).tolist()} <= {tuple(sorted(c)) for c in np.abs(x - x[0]).tolist()}


def test_noise_and_limits():
    acc, n = np.array([30.0, -10.0]), 100
    big = P.privatize(acc, n, 1e7, 0.5, 1.0, seed=1)
    assert np.allclose(big.z, acc / n, atol=1e-3)
    assert P.gaussian_sigma(0.5, 1e-5, 1) < P.gaussian_sigma(0.5, 1e-5, 1, "classic")
    with pytest.raises(ValueError):
        P.gaussian_sigma(2.0, 1e-5, 1, "classic")
    draws = np.array([P.privatize(acc, 10**6, 1, 1e-5, 1.0, seed=k).z * 10**6 - acc for k in range(2000)])
    assert abs(draws.std() / P.calibrate(1, 1e-5, 1.0).sigma_sum - 1) < 0.05


def test_adam_schedules():
    for s in ("constant", "cosine", "step", "plateau"):
        o = Adam(0.1, s, 10, patience=1)
        p = {"w": np.array([5.0])}
        for _ in range(10):
            o.update(p, {"w": 2 * p["w"]})
            o.observe(1.0)
        assert p["w"][0] < 5
        assert o.current() <= 0.1


def test_gradient_through_the_unrolled_steps():
    x, _ = planted_mixture(2, 2, 60, 1)
    w, th = np.random.default_rng(0).standard_normal((5, 2)), np.array([[0.3, 0.4], [0.6, 0.7]])
    _, g, top = M.unrolled_gradient(x, w, th, 4, 0.05)
    assert np.isfinite(top)
    for i in np.ndindex(5, 2):
        e = np.zeros_like(w)
        e[i] = 1e-6
        num = (M.unrolled_gradient(x, w + e, th, 4, 0.05)[0] - M.unrolled_gradient(x, w - e, th, 4, 0.05)[0]) / 2e-6
        assert np.isclose(g[i], num, atol=1e-5)
    pair, log = M.train_unrolled_backprop([x], 2, 20, rounds=20)
    assert len(log) == 20 and pair.fm.m == 20


def test_batch_inference_and_codes(spark):
    from sketchfit.functions.udfs import autoencoder_codes, predict_features

    fm = fourier_map(3, 8, 1.0)
    x = np.random.default_rng(0).random((20, 3))
    df = spark.createDataFrame([(r.tolist(),) for r in x], "features array<double>")
    got = np.array([r.z for r in df.select(predict_features(fm)("features").alias("z")).collect()])
    assert np.allclose(got, fm.batch(x))
    ae = M.Autoencoder(3, 2, 4, "mean")
    out = autoencoder_codes(df, ae, x.mean(0)).collect()
    assert len(out) == 20 and len(out[0].code) == 2 and len(out[0].bits) == 3


def _sets(spark, sets):
    rows = [(name, f"{name}-{i}", [float(v) for v in r]) for name, x in sets.items() for i, r in enumerate(x)]
    return spark.createDataFrame(rows, "dataset_id string, row_key string, features array<double>")


def test_fit_from_sketch_equals_local_fit(spark):
    sets = {f"s{i}": planted_mixture(2, 3, 90 + i, i)[0] for i in range(3)}
    df = _sets(spark, sets)
    got: dict = {}
    unrolled = M.UnrolledPair(fourier_map(3, 16, 0.5, "gaussian", 1), 30, 0.02, "adam", 0.08, "uniform")
    moment = M.train_moment_pair(np.array([M.moment_of(x) for x in sets.values()]), 3, 4, steps=10, augment=1)
    learned = M.LearnedPair(residual_mlp(3, 5, "ln_gelu", 1, 6, "none", 1), residual_mlp(5, 4, "ln_gelu", 1, 6, "none", 2))
    want = {
        "unrolled": lambda x: unrolled.decode(unrolled.fm.batch(x).mean(0), 2).theta,
        "moment": lambda x: moment.moment(M.moment_of(x)),
        "learned": lambda x: learned.decode(learned.sketch(x))[None],
    }
    for kind, pair in (("unrolled", unrolled), ("moment", moment), ("learned", learned)):
        got = {}
        for r in M.fit_from_sketch(df, pair, k=2).orderBy("dataset_id", "i").collect():
            assert r.n == len(sets[r.dataset_id])
            got.setdefault(r.dataset_id, []).append(r.theta)
        for name, x in sets.items():
            assert np.allclose(got[name], want[kind](x), atol=1e-6), kind
        assert M.fit_from_sketch(df.limit(0), pair, k=2).count() == 0


def test_pilot_scale(spark):
    from sketchfit.operators.maps import pilot_scale

    x = np.random.default_rng(0).random((40, 2))
    got = pilot_scale(_sets(spark, {"a": x, "one": x[:1], "equal": np.repeat(x[:1], 5, axis=0)}), 64)
    far = [np.linalg.norm(x[i] - x[j]) for i in range(40) for j in range(i)]
    assert np.isclose(got["a"], np.median(far)) and got["one"] == got["equal"] == 1.0
    assert pilot_scale(_sets(spark, {"a": x}).limit(0)) == {}


def test_privacy_curve_and_log(spark):
    from sketchfit.operators.measures import privacy_curve

    got = privacy_curve(lambda eps, r: r / eps, (0.5, 2.0), 5)
    assert [(e, q) for e, q, _ in got] == [(e, q) for e in (0.5, 2.0) for q in (0.1, 0.5, 0.9)]
    assert [v for _, q, v in got if q == 0.5] == [4.0, 1.0]
    rows = M.training_log(spark, [(0, 2.0, float("nan")), (5, 1.0, 3.0)]).orderBy("step").collect()
    assert [tuple(r) for r in rows] == [(0, 2.0, None), (5, 1.0, 3.0)]
    assert [tuple(r) for r in M.training_log(spark, [0.5, 0.25]).orderBy("step").collect()] == [(0, 0.5, None), (1, 0.25, None)]
