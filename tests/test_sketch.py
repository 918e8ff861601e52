"""Hand-sized cases and laws of the sketch algebra, maps, moments and measures."""

import numpy as np
import pytest

from sketchfit.functions import keyed_random as K
from sketchfit.operators import measures as E
from sketchfit.operators import sketch as S
from sketchfit.operators import tasks as T
from sketchfit.operators.maps import FeatureMap, concat_maps, fourier_map, identity_map, linear_act_map, nystrom_map, outer_lt_map, random_projection


def frame(spark, rows, ids=None):
    return spark.createDataFrame([(ids[i] if ids else "a", [float(v) for v in r]) for i, r in enumerate(rows)], "dataset_id string, features array<double>")


def test_mean_sketch_by_hand(spark):
    for engine in ("sql", "arrow", "summarizer"):
        r = S.mean(S.mean_sketch(frame(spark, [(0, 0), (1, 0), (0, 1)]), identity_map(2), "dataset_id", engine)).first()
        assert r.n == 3 and np.allclose(r.z, [1 / 3, 1 / 3])


def test_weighted_merge_and_removal(spark):
    one, three = S.mean_sketch(frame(spark, [(4,)]), identity_map(1), "dataset_id"), S.mean_sketch(frame(spark, [(0,)] * 3), identity_map(1), "dataset_id")
    both = S.merge(one, three)
    assert S.mean(both).first().z == [1.0]
    assert S.merge(one, three, "average").first().z == [2.0]
    back = S.subtract(both, three).first()
    assert back.n == 1 and back.acc == [4.0]


def test_engines_and_layouts_agree_exactly(spark):
    x = np.random.default_rng(0).standard_normal((300, 3))
    df = frame(spark, x, [str(i % 4) for i in range(300)])
    fm = fourier_map(3, 10, 1.0)
    states = []
    for n in (1, 4, 17):
        for engine in ("sql", "arrow"):
            states.append({(r.dataset_id, r.j): r.acc_fx for r in S.long_form(S.mean_sketch(df.repartition(n), fm, "dataset_id", engine)).collect()})
    assert all(s.keys() == states[0].keys() and max(abs(s[k] - states[0][k]) for k in s) <= 1 for s in states)
    assert states[0] == states[2] == states[4]


def test_second_moment_by_hand(spark):
    v = S.second_moment(frame(spark, [(1, 2), (3, -1)]), 2, "dataset_id").first().v
    assert np.allclose(v, [5, -0.5, 2.5])
    r = S.unpack_lt(np.array(v), 2)
    assert len(S.pack_lt(r, "full")) == 4 and np.isclose(S.pack_lt(r, "lt_iso")[1], -0.5 * np.sqrt(2))


def test_iso_layout_keeps_inner_products():
    a, b = (np.random.default_rng(i).standard_normal((5, 5)) for i in (1, 2))
    a, b = a + a.T, b + b.T
    assert np.isclose(S.pack_lt(a, "lt_iso") @ S.pack_lt(b, "lt_iso"), (a * b).sum())


def test_clip_inside_the_scan(spark):
    for limit, want in ((1, (0.6, 0.8)), (10, (3, 4))):
        for engine in ("sql", "arrow"):
            assert np.allclose(S.mean(S.mean_sketch(frame(spark, [(3, 4)]), identity_map(2), "dataset_id", engine, clip=limit)).first().z, want)
    assert S.mean(S.mean_sketch(frame(spark, [(0, 0)]), identity_map(2), "dataset_id", clip=1.0)).first().z == [0.0, 0.0]


def test_moment_sketch_rewrites_agree(spark):
    x = np.random.default_rng(0).standard_normal((50, 4))
    a = random_projection(4, 6, seed=2)
    z = [np.array(S.moment_sketch(frame(spark, x), a, 4, "dataset_id", how).first().z) for how in ("gram", "per_row")]
    assert np.allclose(z[0], z[1]) and np.allclose(z[0], a @ S.pack_lt(x.T @ x / 50))


def test_map_ids_and_kinds():
    assert fourier_map(3, 8, 1.0, seed=1).map_id != fourier_map(3, 8, 1.0, seed=2).map_id
    assert fourier_map(3, 8, 1.0, seed=1).map_id == fourier_map(3, 8, 1.0, seed=1).map_id
    x = np.random.default_rng(0).random((20, 3))
    marks = x[:6]
    f = nystrom_map(marks, 2.0)
    assert np.allclose(f.batch(marks) @ f.batch(marks).T, np.exp(-2 * ((marks[:, None] - marks[None]) ** 2).sum(-1)), atol=1e-6)
    assert f.numbers == 6 + 18
    c = concat_maps(identity_map(3), outer_lt_map(3))
    assert c.batch(x).shape == (20, 9)
    assert np.allclose(np.linalg.norm(fourier_map(3, 8, 1.0).batch(x), axis=1), 2)
    assert linear_act_map(np.eye(3), "cos_sin").batch(x).shape == (20, 6)


def test_unknown_engine_is_refused(spark):
    with pytest.raises(ValueError):
        S.mean_sketch(frame(spark, [(1,)]), identity_map(1), engine="rdd")
    with pytest.raises(ValueError):
        S.mean_sketch(frame(spark, [(1.0, 2.0)]), nystrom_map(np.eye(2), 1.0), engine="sql")
    assert isinstance(identity_map(2), FeatureMap)


def test_keyed_numbers_match_the_columns(spark):
    from pyspark.sql import functions as F

    got = spark.range(5).select(F.col("id"), K.uniform_col("k", F.col("id")).alias("u"), K.normal_col("k", F.col("id")).alias("g")).collect()
    assert all(r.u == K.uniform(f"k-{r.id}") and abs(r.g - K.normal(f"k-{r.id}")) < 1e-12 for r in got)


def test_errors_from_moments():
    x = np.random.default_rng(0).standard_normal((100, 4))
    r = x.T @ x / 100
    v = T.pca_from_moment(r)
    e = T.pca_error_profile(r, v)
    assert np.isclose(e[1], ((x - x @ v[:, :2] @ v[:, :2].T) ** 2).sum() / 100) and abs(e[-1]) < 1e-12
    th = T.ridge_from_moment(r, 1, 0.0)
    assert np.isclose(T.ridge_mse(r, th, 1), ((x[:, :1] - x[:, 1:] @ th.T) ** 2).mean())
    assert np.allclose(T.ridge_from_moment(r, 1, 1.0, "sum", 2), T.ridge_from_moment(r, 1, 0.5, "mean"))
    assert T.lre(2.0, 2.0) == 0


def test_matching_is_optimal():
    from itertools import permutations

    rng = np.random.default_rng(3)
    for _ in range(20):
        a, b = rng.random((4, 2)), rng.random((4, 2))
        cost = ((a[:, None] - b[None]) ** 2).sum(-1)
        assert np.isclose(T.matched_centroids(a, b)[1], min(sum(cost[i, p[i]] for i in range(4)) for p in permutations(range(4))))


def test_replace_one_bound_is_tight():
    u = np.array([[1.0, 0.0]])
    z = np.vstack([u, -u, -u, -u])
    assert np.isclose(E.replace_one_gap(z), 0.5) and np.isclose(E.leave_one_out_gap(z), 0.5)
    assert E.stability(1, 1, 1, 4, "strict") == 2 * E.stability(1, 1, 1, 4)


def test_balanced_accuracy_by_hand(spark):
    df = spark.createDataFrame([([1, 1, 0, 0, 0, 0], [1, 0, 0, 0, 0, 1])], "t array<int>, p array<int>")
    assert np.isclose(E.balanced_accuracy(df, "t", "p").first().ba, 0.625)
    none = spark.createDataFrame([([0, 0], [0, 1])], "t array<int>, p array<int>")
    r = E.balanced_accuracy(none, "t", "p").first()
    assert r.defined == 1 and r.ba == 0.5


def test_sizes():
    assert E.sketch_pct(19306, 196) == 100 and E.size_grid(196)[-1] == 19306
    assert E.generalization_bound(1, 1, 1, 1, 1, 100, 0.05) < E.generalization_bound(1, 1, 1, 1, 1, 100, 0.05, "strict")
