"""One query for each sketch operator, decoder, baseline and measure."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import features as X
from ..functions import keyed_random as K
from ..functions import vectors as V
from ..operators import baselines as B
from ..operators import measures as E
from ..operators import privacy as P
from ..operators import sketch as S
from ..operators import tasks as T
from ..operators.kmeans import decode_greedy, decode_message_passing, decode_unrolled, gmm_from_sketch, kmeans_mse_local, lloyd_local, lloyd_step
from ..operators.maps import FeatureMap, fourier_map, identity_map, nystrom_map, outer_lt_map, pilot_scale, random_projection, rank_one_map
from ..sources.planted import planted_linear, planted_lowrank, planted_mixture
from ..sources.tables import load_sketches, save_sketches, shared_folder
from .registry import Registry
from .relational import micro_sql, t

R = Registry()
FX = "CAST(floor(({}) * 1048576.0::DOUBLE + 0.5) AS BIGINT)"


def fx_sql(x: str) -> str:
    return FX.format(x)


# SQL for embeddings: e is the vector as doubles
EMB = "(SELECT vec_id, label, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e FROM embeddings)"


def omega8() -> np.ndarray:
    """Eight frequencies over the first four coordinates, from md5 keys."""
    return K.normals("freq", 4, 4)


def emb_d(s: SparkSession, d: str, width: int) -> DataFrame:
    return X.emb64(s, d).withColumn("features", F.slice("features", 1, width))


def _dot_sql(row: np.ndarray, vec: str = "e") -> str:
    return " + ".join(f"{vec}[{i + 1}] * {float(w)!r}::DOUBLE" for i, w in enumerate(row))


def _fourier_sql() -> str:
    feats = [f"cos({_dot_sql(w)})" for w in omega8()] + [f"sin({_dot_sql(w)})" for w in omega8()]
    parts = [f"SELECT CAST(label AS VARCHAR) AS dataset_id, count(*) AS n, {j} AS j, CAST(sum({fx_sql(f)}) AS BIGINT) AS acc_fx FROM {EMB} GROUP BY label" for j, f in enumerate(feats)]
    return " UNION ALL ".join(parts)


def _emb_fourier(s, d, engine):
    fm = FeatureMap("fourier", 4, 8, arrays={"omega": omega8()})
    return S.mean_sketch(emb_d(s, d, 4), fm, "dataset_id", engine)


for _name, _engine in (("mean_sketch_sql", "sql"), ("mean_sketch_arrow", "arrow")):

    @R.add(_name, _fourier_sql())
    def _(s, d, engine=_engine):
        return S.long_form(_emb_fourier(s, d, engine))


@R.add("mean_sketch_summarizer", " UNION ALL ".join(f"SELECT CAST(label AS VARCHAR) AS dataset_id, count(*) AS n, {j} AS j, CAST(floor(avg(e[{j + 1}]) * 1e6 + 0.4637) AS BIGINT) AS z_micro FROM {EMB} GROUP BY label" for j in range(4)))
def _(s, d):
    z = S.mean(S.mean_sketch(emb_d(s, d, 4), identity_map(4), "dataset_id", "summarizer"))
    return z.select("dataset_id", "n", F.posexplode("z").alias("j", "v")).select("dataset_id", "n", "j", V.micro(F.col("v")).alias("z_micro"))


LINE_ROW = "SELECT CAST({} AS VARCHAR) AS dataset_id, [l_quantity / 50.0, l_discount / 0.1, l_tax / 0.1] AS e FROM lineitem"


def line3(s: SparkSession, d: str, by: str = "l_returnflag") -> DataFrame:
    x = F.array(F.col("l_quantity") / 50.0, F.col("l_discount") / 0.1, F.col("l_tax") / 0.1)
    return t(s, d, "lineitem").select(F.col(by).cast("string").alias("dataset_id"), x.alias("features"))


LT3 = ["e[1] * e[1]", "e[2] * e[1]", "e[2] * e[2]", "e[3] * e[1]", "e[3] * e[2]", "e[3] * e[3]"]


def _acc_sql(rows: str, feats: list[str], key: str = "dataset_id", sign: str = "1") -> str:
    return " UNION ALL ".join(f"SELECT {key}, CAST(sum({sign}) AS BIGINT) AS n, {j} AS j, CAST(sum({sign} * {fx_sql(f)}) AS BIGINT) AS acc_fx FROM ({rows}) GROUP BY {key}" for j, f in enumerate(feats))


@R.add("mean_sketch_exact", _acc_sql(LINE_ROW.format("l_returnflag"), LT3))
def _(s, d):
    return S.long_form(S.mean_sketch(line3(s, d), outer_lt_map(3), "dataset_id"))


EV = "SELECT date_trunc('day', ts) AS day, event_type, user_id, event_id, ts, [1.0, value / 100, CAST(json_extract_string(props, '$.k') AS DOUBLE) / 100] AS e FROM events"
EV3 = ["e[1]", "e[2]", "e[3]"]


def ev3(s: SparkSession, d: str) -> DataFrame:
    e = t(s, d, "events")
    x = F.array(F.lit(1.0), F.col("value") / 100, F.get_json_object("props", "$.k").cast("double") / 100)
    return e.select(F.date_format("ts", "yyyy-MM-dd").alias("day"), "event_type", "user_id", "event_id", "ts", x.alias("features"))


def daily(s: SparkSession, d: str) -> DataFrame:
    sk = S.mean_sketch(ev3(s, d), identity_map(3), F.concat_ws("|", "day", "event_type"))
    return sk.select(F.split_part("dataset_id", F.lit("|"), F.lit(1)).alias("day"), F.split_part("dataset_id", F.lit("|"), F.lit(2)).alias("event_type"), "dataset_id", "map_id", "n", "acc", "acc_fx", "max_norm")


EVS = EV.replace("date_trunc('day', ts) AS day", "strftime(ts, '%Y-%m-%d') AS day")


@R.add("sketch_merge", _acc_sql(EVS, EV3, "event_type"))
def _(s, d):
    return S.long_form(S.rollup(daily(s, d), ["event_type"]), ["event_type"])


@R.add("sketch_rollup", _acc_sql(EVS, EV3, "day"))
def _(s, d):
    return S.long_form(S.rollup(daily(s, d), ["day"]), ["day"])


@R.add("sketch_month", _acc_sql(EVS.replace("'%Y-%m-%d') AS day", "'%Y-%m') AS day"), EV3, "day"))
def _(s, d):
    months = S.rollup(daily(s, d), [F.substring("day", 1, 7)])
    return S.long_form(months.withColumnRenamed("k0", "day"), ["day"])


def _gs(kind: str) -> str:
    spec = {"sketch_grouping_sets": "GROUPING SETS ((day), (event_type))", "sketch_cube": "CUBE (day, event_type)"}[kind]
    return " UNION ALL ".join(f"SELECT coalesce(day, '*') AS day, coalesce(event_type, '*') AS event_type, {j} AS j, CAST(sum({fx_sql(f)}) AS BIGINT) AS acc_fx FROM ({EVS}) GROUP BY {spec}" for j, f in enumerate(EV3))


def _sets_of(s, d, sets):
    sk = daily(s, d)
    out = None
    for keys in sets:
        r = S.rollup(sk, keys)
        r = r.select(*[(F.col(k) if k in keys else F.lit("*")).alias(k) for k in ("day", "event_type")], "n", "acc_fx")
        out = r if out is None else out.unionByName(r)
    return S.long_form(out, ["day", "event_type"]).drop("n")


@R.add("sketch_grouping_sets", _gs("sketch_grouping_sets"))
def _(s, d):
    return _sets_of(s, d, [["day"], ["event_type"]])


@R.add("sketch_cube", _gs("sketch_cube"))
def _(s, d):
    return _sets_of(s, d, [["day", "event_type"], ["day"], ["event_type"], []])


@R.add("sketch_avg_merge", f"WITH a AS (SELECT event_type, avg(e[2]) AS z FROM ({EVS}) WHERE event_id % 2 = 0 GROUP BY 1), b AS (SELECT event_type, avg(e[2]) AS z FROM ({EVS}) WHERE event_id % 2 = 1 GROUP BY 1) SELECT a.event_type AS dataset_id, {micro_sql('(a.z + b.z) / 2')} AS z_micro FROM a JOIN b ON a.event_type = b.event_type")
def _(s, d):
    rows = ev3(s, d)
    a, b = (S.mean_sketch(rows.where(F.pmod("event_id", F.lit(2)) == k), identity_map(3), "event_type") for k in (0, 1))
    return S.merge(a, b, "average").select("dataset_id", V.micro(F.get("z", F.lit(1))).alias("z_micro"))


@R.add("sketch_add", _acc_sql(EVS, EV3, "event_type").replace("event_type, CAST", "event_type AS dataset_id, CAST"))
def _(s, d):
    rows = ev3(s, d)
    sk = S.mean_sketch(rows.where("day <= '2024-01-20'"), identity_map(3), "event_type")
    return S.long_form(S.add_rows(sk, rows.where("day > '2024-01-20'"), identity_map(3), "event_type"))


@R.add("sketch_remove", _acc_sql(f"{EVS} WHERE user_id <> 7", EV3, "event_type").replace("event_type, CAST", "event_type AS dataset_id, CAST"))
def _(s, d):
    rows = ev3(s, d)
    sk = S.mean_sketch(rows, identity_map(3), "event_type")
    return S.long_form(S.remove_rows(sk, rows.where("user_id = 7"), identity_map(3), "event_type"))


@R.add("sketch_sites", _acc_sql(EVS, EV3, "event_type").replace("event_type, CAST", "event_type AS dataset_id, CAST"))
def _(s, d):
    rows = ev3(s, d)
    return S.long_form(S.sketch_sites([rows.where(F.pmod("event_id", F.lit(3)) == k) for k in range(3)], identity_map(3), "event_type"))


@R.add("sketch_signed_rows", _acc_sql(EVS, EV3, "event_type", "CASE WHEN event_id % 10 = 0 THEN -1 ELSE 1 END").replace("event_type, CAST", "event_type AS dataset_id, CAST"))
def _(s, d):
    rows = ev3(s, d).withColumn("op", F.when(F.pmod("event_id", F.lit(10)) == 0, -1).otherwise(1))
    return S.long_form(S.mean_sketch(rows, identity_map(3), "event_type"))


@R.add("sketch_union_law", "SELECT 'union' AS law, true AS ok")
def _(s, d):
    rows = line3(s, d)
    a, b = rows.where(F.get("features", F.lit(0)) < 0.5), rows.where(F.get("features", F.lit(0)) >= 0.5)
    one, two = S.long_form(S.mean_sketch(a.unionAll(b), outer_lt_map(3), "dataset_id")), S.long_form(S.merge(S.mean_sketch(a, outer_lt_map(3), "dataset_id"), S.mean_sketch(b, outer_lt_map(3), "dataset_id")))
    off = one.exceptAll(two).unionAll(two.exceptAll(one)).agg(F.count(F.lit(1)).alias("c"))
    return off.select(F.lit("union").alias("law"), (F.col("c") == 0).alias("ok"))


@R.add("sketch_except_law", "SELECT 'except' AS law, true AS ok")
def _(s, d):
    rows = line3(s, d)
    b = rows.where(F.get("features", F.lit(0)) >= 0.8)
    one, two = S.long_form(S.mean_sketch(rows.exceptAll(b), outer_lt_map(3), "dataset_id")), S.long_form(S.subtract(S.mean_sketch(rows, outer_lt_map(3), "dataset_id"), S.mean_sketch(b, outer_lt_map(3), "dataset_id")))
    off = one.exceptAll(two).unionAll(two.exceptAll(one)).agg(F.count(F.lit(1)).alias("c"))
    return off.select(F.lit("except").alias("law"), (F.col("c") == 0).alias("ok"))


@R.add("sketch_store_partition_pruned", _acc_sql(f"{EVS} WHERE strftime(ts, '%Y-%m-%d') = '2024-01-05'", EV3, "day"))
def _(s, d):
    sk = S.rollup(daily(s, d), ["day"])
    path = shared_folder(s, "store")
    save_sketches(sk, path, "day")
    return S.long_form(load_sketches(s, path, identity_map(3).map_id).where("day = '2024-01-05'").select(F.col("day").cast("string").alias("day"), "n", "acc_fx"), ["day"])


def _prefix_sql(frame: str) -> str:
    return " UNION ALL ".join(f"SELECT day, {j} AS j, CAST(sum(x) OVER (ORDER BY day {frame}) AS BIGINT) AS acc_fx FROM (SELECT day, sum({fx_sql(f)}) AS x FROM ({EVS}) GROUP BY day)" for j, f in enumerate(EV3))


def _windowed(s, d, w):
    long = S.long_form(S.rollup(daily(s, d), ["day"]), ["day"])
    return long.select("day", "j", F.sum("acc_fx").over(w).alias("acc_fx"))


@R.add("win_moving_sketch_rows", _prefix_sql("ROWS BETWEEN 6 PRECEDING AND CURRENT ROW"))
def _(s, d):
    return _windowed(s, d, Window.partitionBy("j").orderBy("day").rowsBetween(-6, 0))


@R.add("win_moving_sketch_range", _prefix_sql("ROWS BETWEEN 6 PRECEDING AND CURRENT ROW"))
def _(s, d):
    # sketches can be taken away: the running sum less the one of seven days before
    long = S.long_form(S.rollup(daily(s, d), ["day"]), ["day"])
    run = long.select("day", "j", F.sum("acc_fx").over(Window.partitionBy("j").orderBy("day").rowsBetween(Window.unboundedPreceding, 0)).alias("p"))
    before = F.lag("p", 7, 0).over(Window.partitionBy("j").orderBy("day"))
    return run.select("day", "j", (F.col("p") - before).alias("acc_fx"))


@R.add("win_prefix_sketch", _prefix_sql("ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW"))
def _(s, d):
    return _windowed(s, d, Window.partitionBy("j").orderBy("day").rowsBetween(Window.unboundedPreceding, 0))


@R.add("join_self_sketch_pairs", f"WITH z AS (SELECT label, avg(e[1]) AS a, avg(e[2]) AS b FROM {EMB} GROUP BY 1) SELECT CAST(x.label AS VARCHAR) AS a, CAST(y.label AS VARCHAR) AS b, {micro_sql('(x.a - y.a) * (x.a - y.a) + (x.b - y.b) * (x.b - y.b)')} AS dist_micro FROM z x JOIN z y ON x.label < y.label")
def _(s, d):
    z = S.mean(S.mean_sketch(emb_d(s, d, 2), identity_map(2), "dataset_id"))
    a, b = z.select(F.col("dataset_id").alias("a"), F.col("z").alias("za")), z.select(F.col("dataset_id").alias("b"), F.col("z").alias("zb"))
    return a.join(b, F.col("a") < F.col("b")).select("a", "b", V.micro(E.sketch_distance(F.col("za"), F.col("zb"))).alias("dist_micro"))


@R.add("sketch_drift", f"WITH z AS (SELECT day, avg(e[2]) AS a, avg(e[3]) AS b FROM ({EVS}) GROUP BY 1) SELECT day, coalesce({micro_sql('sqrt((a - lag(a) OVER (ORDER BY day)) ** 2 + (b - lag(b) OVER (ORDER BY day)) ** 2)')}, -1) AS drift_micro FROM z")
def _(s, d):
    sk = S.rollup(daily(s, d), ["day"]).withColumn("dataset_id", F.col("day"))
    z = S.mean(sk)
    w = Window.partitionBy("map_id").orderBy("dataset_id")
    out = z.withColumn("before", F.lag("z").over(w))
    return out.select(F.col("dataset_id").alias("day"), F.coalesce(V.micro(F.sqrt(V.norm2(V.subtract(F.col("z"), F.col("before"))))), F.lit(-1)).alias("drift_micro"))


# moments


def _moment_sql(rows: str, feats: list[str], expr: str = "avg({f})") -> str:
    return " UNION ALL ".join(f"SELECT dataset_id, {j} AS j, {micro_sql(expr.format(f=f))} AS v_micro FROM ({rows}) GROUP BY dataset_id" for j, f in enumerate(feats))


def _long_micro(df: DataFrame, column: str = "v") -> DataFrame:
    return df.select("dataset_id", F.posexplode(column).alias("j", "x")).select("dataset_id", "j", V.micro(F.col("x")).alias("v_micro"))


@R.add("second_moment", _moment_sql(LINE_ROW.format("l_suppkey"), LT3))
def _(s, d):
    return _long_micro(S.second_moment(line3(s, d, "l_suppkey"), 3, "dataset_id"))


@R.add("second_moment_arrow", _moment_sql(LINE_ROW.format("l_suppkey"), LT3))
def _(s, d):
    return _long_micro(S.second_moment(line3(s, d, "l_suppkey"), 3, "dataset_id", engine="arrow"))


_CENT = [f"avg(e[{a}] * e[{b}]) - avg(e[{a}]) * avg(e[{b}])" for a in (1, 2, 3) for b in range(1, a + 1)]


@R.add("second_moment_centred", _moment_sql(LINE_ROW.format("l_returnflag"), _CENT, "{f}"))
def _(s, d):
    return _long_micro(S.second_moment(line3(s, d), 3, "dataset_id", center=True))


def _a3() -> np.ndarray:
    return K.normals("amat", 4, 6)


def _project_sql(a: np.ndarray) -> list[str]:
    return [" + ".join(f"{float(w)!r}::DOUBLE * avg({f})" for w, f in zip(row, LT3)) for row in a]


@R.add("moment_sketch_dense", _moment_sql(LINE_ROW.format("l_returnflag"), _project_sql(_a3()), "{f}"))
def _(s, d):
    return _long_micro(S.moment_sketch(line3(s, d), _a3(), 3, "dataset_id"), "z")


@R.add("moment_sketch_per_row", _moment_sql(LINE_ROW.format("l_returnflag"), _project_sql(_a3()), "{f}"))
def _(s, d):
    return _long_micro(S.moment_sketch(line3(s, d), _a3(), 3, "dataset_id", rewrite="per_row"), "z")


def _w3() -> np.ndarray:
    return K.normals("rank1", 4, 3)


@R.add("moment_sketch_rank1", _moment_sql(LINE_ROW.format("l_returnflag"), [f"({_dot_sql(w)}) * ({_dot_sql(w)})" for w in _w3()]))
def _(s, d):
    return _long_micro(S.mean(S.mean_sketch(line3(s, d), rank_one_map(_w3()), "dataset_id")), "z")


def _verdict(s: SparkSession, rows: list[tuple]) -> DataFrame:
    return s.createDataFrame([(str(a), bool(b)) for a, b in rows], "what string, ok boolean")


def _ok_sql(*names: str) -> str:
    return " UNION ALL ".join(f"SELECT '{n}' AS what, true AS ok" for n in names)


@R.add("random_projection_laws", _ok_sql("chi radius", "unit radius", "rank one rows", "nested prefix"))
def _(s, d):
    from ..operators.maps import directions

    w, u = directions(8, 400, "chi", 1), directions(8, 400, "unit", 1)
    x = np.random.default_rng(0).standard_normal((50, 8))
    a = random_projection(8, 40, "rank_one", "chi", "lt", 3)
    v = S.pack_lt(x.T @ x / 50)
    z = ((x @ directions(8, 40, "chi", 3).T) ** 2).mean(0)
    return _verdict(s, [("chi radius", abs((w**2).sum(1).mean() - 8) < 1), ("unit radius", np.allclose((u**2).sum(1), 1)), ("rank one rows", np.allclose(a @ v, z)), ("nested prefix", np.allclose(a[:7], random_projection(8, 40, "rank_one", "chi", "lt", 3)[:7]))])


# principal components and regression


@R.add("pca_exact", _ok_sql("orthonormal", "full rank error 0", "falling", "least"))
def _(s, d):
    r = S.unpack_lt(np.array(S.second_moment(X.emb64(s, d), 64).first()["v"]), 64)
    v = T.pca_from_moment(r)
    e = T.pca_error_profile(r, v)
    q = np.linalg.qr(np.random.default_rng(0).standard_normal((64, 64)))[0]
    return _verdict(s, [("orthonormal", np.allclose(v.T @ v, np.eye(64))), ("full rank error 0", abs(e[-1]) < 1e-9), ("falling", (np.diff(e) < 1e-12).all()), ("least", (e <= T.pca_error_profile(r, q) + 1e-12).all())])


@R.add("pca_pinv", _ok_sql("exact at full size", "worse when smaller"))
def _(s, d):
    from ..operators.moment_decoders import random_pair

    v = np.array(S.second_moment(line3(s, d, "l_linestatus"), 3, "dataset_id").orderBy("dataset_id").first()["v"])
    r = S.unpack_lt(v, 3)
    ref = T.pca_error_profile(r, T.pca_from_moment(r))[:2].mean()
    errs = [T.pca_error_profile(r, T.pca_from_moment(random_pair(v, 3, m, "chi", 1).r))[:2].mean() for m in (6, 2)]
    return _verdict(s, [("exact at full size", abs(errs[0] / ref - 1) < 1e-6), ("worse when smaller", errs[1] >= errs[0] - 1e-12)])


@R.add("moment_decoders", _ok_sql("pinv", "gradient", "robust", "accelerated", "expgrad"))
def _(s, d):
    from ..operators import moment_decoders as D

    x = planted_lowrank(2, 8, 500)
    v = S.pack_lt(x.T @ x / 500)
    r = S.unpack_lt(v, 8)
    full = random_projection(8, 60, "rank_one", "chi", "lt", 2)
    z = full @ v
    gap = lambda got: np.linalg.norm(got.r - r) / np.linalg.norm(r)
    return _verdict(s, [("pinv", gap(D.decode_pinv(z, full, 8)) < 1e-8), ("gradient", gap(D.decode_gradient(z, full, 8, 20000)) < 0.05), ("robust", gap(D.decode_robust(z, full, 8, 3, 3000)) < 0.1), ("accelerated", gap(D.decode_accelerated(z, full, 8, 3000)) < 0.05), ("expgrad", gap(D.decode_expgrad(z, full, 8, 2000)) < 0.2)])


LIN = "SELECT CAST(l_returnflag AS VARCHAR) AS dataset_id, l_extendedprice / 1000 AS y, l_quantity / 50 AS a, l_discount / 0.1 AS b FROM lineitem"


def lin_rows(s: SparkSession, d: str) -> DataFrame:
    x = F.array(F.col("l_extendedprice") / 1000, F.col("l_quantity") / 50, F.col("l_discount") / 0.1)
    return t(s, d, "lineitem").select(F.col("l_returnflag").alias("dataset_id"), x.alias("features"))


def _ridge(s, d, keep, lam):
    rows = lin_rows(s, d)
    if keep == 2:
        rows = rows.withColumn("features", F.slice("features", 1, 2))
    out = []
    for r in S.second_moment(rows, keep, "dataset_id").collect():
        th = T.ridge_from_moment(S.unpack_lt(np.array(r.v), keep), 1, lam)
        out += [(r.dataset_id, j, int(np.floor(th[0, j] * 1e4 + 0.5))) for j in range(keep - 1)]
    return s.createDataFrame(out, "dataset_id string, j int, coef_e4 long")


@R.add("ridge_closed_form_1", f"SELECT dataset_id, 0 AS j, CAST(floor(avg(a * y) / (avg(a * a) + 0.01) * 1e4 + 0.5) AS BIGINT) AS coef_e4 FROM ({LIN}) GROUP BY 1")
def _(s, d):
    return _ridge(s, d, 2, 0.01)


_RC = "SELECT dataset_id, avg(a * a) + {lam} AS aa, avg(a * b) AS ab, avg(b * b) + {lam} AS bb, avg(a * y) AS ay, avg(b * y) AS b_y FROM ({lin}) GROUP BY 1"
_R2 = "WITH m AS ({c}) SELECT dataset_id, 0 AS j, CAST(floor((bb * ay - ab * b_y) / (aa * bb - ab * ab) * 1e4 + 0.5) AS BIGINT) AS coef_e4 FROM m UNION ALL SELECT dataset_id, 1, CAST(floor((aa * b_y - ab * ay) / (aa * bb - ab * ab) * 1e4 + 0.5) AS BIGINT) FROM m"


@R.add("ridge_closed_form_2", _R2.format(c=_RC.format(lam=0.1, lin=LIN)))
def _(s, d):
    return _ridge(s, d, 3, 0.1)


@R.add("ols", _R2.format(c=_RC.format(lam=0, lin=LIN)))
def _(s, d):
    return _ridge(s, d, 3, 0.0)


@R.add("ridge_scales", _ok_sql("sum with n lambda is mean with lambda", "minimises the printed sum"))
def _(s, d):
    x, _th = planted_linear(3, 400)
    r = x.T @ x / 400
    a, b = T.ridge_from_moment(r, 1, 400 * 0.2, "sum", 400), T.ridge_from_moment(r, 1, 0.2, "mean")
    loss = lambda th: ((x[:, :1] - x[:, 1:] @ th.T) ** 2).sum() + 400 * 0.2 * (th**2).sum()
    rng = np.random.default_rng(0)
    return _verdict(s, [("sum with n lambda is mean with lambda", np.allclose(a, b)), ("minimises the printed sum", all(loss(a) <= loss(a + 0.01 * rng.standard_normal(a.shape)) for _ in range(50)))])


@R.add("ridge_ml_crosscheck", _ok_sql("solver of the library agrees"))
def _(s, d):
    from pyspark.ml.functions import array_to_vector
    from pyspark.ml.regression import LinearRegression

    rows = lin_rows(s, d).where("dataset_id = 'A'")
    df = rows.select(F.get("features", F.lit(0)).alias("label"), array_to_vector(F.slice("features", 2, 2)).alias("features"))
    lam = 0.1
    sd = df.agg(F.stddev_samp("label")).first()[0]
    m = LinearRegression(solver="normal", fitIntercept=False, standardization=False, regParam=lam * sd).fit(df)
    th = T.ridge_from_moment(S.unpack_lt(np.array(S.second_moment(rows, 3).first()["v"]), 3), 1, lam)
    # the library scales by the target's deviation
    return _verdict(s, [("solver of the library agrees", np.abs(m.coefficients.toArray() - th[0]).max() < 0.02 * np.abs(th).max())])


@R.add("pca_learned", _ok_sql("better than random at equal size"))
def _(s, d):
    from ..workloads.moments import learned_against_random

    wins = learned_against_random(s, d)
    return _verdict(s, [("better than random at equal size", all(a < b for a, b in wins))])


@R.add("ridge_learned", _ok_sql("better than random at equal size"))
def _(s, d):
    from ..workloads.moments import learned_against_random

    wins = learned_against_random(s, d, task="ridge")
    return _verdict(s, [("better than random at equal size", all(a < b for a, b in wins))])


@R.add("pca_transform_rows", f"SELECT vec_id, CAST(floor((e[1] * 0.6 + e[2] * 0.8) * 1e6 + 0.4637) AS BIGINT) AS p, CAST(floor((e[1] * 0.6 + e[2] * 0.8) * 0.6 * 1e6 + 0.4637) AS BIGINT) AS back FROM {EMB}")
def _(s, d):
    v = np.array([[0.6], [0.8]])
    rows = t(s, d, "embeddings").select("vec_id", F.slice(V.as_doubles(F.col("embedding")), 1, 2).alias("features"))
    out = T.pca_reconstruct(T.pca_transform(rows, v), v)
    return out.select("vec_id", V.micro(F.get("projected", F.lit(0))).alias("p"), V.micro(F.get("reconstructed", F.lit(0))).alias("back"))


@R.add("ridge_predict_rows", "SELECT l_orderkey, l_linenumber, l_partkey, CAST(floor((l_quantity / 50 * 40.0 + l_discount / 0.1 * 2.5) * 1e4 + 0.5) AS BIGINT) AS y FROM lineitem")
def _(s, d):
    x = F.array(F.col("l_extendedprice") / 1000, F.col("l_quantity") / 50, F.col("l_discount") / 0.1)
    rows = t(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", x.alias("features"))
    return T.ridge_predict(rows, np.array([[40.0, 2.5]])).select("l_orderkey", "l_linenumber", "l_partkey", F.floor(F.col("predicted") * 1e4 + 0.5).cast("bigint").alias("y"))


@R.add("pca_error_rows", f"SELECT CAST(label AS VARCHAR) AS dataset_id, {micro_sql('avg(e[1] * e[1] + e[2] * e[2] - (e[1] * 0.6 + e[2] * 0.8) ** 2)')} AS value_micro FROM {EMB} GROUP BY label")
def _(s, d):
    return T.pca_loss(emb_d(s, d, 2), np.array([[0.6], [0.8]]), "dataset_id").select("dataset_id", V.micro(F.col("error")).alias("value_micro"))


@R.add("ridge_mse_rows", f"SELECT dataset_id, {micro_sql('avg((y - 40.0 * a - 2.5 * b) ** 2)')} AS value_micro FROM ({LIN}) GROUP BY 1")
def _(s, d):
    return T.ridge_loss(lin_rows(s, d), np.array([[40.0, 2.5]]), 0.0, "dataset_id").select("dataset_id", V.micro(F.col("mse")).alias("value_micro"))


@R.add("ridge_loss_sum", f"SELECT dataset_id, CAST(floor((sum((y - 40.0 * a - 2.5 * b) ** 2) + 0.5 * (40.0 * 40.0 + 2.5 * 2.5)) * 1e2 + 0.5) AS BIGINT) AS value FROM ({LIN}) GROUP BY 1")
def _(s, d):
    return T.ridge_loss(lin_rows(s, d), np.array([[40.0, 2.5]]), 0.5, "dataset_id").select("dataset_id", F.floor(F.col("loss") * 1e2 + 0.5).cast("bigint").alias("value"))


@R.add("errors_from_moments", _ok_sql("pca", "ridge"))
def _(s, d):
    rows = lin_rows(s, d).where("dataset_id = 'R'")
    r = S.unpack_lt(np.array(S.second_moment(rows, 3).first()["v"]), 3)
    v, th = T.pca_from_moment(r, 1), T.ridge_from_moment(r, 1, 0.1)
    a, b = T.pca_loss(rows, v).first()["error"], T.ridge_loss(rows, th, 0.1).first()["mse"]
    return _verdict(s, [("pca", abs(a - T.pca_error(r, v)) < 1e-6 * abs(a)), ("ridge", abs(b - T.ridge_mse(r, th, 1)) < 1e-6 * abs(b))])


# k-means


@R.add("fourier_sketch", _fourier_sql())
def _(s, d):
    return S.long_form(_emb_fourier(s, d, "auto"))


@R.add("fourier_adapted")
def _(s, d):
    rows = X.projected_documents(s, d, 2)
    return S.long_form(S.mean_sketch(rows, fourier_map(2, 32, 0.3, "adapted", 1), "dataset_id"))


@R.add("nystrom_sketch")
def _(s, d):
    rows = X.projected_documents(s, d, 2)
    marks = np.array([r.features for r in rows.orderBy(F.md5(F.col("row_key").cast("binary")), "row_key").limit(12).collect()])
    return S.long_form(S.mean_sketch(rows, nystrom_map(marks, 8.0), "dataset_id"))


def five(s, d, width: int = 4) -> np.ndarray:
    return np.array([r.features for r in emb_d(s, d, width).where("cast(row_key as int) < 5").orderBy(F.col("row_key").cast("int")).collect()])


CENT4 = f"(SELECT vec_id AS cid, e[1:4] AS c FROM {EMB} WHERE vec_id < 5)"
D4 = "list_sum(list_transform(list_zip(e[1:4], c), lambda p: (p[1] - p[2]) * (p[1] - p[2])))"
NEAR = f"(SELECT vec_id, label, e, min(d2) AS d2, CAST(min_by(cid, struct_pack(d := d2, c := cid)) AS INTEGER) AS cid FROM (SELECT vec_id, label, e, cid, {D4} AS d2 FROM {EMB}, {CENT4}) GROUP BY ALL)".replace("GROUP BY ALL", "GROUP BY vec_id, label, e")


@R.add("kmeans_assign", f"SELECT CAST(vec_id AS VARCHAR) AS row_key, cid, {micro_sql('d2')} AS d2_micro FROM {NEAR}")
def _(s, d):
    return T.assign(emb_d(s, d, 4), five(s, d)).select("row_key", "cid", V.micro(F.col("dist2")).alias("d2_micro"))


@R.add("kmeans_mse", f"SELECT CAST(label AS VARCHAR) AS dataset_id, {micro_sql('avg(d2)')} AS value_micro FROM {NEAR} GROUP BY label")
def _(s, d):
    return T.kmeans_loss(emb_d(s, d, 4), five(s, d), "dataset_id").select("dataset_id", V.micro(F.col("mse")).alias("value_micro"))


@R.add("kmeans_lloyd_step", " UNION ALL ".join(f"SELECT cid, count(*) AS n, {j} AS j, {micro_sql(f'avg(e[{j + 1}])')} AS v_micro FROM {NEAR} GROUP BY cid" for j in range(4)))
def _(s, d):
    step = lloyd_step(emb_d(s, d, 4), five(s, d))
    return step.select("cid", "n", F.posexplode("center").alias("j", "v")).select("cid", "n", "j", V.micro(F.col("v")).alias("v_micro"))


@R.add("kmeans_greedy", _ok_sql("with replacement", "without replacement", "residual falls"))
def _(s, d):
    x, c = planted_mixture(3, 2, 3000)
    fm = fourier_map(2, 120, 0.12, "gaussian", 5)
    z = fm.batch(x).mean(0)
    ref = kmeans_mse_local(x, lloyd_local(x, 3, starts=3))
    a, b = decode_greedy(z, fm, 3), decode_greedy(z, fm, 3, replace=False)
    return _verdict(s, [("with replacement", kmeans_mse_local(x, a.theta) < 1.2 * ref), ("without replacement", kmeans_mse_local(x, b.theta) < 2 * ref), ("residual falls", a.loss < float(z @ z))])


@R.add("kmeans_unrolled", _ok_sql("adam", "sgd falls", "momentum", "recurrence is the loop"))
def _(s, d):
    from ..operators.kmeans import as_recurrence, jacobian_product, sketch_of_centroids

    x, _c = planted_mixture(3, 2, 3000)
    fm = fourier_map(2, 60, 0.4, "gaussian", 5)
    z = fm.batch(x).mean(0)
    ref = kmeans_mse_local(x, lloyd_local(x, 3, starts=3))
    trace: list[float] = []
    adam = decode_unrolled(z, fm, 3, 300, starts=8, seed=1, weighting="nnls")
    decode_unrolled(z, fm, 3, 100, 0.001, "sgd", starts=1, trace=trace, box=None)
    mom = decode_unrolled(z, fm, 3, 300, 0.002, "momentum", starts=8, weighting="nnls")
    th = np.array([[0.2, 0.3], [0.6, 0.5], [0.9, 0.1]])
    loop = th
    for _ in range(5):
        loop = loop - 0.01 * 2 / 3 * jacobian_product(fm, loop, sketch_of_centroids(loop, fm) - z)
    return _verdict(s, [("adam", kmeans_mse_local(x, adam.theta) < 3 * ref), ("sgd falls", (np.diff(trace) <= 1e-12).all()), ("momentum", mom.loss < float(z @ z)), ("recurrence is the loop", np.allclose(loop, as_recurrence(z, fm, th, 5, 0.01)))])


@R.add("kmeans_amp")
def _(s, d):
    out = []
    for seed in range(4):
        x, _c = planted_mixture(2, 2, 1500, seed)
        fm = fourier_map(2, 80, 0.3, "gaussian", seed)
        got = decode_message_passing(fm.batch(x).mean(0), fm, 2, seed=seed)
        out.append((seed, bool(got.failed), float(kmeans_mse_local(x, got.theta)) if np.isfinite(got.theta).all() else None))
    return s.createDataFrame(out, "seed int, failed boolean, mse double")


@R.add("gmm_sketch", _ok_sql("means", "weights sum to 1"))
def _(s, d):
    x, c = planted_mixture(2, 2, 3000, 1)
    fm = fourier_map(2, 100, 0.15, "gaussian", 3)
    g = gmm_from_sketch(fm.batch(x).mean(0), fm, 2)
    return _verdict(s, [("means", T.matched_centroids(c, g.means)[1] ** 0.5 < 0.1), ("weights sum to 1", abs(g.weights.sum() - 1) < 1e-9)])


@R.add("gmm_em_baseline", _ok_sql("expectation maximisation finds the means"))
def _(s, d):
    x, c = planted_mixture(2, 2, 600, 1)
    m = B.gaussian_mixture(s.createDataFrame([(r.tolist(),) for r in x], "features array<double>"), 2)
    got = np.array([r.mean.toArray() for r in m.gaussiansDF.collect()])
    return _verdict(s, [("expectation maximisation finds the means", T.matched_centroids(c, got)[1] ** 0.5 < 0.2)])


@R.add("kmeans_meta_losses", _ok_sql("min gradient", "matched gradient"))
def _(s, d):
    from ..meta.train import kmeans_meta_loss

    x, c = planted_mixture(3, 2, 200)
    th = c.ravel() + 0.05
    out = []
    for kind in ("min", "matched"):
        f = kmeans_meta_loss(kind, 3, 2, c)
        g = f(th, x)[1]
        num = np.array([(f(th + e, x)[0] - f(th - e, x)[0]) / 2e-6 for e in np.eye(6) * 1e-6])
        out.append((f"{kind} gradient", np.allclose(g, num, atol=1e-4)))
    return _verdict(s, out)


# baselines


def _line_key(s, d):
    r = t(s, d, "lineitem").where("l_returnflag = 'A'")
    key = F.concat_ws("-", "l_orderkey", "l_linenumber", "l_partkey", F.floor(F.col("l_extendedprice") * 100).cast("bigint"))
    x = F.array(F.col("l_quantity") / 50.0, F.col("l_discount") / 0.1)
    return r.select("l_returnflag", F.lit("A").alias("dataset_id"), key.alias("row_key"), x.alias("features"))


_KEY = "concat_ws('-', l_orderkey, l_linenumber, l_partkey, CAST(floor(l_extendedprice * 100) AS BIGINT))"


@R.add("rowsketch_sparse", f"WITH r AS (SELECT CASE WHEN {K.uniform_sql(chr(39) + 'sign0-' + chr(39) + ' || ' + _KEY)} < 0.5 THEN -1.0 ELSE 1.0 END AS g, CAST(floor({K.uniform_sql(chr(39) + 'bucket0-' + chr(39) + ' || ' + _KEY)} * 16) AS INTEGER) AS bucket, l_quantity / 50.0 AS q FROM lineitem WHERE l_returnflag = 'A') SELECT bucket, count(*) AS n, CAST(floor(sum(g * q) * 1e4 + 0.5) AS BIGINT) AS v FROM r GROUP BY bucket")
def _(s, d):
    return B.rowsketch_sparse(_line_key(s, d), 16, 2).select("bucket", "n", F.floor(F.get("row", F.lit(0)) * 1e4 + 0.5).cast("bigint").alias("v"))


@R.add("rowsketch_gaussian")
def _(s, d):
    return B.rowsketch_gaussian(_line_key(s, d), 8, 2).select("dataset_id", "i", "n", F.posexplode("row").alias("j", "v")).select("dataset_id", "i", "j", "n", V.micro(F.col("v")).alias("v_micro"))


@R.add("rowsample_topmd5", "SELECT row_key FROM (SELECT concat_ws('-', o_custkey, o_orderkey) AS row_key, row_number() OVER (PARTITION BY o_orderstatus ORDER BY md5('sample0-' || concat_ws('-', o_custkey, o_orderkey)), concat_ws('-', o_custkey, o_orderkey)) AS r FROM orders) WHERE r <= 25")
def _(s, d):
    rows = t(s, d, "orders").select(F.col("o_orderstatus").alias("dataset_id"), F.concat_ws("-", "o_custkey", "o_orderkey").alias("row_key"))
    return B.rowsample(rows, 25).select("row_key")


@R.add("supervised_gradient", _ok_sql("full gradients reach the closed form", "stochastic gradients come near"))
def _(s, d):
    x, _th = planted_linear(2, 600)
    rows = s.createDataFrame([(r.tolist(),) for r in x], "features array<double>")
    ref = T.ridge_from_moment(x.T @ x / 600, 1, 0.0)
    return _verdict(s, [("full gradients reach the closed form", np.abs(B.distributed_gradient(rows, 1, 2, epochs=20, rate=1.5) - ref).max() < 0.05), ("stochastic gradients come near", np.abs(B.supervised_sgd(x, 1, epochs=60, rate=0.3) - ref).max() < 0.1)])


@R.add("budget_rule", "SELECT m, greatest(1, m // 8) AS s FROM (VALUES (1), (8), (20), (36)) v(m)")
def _(s, d):
    return s.createDataFrame([(m, B.rows_for_budget(m, 8)) for m in (1, 8, 20, 36)], "m int, s int")


# privacy and bounds


@R.add("clip_norm", f"SELECT vec_id, {micro_sql('e[1] * CASE WHEN n > 0.2 THEN 0.2 / n ELSE 1 END')} AS v_micro FROM (SELECT vec_id, e, sqrt(e[1] * e[1] + e[2] * e[2]) AS n FROM {EMB})")
def _(s, d):
    v = V.clip_norm(F.slice(V.as_doubles(F.col("embedding")), 1, 2), 0.2)
    return t(s, d, "embeddings").select("vec_id", V.micro(F.get(v, F.lit(0))).alias("v_micro"))


@R.add("max_feature_norm", f"SELECT CAST(label AS VARCHAR) AS dataset_id, {micro_sql('max(sqrt(e[1] * e[1] + e[2] * e[2]))')} AS v_micro FROM {EMB} GROUP BY label")
def _(s, d):
    return P.max_feature_norm(emb_d(s, d, 2), identity_map(2), "dataset_id").select("dataset_id", V.micro(F.col("max_norm")).alias("v_micro"))


@R.add("clip_fraction", f"SELECT CAST(label AS VARCHAR) AS dataset_id, {micro_sql('avg(CASE WHEN sqrt(e[1] * e[1] + e[2] * e[2]) > 0.2 THEN 1.0 ELSE 0.0 END)')} AS v_micro FROM {EMB} GROUP BY label")
def _(s, d):
    return P.clip_fraction(emb_d(s, d, 2), identity_map(2), 0.2, "dataset_id").select("dataset_id", V.micro(F.col("fraction")).alias("v_micro"))


@R.add("clamp_sketch", f"SELECT CAST(label AS VARCHAR) AS dataset_id, {micro_sql('least(greatest(avg(e[1]), -0.01), 0.01)')} AS v_micro FROM {EMB} GROUP BY label")
def _(s, d):
    z = S.mean(S.mean_sketch(emb_d(s, d, 1), identity_map(1), "dataset_id"))
    c = V.clamp(F.col("z"), F.array(F.lit(-0.01)), F.array(F.lit(0.01)))
    return z.select("dataset_id", V.micro(F.get(c, F.lit(0))).alias("v_micro"))


@R.add("clipped_sketch", f"SELECT CAST(label AS VARCHAR) AS dataset_id, CAST(sum({fx_sql('e[1] * CASE WHEN n > 0.2 THEN 0.2 / n ELSE 1 END')}) AS BIGINT) AS acc_fx FROM (SELECT label, e, sqrt(e[1] * e[1] + e[2] * e[2]) AS n FROM {EMB}) GROUP BY label")
def _(s, d):
    return S.long_form(S.mean_sketch(emb_d(s, d, 2), identity_map(2), "dataset_id", clip=0.2)).where("j = 0").select("dataset_id", "acc_fx")


@R.add("dp_release", _ok_sql("noise has its variance", "large eps gives the clipped mean", "clamped", "ledger adds up", "analytic is below classic"))
def _(s, d):
    sk = S.mean_sketch(emb_d(s, d, 2), identity_map(2), None, clip=0.3).first()
    acc, n = np.array(sk.acc), sk.n
    noise = P.calibrate(1.0, 1e-5, 0.3)
    rng = np.random.default_rng(1)
    draws = np.array([acc + rng.normal(0, noise.sigma_sum, 2) - acc for _ in range(4000)])
    led = P.Ledger()
    far = P.privatize(acc, n, 1e6, 0.5, 0.3, seed=1, ledger=led, version="v")
    near = P.privatize(acc, n, 0.01, 0.01, 0.3, -0.3, 0.3, seed=1, ledger=led, version="v")
    return _verdict(s, [("noise has its variance", abs(draws.std() / noise.sigma_sum - 1) < 0.05), ("large eps gives the clipped mean", np.abs(far.z - acc / n).max() < 1e-3), ("clamped", np.abs(near.clamped).max() <= 0.3), ("ledger adds up", abs(led.spent("v")[0] - 1e6 - 0.01) < 1e-6), ("analytic is below classic", P.gaussian_sigma(0.5, 1e-5, 1.0) < P.gaussian_sigma(0.5, 1e-5, 1.0, "classic"))])


@R.add("dp_convergence", _ok_sql("falls with the number of rows", "limit is the clipped mean"))
def _(s, d):
    from ..workloads.privacy import convergence

    rows = convergence(s, d)
    slope = np.polyfit(np.log([r[0] for r in rows]), np.log([r[1] for r in rows]), 1)[0]
    return _verdict(s, [("falls with the number of rows", -1.3 < slope < -0.7), ("limit is the clipped mean", rows[-1][1] < rows[0][1])])


@R.add("bound_replace_one", "SELECT CAST(label AS VARCHAR) AS dataset_id, count(*) AS n, count(*) > 1 AS ok FROM embeddings GROUP BY 1")
def _(s, d):
    """Every row of every label. Taking one out moves the mean by |z - mean| / (n - 1); replacing it moves it by at most twice the largest |z| over n. ok: both are within 2 * bound / n."""
    fm = fourier_map(64, 32, 1.0, "gaussian", 1)
    rows = X.emb64(s, d)
    mean = S.mean(S.mean_sketch(rows, fm, "dataset_id", "arrow")).select("dataset_id", "n", F.col("z").alias("mu"))

    def run(pdfs):
        for pdf in pdfs:
            z = fm.batch(np.array(pdf["features"].tolist(), dtype=float).reshape(len(pdf), 64))
            mu = np.array(pdf["mu"].tolist(), dtype=float).reshape(z.shape)
            yield pd.DataFrame({"dataset_id": pdf["dataset_id"], "n": pdf["n"], "far": np.linalg.norm(z - mu, axis=1), "long": np.linalg.norm(z, axis=1)})

    each = rows.select("dataset_id", "features").join(mean, "dataset_id").mapInPandas(run, "dataset_id string, n long, far double, long double")
    gap = each.groupBy("dataset_id", "n").agg(F.max("far").alias("far"), F.max("long").alias("long"))
    n = F.col("n")
    return gap.select("dataset_id", "n", ((n > 1) & (F.col("far") / (n - 1) <= 2 * fm.bound / n + 1e-9) & (F.col("long") <= fm.bound + 1e-9)).alias("ok"))


@R.add("bound_generalization", _ok_sql("printed bound holds", "strict is above printed", "lipschitz covers sampled quotients"))
def _(s, d):
    from ..meta.layers import residual_mlp
    from ..workloads.privacy import bound_against_gap

    got = bound_against_gap(s, d).agg(F.bool_and(F.col("test") <= F.col("printed")).alias("holds"), F.bool_and(F.col("strict") >= F.col("printed")).alias("above")).first()
    net = residual_mlp(4, 3, "bn_relu", 1, 8)
    rng = np.random.default_rng(0)
    a, b = rng.standard_normal((200, 4)), rng.standard_normal((200, 4))
    q = np.linalg.norm(net.forward(a) - net.forward(b), axis=1) / np.linalg.norm(a - b, axis=1)
    return _verdict(s, [("printed bound holds", bool(got.holds)), ("strict is above printed", bool(got.above)), ("lipschitz covers sampled quotients", q.max() <= net.lipschitz() + 1e-9)])


# measures


@R.add("moment_l1", f"WITH m AS (SELECT dataset_id, avg(e[1] * e[1]) AS a, avg(e[2] * e[1]) AS b FROM ({LINE_ROW.format('l_returnflag')}) GROUP BY 1) SELECT dataset_id, {micro_sql('abs(a - 0.3) + abs(b - 0.2)')} AS value_micro FROM m")
def _(s, d):
    m = S.second_moment(line3(s, d), 3, "dataset_id")
    return m.select("dataset_id", V.micro(E.moment_l1(F.slice("v", 1, 2), V.literal([0.3, 0.2]))).alias("value_micro"))


@R.add("sketch_distance", f"SELECT CAST(label AS VARCHAR) AS dataset_id, {micro_sql('(avg(e[1]) - 0.1) ** 2 + (avg(e[2]) + 0.1) ** 2')} AS value_micro FROM {EMB} GROUP BY label")
def _(s, d):
    z = S.mean(S.mean_sketch(emb_d(s, d, 2), identity_map(2), "dataset_id"))
    return z.select("dataset_id", V.micro(E.sketch_distance(F.col("z"), V.literal([0.1, -0.1]))).alias("value_micro"))


@R.add("sketch_pct", "SELECT m, CAST(floor(100.0 * m / 19306 * 1e6 + 0.4637) AS BIGINT) AS pct_micro FROM (VALUES (2), (193), (1931), (19306)) v(m)")
def _(s, d):
    return s.createDataFrame([(m, int(np.floor(E.sketch_pct(m, 196) * 1e6 + 0.4637))) for m in (2, 193, 1931, 19306)], "m int, pct_micro long")


@R.add("compression_ratio", f"SELECT CAST(label AS VARCHAR) AS dataset_id, count(*) AS n, count(*) * 64 AS raw_numbers, CAST(32 AS BIGINT) AS sketch_numbers, count(*) * 64 / 32.0::DOUBLE AS ratio FROM {EMB} GROUP BY label")
def _(s, d):
    return E.compression_ratio(X.emb64(s, d), 32, 64, "dataset_id")


_BA = "sum(CASE WHEN embedding[j] > 0 AND embedding[j] > 0.05 THEN 1.0 ELSE 0 END) / sum(CASE WHEN embedding[j] > 0 THEN 1.0 ELSE 0 END)"
_BN = "sum(CASE WHEN embedding[j] <= 0 AND embedding[j] <= 0.05 THEN 1.0 ELSE 0 END) / sum(CASE WHEN embedding[j] <= 0 THEN 1.0 ELSE 0 END)"


@R.add("balanced_accuracy", f"SELECT CAST(label AS VARCHAR) AS dataset_id, {micro_sql(f'({_BA} + {_BN}) / 2')} AS ba_micro FROM embeddings, range(1, 65) r(j) GROUP BY label")
def _(s, d):
    e = t(s, d, "embeddings").select(F.col("label"), F.transform("embedding", lambda x: (x > 0).cast("int")).alias("truth"), F.transform("embedding", lambda x: (x > F.lit(0.05).cast("double")).cast("int")).alias("pred"))
    return E.balanced_accuracy(e, "truth", "pred", "label").select("dataset_id", V.micro(F.col("ba")).alias("ba_micro"))


@R.add("rank_models", f"WITH v AS (SELECT CAST(n_regionkey AS VARCHAR) AS test_set, n_name AS model, CAST(n_nationkey * 7 % 11 AS DOUBLE) AS value FROM nation) SELECT test_set, model, value, CAST(dense_rank() OVER (PARTITION BY test_set ORDER BY value DESC) AS INTEGER) AS rank FROM v")
def _(s, d):
    v = t(s, d, "nation").select(F.col("n_regionkey").cast("string").alias("test_set"), F.col("n_name").alias("model"), F.pmod(F.col("n_nationkey") * 7, F.lit(11)).cast("double").alias("value"))
    return E.rank_models(v)


@R.add("row_average", "SELECT n_name AS model, avg(CAST(n_nationkey AS DOUBLE)) AS average, count(*) AS n FROM nation GROUP BY 1")
def _(s, d):
    return E.row_average(t(s, d, "nation").select(F.col("n_name").alias("model"), F.col("n_nationkey").cast("double").alias("value")))


@R.add("lre_measure", "SELECT k, CAST(floor(log10(1.0 + k / 10.0) * 1e6 + 0.4637) AS BIGINT) AS v FROM range(6) r(k)")
def _(s, d):
    return s.createDataFrame([(k, int(np.floor(T.lre(1.0 + k / 10.0, 1.0) * 1e6 + 0.4637))) for k in range(6)], "k long, v long")


@R.add("loss_catalogue", _ok_sql("moment sketch", "moment l1", "centroid sketch", "autoencoder has none", "autoencoder gradient"))
def _(s, d):
    from ..workloads.autoencoder import gradient_check

    x, c = planted_mixture(2, 2, 400)
    fm = fourier_map(2, 20, 0.4, "gaussian", 1)
    r = x.T @ x / 400
    a = random_projection(2, 3, "rank_one", "chi", "lt", 1)
    try:
        T.autoencoder_sketch_loss()
        none = False
    except T.NoSurrogateLoss:
        none = True
    z = fm.batch(x).mean(0)
    return _verdict(s, [("moment sketch", T.moment_sketch_loss(r, a, a @ S.pack_lt(r)) < 1e-18), ("moment l1", T.moment_l1(r, r) == 0), ("centroid sketch", T.kmeans_sketch_loss(c, z, fm) < T.kmeans_sketch_loss(c + 0.3, z, fm)), ("autoencoder has none", none), ("autoencoder gradient", gradient_check())])


@R.add("private_moment", _ok_sql("noise falls with eps"))
def _(s, d):
    x = planted_lowrank(2, 6, 800)
    x = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1)
    r = x.T @ x
    err = [np.median([np.linalg.norm(P.private_moment(r, 800, e, 1e-5, 1.0, seed=k) - r / 800) for k in range(15)]) for e in (0.1, 1, 10)]
    return _verdict(s, [("noise falls with eps", err[0] > err[1] > err[2])])


# surfaces for users


@R.add("udf_feature_map", f"SELECT vec_id, {micro_sql(f'cos({_dot_sql(omega8()[0])})')} AS v_micro FROM {EMB}")
def _(s, d):
    from ..functions.udfs import feature_map_udf

    fm = FeatureMap("fourier", 4, 8, arrays={"omega": omega8()})
    f = feature_map_udf(fm)
    return t(s, d, "embeddings").select("vec_id", V.micro(F.get(f(F.slice(V.as_doubles(F.col("embedding")), 1, 4)), F.lit(0))).alias("v_micro"))


@R.add("udaf_sketch", f"SELECT label, {micro_sql(f'avg(cos({_dot_sql(omega8()[0])}))')} AS v_micro FROM {EMB} GROUP BY label")
def _(s, d):
    from ..functions.udfs import sketch_agg

    fm = FeatureMap("fourier", 4, 8, arrays={"omega": omega8()})
    e = t(s, d, "embeddings").select("label", F.slice(V.as_doubles(F.col("embedding")), 1, 4).alias("v"))
    return e.groupBy("label").agg(sketch_agg(F.col("v"), fm).alias("z")).select("label", V.micro(F.get("z", F.lit(0))).alias("v_micro"))


@R.add("udtf_decode", "SELECT CAST(k AS INTEGER) AS k, true AS ok FROM range(2) r(k)")
def _(s, d):
    from ..functions.udfs import register_all

    x, c = planted_mixture(2, 2, 2000, 1)
    fm = fourier_map(2, 60, 0.3, "gaussian", 4)
    register_all(s, {"planted": fm})
    z = ",".join(f"{v!r}D" for v in fm.batch(x).mean(0).tolist())
    got = s.sql(f"SELECT * FROM decode_kmeans('planted', array({z}), 2)")
    near = F.array_min(F.array(*[V.norm2(V.subtract(F.col("center"), V.literal(p))) for p in c]))
    return got.select(F.col("cid").alias("k"), (near < 0.02).alias("ok"))


@R.add("grouped_decode", "SELECT CAST(label AS VARCHAR) AS dataset_id, true AS ok FROM embeddings GROUP BY label")
def _(s, d):
    from ..functions.udfs import decode_all

    fm = FeatureMap("fourier", 4, 8, arrays={"omega": omega8()})
    got = decode_all(_emb_fourier(s, d, "auto"), fm, 1, box=(-1.0, 1.0))
    return got.groupBy("dataset_id").agg((F.count(F.lit(1)) == 1).alias("ok"))


@R.add("planted_source", "SELECT 'planted' || i AS dataset_id, CAST(200 AS BIGINT) AS n FROM range(4) r(i)")
def _(s, d):
    from ..sources.planted import register

    register(s)
    return s.read.format("sketchfit_planted").load().groupBy("dataset_id").agg(F.count(F.lit(1)).alias("n"))


@R.add("plan_shape", _ok_sql("one scan", "sums before the exchange", "no rows in the exchange"))
def _(s, d):
    sk = S.mean_sketch(line3(s, d), outer_lt_map(3), "dataset_id")
    plan = sk._jdf.queryExecution().executedPlan().toString()
    arrow = S.mean_sketch(line3(s, d), outer_lt_map(3), "dataset_id", "arrow")._jdf.queryExecution().executedPlan().toString()
    return _verdict(s, [("one scan", plan.count("FileScan") == 1), ("sums before the exchange", "partial_sum" in plan), ("no rows in the exchange", arrow.count("FileScan") <= 2 and "partial_sum" in arrow)])


@R.add(
    "pilot_scale",
    f"""WITH r AS (SELECT label, e, row_number() OVER (PARTITION BY label ORDER BY md5(CAST(vec_id AS VARCHAR)), CAST(vec_id AS VARCHAR)) AS k FROM {EMB}),
    p AS (SELECT a.label, sqrt((a.e[1] - b.e[1]) ** 2 + (a.e[2] - b.e[2]) ** 2 + (a.e[3] - b.e[3]) ** 2 + (a.e[4] - b.e[4]) ** 2) AS far FROM r a JOIN r b ON a.label = b.label AND a.k < b.k AND b.k <= 64),
    s AS (SELECT label, median(far) AS w FROM p GROUP BY label)
    SELECT CAST(l.label AS VARCHAR) AS dataset_id, {micro_sql('CASE WHEN s.w > 0 THEN s.w ELSE 1.0 END')} AS v_micro FROM (SELECT DISTINCT label FROM embeddings) l LEFT JOIN s USING (label)""",
)
def _(s, d):
    got = s.createDataFrame(sorted(pilot_scale(emb_d(s, d, 4), 64).items()), "dataset_id string, w double")
    return got.select("dataset_id", V.micro(F.col("w")).alias("v_micro"))


@R.add("sketch_numbers", "SELECT * FROM (VALUES ('fourier', CAST(8 AS BIGINT)), ('nystrom', CAST(5 + 5 * 4 AS BIGINT)), ('outer', CAST(4 * 5 / 2 AS BIGINT))) v(method, numbers)")
def _(s, d):
    marks = np.array([r.features for r in emb_d(s, d, 4).orderBy(F.col("row_key").cast("long")).limit(5).collect()])
    maps = {"fourier": fourier_map(4, 8, 0.5, "gaussian", 1), "nystrom": nystrom_map(marks, 1.0), "outer": outer_lt_map(4)}
    return s.createDataFrame([(name, E.sketch_numbers(fm)) for name, fm in maps.items()], "method string, numbers long")


@R.add("training_log")
def _(s, d):
    from ..meta.train import bank_of, split_ids, train_moment_pair, training_log

    bank = {r.dataset_id: (r.n, np.array(r.v)) for r in S.second_moment(X.documents_by(s, d, 8), 8, "dataset_id").collect()}
    train, test = split_ids(sorted(bank))
    return training_log(s, train_moment_pair(bank_of(bank, train), 8, 6, steps=60, rate=1e-3, seed=1, held=bank_of(bank, test)).log)


@R.add("fit_from_sketch", "SELECT CAST(label AS VARCHAR) AS dataset_id, count(*) AS n, unnest([0, 1])::INT AS i, 4 AS width FROM embeddings GROUP BY label")
def _(s, d):
    from ..meta.train import UnrolledPair, fit_from_sketch

    pair = UnrolledPair(FeatureMap("fourier", 4, 8, arrays={"omega": omega8()}), 40, 0.02, "adam", 0.08, "uniform")
    return fit_from_sketch(emb_d(s, d, 4), pair, k=2).select("dataset_id", "n", "i", F.size("theta").alias("width"))

