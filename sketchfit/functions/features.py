"""From table rows to samples: dataset_id, row_key, cls, features."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from . import vectors as V
from .keyed_random import fast_normals, uniform


def assemble(*cols: Column | str) -> Column:
    return F.array(*[(F.col(c) if isinstance(c, str) else c).cast("double") for c in cols])


def on_null(df: DataFrame, policy: str, column: str = "features") -> DataFrame:
    """error: fail on a row with a null; skip_row: leave it out; zero: put 0."""
    bad = F.col(column).isNull() | F.exists(F.coalesce(column, F.array()), lambda x: x.isNull())
    if policy == "skip_row":
        return df.where(~bad)
    if policy == "zero":
        return df.withColumn(column, F.transform(column, lambda x: F.coalesce(x, F.lit(0.0))))
    return df.withColumn(column, F.when(bad, F.raise_error(F.lit("a sample holds a null"))).otherwise(F.col(column)))


def feature_subset(width: int, d: int, seed: int = 0) -> list[int]:
    """d of `width` places, by the order of their keys' uniforms."""
    return sorted(sorted(range(width), key=lambda j: (uniform(f"subset{seed}-{j}"), j))[:d])


def fit_width(v: Column, width: int, d: int, seed: int = 0) -> Column:
    """Exactly d numbers: zero-padded when narrower, a seeded subset of the features when wider."""
    if width <= d:
        return F.concat(v, F.array_repeat(F.lit(0.0), d - width)) if width < d else v
    return F.array(*[F.get(v, F.lit(j)) for j in feature_subset(width, d, seed)])


def profile(df: DataFrame, d: int, by: Sequence[str] = ("dataset_id",)) -> DataFrame:
    """Per dataset and feature: least, largest, mean and deviation, in one pass."""
    x = [F.get("features", F.lit(j)) for j in range(d)]
    cols = [f(c).alias(f"{n}{j}") for j, c in enumerate(x) for n, f in (("lo", F.min), ("hi", F.max), ("mu", F.avg), ("sd", F.stddev_pop))]
    flat = df.groupBy(*by).agg(*cols)
    return flat.select(*by, *[F.array(*[f"{n}{j}" for j in range(d)]).alias(n) for n in ("lo", "hi", "mu", "sd")])


def scaled(df: DataFrame, d: int, how: str = "minmax", by: Sequence[str] = ("dataset_id",)) -> DataFrame:
    """minmax to [0, 1]; maxabs to [-1, 1]; zscore. A constant feature becomes 0. The profile has one row for each dataset."""
    p = profile(df, d, by)
    both = df.join(p, list(by))
    if how == "minmax":
        shift, width = F.col("lo"), V.subtract(F.col("hi"), F.col("lo"))
    elif how == "zscore":
        shift, width = F.col("mu"), F.col("sd")
    else:
        shift, width = F.transform("lo", lambda x: F.lit(0.0)), F.zip_with("lo", "hi", lambda a, b: F.greatest(F.abs(a), F.abs(b)))
    new = F.zip_with(V.subtract(F.col("features"), shift), width, lambda a, w: F.when(w > 0, a / w).otherwise(F.lit(0.0)))
    return both.withColumn("features", new).drop("lo", "hi", "mu", "sd")


def one_hot(c: Column, values: Sequence) -> Column:
    return F.array(*[(c.eqNullSafe(F.lit(v))).cast("tinyint") for v in values])


def permute_negate(v: Column, width: int, seed: int) -> Column:
    """The places in a seeded order, some of them negated."""
    order = sorted(range(width), key=lambda j: (uniform(f"perm{seed}-{j}"), j))
    return F.array(*[(F.lit(1) - F.get(v, F.lit(j)) if uniform(f"neg{seed}-{j}") < 0.5 else F.get(v, F.lit(j))).cast("tinyint") for j in order])


def hashed_text(df: DataFrame, text: str, d: int, keep: Sequence[str]) -> DataFrame:
    """Square roots of the frequencies of hashed letter bigrams, whole texts; case is folded."""
    schema = T.StructType([*[df.schema[c] for c in keep], T.StructField("features", T.ArrayType(T.DoubleType()))])
    arrow = to_arrow_schema(schema)
    view = df.select(*keep, F.lower(F.coalesce(F.col(text), F.lit(""))).alias("__text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for t in batch.column(len(keep)).to_pylist():
                b = np.frombuffer(t.encode("utf-8", "surrogatepass"), dtype=np.uint8).astype(np.int64)
                letter = ((b >= 97) & (b <= 122)) | (b >= 128)
                ok = letter[:-1] & letter[1:]
                h = ((b[:-1] * 257 + b[1:]) * 2654435761 >> 7) % d
                c = np.bincount(h[ok], minlength=d)
                out.append(np.sqrt(c / max(c.sum(), 1)))
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], pa.array(out, arrow.field(len(keep)).type)], schema=arrow)

    return view.mapInArrow(run, schema)


# collections of datasets on the given tables --------------------------------------------------------------------------


def emb64(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return e.select(F.col("label").cast("string").alias("dataset_id"), F.col("vec_id").cast("string").alias("row_key"), F.col("label").cast("string").alias("cls"), V.as_doubles(F.col("embedding")).alias("features"))


def line_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with its part; the part table is a dimension and is broadcast when Spark finds it small."""
    li = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    pt = spark.read.parquet(f"{sf_dir}/part.parquet").select("p_partkey", "p_brand", "p_size", "p_retailprice")
    rows = li.join(pt, li.l_partkey == pt.p_partkey)
    net = F.col("l_extendedprice") * (1 - F.col("l_discount"))
    return rows.withColumn("net", net).withColumn("charge", net * (1 + F.col("l_tax")))


LINE = ("charge", "net", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "p_retailprice", "p_size")
#: Divisors that bring the columns of LINE to about [0, 1]; fixed, so no pass over the data is needed.
LINE_SCALE = (120000.0, 110000.0, 50.0, 110000.0, 0.1, 0.1, 1000.0, 50.0)


def line_num(spark: SparkSession, sf_dir: str, by: str = "l_suppkey") -> DataFrame:
    """The first number is the ridge target."""
    r = line_rows(spark, sf_dir)
    key = F.md5(F.concat_ws("|", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_shipdate").cast("binary"))
    x = F.array(*[F.col(c).cast("double") / F.lit(s) for c, s in zip(LINE, LINE_SCALE)])
    return r.select(F.col(by).cast("string").alias("dataset_id"), key.alias("row_key"), F.col("l_returnflag").alias("cls"), x.alias("features"))


def line_flag_brand(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = line_rows(spark, sf_dir)
    day = F.dayofyear("l_shipdate") * F.lit(2 * np.pi / 365.25)
    x = F.array(*[F.col(c).cast("double") / F.lit(s) for c, s in zip(LINE, LINE_SCALE)], F.sin(day), F.cos(day))
    return r.select(F.concat_ws("-", "l_returnflag", "p_brand").alias("dataset_id"), F.col("l_orderkey").cast("string").alias("row_key"), F.col("l_returnflag").alias("cls"), x.alias("features"))


def documents_by(spark: SparkSession, sf_dir: str, d: int = 64, by: str = "source") -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    f = hashed_text(docs.select("doc_id", "source", "lang", "text"), "text", d, ["doc_id", "source", "lang"])
    return f.select(F.col(by).alias("dataset_id"), F.col("doc_id").cast("string").alias("row_key"), F.col("lang").alias("cls"), "features")


def projected_documents(spark: SparkSession, sf_dir: str, d: int, by: str = "source", balanced: bool = False, width: int = 64) -> DataFrame:
    """Hashed documents through a fixed random projection, scaled to [0, 1] over the whole table; balanced: as many rows of each language."""
    base = documents_by(spark, sf_dir, width, by)
    if balanced:
        w = Window.partitionBy("cls").orderBy(F.md5(F.col("row_key").cast("binary")), "row_key")
        least = base.groupBy("cls").count().agg(F.min("count").alias("least"))
        base = base.withColumn("r", F.row_number().over(w)).join(F.broadcast(least)).where("r <= least").drop("r", "least")  # one row
    p = fast_normals(64 + d, width, d) / np.sqrt(d)
    x = F.array(*[V.dot_literal(F.col("features"), p[:, j]) for j in range(d)])
    rows = base.withColumn("features", x).withColumn("all", F.lit(1))
    return scaled(rows, d, "minmax", ["all"]).drop("all")


EVENT_TYPES = ("click", "view", "purchase", "signup", "error")


def event_features() -> Column:
    """[1 for counting, value, hour and weekday on circles, the number in props]."""
    ts = F.col("ts").cast("timestamp")
    hour, day = F.hour(ts) * F.lit(2 * np.pi / 24), F.dayofweek(ts) * F.lit(2 * np.pi / 7)
    k = F.get_json_object("props", "$.k").cast("double") / 100
    return F.array(F.lit(1.0), F.col("value").cast("double") / 100, F.sin(hour), F.cos(hour), F.sin(day), F.cos(day), F.coalesce(k, F.lit(0.0)))


EVENT_WIDTH = 7


def events_by_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    return e.select(F.col("user_id").cast("string").alias("dataset_id"), F.col("event_id").cast("string").alias("row_key"), F.col("event_type").alias("cls"), F.col("ts"), event_features().alias("features"))


def bit_sets(spark: SparkSession, sf_dir: str, d: int = 48) -> DataFrame:
    """Seven binary datasets of width d: test_set, row_key, cls, features (0 and 1)."""
    t = lambda n: spark.read.parquet(f"{sf_dir}/{n}.parquet")

    def padded(v: Column, width: int) -> Column:
        return fit_width(v.cast("array<double>"), width, d)

    def thermometer(c: Column, steps: Sequence[float]) -> list[Column]:
        return [(c > s).cast("tinyint") for s in steps]

    orders = t("orders")
    o = F.concat(one_hot(F.col("o_orderstatus"), ("F", "O", "P")), one_hot(F.substring("o_orderpriority", 1, 1), "12345"), F.array(*thermometer(F.col("o_totalprice"), range(30000, 480000, 30000))), F.array(*[(F.month("o_orderdate") == m).cast("tinyint") for m in range(1, 13)]))
    out = orders.select(F.lit("orders").alias("dataset_id"), F.col("o_orderkey").cast("string").alias("row_key"), F.substring("o_orderpriority", 1, 1).alias("cls"), padded(o, 3 + 5 + 15 + 12).alias("features"))
    li = t("lineitem")
    x = F.concat(one_hot(F.col("l_returnflag"), ("A", "N", "R")), one_hot(F.col("l_linestatus"), ("F", "O")), F.array(*thermometer(F.col("l_quantity"), range(5, 50, 5))), F.array(*thermometer(F.col("l_discount"), [k / 100 for k in range(10)])), F.array(*thermometer(F.col("l_tax"), [k / 100 for k in range(8)])), F.array(*thermometer(F.col("l_extendedprice"), range(10000, 100000, 10000))))
    out = out.unionByName(li.select(F.lit("lineitem").alias("dataset_id"), F.concat_ws("-", "l_orderkey", "l_linenumber", "l_partkey").alias("row_key"), F.col("l_returnflag").alias("cls"), padded(x, 3 + 2 + 9 + 10 + 8 + 9).alias("features")))
    cu = t("customer")
    c = F.concat(one_hot(F.col("c_nationkey"), range(25)), F.array(*thermometer(F.col("c_acctbal"), range(-500, 9500, 1000))), F.array(*[(F.pmod(F.crc32(F.col("c_mktsegment").cast("binary")), F.lit(5)) == k).cast("tinyint") for k in range(5)]))
    out = out.unionByName(cu.select(F.lit("customer").alias("dataset_id"), F.col("c_custkey").cast("string").alias("row_key"), F.col("c_mktsegment").alias("cls"), padded(c, 25 + 10 + 5).alias("features")))
    docs = hashed_text(t("documents").select("doc_id", "source", "lang", "text"), "text", d, ["doc_id", "source", "lang"])
    text_bits = F.transform("features", lambda v: (v > 0.12).cast("double"))
    for lang in ("en", "fr"):
        out = out.unionByName(docs.where(F.col("lang") == lang).select(F.lit(f"documents_{lang}").alias("dataset_id"), F.col("doc_id").cast("string").alias("row_key"), F.col("source").alias("cls"), text_bits.alias("features")))
    b = hashed_text(t("benchmark"), "text", d, ["item_id"])
    out = out.unionByName(b.select(F.lit("benchmark").alias("dataset_id"), F.col("item_id").cast("string").alias("row_key"), F.pmod(F.col("item_id"), F.lit(4)).cast("string").alias("cls"), text_bits.alias("features")))
    e = t("embeddings")
    signs = F.transform(F.slice("embedding", 1, d), lambda v: (v > 0).cast("double"))
    return out.unionByName(e.select(F.lit("embeddings").alias("dataset_id"), F.col("vec_id").cast("string").alias("row_key"), F.col("label").cast("string").alias("cls"), signs.alias("features")))


def bounded_rows(df: DataFrame, rows: int, by: str = "dataset_id") -> dict[str, np.ndarray]:
    """At most `rows` rows of each dataset, those of least key hash, on the driver: the bounded samples that meta-training uses."""
    w = Window.partitionBy(by).orderBy(F.md5(F.col("row_key").cast("binary")), "row_key")
    got = df.withColumn("__r", F.row_number().over(w)).where(F.col("__r") <= rows).select(by, "__r", "features").orderBy(by, "__r").collect()
    out: dict[str, list] = {}
    for r in got:
        out.setdefault(r[by], []).append(r.features)
    return {k: np.array(v, dtype=float) for k, v in out.items()}
