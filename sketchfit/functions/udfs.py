"""What a user calls from SQL or columns: feature maps per row, sketches as aggregates, decoders as table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.maps import FeatureMap


def feature_map_udf(fm: FeatureMap):
    """Column of vectors -> column of features, by Arrow batches."""

    @F.pandas_udf(T.ArrayType(T.DoubleType()))
    def apply(v: pd.Series) -> pd.Series:
        if not len(v):
            return pd.Series([], dtype=object)
        return pd.Series(list(fm.batch(np.stack(v.to_numpy()))))

    return apply


def sketch_agg(v: Column, fm: FeatureMap) -> Column:
    """The mean sketch as an aggregate of built-in functions, so it combines on the map side; for maps of closed form."""
    return F.array(*[F.avg(c) for c in fm.columns(v)])


DECODED = "dataset_id string, cid int, weight double, center array<double>, loss double"


def decode_all(sk: DataFrame, fm: FeatureMap, k: int, how: str = "greedy", box: tuple[float, float] = (0.0, 1.0), **kw) -> DataFrame:
    """Centroids of every dataset's sketch, one task for each dataset; the time does not depend on the datasets' sizes."""
    from ..operators.kmeans import decode_greedy, decode_unrolled

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        z = np.asarray(pdf["acc"].iloc[0], dtype=float) / int(pdf["n"].iloc[0])
        got = decode_greedy(z, fm, k, box, **kw) if how == "greedy" else decode_unrolled(z, fm, k, box=box, **kw)
        return pd.DataFrame({"dataset_id": key[0], "cid": range(len(got.theta)), "weight": got.weights, "center": list(got.theta), "loss": got.loss})

    return sk.select("dataset_id", "n", "acc").groupBy("dataset_id").applyInPandas(run, DECODED)


def register_all(spark: SparkSession, maps: dict[str, FeatureMap]) -> None:
    """SQL names: sketch_features_<map>(vector), and decode_kmeans(map, sketch, k) as a table function."""
    for name, fm in maps.items():
        spark.udf.register(f"sketch_features_{name}", feature_map_udf(fm))
    held = dict(maps)

    @F.udtf(returnType="cid: int, weight: double, center: array<double>, loss: double")
    class DecodeKMeans:
        def eval(self, name: str, z: list, k: int) -> Iterator[tuple]:
            from sketchfit.operators.kmeans import decode_greedy

            got = decode_greedy(np.array(z, dtype=float), held[name], k)
            for i, (w, c) in enumerate(zip(got.weights, got.theta)):
                yield i, float(w), [float(x) for x in c], float(got.loss)

    spark.udtf.register("decode_kmeans", DecodeKMeans)


def predict_features(fm: FeatureMap, batch_size: int = 4096):
    """The same map through the ML library's batch inference function: the model is made once in each worker."""
    from pyspark.ml.functions import predict_batch_udf

    def make():
        return lambda x: fm.batch(x)

    return predict_batch_udf(make, return_type=T.ArrayType(T.DoubleType()), batch_size=batch_size, input_tensor_shapes=[[fm.d]])


def autoencoder_codes(df: DataFrame, ae, z: np.ndarray | None = None) -> DataFrame:
    """code (bottleneck) and bits (reconstruction) of every row of features; z is the dataset's condition."""
    schema = T.StructType([*df.schema.fields, T.StructField("code", T.ArrayType(T.DoubleType())), T.StructField("bits", T.ArrayType(T.IntegerType()))])

    def run(pdfs: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in pdfs:
            if not len(pdf):
                yield pdf.assign(code=pd.Series(dtype=object), bits=pd.Series(dtype=object))
                continue
            x = np.stack(pdf["features"].to_numpy())
            each = None if z is None else np.repeat(z[None], len(x), axis=0)
            yield pdf.assign(code=list(ae.encode(x, each)), bits=list(ae.reconstruct(x, each).astype(np.int32)))

    return df.mapInPandas(run, schema)
