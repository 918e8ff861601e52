"""Row-combination sketches and row sampling: what the mean sketch is compared with, at equal budgets of numbers."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..functions import vectors as V
from ..functions.keyed_random import bucket_col, uniform_col
from ..sources.tables import written


def rows_for_budget(m: int, d: int) -> int:
    return max(1, m // d)


def rowsketch_sparse(df: DataFrame, s: int, d: int, seed: int = 0, key: str = "row_key") -> DataFrame:
    """dataset_id, bucket, j-th sums: every row goes with a random sign to one of s buckets, both by the md5 of its key. R is (SX)'(SX) / n."""
    k = F.col(key).cast("string")
    sign = F.when(uniform_col(f"sign{seed}", k) < 0.5, -1.0).otherwise(1.0)
    x = V.as_doubles(F.col("features"))
    return df.select("dataset_id", bucket_col(s, f"bucket{seed}", k).alias("bucket"), V.scale(x, sign).alias("x")).groupBy("dataset_id", "bucket").agg(F.count(F.lit(1)).alias("n"), F.array(*[F.sum(F.get("x", F.lit(j))) for j in range(d)]).alias("row"))


def keyed_normals(h: np.ndarray, s: int) -> np.ndarray:
    """len(h) x s normals, each a function of its row's 64-bit key and its place alone."""
    z = h.astype(np.uint64)[:, None] + np.arange(1, 2 * s + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    u = ((z ^ (z >> np.uint64(31))) >> np.uint64(11)).astype(float) / (1 << 53)
    return np.sqrt(-2.0 * np.log1p(-u[:, :s])) * np.cos(2.0 * np.pi * u[:, s:])


def rowsketch_gaussian(df: DataFrame, s: int, d: int, seed: int = 0, key: str = "row_key") -> DataFrame:
    """dataset_id, i, n, row: rows of G X / sqrt(s), G drawn per row from its key, so it is the same on every worker and retry. A task adds up a dataset by one matrix product a batch."""
    schema = "dataset_id string, n long, acc array<double>"
    arrow = to_arrow_schema(T._parse_datatype_string(schema))
    rows = df.select(F.col("dataset_id").cast("string"), V.as_doubles(F.col("features")).alias("features"), F.xxhash64(F.col(key).cast("string"), F.lit(seed)).alias("h"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict = {}

        def flush() -> pa.RecordBatch:
            out = pa.RecordBatch.from_arrays([pa.array(list(held), pa.string()), pa.array([v[0] for v in held.values()], pa.int64()), pa.array([v[1].ravel() for v in held.values()], arrow.field(2).type)], schema=arrow)
            held.clear()
            return out

        for batch in batches:
            if not batch.num_rows:
                continue
            x = batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
            g = keyed_normals(batch.column(2).to_numpy(zero_copy_only=False), s)
            coded = batch.column(0).dictionary_encode()
            code, names = coded.indices.fill_null(len(coded.dictionary)).to_numpy(zero_copy_only=False), [*coded.dictionary.to_pylist(), None]
            order = np.argsort(code, kind="stable")
            for rows_of in np.split(order, np.flatnonzero(np.diff(code[order])) + 1):
                name = names[code[rows_of[0]]]
                n, acc = held.get(name, (0, 0.0))
                held[name] = (n + len(rows_of), acc + g[rows_of].T @ x[rows_of])
            if len(held) * s * d >= 8_000_000:
                yield flush()
        if held:
            yield flush()

    parts = rows.mapInArrow(run, schema)
    n = parts.groupBy("dataset_id").agg(F.sum("n").alias("n"))
    long = parts.select("dataset_id", F.posexplode("acc").alias("p", "v")).groupBy("dataset_id", "p").agg(F.sum("v").alias("v"))
    wide = long.select("dataset_id", F.floor(F.col("p") / d).cast("int").alias("i"), F.struct((F.col("p") % d).alias("j"), (F.col("v") / float(np.sqrt(s))).alias("v")).alias("c")).groupBy("dataset_id", "i").agg(F.array_sort(F.collect_list("c")).alias("c"))
    return wide.join(n, F.expr("1=1") & wide["dataset_id"].eqNullSafe(n["dataset_id"])).select(wide["dataset_id"], "i", "n", F.col("c.v").alias("row"))


BLOCK = 64


def _hex(column: pa.Array) -> np.ndarray:
    """The 32 characters of each md5 of a column that is not null, as bytes."""
    text = column.drop_null().cast(pa.string())
    if not len(text):
        return np.zeros((0, 32), dtype=np.uint8)
    at = np.frombuffer(text.buffers()[1], dtype=np.int32)[text.offset : text.offset + len(text) + 1]
    return np.frombuffer(text.buffers()[2], dtype=np.uint8)[at[0] : at[-1]].reshape(-1, 32)


def _uniforms(h: np.ndarray) -> np.ndarray:
    """What `uniform_col` makes of the same md5."""
    digit = np.where(h[:, :13] < 97, h[:, :13] - 48, h[:, :13] - 87)
    return digit @ 16.0 ** np.arange(12, -1, -1) / (1 << 52)


def _grown(a: np.ndarray, n: int, fill: float = 0) -> np.ndarray:
    """a with room for n columns at least."""
    return a if n <= a.shape[-1] else np.concatenate([a, np.full((*a.shape[:-1], n + n // 4 - a.shape[-1]), fill, dtype=a.dtype)], axis=-1)


class _Sums:
    """A task's sums by dataset, one line of memory for each number (sketches of the keyed datasets alone), and its sampled rows."""

    def __init__(self, sizes: list[int], d: int):
        self.sizes, self.d, self.place, self.many = sizes, d, {}, 0
        self.head, self.rest = np.zeros((1 + d * (d + 1) // 2, 0)), np.zeros((2 * sum(sizes) * d, 0))
        self.own = np.zeros(0, dtype=np.int64)  # the column of `rest` of each dataset, -1 without one
        self.at, self.hash, self.x = np.zeros(0, dtype=np.int64), np.zeros(0, dtype="S32"), np.zeros((0, d))

    def numbers(self) -> int:
        return len(self.place) * len(self.head) + self.many * len(self.rest) + len(self.at) * (self.d + 4)

    def add(self, batches: list[pa.RecordBatch]) -> None:
        code = []
        for batch in batches:
            coded = batch.column(0).dictionary_encode()
            names = [*coded.dictionary.to_pylist(), None] if coded.null_count else coded.dictionary.to_pylist()
            own = np.array([self.place.setdefault(name, len(self.place)) for name in names], dtype=np.int64)
            code.append(own[coded.indices.fill_null(len(names) - 1).to_numpy(zero_copy_only=False)])
        at, n = np.concatenate(code), len(self.place)
        self.head, self.own = _grown(self.head, n), _grown(self.own, n, -1)
        x = np.concatenate([batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1) for batch in batches]).T.copy()
        self.head[0, :n] += np.bincount(at, minlength=n)
        for lo, (i, j) in enumerate(zip(*np.tril_indices(self.d)), 1):
            self.head[lo, :n] += np.bincount(at, x[i] * x[j], n)
        keyed = np.concatenate([batch.column(2).is_valid().to_numpy(zero_copy_only=False) for batch in batches])
        if not keyed.any():
            return
        if not keyed.all():
            at, x = at[keyed], x[:, keyed]
        h, negative = (np.concatenate([batch.column(i).drop_null().to_numpy(zero_copy_only=False) for batch in batches]) for i in (2, 3))
        u, least = (np.concatenate([_hex(batch.column(i)) for batch in batches]) for i in (4, 5))
        self._sample(at, np.ascontiguousarray(least).view("S32")[:, 0], x.T)
        new = np.unique(at[self.own[at] < 0])
        self.own[new] = self.many + np.arange(len(new))
        self.many += len(new)
        self.rest = _grown(self.rest, self.many)
        at, n, lo, acc = self.own[at], self.many, 0, self.rest[:, : self.many]
        for s in self.sizes:
            for g in keyed_normals(h, s).T:
                for xj in x:
                    acc[lo] += np.bincount(at, g * xj, n)
                    lo += 1
        u, x = _uniforms(u), np.where(negative, -1.0, 1.0) * x
        for s in self.sizes:
            cell = at * s + np.floor(u * s).astype(np.int64)
            for xj in x:
                acc[lo : lo + s * self.d : self.d] += np.bincount(cell, xj, n * s).reshape(n, s).T
                lo += 1
            lo += (s - 1) * self.d

    def _sample(self, at: np.ndarray, h: np.ndarray, x: np.ndarray) -> None:
        at, h, x = np.concatenate([self.at, at]), np.concatenate([self.hash, h]), np.concatenate([self.x, x])
        first = np.frombuffer(h.tobytes(), dtype=">u8").reshape(-1, 4)[:, 0].astype(np.uint64)
        order = np.lexsort((first, at))
        same = np.flatnonzero((np.diff(at[order]) == 0) & (np.diff(first[order]) == 0))
        if len(same):
            order = np.lexsort((h, at))
        start = np.flatnonzero(np.diff(at[order], prepend=-1))
        rank = np.arange(len(order)) - np.repeat(start, np.diff(start, append=len(order)))
        # equal hashes at the edge are all kept, so no order of rows decides
        edge = np.minimum(start + max(self.sizes), np.append(start[1:], len(order))) - 1
        last = np.repeat(h[order][edge], np.diff(start, append=len(order)))
        keep = order[(rank < max(self.sizes)) | (h[order] == last)]
        self.at, self.hash, self.x = at[keep], h[keep], x[keep]

    def given(self, schema: pa.Schema) -> Iterator[pa.RecordBatch]:
        names, listed = pa.array(list(self.place), pa.string()), schema.field(2).type

        def batch(at: np.ndarray, b: np.ndarray, numbers: np.ndarray, r: pa.Array) -> pa.RecordBatch:
            flat = pa.ListArray.from_arrays(pa.array(np.arange(len(at) + 1, dtype=np.int32) * numbers.shape[1]), pa.array(numbers.ravel()))
            return pa.RecordBatch.from_arrays([names.take(pa.array(at)), pa.array(b.astype(np.int32)), flat.cast(listed), r], schema=schema)

        n = len(self.place)
        own = self.own[:n]
        order = np.argsort(own[own >= 0])
        for first, at, acc in ((0, np.arange(n), self.head[:, :n]), (-(-len(self.head) // BLOCK), np.flatnonzero(own >= 0)[order], self.rest[:, : self.many])):
            for lo in range(0, len(acc), BLOCK):
                if len(at):
                    wide = np.zeros((len(at), BLOCK))
                    wide[:, : len(acc) - lo] = acc[lo : lo + BLOCK].T
                    yield batch(at, np.full(len(at), first + lo // BLOCK), wide, pa.nulls(len(at), pa.string()))
        if len(self.at):
            yield batch(self.at, np.full(len(self.at), -1), self.x, pa.array(self.hash.tolist(), pa.binary()).cast(pa.string()))


def states(df: DataFrame, sizes: list[int], d: int, seed: int = 0, key: str = "row_key", keyed: Column | None = None) -> DataFrame:
    """dataset_id, acc, least, all from one scan. acc: the number of rows, the triangle of the sum of X'X, and where `keyed` holds (by dataset; everywhere if not given) the rows
    of `rowsketch_gaussian` (before the division by sqrt(s)) for every s of `sizes`, then those of `rowsketch_sparse`, flat and one after another; least: the rows of `rowsample`
    for the largest s, in order, null elsewhere. Rows of other datasets need no key. A task's partial sums are written once and read for the sums and the sample."""
    schema = "dataset_id string, b int, acc array<double>, r string"
    arrow = to_arrow_schema(T._parse_datatype_string(schema))
    k = F.col("__k")

    def md5(tag: str) -> Column:
        return F.md5(F.concat_ws("-", F.lit(f"{tag}{seed}"), k).cast("binary"))

    base = [F.col("dataset_id").cast("string").alias("dataset_id"), V.as_doubles(F.col("features")).alias("features")]
    own = df if keyed is None else df.where(keyed)  # a filter goes below what makes the key, so other rows need none
    # half a uniform and more begin with a digit of 8 and more
    rows = own.select(*base, F.col(key).cast("string").alias("__k")).select("dataset_id", "features", F.xxhash64(k, F.lit(seed)).alias("h"), (md5("sign") < "8").alias("g"), md5("bucket").alias("u"), md5("sample").alias("r"))
    if keyed is not None:
        rest = df.where(~F.coalesce(keyed, F.lit(False))).select(*base)
        rows = rows.unionByName(rest.select("dataset_id", "features", *[F.lit(None).cast(kind).alias(c) for c, kind in (("h", "long"), ("g", "boolean"), ("u", "string"), ("r", "string"))]))
    head, tail = 1 + d * (d + 1) // 2, 2 * sum(sizes) * d
    held = max(1, min(1 << 17, 2_000_000 // max(sizes)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, waiting, many = _Sums(sizes, d), [], 0
        for batch in batches:
            if not batch.num_rows:
                continue
            waiting.append(batch)
            many += batch.num_rows
            if many < held:
                continue
            sums.add(waiting)
            waiting, many = [], 0
            if sums.numbers() >= 16_000_000:
                yield from sums.given(arrow)
                sums = _Sums(sizes, d)
        if waiting:
            sums.add(waiting)
        if sums.place:
            yield from sums.given(arrow)

    parts = written(rows.mapInArrow(run, schema), "partial-states")
    # a dataset's numbers are summed in blocks, so many of them are spread over tasks, and few make few rows
    sums = parts.where("b >= 0").groupBy("dataset_id", "b").agg(F.array(*[F.sum(F.get("acc", F.lit(j))) for j in range(BLOCK)]).alias("acc"))
    whole = sums.groupBy("dataset_id").agg(F.array_sort(F.collect_list(F.struct("b", "acc"))).alias("c"))
    flat, first = F.flatten(F.col("c.acc")), -(-head // BLOCK) * BLOCK
    whole = whole.select("dataset_id", F.concat(F.slice(flat, 1, head), F.slice(flat, first + 1, tail)).alias("acc"))
    w = Window.partitionBy("dataset_id").orderBy("r", "acc")
    ranked = parts.where("b < 0").withColumn("i", F.row_number().over(w)).where(F.col("i") <= max(sizes))
    least = ranked.groupBy("dataset_id").agg(F.array_sort(F.collect_list(F.struct("i", "acc"))).alias("c")).select(F.col("dataset_id").alias("__id"), F.col("c.acc").alias("least"))
    return whole.join(least, F.col("dataset_id").eqNullSafe(F.col("__id")), "left").drop("__id")


def rowsketches(df: DataFrame, sizes: list[int], d: int, seed: int = 0, key: str = "row_key") -> DataFrame:
    """dataset_id, acc: the sketches of `states`, and at last the number of rows."""
    head = 1 + d * (d + 1) // 2
    return states(df, sizes, d, seed, key).select("dataset_id", F.concat(F.slice("acc", head + 1, 2 * sum(sizes) * d), F.slice("acc", 1, 1)).alias("acc"))


def rowsample(df: DataFrame, s: int, seed: int = 0, key: str = "row_key") -> DataFrame:
    """The s rows of each dataset with the least md5 of their key: a sample that no layout changes."""
    h = F.md5(F.concat_ws("-", F.lit(f"sample{seed}"), F.col(key).cast("string")).cast("binary"))
    w = Window.partitionBy("dataset_id").orderBy("__h", F.col(key).cast("string"))
    return df.withColumn("__h", h).withColumn("__r", F.row_number().over(w)).where(F.col("__r") <= s).drop("__h", "__r")


def rowsamples(df: DataFrame, sizes: list[int], seed: int = 0, key: str = "row_key") -> DataFrame:
    """dataset_id, s, features: the rows of `rowsample` for every s of `sizes`, ranked once."""
    k = F.col(key).cast("string")
    h = F.md5(F.concat_ws("-", F.lit(f"sample{seed}"), k).cast("binary"))
    w = Window.partitionBy("dataset_id").orderBy("__h", "__k")
    ranked = df.select("dataset_id", "features", h.alias("__h"), k.alias("__k")).withColumn("__r", F.row_number().over(w)).where(F.col("__r") <= max(sizes))
    return ranked.select("dataset_id", F.explode(F.array(*map(F.lit, sizes))).alias("s"), "features", "__r").where(F.col("__r") <= F.col("s")).drop("__r")


def moment_from_rows(rows: np.ndarray, n: int) -> np.ndarray:
    return rows.T @ rows / n


def sparse_local(x: np.ndarray, s: int, rng: np.random.Generator) -> np.ndarray:
    out = np.zeros((s, x.shape[1]))
    np.add.at(out, rng.integers(s, size=len(x)), x * rng.choice([-1.0, 1.0], size=(len(x), 1)))
    return moment_from_rows(out, len(x))


def gaussian_local(x: np.ndarray, s: int, rng: np.random.Generator) -> np.ndarray:
    return moment_from_rows(rng.standard_normal((s, len(x))) @ x / np.sqrt(s), len(x))


def supervised_sgd(datasets_rows: np.ndarray, p: int, lam: float = 0.0, epochs: int = 5, rate: float = 0.05, batch: int = 64, seed: int = 0) -> np.ndarray:
    """Ridge weights by stochastic gradient descent over rows: the many-pass counterpart."""
    rng = np.random.Generator(np.random.Philox(seed))
    x, y = datasets_rows[:, p:], datasets_rows[:, :p]
    theta = np.zeros((p, x.shape[1]))
    for _ in range(epochs):
        order = rng.permutation(len(x))
        for i in range(0, len(x), batch):
            k = order[i : i + batch]
            theta -= rate * ((theta @ x[k].T - y[k].T) @ x[k] / len(k) + lam * theta)
    return theta


def distributed_gradient(df: DataFrame, p: int, q: int, lam: float = 0.0, epochs: int = 30, rate: float = 0.5) -> np.ndarray:
    """The same by full gradients: each epoch is one scan whose sums combine on the map side."""
    x = V.as_doubles(F.col("features"))
    theta = np.zeros((p, q))
    for _ in range(epochs):
        rest = F.slice(x, p + 1, q)
        e = [V.dot_literal(rest, theta[i]) - F.get(x, F.lit(i)) for i in range(p)]
        row = df.agg(F.count(F.lit(1)).alias("n"), *[F.sum(e[i] * F.get(x, F.lit(p + j))).alias(f"g{i}_{j}") for i in range(p) for j in range(q)]).first()
        g = np.array([row[f"g{i}_{j}"] for i in range(p) for j in range(q)]).reshape(p, q) / row["n"]
        theta -= rate * (g + lam * theta)
    return theta


def gaussian_mixture(df: DataFrame, k: int, seed: int = 0):
    """Expectation maximisation over rows, from the ML library: the supervised counterpart of a mixture from a sketch."""
    from pyspark.ml.clustering import GaussianMixture
    from pyspark.ml.functions import array_to_vector

    return GaussianMixture(k=k, seed=seed, featuresCol="v").fit(df.select(array_to_vector(V.as_doubles(F.col("features"))).alias("v")))
