r"""Mixing sources to target weights by soft membership.

A multinomial logistic classifier, fitted on a bounded sample of labelled documents (`max_rows`, a parameter), gives each document a posterior
over domains. Non-negative document rates r then minimise the weighted squared distance between the expected domain totals, the sum of r * tokens *
posterior, and the targets. Of all such rates those closest to 1 (in tokens) are taken: they are max(0, 1 - p * y) for one K-vector y, which Newton steps find. A step needs the
K totals and the K x K moments of documents with a positive rate, which one distributed sum gives for several step lengths at once; no state but y lives outside the written posteriors.
The steps go on until the targets are met or, where no rates meet them, the rates are optimal; it is an error if neither comes about.

Defined results: null or empty text has no tokens, a posterior from its features (all zero) and a rate like any other; without labelled rows every posterior is uniform; an empty table
gives an empty result; repeated rows each get a rate; a label without a document is ignored; where an id has several labels or texts, the least one of each is learned from; other columns are carried by `mix` and never read.
"""

from __future__ import annotations

import logging
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .common import UPPER_TO_LOWER, docs_view, stored

WIDTH = 1 << 16
DENSE = 6


def features(text: str | None, seen: dict[bytes, int]) -> tuple[int, np.ndarray, np.ndarray]:
    """Words; sorted hashed words that occur; a few ratios between 0 and about 1. The whole text is read."""
    data = (text or "").encode("utf-8", "surrogatepass")
    words = data.translate(UPPER_TO_LOWER).split()
    kinds = set(words)
    if len(seen) > 150_000:
        seen.clear()
    for w in kinds.difference(seen):
        seen[w] = xxhash.xxh32_intdigest(w.strip(b".,;:!?\"'()")) % WIDTH
    n, size = len(words), max(len(data), 1)
    letters = len(data) - len(data.translate(None, bytes(range(65, 91)) + bytes(range(97, 123)) + bytes(range(128, 256))))
    symbols = len(data) - len(data.translate(None, b"#*$%&|<>{}[]=_~^\\/@"))
    digits = len(data) - len(data.translate(None, b"0123456789"))
    dense = np.array([letters / size, min(1.0, 10 * symbols / size), min(1.0, 10 * digits / size), len(kinds) / max(n, 1), np.log1p(n) / 12, min(1.0, size / max(n, 1) / 20)])
    return n, np.unique(np.fromiter((seen[w] for w in kinds), dtype=np.int64, count=len(kinds))), dense


@dataclass(frozen=True)
class Classifier:
    domains: tuple[str, ...]
    chosen: np.ndarray  # sorted hashed words
    weights: np.ndarray  # (1 + DENSE + words, domains)

    def posterior(self, found: np.ndarray, dense: np.ndarray) -> np.ndarray:
        k = len(self.domains)
        if not len(self.weights):
            return np.full(k, 1 / k)
        hit = np.intersect1d(found, self.chosen, assume_unique=True)
        score = self.weights[0] + dense @ self.weights[1 : 1 + DENSE] + self.weights[1 + DENSE + np.searchsorted(self.chosen, hit)].sum(axis=0)
        e = np.exp(score - score.max())
        return e / e.sum()


FEATURES = "domain string, n long, words array<int>, dense array<double>"


def fit_classifier(docs: DataFrame, labelled: DataFrame, domains: tuple[str, ...], max_rows: int = 8000, keep_words: int = 600, steps: int = 400, decay: float = 1e-4) -> Classifier:
    """docs: docs_view's form; labelled: doc_id, domain. Of more than max_rows labelled documents those with the least hashes of their ids are taken."""
    arrow = to_arrow_schema(T._parse_datatype_string(FEATURES))
    known = labelled.select(F.col("doc_id").cast("long").alias("doc_id"), "domain").where(F.col("domain").isin(*domains)).groupBy("doc_id").agg(F.min("domain").alias("domain"))
    picked = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows)
    rows = docs.join(F.broadcast(picked), "doc_id").groupBy("doc_id", "domain").agg(F.min("text").alias("text")).select("domain", "text")  # at most max_rows ids are broadcast

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            seen: dict[bytes, int] = {}
            got = [features(t, seen) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.string()), pa.array([g[0] for g in got], pa.int64()), pa.array([g[1] for g in got], arrow.field(2).type), pa.array([g[2] for g in got], arrow.field(3).type)], schema=arrow)

    data = rows.mapInArrow(run, FEATURES).toPandas()
    none = Classifier(domains, np.zeros(0, dtype=np.int64), np.zeros((0, len(domains))))
    if not len(data):
        return none
    data = data.iloc[np.lexsort((data["n"], data["domain"]))].reset_index(drop=True)
    k, size = len(domains), len(data)
    y = np.zeros((size, k))
    y[np.arange(size), [domains.index(d) for d in data["domain"]]] = 1
    # words whose presence tells most about the domain: the largest squared deviation from independence, in each domain
    counts = np.zeros((WIDTH, k))
    for row, words in zip(y, data["words"]):
        counts[np.asarray(words)] += row
    total, share = counts.sum(axis=1, keepdims=True), y.mean(axis=0)
    excess = np.where(total >= 5, (counts - total * share) / np.sqrt(total * share + 1), 0)
    chosen = np.unique(np.concatenate([np.argsort(-excess[:, j], kind="stable")[: keep_words // k] for j in range(k)]))
    x = np.zeros((size, 1 + DENSE + len(chosen)))
    x[:, 0] = 1
    for i, (words, dense) in enumerate(zip(data["words"], data["dense"])):
        x[i, 1 : 1 + DENSE] = dense
        x[i, 1 + DENSE + np.searchsorted(chosen, np.intersect1d(words, chosen))] = 1
    w, m, v = np.zeros((x.shape[1], k)), 0.0, 0.0
    for t in range(1, steps + 1):
        s = x @ w
        p = np.exp(s - s.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        g = x.T @ (p - y) / size + decay * w
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        w = w - 0.05 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    return Classifier(domains, chosen, w)


def posteriors(docs: DataFrame, model: Classifier) -> DataFrame:
    """doc_id, h (hash of the text), tokens, p. The model has a fixed number of weights, so it travels with the task."""
    schema = "doc_id long, h long, tokens long, p array<double>"
    arrow = to_arrow_schema(T._parse_datatype_string(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            seen: dict[bytes, int] = {}
            got = [features(t, seen) for t in batch.column(2).to_pylist()]
            p = [model.posterior(f, d) for _, f, d in got]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([g[0] for g in got], pa.int64()), pa.array(p, arrow.field(3).type)], schema=arrow)

    return docs.select("doc_id", F.xxhash64("text").alias("h"), "text").mapInArrow(run, schema)


def replay(p: np.ndarray, moves: np.ndarray) -> np.ndarray:
    r = np.ones(len(p))
    for g in moves:
        r = np.maximum(0.0, r - p @ g)
    return r


def with_rates(post: DataFrame, moves: np.ndarray) -> DataFrame:
    schema = T.StructType([*post.schema.fields, T.StructField("rate", T.DoubleType())])
    arrow = to_arrow_schema(schema)
    at = post.columns.index("p")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            p = np.array(batch.column(at).to_pylist(), dtype=float).reshape(batch.num_rows, -1)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(replay(p, moves) if len(p) else [], pa.float64())], schema=arrow)

    return post.mapInArrow(run, schema)


def totals(post: DataFrame, k: int, points: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For the rates max(0, 1 - p * y) of each row y of `points`: sum of tokens * rate^2, expected domain totals, K x K sum of tokens * p * p' where the rate is positive."""
    width = 1 + k + k * k
    schema = "s array<double>"
    arrow = to_arrow_schema(T._parse_datatype_string(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        s = np.zeros((len(points), width))
        for batch in batches:
            if batch.num_rows:
                t, p = batch.column(0).to_numpy(zero_copy_only=False).astype(float), np.array(batch.column(1).to_pylist(), dtype=float)
                for i, y in enumerate(points):
                    r = replay(p, y[None])
                    s[i, 0] += t @ (r * r)
                    s[i, 1 : 1 + k] += (t * r) @ p
                    s[i, 1 + k :] += (p.T @ (p * (t * (r > 0))[:, None])).ravel()
        yield pa.RecordBatch.from_arrays([pa.array([s.ravel()], arrow.field(0).type)], schema=arrow)

    each = post.select("tokens", "p").mapInArrow(run, schema)
    row = each.agg(*[F.sum(F.col("s")[i]) for i in range(len(points) * width)]).first()
    s = np.array([x or 0.0 for x in row]).reshape(len(points), width)
    return s[:, 0], s[:, 1 : 1 + k], s[:, 1 + k :].reshape(-1, k, k)


@dataclass(frozen=True)
class Fit:
    moves: np.ndarray
    budget: float
    targets: np.ndarray
    reached: np.ndarray
    steps: int


#: Weight of the distance from 1 against that from the targets, and the step lengths tried in one scan.
NEAR_ONE = 1e-8
LENGTHS = 0.5 ** np.arange(12)


def fit_rates(post: DataFrame, weights: list[float], budget: float | None = None, steps: int = 60, tolerance: float = 1e-4) -> Fit:
    """Rates of least squared distance from the targets, with each domain's residual scaled by its own second moment.

    budget: tokens of the mix; by default as many as there are, or more where the domain that gains most would otherwise lose tokens.
    tolerance: largest miss of a target as a share of the budget. Targets that no rates meet are approached as far as possible, with a warning.
    """
    share = np.asarray(weights, dtype=float) / np.sum(weights)
    k = len(share)
    y = np.zeros(k)
    _, at, second = (x[0] for x in totals(post, k, y[None]))
    if budget is None:
        gains = int(np.argmax(share))
        budget = max(at.sum(), at[gains] / share[gains])
    if not at.sum():
        return Fit(np.zeros((0, k)), 0.0, np.zeros(k), at, 0)
    targets = share * budget
    pull = NEAR_ONE * np.maximum(np.diag(second), 1e-9 * at.sum())
    for n in range(steps + 1):
        slope = targets - at + pull * y
        met = np.abs(at - targets).max() <= tolerance * budget
        if met or np.abs(slope).max() <= 1e-3 * tolerance * budget:
            break
        if n == steps:
            raise RuntimeError(f"rates are not optimal after {steps} steps: totals {at.tolist()}, targets {targets.tolist()}")
        root = 1 / np.sqrt(np.diag(second) + pull)
        move = -root * np.linalg.solve((second + np.diag(pull)) * np.outer(root, root), root * slope)
        points = y + LENGTHS[:, None] * move
        squares, ats, seconds = totals(post, k, points)
        best = int(np.argmin(squares / 2 + points @ targets + (points**2) @ pull / 2))
        y, at, second = points[best], ats[best], seconds[best]
    if not met:
        logging.getLogger(__name__).warning("no rates meet the targets %s; totals are %s", targets.tolist(), at.tolist())
    return Fit(y[None] if y.any() else np.zeros((0, k)), float(budget), targets, at, n)


def document_rates(docs: DataFrame, labelled: DataFrame, weights: dict[str, float], id_col: str = "doc_id", text_col: str = "text", max_rows: int = 8000, **kw) -> tuple[DataFrame, Fit]:
    """(doc_id, h, tokens, p, rate), and the fit."""
    view = docs_view(docs, id_col, text_col)
    model = fit_classifier(view, labelled, tuple(weights), max_rows=max_rows)
    post = stored(posteriors(view, model), "posteriors")
    fit = fit_rates(post, list(weights.values()), **kw)
    return with_rates(post, fit.moves), fit


def copies(rate: Column, *keys: Column) -> Column:
    """Whole copies for a rate: its floor, and one more with probability of the rest, by a hash of the document."""
    u = (F.pmod(F.xxhash64(F.lit("copies"), *keys), F.lit(1 << 40)) / F.lit(float(1 << 40)))
    return F.floor(rate + u).cast("int")


def mix(docs: DataFrame, labelled: DataFrame, weights: dict[str, float], id_col: str = "doc_id", text_col: str = "text", max_rows: int = 8000, **kw) -> DataFrame:
    """Whole rows, each as often as its rate says. The rate depends on the text alone, so it is worked out in place from the fit, without a join."""
    view = docs_view(docs, id_col, text_col)
    model = fit_classifier(view, labelled, tuple(weights), max_rows=max_rows)
    fit = fit_rates(stored(posteriors(view, model), "posteriors"), list(weights.values()), **kw)
    at, rate = docs.columns.index(text_col), "__rate"
    schema = T.StructType([*docs.schema.fields, T.StructField(rate, T.DoubleType())])
    arrow = to_arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            seen: dict[bytes, int] = {}
            p = np.array([model.posterior(*features(t, seen)[1:]) for t in batch.column(at).to_pylist()]).reshape(batch.num_rows, -1)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(replay(p, fit.moves) if len(p) else [], pa.float64())], schema=arrow)

    rated = docs.mapInArrow(run, schema)
    n = copies(F.col(rate), F.col(id_col).cast("long"), F.xxhash64(F.col(text_col).cast("string")))
    return rated.withColumn("__n", n).where("__n > 0").withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("__n")))).select(*docs.columns)


def label_domains(labels: DataFrame) -> DataFrame:
    """doc_id, domain of the labels table: toxic, else good or poor by quality; rows without marks are left out."""
    domain = F.when(F.col("toxic") == 1, "toxic").when(F.col("quality") == 1, "good").when(F.col("quality") == 0, "poor")
    return labels.select("doc_id", domain.alias("domain")).where("domain is not null")
