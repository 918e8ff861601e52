r"""Katz backoff language model: counts of the whole corpus, Good-Turing discounts, exactly normalised backoff weights.

P(w)   = d(c) c / N for words of the training text; the mass that discounting frees goes to one unknown type.
P(w|h) = d(c) c / c(h) where h w occurs in training, else alpha(h) P(w), with alpha(h) = (1 - sum of the first over seen w) / (1 - sum of their P(w)).
Where a context's counts leave no mass (all of them above the discounted range), its total counts one more, so alpha stays positive; sums are 1 in every context.

How it scales. Documents are read once into chunks of bounded size, kept in the shared folder as arrays of local word numbers. A chunk sends its distinct words and word pairs, packed and
sorted, to tables partitioned by hash; each partition adds the chunks' counts and answers each chunk with an array aligned to what it asked, so no key travels back. A partition has at most one
entry of a word for each chunk, however frequent the word is. Two rounds do all: counts, then backoff weights. Only counts of counts and totals reach the driver.

Defined results: null or empty text is the end token alone; an untrained word is the unknown type; without training documents N and V are 0 and every token is unknown with probability 1;
repeated rows are each learned from and scored; only id and text are read; an empty table gives an empty result.
"""

from __future__ import annotations

import io
import uuid
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .common import UPPER_TO_LOWER, docs_view, scratch, stored
from .near_duplicates import mix
from .token_files import opened

U = np.uint64
END = U(xxhash.xxh64_intdigest(b""))
START = U(xxhash.xxh64_intdigest(b" "))
TOP = 5  # counts up to this are discounted


def planes(a: np.ndarray) -> bytes:
    """Compressed bytes of an array, its byte planes apart; sorted keys should come as differences."""
    raw = np.ascontiguousarray(a).view(np.uint8).reshape(len(a), a.dtype.itemsize).T.tobytes()
    return zstandard.ZstdCompressor(level=1).compress(raw)


def unplanes(data: bytes, kind) -> np.ndarray:
    raw = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), dtype=np.uint8)
    size = np.dtype(kind).itemsize
    return np.ascontiguousarray(raw.reshape(size, -1).T).view(kind).ravel()


def keys_out(keys: np.ndarray) -> bytes:
    return planes(np.diff(keys, prepend=U(0)))


def keys_in(data: bytes) -> np.ndarray:
    return np.cumsum(unplanes(data, U), dtype=U)


def by_part(keys: np.ndarray, parts: int) -> tuple[np.ndarray, list[tuple[int, int, int]]]:
    """Order by (part, key), and (part, from, to) of each part that has keys."""
    part = (keys % U(parts)).astype(np.int64)
    order = np.lexsort((keys, part))
    p = part[order]
    cut = np.flatnonzero(np.diff(p, prepend=-1))
    return order, [(int(p[a]), int(a), int(b)) for a, b in zip(cut, [*cut[1:], len(p)])]


class Chunk:
    """Documents as local word numbers: tokens of document i are tok[at[i]:at[i+1]], the last of them the end; words are sorted by (part, hash)."""

    def __init__(self, doc_id: np.ndarray, null_id: np.ndarray, held: np.ndarray, at: np.ndarray, tok: np.ndarray, words: np.ndarray):
        self.doc_id, self.null_id, self.held, self.at, self.tok, self.words = doc_id, null_id, held, at, tok, words

    @staticmethod
    def of(docs: list[tuple[int | None, bool, np.ndarray]], parts: int) -> Chunk:
        tokens = np.concatenate([d[2] for d in docs])
        words, tok = np.unique(np.append(tokens, START), return_inverse=True)
        order, _ = by_part(words, parts)
        place = np.empty(len(order), dtype=np.uint32)
        place[order] = np.arange(len(order), dtype=np.uint32)
        at = np.concatenate([[0], np.cumsum([len(d[2]) for d in docs])]).astype(np.int64)
        ids = np.array([d[0] or 0 for d in docs], dtype=np.int64)
        return Chunk(ids, np.array([d[0] is None for d in docs]), np.array([d[1] for d in docs]), at, place[tok[:-1]], words[order])

    def save(self, uri: str) -> None:
        fs, path = opened(uri)
        fs.create_dir(path.rpartition("/")[0], recursive=True)
        buffer = io.BytesIO()
        np.savez(buffer, doc_id=self.doc_id, null_id=self.null_id, held=self.held, at=self.at, tok=np.frombuffer(planes(self.tok), dtype=np.uint8), words=self.words)
        with fs.open_output_stream(path) as out:
            out.write(zstandard.ZstdCompressor(level=1).compress(buffer.getvalue()))

    @staticmethod
    def load(uri: str) -> Chunk:
        fs, path = opened(uri)
        with fs.open_input_stream(path) as f:
            z = np.load(io.BytesIO(zstandard.ZstdDecompressor().decompress(f.read())))
        return Chunk(z["doc_id"], z["null_id"], z["held"], z["at"], unplanes(z["tok"].tobytes(), np.uint32), z["words"])

    def trained(self) -> np.ndarray:
        return np.repeat(~self.held, np.diff(self.at))

    def before(self) -> np.ndarray:
        """The word before each token; the start before a first one."""
        out = np.empty_like(self.tok)
        out[1:] = self.tok[:-1]
        out[self.at[:-1]] = np.flatnonzero(self.words == START)[0]
        return out

    def pairs(self, parts: int):
        """(before, word) of the distinct pairs by (part, key), their keys and parts, and each token's pair."""
        code = self.before().astype(np.int64) * len(self.words) + self.tok
        kinds, which = np.unique(code, return_inverse=True)
        a, b = kinds // len(self.words), kinds % len(self.words)
        keys = mix(mix(self.words[a], 41) ^ self.words[b], 42)
        order, cut = by_part(keys, parts)
        place = np.empty(len(order), dtype=np.int64)
        place[order] = np.arange(len(order))
        return a[order], b[order], keys[order], cut, place[which]


ASK = "kind int, part int, chunk string, keys binary, counts binary"


def read_chunks(docs: DataFrame, folder: str, parts: int, held_out: Callable[[int | None], bool], chunk_tokens: int) -> DataFrame:
    """Writes the chunk files and returns what they ask: kind 1 words, kind 2 pairs, with training counts."""
    arrow = to_arrow_schema(T._parse_datatype_string(ASK))

    def asked(chunk: Chunk) -> pa.RecordBatch:
        name = uuid.uuid4().hex
        chunk.save(f"{folder}/{name}")
        use = chunk.trained()
        rows = []
        c1 = np.bincount(chunk.tok[use], minlength=len(chunk.words)).astype(np.uint32)
        c1[chunk.words == START] = np.count_nonzero(~chunk.held)
        _, cut = by_part(chunk.words, parts)
        rows += [(1, p, name, keys_out(chunk.words[a:b]), planes(c1[a:b])) for p, a, b in cut]
        _, _, keys, cut, which = chunk.pairs(parts)
        c2 = np.bincount(which[use], minlength=len(keys)).astype(np.uint32)
        rows += [(2, p, name, keys_out(keys[a:b]), planes(c2[a:b])) for p, a, b in cut]
        return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), arrow)], schema=arrow)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list = []
        size, seen = 0, {}
        for batch in batches:
            for doc_id, text in zip(*(c.to_pylist() for c in batch.columns)):
                words = (text or "").encode("utf-8", "surrogatepass").translate(UPPER_TO_LOWER).split()
                if len(seen) > 150_000:
                    seen.clear()
                for w in set(words).difference(seen):
                    seen[w] = xxhash.xxh64_intdigest(w)
                held.append((doc_id, held_out(doc_id), np.append(np.fromiter(map(seen.__getitem__, words), dtype=U, count=len(words)), END)))
                size += len(words) + 1
                if size >= chunk_tokens:
                    yield asked(Chunk.of(held, parts))
                    held, size, seen = [], 0, {}
        if held:
            yield asked(Chunk.of(held, parts))

    return docs.select("doc_id", "text").mapInArrow(run, ASK)


ANSWER = "kind int, part int, chunk string, counts binary, stats array<long>"


def add_counts(asked: DataFrame) -> DataFrame:
    """One partition of a table: the sum of each key's counts, answered to each chunk in its order; bit 31 marks the chunk that owns the key.

    stats (in the first answer of a partition): N, V, and the numbers of keys seen 1 to TOP + 1 times.
    """

    def add(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("chunk", kind="stable")
        keys = [keys_in(k) for k in pdf["keys"]]
        counts = np.concatenate([unplanes(c, np.uint32) for c in pdf["counts"]]).astype(np.int64)
        sizes = [len(k) for k in keys]
        flat, which = np.unique(np.concatenate(keys), return_inverse=True)
        total = np.zeros(len(flat), dtype=np.int64)
        np.add.at(total, which, counts)
        first = np.full(len(flat), len(which))
        taught = np.flatnonzero(counts)
        np.minimum.at(first, which[taught], taught)
        answer = np.minimum(total[which], (1 << 31) - 1)
        answer[first[first < len(which)]] |= 1 << 31
        own = total[(flat != START)] if key[0] == 1 else total
        stats = [int(own.sum()), int(np.count_nonzero(own)), *(int(np.count_nonzero(own == r)) for r in range(1, TOP + 2))]
        ends = np.cumsum([0, *sizes])
        blobs = [planes(answer[a:b].astype(np.uint32)) for a, b in zip(ends, ends[1:])]
        return pd.DataFrame({"kind": key[0], "part": key[1], "chunk": pdf["chunk"].to_numpy(), "counts": blobs, "stats": [stats] + [[]] * (len(blobs) - 1)})

    return asked.groupBy("kind", "part").applyInPandas(add, ANSWER)


def discounts(counts_of_counts: list[int]) -> np.ndarray:
    """Factor for counts 0 to TOP (the first unused): Good-Turing up to TOP; 1 - 0.5 / r where the counts of counts allow none."""
    n = [0, *counts_of_counts]
    out = np.ones(TOP + 1)
    cut = (TOP + 1) * n[TOP + 1] / n[1] if n[1] else 1.0
    for r in range(1, TOP + 1):
        good = (r + 1) * n[r + 1] / (r * n[r]) if n[r] else 0.0
        d = (good - cut) / (1 - cut) if cut < 1 else 0.0
        out[r] = d if 0 < d < 1 else 1 - 0.5 / r
    return out


class Model:
    """Totals and discounts of the two tables; small whatever the corpus is."""

    def __init__(self, words: list[int], pairs: list[int]):
        self.n, self.v = words[0], words[1]
        self.d1, self.d2 = discounts(words[2:]), discounts(pairs[2:])
        freed = sum((1 - self.d1[r]) * r * words[1 + r] for r in range(1, TOP + 1))
        if self.n and freed <= 0:  # no rare word: one token's mass for the unknown type
            self.n_eff, self.unknown = self.n + 1, 1 / (self.n + 1)
        else:
            self.n_eff, self.unknown = self.n, (freed / self.n if self.n else 1.0)

    def word(self, c: np.ndarray) -> np.ndarray:
        return np.where(c > 0, used(c, self.d1) / max(self.n_eff, 1), self.unknown)


def used(c: np.ndarray, d: np.ndarray) -> np.ndarray:
    return c * np.where(c <= TOP, d[np.minimum(c, TOP)], 1.0)


def aligned(pdf: pd.DataFrame, kind: int, column: str, dtype) -> np.ndarray:
    part = pdf[pdf["kind"] == kind].sort_values("part")
    return np.concatenate([unplanes(b, dtype) for b in part[column]])


MASS = "part int, chunk string, keys binary, c binary, a binary, b binary"
WEIGHT = "kind int, part int, chunk string, counts binary"


def context_mass(answers: DataFrame, folder: str, parts: int, model: Model) -> DataFrame:
    """For each chunk: its words' counts and, over the pairs it owns, the discounted counts and the P(w) that follow each word."""

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        chunk = Chunk.load(f"{folder}/{key[0]}")
        c1 = (aligned(pdf, 1, "counts", np.uint32) & 0x7FFFFFFF).astype(np.int64)
        c2 = aligned(pdf, 2, "counts", np.uint32)
        h, w, _, _, _ = chunk.pairs(parts)
        mine = c2 >> 31 == 1
        c2 = (c2 & 0x7FFFFFFF).astype(np.int64)
        a = np.bincount(h[mine], weights=used(c2[mine], model.d2), minlength=len(c1))
        b = np.bincount(h[mine], weights=model.word(c1[w[mine]]), minlength=len(c1))
        _, cut = by_part(chunk.words, parts)
        rows = [(p, key[0], keys_out(chunk.words[x:y]), planes(c1[x:y]), planes(a[x:y]), planes(b[x:y])) for p, x, y in cut]
        return pd.DataFrame(rows, columns=["part", "chunk", "keys", "c", "a", "b"])

    return answers.select("kind", "part", "chunk", "counts").groupBy("chunk").applyInPandas(run, MASS)


def backoff_weights(mass: DataFrame) -> DataFrame:
    """alpha of every word, answered to each chunk in its order; negative where the context's total counts one more."""

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("chunk", kind="stable")
        keys = [keys_in(k) for k in pdf["keys"]]
        flat, first, which = np.unique(np.concatenate(keys), return_index=True, return_inverse=True)
        c, a, b = (np.concatenate([unplanes(x, kind) for x in pdf[col]]) for col, kind in (("c", np.int64), ("a", np.float64), ("b", np.float64)))
        c = c[first]
        a, b = np.bincount(which, weights=a), np.bincount(which, weights=b)
        full = (c > 0) & (c - a <= 1e-9 * c)
        total = np.where(full, c + 1, np.maximum(c, 1))
        alpha = np.where(c > 0, (1 - a / total) / np.maximum(1 - b, 1e-300), 1.0)
        answer = np.where(full, -alpha, alpha)[which]
        ends = np.cumsum([0, *(len(k) for k in keys)])
        return pd.DataFrame({"kind": 3, "part": key[0], "chunk": pdf["chunk"].to_numpy(), "counts": [planes(answer[x:y]) for x, y in zip(ends, ends[1:])]})

    return mass.groupBy("part").applyInPandas(run, WEIGHT)


SCORES = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def scores(answers: DataFrame, folder: str, parts: int, model: Model) -> DataFrame:
    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        chunk = Chunk.load(f"{folder}/{key[0]}")
        c1 = (aligned(pdf, 1, "counts", np.uint32) & 0x7FFFFFFF).astype(np.int64)
        c2 = (aligned(pdf, 2, "counts", np.uint32) & 0x7FFFFFFF).astype(np.int64)
        alpha = aligned(pdf, 3, "counts", np.float64)
        h, w, _, _, which = chunk.pairs(parts)
        total = np.where(alpha < 0, c1 + 1, np.maximum(c1, 1))
        p = np.where(c2 > 0, used(c2, model.d2) / total[h], np.abs(alpha[h]) * model.word(c1[w]))
        logs = np.log10(p)[which]
        known = c1[chunk.tok]
        base = np.log10((known + 1) / (model.n + model.v + 1))
        cut = chunk.at[:-1]
        n = np.diff(chunk.at)
        ids = pd.array(chunk.doc_id, dtype="Int64")
        ids[chunk.null_id] = pd.NA
        return pd.DataFrame({"doc_id": ids, "held_out": chunk.held, "n_tokens": n, "n_known": np.add.reduceat((known > 0).astype(np.int64), cut), "train_tokens": model.n, "base_score": np.add.reduceat(base, cut), "score": np.add.reduceat(logs, cut)})

    return answers.groupBy("chunk").applyInPandas(run, SCORES)


def hashed_out(doc_id: int | None, buckets: int = 7, held: int = 2) -> bool:
    return zlib.crc32(("" if doc_id is None else str(doc_id)).encode()) % buckets == held


def katz_scores(docs: DataFrame, held_out: Callable[[int | None], bool] = hashed_out, id_col: str = "doc_id", text_col: str = "text", chunk_tokens: int = 3_000_000, part_pairs: int = 2_000_000) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score (add-one), score (log10 probability by the backoff model) for every row."""
    view = docs_view(docs, id_col, text_col)
    spark = view.sparkSession
    n_bytes = view.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), n_bytes // 9 // part_pairs + 1)
    folder = scratch(spark, "chunks")
    answers = stored(add_counts(read_chunks(view, folder, parts, held_out, chunk_tokens)), "answers")
    per_kind = answers.where("size(stats) > 0").groupBy("kind").agg(*[F.sum(F.col("stats")[i]).alias(f"s{i}") for i in range(TOP + 3)]).collect()
    if not per_kind:
        return spark.createDataFrame([], SCORES)
    stats = {r.kind: list(r)[1:] for r in per_kind}
    model = Model(stats[1], stats[2])
    weights = stored(backoff_weights(context_mass(answers, folder, parts, model)), "weights")
    return scores(answers.select("kind", "part", "chunk", "counts").union(weights), folder, parts, model)
