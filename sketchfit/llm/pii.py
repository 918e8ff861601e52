r"""Personal data: base patterns, then information-theoretic sanitisation.

Base patterns find emails, IPs, cards and phones. The method then asks which plain terms give a protected entity (one such value) away. The words close to a mention form its context; equal
contexts of an entity count once, so copies of a document are no evidence, and only an entity with `support` contexts can be told by a term. The terms of an entity are all terms
of the documents that mention it, wherever they stand. With p(t|c) the share of the contexts of entity c whose document holds term t, and p(t) the share of all documents that hold t, a
term discloses c when the pointwise information log2(p(t|c)/p(t)) reaches `alpha` of the entity's own information -log2 p(c), on at least `support` contexts. Such a term is marked at
every place in every document that mentions the entity; `sanitise` generalises or removes it.

All statistics cover all documents. Every table that is broadcast is counted first; beyond `broadcast_rows` the same joins are shuffles.

Defined results: null text is empty and has no spans; repeated rows each get the same spans; matches that fail a check (range, Luhn, number of digits) are dropped without
a second try; very long runs of digits or letters take linear time; only id and text are read; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .common import docs_view, stored

# The patterns of the base kinds. An email is found from its @; an IP starts where a run of digits starts.
KINDS = ("email", "ip", "card", "phone", "term")
DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
LOCAL = re.compile(r"[A-Za-z0-9._%+-]")
IP = re.compile(r"(?<![0-9])[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
DIGIT = re.compile(r"[0-9]")
NO_ID = -(1 << 63)


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = 2 * d - 9 * (d > 4)
        total += d
    return total % 10 == 0


def only_digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) in code points, sorted."""
    out = []
    if "@" in text:
        end = 0
        for m in DOMAIN.finditer(text):
            at = start = m.start()
            while start > end and LOCAL.match(text[start - 1]):
                start -= 1
            if start < at:
                end = m.end()
                out.append((start, 0, end))
    if DIGIT.search(text):
        for m in IP.finditer(text):
            parts = (p.lstrip("0") for p in m[0].split("."))
            if all(len(p) < 3 or len(p) == 3 and int(p) <= 255 for p in parts):
                out.append((m.start(), 1, m.end()))
        for m in CARD.finditer(text):
            digits = only_digits(m[0])
            if 12 <= len(digits) <= 19 and luhn(digits):
                out.append((m.start(), 2, m.end()))
        if "+" in text:
            for m in PHONE.finditer(text):
                if 9 <= len(only_digits(m[0])) <= 15:
                    out.append((m.start(), 3, m.end()))
    return sorted(out)


PUNCT = ".,;:!?\"'()[]{}<>|*#$%&=+_/\\~`^-"
WORD = re.compile(r"\S+")


def term_hash(word: str) -> int | None:
    """Signed 64-bit hash of a plain term; None for short words and words without a letter."""
    w = word.strip(PUNCT).lower()
    if len(w) < 4 or not any(c.isalpha() for c in w):
        return None
    return xxhash.xxh64_intdigest(w.encode("utf-8", "surrogatepass")) - (1 << 63)


def mentions(text: str, spans: list[tuple[int, int, int]], words: int, reach: int) -> list[tuple[int, int]]:
    """(entity, context) of each span; the context is a hash of the `words` words on both sides, at most `reach` characters away."""
    out = []
    for start, kind, end in spans:
        value = text[start:end].lower() if kind == 0 else only_digits(text[start:end])
        entity = xxhash.xxh64_intdigest(f"{kind}:{value}".encode()) - (1 << 63)
        lo, hi = max(0, start - reach), min(len(text), end + reach)
        near = WORD.findall(text[lo:start])[-words:] + WORD.findall(text[end:hi])[:words]
        out.append((entity, xxhash.xxh64_intdigest(" ".join(near).encode("utf-8", "surrogatepass")) - (1 << 63)))
    return out


def term_places(text: str, spans: list[tuple[int, int]]) -> Iterator[tuple[int, int, int]]:
    """(term, start, end) of the plain terms of a text that stand clear of the spans (sorted, as (start, end))."""
    at = 0
    for m in WORD.finditer(text):
        while at < len(spans) and spans[at][1] <= m.start():
            at += 1
        if at < len(spans) and spans[at][0] < m.end():
            continue
        w = m[0]
        if (h := term_hash(w)) is not None:
            yield h, m.start() + len(w) - len(w.lstrip(PUNCT)), m.start() + len(w.rstrip(PUNCT))


def joined(spans) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


FOUND = "doc_id long, k2 long, n array<long>, base_sha256 string, base array<struct<start:int,kind:int,stop:int>>, near array<struct<entity:long,context:long>>"


def scan(docs: DataFrame, words: int, reach: int) -> DataFrame:
    arrow = to_arrow_schema(T._parse_datatype_string(FOUND))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cols: list[list] = [[] for _ in arrow]
            for doc_id, k2, text in zip(*(c.to_pylist() for c in batch.columns)):
                spans = base_spans(text)
                kinds = [k for _, k, _ in spans]
                near = mentions(text, spans, words, reach) if spans else []
                row = (doc_id, k2, [kinds.count(k) for k in range(4)], hashlib.sha256(joined(spans).encode()).hexdigest(), [{"start": s, "kind": k, "stop": e} for s, k, e in spans], [dict(zip(("entity", "context"), x)) for x in near])
                for c, v in zip(cols, row):
                    c.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(cols, arrow)], schema=arrow)

    return docs.mapInArrow(run, FOUND)


def term_counts(docs: DataFrame, wanted: set[int] | None) -> DataFrame:
    """term, df: documents that hold each term (of `wanted`, or any), summed within a task before the shuffle."""
    schema = "term long, df long"
    arrow = to_arrow_schema(T._parse_datatype_string(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: dict[int, int] = {}
        hashes: dict[str, int | None] = {}

        def flush():
            out = pa.RecordBatch.from_arrays([pa.array(list(counts), pa.int64()), pa.array(list(counts.values()), pa.int64())], schema=arrow)
            counts.clear()
            return out

        for batch in batches:
            for text in batch.column(0).to_pylist():
                kinds = set(text.split())
                for w in kinds.difference(hashes):
                    h = term_hash(w)
                    hashes[w] = h if wanted is None or h in wanted else None
                for h in {hashes[w] for w in kinds}:
                    if h is not None:
                        counts[h] = counts.get(h, 0) + 1
                if len(hashes) > 200_000:
                    hashes.clear()
            if len(counts) > 200_000:
                yield flush()
        yield flush()

    return docs.select("text").mapInArrow(run, schema).groupBy("term").agg(F.sum("df").alias("df"))


def terms_of(texts: DataFrame) -> DataFrame:
    """doc_id, k2, term for each distinct term of the documents; texts: doc_id, k2, text, base."""
    schema = "doc_id long, k2 long, terms array<long>"
    arrow = to_arrow_schema(T._parse_datatype_string(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                rows = [(i, k, sorted({h for h, _, _ in term_places(t, sorted((s["start"], s["stop"]) for s in base))})) for i, k, t, base in zip(*(c.slice(lo, 500).to_pylist() for c in batch.columns))]
                yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), arrow)], schema=arrow)

    return texts.select("doc_id", "k2", "text", "base").mapInArrow(run, schema).select("doc_id", "k2", F.explode("terms").alias("term"))


def marked(texts: DataFrame) -> DataFrame:
    """doc_id, k2, added: the places of `terms` in each text; texts: doc_id, k2, text, base, terms."""
    schema = "doc_id long, k2 long, added array<struct<start:int,kind:int,stop:int>>"
    arrow = to_arrow_schema(T._parse_datatype_string(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                rows = []
                for i, k, t, base, terms in zip(*(c.slice(lo, 500).to_pylist() for c in batch.columns)):
                    want = set(terms)
                    rows.append((i, k, [{"start": a, "kind": 4, "stop": b} for h, a, b in term_places(t, sorted((s["start"], s["stop"]) for s in base)) if h in want]))
                yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), arrow)], schema=arrow)

    return texts.select("doc_id", "k2", "text", "base", "terms").mapInArrow(run, schema)


def disclosing(docs: DataFrame, told: DataFrame, texts: DataFrame, alpha: float, support: int, broadcast_rows: int) -> DataFrame:
    """(entity, term, information) of the pairs over the threshold. told: doc_id, k2, entity, context of recurring entities; texts: the documents that mention them."""
    terms = stored(terms_of(texts), "terms")
    both = told.join(terms, ["doc_id", "k2"]).select("entity", "term", "context").distinct().groupBy("entity", "term").agg(F.count("context").alias("both"))
    pairs = stored(both.where(F.col("both") >= support), "pairs")
    contexts = told.select("entity", "context").distinct().groupBy("entity").agg(F.count("context").alias("contexts"))
    holders = told.select("entity", "doc_id", "k2").distinct().groupBy("entity").agg(F.count("k2").alias("docs"))
    kinds = pairs.select("term").distinct()
    n_terms = kinds.count()
    if not n_terms:
        return pairs.select("entity", "term", F.lit(0.0).alias("information"))
    wanted = {r.term for r in kinds.collect()} if n_terms <= broadcast_rows else None
    n = float(docs.count())
    joined_up = pairs.join(contexts, "entity").join(holders, "entity").join(term_counts(docs, wanted), "term")
    pmi = F.log2((F.col("both") / F.col("contexts")) / (F.col("df") / n))
    own = F.log2(F.lit(n) / F.col("docs"))
    return stored(joined_up.withColumn("information", pmi).where((F.col("information") > 0) & (F.col("information") >= alpha * own)).select("entity", "term", "information"), "disclosing")


def personal_data(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 6, reach: int = 120, alpha: float = 0.75, support: int = 3, broadcast_rows: int = 200_000) -> DataFrame:
    """doc_id, k2 (hash of the text), n (counts of base kinds), base_sha256, spans: array of (start, kind, stop), base and added ones."""
    view = docs_view(docs, id_col, text_col).select(F.coalesce("doc_id", F.lit(NO_ID)).alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).withColumn("k2", F.xxhash64("text"))
    found = stored(scan(view.select("doc_id", "k2", "text"), words, reach), "found")
    given = F.nullif(F.col("doc_id"), F.lit(NO_ID)).alias("doc_id")
    plain = found.select(given, "k2", "n", "base_sha256", F.col("base").alias("spans"))
    near = found.select("doc_id", "k2", F.explode("near").alias("m")).select("doc_id", "k2", "m.entity", "m.context").distinct()
    often = stored(near.select("entity", "context").distinct().groupBy("entity").agg(F.count("context").alias("c")).where(F.col("c") >= support).select("entity"), "often")
    n = often.count()
    if not n:
        return plain
    told = stored(near.join(F.broadcast(often) if n <= broadcast_rows else often, "entity"), "told")
    held = stored(told.select("doc_id", "k2").distinct(), "held")
    n_held = held.count()
    some = found.select("doc_id", "k2", "base").join(F.broadcast(held) if n_held <= broadcast_rows else held, ["doc_id", "k2"], "left_semi").dropDuplicates(["doc_id", "k2"])
    texts = view.join(F.broadcast(held) if n_held <= broadcast_rows else held, ["doc_id", "k2"], "left_semi").dropDuplicates(["doc_id", "k2"]).join(some, ["doc_id", "k2"])
    texts = stored(texts.select("doc_id", "k2", "text", "base"), "texts")
    pairs = disclosing(view, told, texts, alpha, support, broadcast_rows)
    per_doc = told.join(pairs, "entity").groupBy("doc_id", "k2").agg(F.collect_set("term").alias("terms"))
    added = marked(texts.join(per_doc, ["doc_id", "k2"]))
    spans = F.array_sort(F.concat("base", F.coalesce("added", F.array().cast("array<struct<start:int,kind:int,stop:int>>"))))
    return found.join(added, ["doc_id", "k2"], "left").select(given, "k2", "n", "base_sha256", spans.alias("spans"))


def sanitise(docs: DataFrame, mode: str = "generalise", id_col: str = "doc_id", text_col: str = "text", **kw) -> DataFrame:
    """Whole rows with personal data masked by kind; disclosing terms become their shape (`generalise`) or go (`remove`)."""
    found = personal_data(docs, id_col, text_col, **kw).where("size(spans) > 0").dropDuplicates(["doc_id", "k2"])
    found = found.select(F.coalesce("doc_id", F.lit(NO_ID)).alias("__k1"), F.col("k2").alias("__k2"), F.col("spans").alias("__spans"))
    key = (F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)) == F.col("__k1")) & (F.xxhash64(F.coalesce(F.col(text_col).cast("string"), F.lit(""))) == F.col("__k2"))
    own, at = docs.columns, docs.columns.index(text_col)
    both = docs.join(found, key, "left").select(*own, "__spans")
    arrow = to_arrow_schema(docs.schema)

    def masked(text: str | None, spans) -> str | None:
        if not spans:
            return text
        out, end = [], 0
        for s in spans:
            if s["start"] < end:
                continue
            out.append(text[end : s["start"]])
            kind, end = s["kind"], s["stop"]
            if kind < 4:
                out.append(f"[{KINDS[kind].upper()}]")
            elif mode == "generalise":
                out.append(re.sub(r"[^\W\d_]+", lambda m: "Xx" if m[0][0].isupper() else "x", text[s["start"] : end]))
        out.append(text[end:])
        return "".join(out)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cols = list(batch.columns[:-1])
            texts = [masked(t, s) for t, s in zip(cols[at].to_pylist(), batch.column(len(own)).to_pylist())]
            cols[at] = pa.array(texts, type=arrow.field(at).type)
            yield pa.RecordBatch.from_arrays(cols, schema=arrow)

    return both.mapInArrow(run, docs.schema)
