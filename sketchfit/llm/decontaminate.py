r"""Benchmark decontamination with a positional inverted index, in DataFrame operations only.

A posting is (term, document, position). The corpus index is built for the terms that a search needs: each window of a benchmark item is
searched from its two rarest terms (document counts come from a first pass over the whole corpus). Both lists are adjusted by the
term's offset in its item, so that postings of one occurrence meet in one alignment (document, item, shift). Alignments that hold at least two
of the chosen offsets are then compared word by word, and runs of matching words as long as a window are hits.

Nothing is dropped for being frequent: a frequent rarest term only makes more candidates. The benchmark is broadcast below a checked number of
words (`broadcast_words`), beyond which the same joins run as shuffles; so do the documents of candidates.

Defined results: null or empty text has no words and no hits; an item without words has no window; an item of fewer words than a window is one window;
repeated rows (same id and text) each get the same result; a null doc_id is an ordinary value; other columns are never read. Empty tables
give no hits.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import docs_view, stored

SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
NO_ID = -(1 << 63)


def lowered(text: Column) -> Column:
    """A-Z alone in lower case; for plain ASCII the built-in does the same, faster."""
    text = F.coalesce(text, F.lit(""))
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))


def words(text: Column) -> Column:
    """Words with at most one empty string at either end, so positions count from the same origin within a text."""
    return F.split(lowered(text), SEPARATORS, -1)


def word_count(found: Column) -> Column:
    n = F.size(found)
    return (n - (F.element_at(found, 1) == "").cast("int") - ((F.element_at(found, -1) == "") & (n > 1)).cast("int")).cast("long")


def postings(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The whole positional index: term, doc_id, positions (ascending). Write it partitioned by a hash of the term to search it often."""
    view = docs_view(docs, id_col, text_col)
    return view.select("doc_id", F.posexplode(words(F.col("text"))).alias("pos", "term")).where("term <> ''").groupBy("term", "doc_id").agg(F.array_sort(F.collect_list("pos")).alias("positions"))


def phrase(index: DataFrame, terms: list[str]) -> DataFrame:
    """doc_id and start of every exact occurrence; lists are intersected from the rarest term on."""
    if not terms:
        return index.select("doc_id", F.lit(0).alias("start")).where("false")
    seen = {r.term: r["count"] for r in index.where(F.col("term").isin(sorted(set(terms)))).groupBy("term").count().collect()}
    out = None
    for k in sorted(range(len(terms)), key=lambda i: seen.get(terms[i], 0)):
        part = index.where(F.col("term") == terms[k]).select("doc_id", F.explode("positions").alias("p")).select("doc_id", (F.col("p") - k).alias("start"))
        out = part if out is None else out.join(part, ["doc_id", "start"], "left_semi")
    return out


def proximity(index: DataFrame, terms: list[str], span: int) -> DataFrame:
    """doc_id, first and last of the places where all terms, in any order, lie within `span` consecutive words.

    For each position of the last-ending term the latest earlier position of every other term is taken, so each place is the tightest for its end.
    """
    wanted = sorted(set(terms))
    hits = index.where(F.col("term").isin(wanted)).select("doc_id", "term", F.explode("positions").alias("p"))
    before = Window.partitionBy("doc_id").orderBy("p").rangeBetween(-(span - 1), 0)
    for i, t in enumerate(wanted):
        hits = hits.withColumn(f"__{i}", F.max(F.when(F.col("term") == t, F.col("p"))).over(before))
    latest = [F.col(f"__{i}") for i in range(len(wanted))]
    all_there = F.lit(True)
    for c in latest:
        all_there = all_there & c.isNotNull()
    return hits.where(all_there).select("doc_id", (F.least(*latest) if len(latest) > 1 else latest[0]).alias("first"), F.col("p").alias("last"))


def item_words(items: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """item, off, term, len: the words of each item, offsets from 0."""
    view = items.select(F.col(id_col).cast("string").alias("item"), words(F.col(text_col).cast("string")).alias("w"))
    view = view.select("item", F.monotonically_increasing_id().alias("copy"), F.expr("filter(w, x -> x <> '')").alias("w")).where("size(w) > 0")
    view = view.groupBy("item", "w").agg(F.min("copy").alias("copy"))  # an item may stand there twice, or an id have two texts
    return view.select("item", "copy", F.size("w").alias("len"), F.posexplode("w").alias("off", "term"))


def find_hits(docs: DataFrame, items: DataFrame, window: int = 10, item_id: str = "item_id", item_text: str = "text", broadcast_words: int = 2_000_000) -> tuple[DataFrame, DataFrame]:
    """(documents with keys and word counts, hits: k1, k2, item, first, last) for views of docs_view's form."""
    spark = docs.sparkSession
    bench = stored(item_words(items, item_id, item_text), "bench")
    small = bench.count() <= broadcast_words
    hint = F.broadcast if small else (lambda df: df)

    keyed = docs.select(F.coalesce("doc_id", F.lit(NO_ID)).alias("k1"), F.xxhash64("text").alias("k2"), "doc_id", words(F.col("text")).alias("w"))
    tokens = keyed.select("k1", "k2", F.posexplode("w").alias("pos", "term"))

    # how rare each benchmark term is among all documents' tokens
    counts = tokens.select("term").join(hint(bench.select("term").distinct()), "term").groupBy("term").count()
    counts = stored(counts, "counts")
    rare = bench.join(hint(counts), "term", "left").fillna(0, ["count"])
    last = F.greatest(F.col("len") - window, F.lit(0))
    starts = F.sequence(F.greatest(F.col("off") - window + 1, F.lit(0)), F.least(F.col("off"), last))
    in_windows = rare.select("item", "copy", "off", "term", "len", "count", F.explode(starts).alias("start"))
    order = Window.partitionBy("item", "copy", "start").orderBy("count", "term", "off")
    chosen = in_windows.withColumn("r", F.row_number().over(order)).where("r <= 2").select("item", "copy", "off", "term", "len").distinct()

    # postings of the chosen terms, adjusted by offset, meet in alignments
    met = tokens.join(hint(stored(chosen, "chosen")), "term").select("k1", "k2", "item", "copy", "len", (F.col("pos") - F.col("off")).alias("shift"), "off")
    aligned = met.groupBy("k1", "k2", "item", "copy", "shift").agg(F.count("off").alias("n"), F.first("len").alias("len")).where(F.col("n") >= F.least(F.col("len"), F.lit(2), F.lit(window)))
    aligned = stored(aligned.select("k1", "k2", "item", "copy", "shift"), "aligned")

    # word by word, in the documents that have candidates
    some = aligned.select("k1", "k2").distinct()
    near = F.broadcast(some) if some.count() <= broadcast_words else some
    theirs = keyed.join(near, ["k1", "k2"], "left_semi").select("k1", "k2", "w").dropDuplicates(["k1", "k2"]).select("k1", "k2", F.posexplode("w").alias("pos", "term"))
    expected = aligned.join(hint(bench), ["item", "copy"]).select("k1", "k2", (F.col("shift") + F.col("off")).alias("pos"), "term", "item", "copy", "shift", "off", "len")
    same = theirs.join(expected, ["k1", "k2", "pos", "term"])
    run = Window.partitionBy("k1", "k2", "item", "copy", "shift").orderBy("off")
    islands = same.withColumn("g", F.col("off") - F.row_number().over(run)).groupBy("k1", "k2", "item", "copy", "shift", "g").agg(F.min("pos").alias("first"), F.max("pos").alias("last"), F.count("off").alias("n"), F.first("len").alias("len"))
    hits = islands.where(F.col("n") >= F.least(F.col("len"), F.lit(window))).select("k1", "k2", "item", "first", "last")
    return keyed, stored(hits, "hits")


def contamination(docs: DataFrame, items: DataFrame, window: int = 10, id_col: str = "doc_id", text_col: str = "text", **kw) -> DataFrame:
    """One row per document: doc_id, n_words, n_hit, n_items, items (ids in string order), contaminated."""
    keyed, hits = find_hits(docs_view(docs, id_col, text_col), items, window, **kw)
    covered = hits.select("k1", "k2", F.explode(F.sequence("first", "last")).alias("pos")).distinct().groupBy("k1", "k2").agg(F.count("pos").alias("n_hit"))
    which = hits.select("k1", "k2", "item").distinct().groupBy("k1", "k2").agg(F.array_sort(F.collect_list("item")).alias("items"))
    found = covered.join(which, ["k1", "k2"])
    rows = keyed.select("k1", "k2", "doc_id", word_count(F.col("w")).alias("n_words")).join(found, ["k1", "k2"], "left")
    items_col = F.coalesce("items", F.array().cast("array<string>"))
    return rows.select("doc_id", "n_words", F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"), F.size(items_col).cast("long").alias("n_items"), items_col.alias("items"), F.coalesce(F.col("n_hit") > 0, F.lit(False)).alias("contaminated"))


def drop_contaminated(docs: DataFrame, items: DataFrame, window: int = 10, id_col: str = "doc_id", text_col: str = "text", **kw) -> DataFrame:
    """Whole rows of the documents without a hit."""
    view = docs_view(docs, id_col, text_col)
    _, hits = find_hits(view, items, window, **kw)
    bad = hits.select(F.col("k1").alias("__b1"), F.col("k2").alias("__b2")).distinct()  # names that the documents' own columns cannot meet
    own = docs.columns
    keyed = docs.withColumns({"__k1": F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)), "__k2": F.xxhash64(F.col(text_col).cast("string"))})
    few = bad.count() <= kw.get("broadcast_words", 2_000_000)
    return keyed.join(F.broadcast(bad) if few else bad, (F.col("__k1") == F.col("__b1")) & (F.col("__k2") == F.col("__b2")), "left_anti").select(*own)
