r"""Quality rules by compression bands.

A document passes when it holds enough words, does not repeat itself, and its zstandard ratio (bytes before /
bytes after) lies in a band that depends on its length. Every fixed chunk, the last one too, has a band for its own
length; a document goes when more than a share of its chunks, or some chunks in a row, fall outside, so a long text
cannot hide a repetitive or random stretch behind the rest.

Defined results: null or empty text has no words, fails the base rule and is not kept; repeated rows are each judged
alone; an empty table gives an empty result; other columns are carried untouched and may have any name.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from .common import ASCII_SPACE, over_rows

SYMBOLS = b"#*$%&|<>"


Limits = tuple[tuple[int, float, float], ...]

# Fixed values: (bytes from, lowest ratio, highest ratio) by rising length. Short texts compress little and vary more. The highest ratios of
# wholes stand a few hundredths above those of prose measured on a whole table, the lowest well below, towards what random characters reach.
WHOLE: Limits = (
    (0, 0.0, 2.6), (300, 1.1, 1.9), (400, 1.15, 2.0), (560, 1.2, 2.05), (800, 1.25, 2.15), (1100, 1.35, 2.2), (1600, 1.45, 2.32), (2200, 1.5, 2.32),
    (3200, 1.55, 2.36), (4500, 1.6, 2.42), (6400, 1.65, 2.45), (9000, 1.7, 2.56), (18000, 1.75, 2.68), (40000, 1.8, 3.2), (200000, 1.8, 4.5),
)
CHUNK: Limits = ((0, 0.0, 99.0), (64, 0.8, 3.0), (128, 1.0, 3.5), (256, 1.1, 4.0), (512, 1.2, 4.5), (1024, 1.3, 5.0))


def limits_of(limits: Limits, n: int) -> tuple[float, float]:
    low, high = limits[0][1:]
    for start, lo, hi in limits:
        if n >= start:
            low, high = lo, hi
    return low, high


@dataclass(frozen=True)
class Bands:
    """Bands of wholes and chunks; bad_share: largest share of a text's chunks outside their band; bad_run: so many in a row are too many."""

    whole: Limits = WHOLE
    parts: Limits = CHUNK
    chunk: int = 1024
    bad_share: float = 0.2
    bad_run: int = 4
    level: int = 3


def compression(data: bytes, bands: Bands, coder: zstandard.ZstdCompressor) -> tuple[float, int, int, bool]:
    """Ratio of the whole, chunks outside their band, chunks, verdict."""
    if not data:
        return 0.0, 0, 0, False
    ratio = len(data) / len(coder.compress(data))
    low, high = limits_of(bands.whole, len(data))
    bad = run = longest = n = 0
    for at in range(0, len(data), bands.chunk):
        part = data[at : at + bands.chunk]
        least, most = limits_of(bands.parts, len(part))
        n += 1
        if least <= len(part) / len(coder.compress(part)) <= most:
            run = 0
        else:
            bad, run = bad + 1, run + 1
            longest = max(longest, run)
    return ratio, bad, n, low <= ratio <= high and bad <= bands.bad_share * n and longest < bands.bad_run


def base_counts(text: str) -> tuple[int, int, int, int, int]:
    """Words, their code points, symbols, repeated lines, words in repeated 3-word windows."""
    data = text.encode("utf-8", "surrogatepass")
    words = data.split()
    n = len(words)
    word_chars = len(text) - (len(data) - len(data.translate(None, ASCII_SPACE)))
    symbols = len(data) - len(data.translate(None, SYMBOLS))
    seen, dup_lines = set(), 0
    for line in data.split(b"\n"):
        if line in seen:
            dup_lines += 1
        elif line.strip():
            seen.add(line)
    windows = list(zip(words, words[1:], words[2:]))
    repeated = 0
    counts = Counter(windows)
    if len(counts) < len(windows):
        end = 0
        for i, w in enumerate(windows):
            if counts[w] > 1:
                repeated += i + 3 - max(end, i)
                end = i + 3
    return n, word_chars, symbols, dup_lines, repeated


FIELDS = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, ratio double, bad_chunks long, n_chunks long, kept boolean"


def judged(text: str | None, bands: Bands, coder: zstandard.ZstdCompressor) -> tuple:
    text = text or ""
    n, chars, symbols, lines, repeat = base_counts(text)
    failed = n < 50 or 100 * repeat > 50 * n
    ratio, bad, full, fine = compression(text.encode("utf-8", "surrogatepass"), bands, coder)
    return n, chars, symbols, lines, repeat, failed, ratio, bad, full, fine and not failed


def judge(docs: DataFrame, bands: Bands = Bands(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, the counts, ratios and the verdict."""
    coder = None

    def each(key, text):
        nonlocal coder
        coder = coder or zstandard.ZstdCompressor(level=bands.level)
        return (key, *judged(text, bands, coder))

    # each worker makes its own coder: it cannot be pickled
    kind = docs.schema[id_col].dataType.simpleString()
    return over_rows(docs.select(F.col(id_col), F.col(text_col).cast("string")), f"`{id_col}` {kind}, {FIELDS}", each)


def keep_good(docs: DataFrame, bands: Bands = Bands(), text_col: str = "text") -> DataFrame:
    """Whole rows of the documents that pass, in one narrow pass."""
    at = docs.columns.index(text_col)
    schema = docs.schema
    arrow = to_arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = zstandard.ZstdCompressor(level=bands.level)
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                part = batch.slice(lo, 1000)
                verdicts = [judged(t, bands, coder)[-1] for t in part.column(at).to_pylist()]
                yield pa.RecordBatch.from_arrays(part.filter(pa.array(verdicts, pa.bool_())).columns, schema=arrow)

    return docs.mapInArrow(run, schema)
