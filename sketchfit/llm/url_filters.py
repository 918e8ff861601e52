r"""URL filters as a sort-merge range join on reversed hosts.

A host `a.b.c` becomes the key `c.b.a.`, so that a rule for a host and its subdomains covers one interval of keys:
from the rule's own key up to that key with its last `.` raised to `/`. Pages are range-partitioned and sorted by key and each
partition is swept once; a stack holds the host rules whose interval is open, nested ones on top, and each keeps its
path rules sorted, so that the longest fitting path is found by bisection along a chain of nested prefixes.

Rules are broadcast below a checked count (`max_rules`). Beyond it each url is joined by equality with the rule table on every
suffix of its host, which needs no broadcast and lets Spark split skewed hosts.

Defined results: a null url, or one without `://`, has empty host and path and no rule; the default verdict holds then. Repeated rows are
each judged. Rules of equal length: the longer host wins. Empty tables give empty results; other columns are carried untouched.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Iterator, Sequence

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

Rule = tuple[str, str]  # (verdict, host/path)


def split_url(url) -> tuple:
    """Column pair (host, path); A-Z alone are lower-cased in the host."""
    rest = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://(.*)$", 1)
    host = F.translate(F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    path = F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)
    return host, path


def reversed_key(host):
    """`a.b.c` -> `c.b.a.`"""
    return F.concat(F.array_join(F.reverse(F.split(host, r"\.", -1)), "."), F.lit("."))


class PathRules:
    """The path rules of one host, sorted; each knows the nearest rule whose path is a prefix of its own."""

    def __init__(self, paths: dict[str, str]):
        self.paths = sorted(paths)
        self.verdict = paths
        self.outer: list[int] = []
        stack: list[int] = []
        for i, p in enumerate(self.paths):
            while stack and not p.startswith(self.paths[stack[-1]]):
                stack.pop()
            self.outer.append(stack[-1] if stack else -1)
            stack.append(i)

    def longest(self, path: str) -> str | None:
        i = bisect_right(self.paths, path) - 1
        while i >= 0 and not path.startswith(self.paths[i]):
            i = self.outer[i]
        return self.paths[i] if i >= 0 else None


def rule_intervals(rules: Sequence[Rule]) -> list[tuple[str, str, str, PathRules]]:
    """(first key, end of keys, host, path rules) by first key; a host's interval nests in or is apart from any other's."""
    by_host: dict[str, dict[str, str]] = {}
    for verdict, rule in rules:
        host, slash, path = rule.partition("/")
        by_host.setdefault(host.lower(), {})[slash + path] = verdict
    out = []
    for host, paths in by_host.items():
        key = ".".join(reversed(host.split("."))) + "."
        out.append((key, key[:-1] + "/", host, PathRules(paths)))
    return sorted(out, key=lambda x: x[0].encode())


def sweep(pairs: Iterator[tuple[str, str]], intervals: list[tuple[str, str, str, PathRules]], default: str) -> Iterator[tuple[str | None, str]]:
    """Verdicts for (key, path) pairs that come sorted by key; each interval is opened and closed once."""
    stack: list[tuple[str, str, str, PathRules]] = []
    at = 0
    for key, path in pairs:
        k = key.encode()
        while at < len(intervals) and intervals[at][0].encode() <= k:
            while stack and stack[-1][1].encode() <= intervals[at][0].encode():
                stack.pop()
            stack.append(intervals[at])
            at += 1
        while stack and stack[-1][1].encode() <= k:
            stack.pop()
        best: tuple[int, int, str, str] | None = None
        for _, _, host, rules in stack:
            found = rules.longest(path)
            if found is not None and (best is None or (len(host) + len(found), len(host)) > best[:2]):
                best = (len(host) + len(found), len(host), host + found, rules.verdict[found])
        yield (best[2], best[3]) if best else (None, default)


def filter_urls(pages: DataFrame, rules: Sequence[Rule] | DataFrame, default: str = "allow", url_col: str = "url", max_rules: int = 500_000) -> DataFrame:
    """All columns of pages with host, path, rule and verdict; those four names are replaced if pages has them already."""
    if isinstance(rules, DataFrame):
        few = rules.select("verdict", "rule").limit(max_rules + 1).collect()
        if len(few) > max_rules:
            return by_suffix(pages, rules, default, url_col)
        rules = [(r.verdict, r.rule) for r in few]
    intervals = rule_intervals(rules)
    host, path = split_url(F.col(url_col))
    own = [c for c in pages.columns if c not in ("host", "path", "rule", "verdict")]
    keyed = pages.select(*own, host.alias("host"), path.alias("path")).withColumn("__key", F.when(F.col("host") == "", F.lit("")).otherwise(reversed_key(F.col("host"))))
    sort = [F.col("__key"), F.xxhash64(F.col(own[0]), F.col(url_col))]  # the hash splits a host that holds many pages
    dealt = keyed.withColumn("__tie", sort[1]).repartitionByRange(F.col("__key"), F.col("__tie")).sortWithinPartitions("__key").drop("__tie")
    schema = T.StructType([*keyed.schema.fields, T.StructField("rule", T.StringType()), T.StructField("verdict", T.StringType())])
    arrow = to_arrow_schema(schema)
    names = keyed.columns
    i_key, i_path = names.index("__key"), names.index("path")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def pairs():
            for batch in batches:
                waiting.append(batch)
                yield from zip(batch.column(i_key).to_pylist(), batch.column(i_path).to_pylist())

        waiting: list[pa.RecordBatch] = []
        out: list[tuple[str | None, str]] = []
        for got in sweep(pairs(), intervals, default):
            out.append(got)
            if len(out) == waiting[0].num_rows:
                batch = waiting.pop(0)
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([x[0] for x in out], pa.string()), pa.array([x[1] for x in out], pa.string())], schema=arrow)
                out = []
            while waiting and not waiting[0].num_rows:
                waiting.pop(0)

    return dealt.mapInArrow(run, schema).drop("__key")


def by_suffix(pages: DataFrame, rules: DataFrame, default: str, url_col: str) -> DataFrame:
    """The way for rule tables too large to broadcast: equality on each suffix of the host, then the path's prefix."""
    host, path = split_url(F.col(url_col))
    own = [c for c in pages.columns if c not in ("host", "path", "rule", "verdict")]
    row = F.struct(*[F.col(c) for c in own]).alias("__row")
    keyed = pages.select(row, host.alias("host"), path.alias("path"), F.monotonically_increasing_id().alias("__id")).checkpoint()
    labels = F.split("host", r"\.", -1)
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    r = rules.select(F.col("verdict").alias("__verdict"), F.col("rule").alias("__rule"), F.lower(F.substring_index("rule", "/", 1)).alias("__host"))
    r = r.withColumn("__path", F.expr("substring(__rule, length(__host) + 1)"))
    hits = keyed.select("__id", "path", F.explode(suffixes).alias("__host")).join(r, "__host").where(F.startswith(F.col("path"), F.col("__path")))
    best = hits.groupBy("__id").agg(F.max(F.struct(F.length("__rule").alias("n"), F.length("__host").alias("h"), F.concat("__host", "__path").alias("rule"), F.col("__verdict").alias("v"))).alias("b"))
    out = keyed.join(best, "__id", "left")
    return out.select("__row.*", "host", "path", F.col("b.rule").alias("rule"), F.coalesce("b.v", F.lit(default)).alias("verdict"))
