r"""Exact n-gram Jaccard join with signature trees.

1. Every document becomes the set of hashes of its word n-grams; equal sets form one class, which goes on as one row.
2. Two sets with Jaccard >= t differ in at most (1-t)/(1+t) of their summed sizes. Each set is dealt into more parts than it may have
   differences (by hash of the n-gram, for size levels that any similar pair shares), so a similar pair has an equal part. Equal parts form buckets.
3. Each set is first compared with one earlier set of its buckets, which joins most copies; connected components follow.
4. Buckets that still hold several components are searched by a signature tree: its nodes hold OR-combined (and AND-combined) n-gram bitmaps and size
   ranges, and a dual traversal leaves out node pairs whose largest possible overlap is too small or which lie in one component already.
   Bitmaps are as wide as their sets ask for, or a bitmap full of ones would rule out no pair of large sets; a bucket's are folded to the narrowest.
   Buckets over a limit are cut into blocks, one task for each pair of blocks, so no task holds an unbounded group and no pair is lost.
   Where every pair that a search proposed is in one component in the end, the pairs that it passed over are too: only buckets with a refuted pair are searched again.

Components are exact: part keys only propose, every link is decided on the whole sets. No document or partner is dropped for being frequent.

Defined results: null text and text without words have an empty set and stand alone; fewer words than n give one n-gram of the whole sequence; repeated rows and equal
doc_ids stay separate rows; only id and text are read, so other columns may have any name; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .common import UPPER_TO_LOWER, docs_view, release, stored, with_totals
from .components import components
from .packed import parts_for, repeated

U = np.uint64
LEVEL = 1.3
NO_ID = -(1 << 63)


def mix(x: np.ndarray, salt: int) -> np.ndarray:
    """A bijection of 64-bit values that spreads every input bit (finaliser of a common generator)."""
    x = x + U(salt * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


class WordHashes:
    """64-bit hashes of words; a bounded number is remembered, besides those of the text at hand."""

    def __init__(self, most: int = 150_000):
        self.seen: dict[bytes, int] = {}
        self.most = most

    def of(self, words: list[bytes]) -> np.ndarray:
        if len(self.seen) > self.most:
            self.seen = {}
        seen = self.seen
        for w in set(words).difference(seen):
            seen[w] = xxhash.xxh64_intdigest(w)
        return np.fromiter(map(seen.__getitem__, words), dtype=U, count=len(words))


def shingle_set(text: str | None, n: int, hashes: WordHashes) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the word n-grams; A-Z lower-cased."""
    words = (text or "").encode("utf-8", "surrogatepass").translate(UPPER_TO_LOWER).split()
    if not words:
        return np.zeros(0, dtype=U)
    h = hashes.of(words)
    m = min(n, len(words))
    s = np.full(len(words) - m + 1, U(m))
    for i in range(m):
        s = mix(s ^ h[i : len(h) - m + 1 + i], i + 1)
    return np.unique(s)


def level_start(i: int) -> int:
    return math.ceil(LEVEL**i)


def level_of(n: int) -> int:
    i = max(0, int(math.log(n) / math.log(LEVEL)) - 1)
    while level_start(i + 1) <= n:
        i += 1
    return i


def parts_of(i: int, num: int, den: int) -> tuple[int, int]:
    """(parts, empty parts a set may leave out) of a level: more than the differences of any similar pair in it, plus slack for empty parts."""
    most = level_start(i + 1) - 1
    diff = (den - num) * 2 * most // (den + num)
    if not diff:
        return 1, 0
    slack = 3 + math.ceil(2 * (diff + 1) * math.exp(-level_start(i) / (diff + 1)))
    return diff + 1 + slack, slack


def part_keys(s: np.ndarray, num: int, den: int) -> np.ndarray:
    """One key for each part and level; sets with Jaccard >= num/den share at least one."""
    n = len(s)
    if not n:
        return np.zeros(0, dtype=U)
    i = level_of(n)
    levels = [i]
    if n * den >= level_start(i + 1) * num:  # a similar set may be in the next level
        levels.append(i + 1)
    spread, value, out = mix(s, 11), mix(s, 12), []
    for level in levels:
        k, slack = parts_of(level, num, den)
        if k == 1:
            continue  # only equal sets can be similar there
        part = (spread % U(k)).astype(np.int64)
        order = np.argsort(part, kind="stable")
        cuts = np.flatnonzero(np.diff(part[order], prepend=-1))
        ids = part[order][cuts]
        sums = np.add.reduceat(value[order], cuts)
        if k - len(ids) > slack:
            ids, sums = np.concatenate([ids, missing := np.setdiff1d(np.arange(k), ids)]), np.concatenate([sums, np.zeros(len(missing), dtype=U)])
        out.append(mix(mix(sums, 13) ^ ids.astype(U), 14 + level))
    return np.concatenate(out) if out else np.zeros(0, dtype=U)


def similar(a: np.ndarray, b: np.ndarray, num: int, den: int) -> bool:
    if min(len(a), len(b)) * den < max(len(a), len(b)) * num:
        return False
    both = len(np.intersect1d(a, b, assume_unique=True))
    return den * both >= num * (len(a) + len(b) - both) and both > 0


SETS = "doc_id long, n long, sid binary, keys binary"


def signatures(docs: DataFrame, n: int, num: int, den: int) -> DataFrame:
    arrow = to_arrow_schema(T._parse_datatype_string(SETS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hashes = WordHashes()
            for lo in range(0, batch.num_rows, 1000):
                rows = []
                for doc_id, text in zip(*(c.slice(lo, 1000).to_pylist() for c in batch.columns[:2])):
                    s = shingle_set(text, n, hashes)
                    sid = hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None
                    rows.append((doc_id, len(s), sid, part_keys(s, num, den).tobytes()))
                yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), arrow)], schema=arrow)

    return docs.mapInArrow(run, SETS)


def sets_of(docs: DataFrame, n: int) -> DataFrame:
    """sid, n (number of grams), grams (array of longs), bits (bitmap of the grams) of documents."""
    schema = "sid binary, n long, grams array<long>, bits binary"
    arrow = to_arrow_schema(T._parse_datatype_string(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hashes = WordHashes()
            for lo in range(0, batch.num_rows, 512):
                sets = [shingle_set(t, n, hashes) for t in batch.column(1).slice(lo, 512).to_pylist()]
                sids = [hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None for s in sets]
                offsets = np.concatenate([[0], np.cumsum([len(s) for s in sets])]).astype(np.int32)
                flat = pa.array(np.concatenate(sets).view(np.int64) if sets else [], type=pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(sids, pa.binary()), pa.array([len(s) for s in sets], pa.int64()), pa.ListArray.from_arrays(pa.array(offsets), flat).cast(arrow.field(2).type), pa.array([bitmap(s) for s in sets], pa.binary())], schema=arrow)

    return docs.mapInArrow(run, schema)


BITS, MOST_BITS = 4096, 1 << 17
FANOUT = 8


def bitmap(s: np.ndarray) -> bytes:
    """A bit for each n-gram's hash; at least twice as many bits as n-grams, up to MOST_BITS, and a power of two."""
    width = min(max(BITS, 1 << (2 * len(s) - 1).bit_length()), MOST_BITS) if len(s) else BITS
    bits = np.zeros(width, dtype=bool)
    bits[(mix(s, 21) % U(width)).astype(np.int64)] = True
    return np.packbits(bits).tobytes()


def folded(bits: bytes, n_bytes: int) -> bytes:
    """The bitmap that the same set would have at a smaller width."""
    if len(bits) == n_bytes:
        return bits
    return np.bitwise_or.reduce(np.frombuffer(bits, dtype=np.uint8).reshape(-1, n_bytes), axis=0).tobytes()


class Node:
    __slots__ = ("low", "high", "some", "every", "comp", "below", "at")

    def __init__(self, low, high, some, every, comp, below, at=-1):
        self.low, self.high, self.some, self.every, self.comp, self.below, self.at = low, high, some, every, comp, below, at


def signature_tree(places: list[int], sizes: list[int], bits: list[bytes], comps: list[int]) -> Node:
    """Leaves by size; inner nodes join up to FANOUT neighbours: size range, OR and AND of the bitmaps, the component if it is one."""
    nodes = []
    for at in sorted(places, key=lambda i: (sizes[i], bits[i])):
        word = int.from_bytes(bits[at], "big")
        nodes.append(Node(sizes[at], sizes[at], word, word, comps[at], (), at))
    while len(nodes) > 1:
        up = []
        for i in range(0, len(nodes), FANOUT):
            part = nodes[i : i + FANOUT]
            some, every = 0, -1
            for x in part:
                some |= x.some
                every &= x.every
            comp = part[0].comp if all(x.comp == part[0].comp for x in part) else -1
            up.append(Node(min(x.low for x in part), max(x.high for x in part), some, every, comp, tuple(part)))
        nodes = up
    return nodes[0]


def tree_pairs(sizes: list[int], bits: list[bytes], comps: list[int], num: int, den: int, joins: Callable[[int, int], bool], sides: list[int] | None = None) -> None:
    """Dual traversal: joins(i, j) is asked for every pair of places in different components whose bound allows Jaccard >= num/den.

    Where it says yes, the two components are one from then on. sides: only pairs across two blocks.
    """
    top = {c: c for c in comps}

    def find(c: int) -> int:
        while top[c] != c:
            top[c] = top[top[c]]
            c = top[c]
        return c

    def apart(a: Node, b: Node) -> bool:
        if a.high * den < b.low * num or b.high * den < a.low * num:
            return True
        if a.comp != -1 and b.comp != -1 and find(a.comp) == find(b.comp):
            return True
        overlap = min(a.high - (a.every & ~b.some).bit_count(), b.high - (b.every & ~a.some).bit_count())
        return (num + den) * overlap < num * (a.low + b.low)

    width = min(map(len, bits), default=0)
    bits = [folded(b, width) for b in bits]
    groups = [[i for i in range(len(sizes)) if sides is None or sides[i] == side] for side in ((0,) if sides is None else (0, 1))]
    if not all(groups):
        return
    roots = [signature_tree(g, sizes, bits, comps) for g in groups]
    stack = [(roots[0], roots[-1])]
    while stack:
        a, b = stack.pop()
        if a is b:
            if a.comp == -1:
                stack.extend((x, y) for i, x in enumerate(a.below) for y in a.below[i:])
        elif not apart(a, b):
            if not a.below and not b.below:
                if joins(a.at, b.at):
                    top[find(a.comp)] = find(b.comp)
            elif a.below and (not b.below or a.high - a.low >= b.high - b.low):
                stack.extend((x, b) for x in a.below)
            else:
                stack.extend((a, y) for y in b.below)


def tree_links(sets: list[np.ndarray], num: int, den: int) -> list[tuple[int, int]]:
    """For sets in memory: links enough to connect all that are similar, each decided on the whole sets."""
    links: list[tuple[int, int]] = []

    def joins(i: int, j: int) -> bool:
        if similar(sets[i], sets[j], num, den):
            links.append((i, j))
            return True
        return False

    if sets:
        tree_pairs([len(s) for s in sets], [bitmap(s) for s in sets], list(range(len(sets))), num, den, joins)
    return links


def proved(pairs: DataFrame, grams: DataFrame, num: int, den: int) -> DataFrame:
    """The pairs (a, b) whose whole sets are similar."""
    one = grams.select(F.col("rid").alias("a"), F.col("grams").alias("g1"))
    two = grams.select(F.col("rid").alias("b"), F.col("grams").alias("g2"))
    common = F.size(F.array_intersect("g1", "g2"))
    return pairs.join(one, "a").join(two, "b").where(den * common >= num * (F.size("g1") + F.size("g2") - common)).select("a", "b")


def proved_in_turns(pairs: DataFrame, grams: DataFrame, links: DataFrame, labels: DataFrame, num: int, den: int) -> tuple[DataFrame, DataFrame]:
    """(links, labels) with those of the pairs (a, b, cost) added. The sets of all pairs may be far more than the sets themselves: each turn moves about as much as
    these are, and pairs that an earlier turn's links have joined need no proof."""
    moved, whole = pairs.agg(F.sum("cost")).first()[0] or 0, grams.agg(F.sum("n")).first()[0] or 1
    turns = max(1, -(-moved // whole))
    turn = lambda c: F.pmod(F.xxhash64(c), F.lit(turns))
    for t in range(turns):
        mine = pairs.where(turn("a") == t).select("a", "b")
        if t:
            comp = labels.select("id", "comp")
            mine = mine.join(comp.toDF("a", "ca"), "a", "left").join(comp.toDF("b", "cb"), "b", "left").where(~F.coalesce(F.col("ca") == F.col("cb"), F.lit(False))).select("a", "b")
        more = stored(proved(mine, grams, num, den), "links")
        if more.limit(1).count():
            old = links
            links = stored(links.union(more), "links")
            release(old)
            labels = components(links)
        release(more)
    return links, labels


def open_buckets(buckets: DataFrame, labels: DataFrame) -> DataFrame:
    """key, rid, comp of the buckets that hold several components, of buckets with the same sets one."""
    named = buckets.join(labels.withColumnRenamed("id", "rid"), "rid", "left").withColumn("comp", F.coalesce("comp", "rid"))
    named = stored(named, "named")
    kinds = named.groupBy("key").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count("rid").alias("c"), F.expr("bit_xor(xxhash64(rid))").alias("x"), F.sum(F.shiftright(F.xxhash64("rid", F.lit(1)), 8)).alias("y"))
    keys = stored(kinds.where("lo < hi").groupBy("c", "x", "y").agg(F.min("key").alias("key")).select("key", "c"), "keys")
    return with_totals(named, keys, ["key"]).select("key", "rid", "comp")


def tree_candidates(left: DataFrame, marks: DataFrame, num: int, den: int, block_sets: int, spanning: bool) -> DataFrame:
    """(a, b, cost: summed sizes) that the signature trees of the buckets cannot rule out; spanning: once two components have met in a bucket, no more of them there.

    A bucket of more than block_sets sets, or of 2 KB of bitmaps for each of these, is cut into blocks and each pair of blocks is a task's group.
    """
    weighed = left.select("key", "rid").join(marks.select("rid", F.octet_length("bits").alias("w")), "rid")
    cut = weighed.groupBy("key").agg(F.count("rid").alias("c"), F.sum("w").alias("w"))
    cut = cut.select("key", "c", F.ceil(F.greatest("c", F.col("w") / 2048) / block_sets).cast("int").alias("m"))
    block = F.pmod(F.xxhash64("rid"), F.col("m")).cast("int")
    dealt = with_totals(left, cut, ["key"]).withColumn("block", block).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("m") - 1)))
    dealt = dealt.select("key", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "rid", "comp").join(marks, "rid")

    schema = "a long, b long, cost long"
    arrow = to_arrow_schema(T._parse_datatype_string(schema))

    def pairs_of(group: tuple, rows: list[tuple]) -> list[tuple[int, int, int]]:
        side, rid, comp, n, bits = zip(*rows)
        out: list[tuple[int, int, int]] = []

        def joins(x: int, y: int) -> bool:
            out.append((min(rid[x], rid[y]), max(rid[x], rid[y]), n[x] + n[y]))
            return spanning

        sides = None if group[1] == group[2] else [int(x == group[2]) for x in side]
        tree_pairs(list(n), list(bits), list(comp), num, den, joins, sides)
        return out

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by group; one group of bounded size is held at a time."""
        group, held, found = None, [], []
        for part in (batch.slice(lo, 500) for batch in batches for lo in range(0, batch.num_rows, 500)):
            for key, i, j, *row in zip(*(c.to_pylist() for c in part.columns)):
                if (key, i, j) != group:
                    if held:
                        found += pairs_of(group, held)
                    group, held = (key, i, j), []
                held.append(tuple(row))
            if len(found) > 100_000:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*found)], schema=arrow)
                found = []
        if held:
            found += pairs_of(group, held)
        if found:
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*found)], schema=arrow)

    rows = dealt.select("key", "i", "j", "block", "rid", "comp", "n", "bits")
    return rows.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j").mapInArrow(search, schema).distinct()


def disputed(left: DataFrame, pairs: DataFrame, labels: DataFrame) -> DataFrame:
    """key, rid of the buckets that may hold both ends of a proposed pair whose components still differ."""
    named = lambda x, c: labels.select(F.col("id").alias(x), F.col("comp").alias(c))
    refuted = pairs.join(named("a", "ca"), "a", "left").join(named("b", "cb"), "b", "left").where(F.coalesce("ca", "a") != F.coalesce("cb", "b"))
    ends = refuted.select(F.col("a").alias("rid")).union(refuted.select("b")).distinct()
    keys = left.join(ends, "rid").groupBy("key").agg(F.count("rid").alias("k")).where("k > 1").select("key")
    total = left.groupBy("key").agg(F.count("rid").alias("c")).join(keys, "key")
    return with_totals(left, total, ["key"]).select("key", "rid")


def link_classes(docs: DataFrame, n: int, num: int, den: int, block_sets: int = 4000, partition_keys: int = 750_000) -> tuple[DataFrame, DataFrame]:
    """(doc_id, n, sid of every row; sid and component_id of every class of equal sets). docs: docs_view's form without null ids."""
    signed = stored(signatures(docs, n, num, den), "signatures")
    keyed = signed.where("sid is not null").groupBy("sid").agg(F.min("doc_id").alias("doc_id"), F.first("keys").alias("keys"))
    keyed = stored(keyed.withColumn("rid", F.monotonically_increasing_id()), "classes")
    sizes = stored(signed.select("doc_id", "n", "sid"), "sizes")
    release(signed)  # part keys are the bulk of it
    buckets = stored(repeated(keyed, ["rid"], parts_for(keyed, "keys", partition_keys)), "buckets")
    reps = stored(keyed.select("sid", "doc_id", "rid"), "classes")
    release(keyed)

    # one earlier set for each set; ids of classes rise in no meaningful order, any choice is right
    heads = stored(buckets.groupBy("key").agg(F.min("rid").alias("head"), F.count("rid").alias("c")), "heads")
    tried = with_totals(buckets, heads, ["key"]).where("rid <> head").groupBy("rid", "head").agg(F.count("key").alias("c"))
    first = stored(tried.groupBy("rid").agg(F.max_by("head", F.struct("c", -F.col("head"))).alias("head")), "first")
    ids = stored(first.select("rid").union(first.select("head")).union(buckets.select("rid")).distinct(), "ids")
    some = reps.select("rid", "sid", "doc_id").join(ids, "rid")
    few = some.count() <= 1_000_000
    wanted = some.select("doc_id").distinct()
    theirs = docs.join(F.broadcast(wanted) if few else wanted, "doc_id", "left_semi")
    grams = sets_of(theirs.select("doc_id", "text"), n).where("sid is not null").join(some.select("sid", "rid"), "sid").dropDuplicates(["rid"])
    grams = stored(grams.select("rid", "n", "grams", "bits"), "grams")
    links = stored(proved(first.select(F.col("rid").alias("a"), F.col("head").alias("b")), grams, num, den), "links")
    labels = components(links)

    # what is left: first enough pairs to join what belongs together, then every pair that the bounds leave
    marks = grams.select("rid", "n", "bits")
    left = stored(open_buckets(buckets, labels), "open")
    for spanning in (True, False):
        if not left.limit(1).count():
            break
        pairs = stored(tree_candidates(left, marks, num, den, block_sets, spanning), "candidates")
        links, labels = proved_in_turns(pairs, grams, links, labels, num, den)
        if spanning:
            again = stored(open_buckets(disputed(left, pairs, labels), labels), "open")
            release(left)
            left = again
        release(pairs)
    release(left)
    classes = reps.select("sid", "doc_id", "rid").join(labels.withColumnRenamed("id", "rid"), "rid", "left").withColumn("comp", F.coalesce("comp", "rid"))
    classes = stored(classes.select("sid", "doc_id", "comp"), "classes")
    least = classes.groupBy("comp").agg(F.min("doc_id").alias("component_id"), F.count("sid").alias("c"))
    out = stored(with_totals(classes, least, ["comp"]).select("sid", "component_id"), "groups")
    release(reps, buckets, heads, first, ids, grams, classes)
    return sizes, out


def jaccard_components(docs: DataFrame, n: int = 5, num: int = 80, den: int = 100, id_col: str = "doc_id", text_col: str = "text", **kw) -> DataFrame:
    """doc_id, n_shingles, component_id (least doc_id reachable by links of Jaccard >= num/den) for every row. The whole corpus is shingled once."""
    view = docs_view(docs, id_col, text_col).withColumn("doc_id", F.coalesce("doc_id", F.lit(NO_ID)))
    sizes, groups = link_classes(view, n, num, den, **kw)
    joined = sizes.join(groups, "sid", "left")
    given = lambda c: F.nullif(c, F.lit(NO_ID))
    return joined.select(given(F.col("doc_id")).alias("doc_id"), F.col("n").alias("n_shingles"), given(F.coalesce("component_id", "doc_id")).alias("component_id"))


def drop_near_duplicates(docs: DataFrame, n: int = 5, num: int = 80, den: int = 100, id_col: str = "doc_id", text_col: str = "text", **kw) -> DataFrame:
    """Whole rows: of each component the one with the least doc_id stays, of rows with one id and text one; documents without words stay.

    Rows that share an id but not the text are told apart by the text: both stay where that id is the least of their component.
    """
    comp = jaccard_components(docs, n, num, den, id_col, text_col, **kw)
    keep = comp.where(F.col("component_id").eqNullSafe(F.col("doc_id"))).select("doc_id", "n_shingles").distinct()
    own = docs.columns
    few = keep.select(F.col("doc_id").alias("__keep")).distinct()
    rows = docs.join(few, docs[id_col].cast("long").eqNullSafe(few["__keep"]), "left_semi")
    return rows.withColumn("__h", F.xxhash64(F.col(text_col).cast("string"))).dropDuplicates([id_col, "__h"]).select(*own)
