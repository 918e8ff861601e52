"""The ten operators against plain versions, on odd rows and on empty tables."""

import hashlib
import io
import math
import random
import re
import tracemalloc
import zlib
from collections import Counter, defaultdict
from types import SimpleNamespace

import numpy as np
import pyarrow as pa
import pytest

from sketchfit.llm import chunk_dedup, decontaminate, katz, mixing, near_duplicates, packed, pii, quality_rules, queries, suffix_dedup, token_files, url_filters
from sketchfit.llm.common import UPPER_TO_LOWER


def docs_of(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


def texts_of(df):
    return [(r.doc_id, r.text or "") for r in df.select("doc_id", "text").collect()]


def words_of(text):
    return text.encode().translate(UPPER_TO_LOWER).split()


# quality rules


def test_quality_counts(spark, sf, odd):
    for df in (docs_of(spark, sf), odd):
        for (_, text), r in zip(texts_of(df), quality_rules.judge(df).collect()):
            w = re.findall(r"[^\x20\x09-\x0D]+", text)
            hit = set()
            seen = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
            for i in range(len(w) - 2):
                if seen[tuple(w[i : i + 3])] > 1:
                    hit |= {i, i + 1, i + 2}
            lines, old = 0, set()
            for line in text.split("\n"):
                if re.search(r"[^\x20\x09-\x0D]", line):
                    lines += line in old
                    old.add(line)
            assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), lines, len(hit))
            assert r.base_failed == (len(w) < 50 or 100 * len(hit) > 50 * len(w))
            assert not (r.base_failed and r.kept)


def test_quality_bands(spark, none, odd):
    import zstandard

    c, b = zstandard.ZstdCompressor(level=3), quality_rules.Bands()
    rng = random.Random(0)
    plain = " ".join("".join(rng.choice("etaoinshr") for _ in range(rng.randint(2, 9))) for _ in range(1500))
    assert quality_rules.judged(plain, b, c)[-1]
    assert not quality_rules.judged("spam and eggs again now " * 400, b, c)[-1]
    noise = " ".join("".join(chr(rng.randint(33, 126)) for _ in range(12)) for _ in range(900))
    assert not quality_rules.judged(noise, b, c)[-1]
    assert not quality_rules.judged(plain + " again and again it goes on" * 2000, b, c)[-1]
    for size, cut in ((3000, 1000), (7000, 2500)):  # stretches within texts of less than 8 KiB, at the end and inside
        assert quality_rules.judged(plain[:size], b, c)[-1]
        assert not quality_rules.judged(plain[:size] + noise[:cut], b, c)[-1] and not quality_rules.judged(plain[:size] + "na " * cut + plain[size : 2 * size], b, c)[-1]
    for text in (plain, noise, plain[:700], plain[:4000] + noise[:2000], "", "x"):
        data = text.encode()
        ratio, bad, n, fine = quality_rules.compression(data, b, c)
        if not data:
            assert (ratio, bad, n, fine) == (0.0, 0, 0, False)
            continue
        within = lambda d, table: (lambda lo_hi: lo_hi[0] <= len(d) / len(c.compress(d)) <= lo_hi[1])([x[1:] for x in table if len(d) >= x[0]][-1])
        marks = "".join("." if within(data[i : i + b.chunk], b.parts) else "x" for i in range(0, len(data), b.chunk))
        assert (bad, n) == (marks.count("x"), len(marks)) and ratio == len(data) / len(c.compress(data))
        assert fine == (within(data, b.whole) and marks.count("x") <= b.bad_share * len(marks) and "x" * b.bad_run not in marks)
    assert quality_rules.judge(none).count() == 0 and quality_rules.keep_good(none).columns == none.columns
    assert quality_rules.keep_good(odd).columns == odd.columns


# url filters


def test_urls_against_plain_rules(spark):
    rng = random.Random(1)
    hosts, paths = ["org", "example.org", "a.example.org", "com", "x.com", "notexample.org", "b.a.example.org"], ["/", "/es/", "/es/1", "/en/1", "/en/12", "/fr/", "", "/d"]
    rules = [(rng.choice(["allow", "block"]), rng.choice(hosts) + p) for p in paths[:6] for _ in range(3)]
    rules = list({r: (v, r) for v, r in rules}.values())
    urls = [None, "", "no scheme", "http://", "HTTP://A.Example.ORG/es/1?q#f", "http://h://x"] + [f"http://{h}{p}{t}" for h in hosts for p in paths for t in ("", "?q=1", "#x")]
    df = spark.createDataFrame([(i, u, "v") for i, u in enumerate(urls * 2)], "page_id long, url string, verdict string")

    def plain(url):
        rest = (url or "").partition("://")[2]
        m = re.match(r"([^/?#]*)([^?#]*)", rest)
        host = "".join(c.lower() if "A" <= c <= "Z" else c for c in m[1])
        fit = [(len(r), len(r.partition("/")[0]), r, v) for v, r in rules if (host == r.partition("/")[0] or host.endswith("." + r.partition("/")[0])) and m[2].startswith(r[len(r.partition("/")[0]) :])]
        best = max(fit, default=None)
        return host, m[2], best and best[2], best[3] if best else "allow"

    table = spark.createDataFrame(rules, "verdict string, rule string")
    for got in (url_filters.filter_urls(df, rules), url_filters.filter_urls(df, table), url_filters.filter_urls(df, table, max_rules=3)):
        rows = got.collect()
        assert len(rows) == len(urls) * 2
        assert all((r.host, r.path, r.rule, r.verdict) == plain(r.url) for r in rows)
    assert url_filters.filter_urls(df.where("false"), rules).count() == 0
    assert url_filters.filter_urls(df, []).where("verdict <> 'allow'").count() == 0


# suffix-array removal


def plain_repeats(texts, length):
    data = [t.encode() for _, t in texts]
    seen = Counter(t[i : i + length] for t in data for i in range(len(t) - length + 1))
    out = []
    for t in data:
        gone = np.zeros(len(t), dtype=bool)
        for i in range(len(t) - length + 1):
            if seen[t[i : i + length]] > 1:
                gone[i : i + length] = True
        edges = np.flatnonzero(np.diff(np.concatenate([[0], gone.astype(int), [0]])))
        out.append((len(t), [(int(a), int(b)) for a, b in zip(edges[::2], edges[1::2])], bytes(np.frombuffer(t, dtype=np.uint8)[~gone])))
    return out


@pytest.mark.parametrize("length, q, reach, levels", [(60, 20, 60, (12, 4, 1)), (30, 30, 30, (1,)), (40, 16, 40, (25, 5, 1)), (60, 16, 37, (12, 4, 1))])
def test_repeats_against_plain(spark, length, q, reach, levels):
    rng = random.Random(length)
    base = ["".join(rng.choice("abcdé ") for _ in range(rng.randint(20, 200))) for _ in range(12)]
    texts = [(i, "".join(rng.choice(base) for _ in range(rng.randint(0, 4)))) for i in range(60)] + [(60, "ab" * 200), (61, "a" * 150), (62, "a" * 149 + "b")]
    texts += [(70 + i, base[0] * 2 + base[1][:i]) for i in range(10)]
    df = spark.createDataFrame(texts, "doc_id long, text string")
    want = dict(zip((k for k, _ in texts), plain_repeats(texts, length)))
    shared = {k for (k, _), (_, runs, _) in zip(texts, plain_repeats(texts, reach)) if runs}
    once = {k for (k, _), (_, runs, _) in zip(texts, plain_repeats(texts, q)) if not runs}
    for r in suffix_dedup.remove_repeats(df, length, q, reach, levels=levels).collect():
        assert (r.n_bytes, [(s.start, s.stop) for s in r.spans], bytes(r.kept)) == want[r.doc_id], r.doc_id
        assert (r.n_repeat_grams > 0) if r.doc_id in shared else r.n_repeat_grams == 0 or r.doc_id not in once


def test_repeats_of_clashing_ids(spark):
    rng = random.Random(9)
    base = ["".join(rng.choice("abcd ") for _ in range(90)) for _ in range(4000)]
    texts = [(None, base[i % 4000]) for i in range(6000)] + [(7, b) for b in base[:50]] + [(7, base[3][:40] + base[4][:60])]
    want = Counter((k, bytes(x[2])) for (k, _), x in zip(texts, plain_repeats([(k, t) for k, t in texts], 50)))
    got = suffix_dedup.remove_repeats(spark.createDataFrame(texts, "doc_id long, text string"), 50, 20, 50, levels=(10, 1)).collect()
    assert Counter((r.doc_id, bytes(r.kept)) for r in got) == want


@pytest.mark.parametrize("length,q", [(40, 12), (30, 30), (9, 1)])
def test_anchors_do_not_depend_on_segments(length, q):
    raw = np.random.default_rng(3).integers(97, 103, 5000).astype(np.uint8)
    whole = suffix_dedup.anchors(raw, length, q)
    assert len(np.unique(whole[0])) == len(whole[0])
    for segment in (7, 64, 1000):
        for a, b in zip(whole, suffix_dedup.anchors(raw, length, q, segment)):
            assert np.array_equal(a, b)


def test_repeats_across_segments(spark):
    rng = np.random.default_rng(4)
    make = lambda n: bytes(rng.integers(97, 123, n).astype(np.uint8)).decode()
    cut, length = suffix_dedup.SEGMENT, 400
    long, other, third = make(cut + 3000), make(900), make(cut + 200)
    # a repeat over the first cut, one at the end of a text that ends just past a cut
    texts = [long, other + long[cut - 700 : cut + 500] + other[::-1], third, make(50) + third[cut - 450 :] + make(50)]
    seen: dict[bytes, int] = {}
    windows = [[hashlib.blake2b(t[i : i + length].encode(), digest_size=16).digest() for i in range(len(t) - length + 1)] for t in texts]
    for w in windows:
        for x in w:
            seen[x] = seen.get(x, 0) + 1
    got = {r.doc_id: r for r in suffix_dedup.remove_repeats(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), length).collect()}
    for k, (t, w) in enumerate(zip(texts, windows)):
        gone = np.zeros(len(t), dtype=bool)
        for i, x in enumerate(w):
            if seen[x] > 1:
                gone[i : i + length] = True
        assert bytes(got[k].kept) == bytes(np.frombuffer(t.encode(), dtype=np.uint8)[~gone]), k


def test_exchange_tells_every_repeat(spark, monkeypatch):
    """Hot keys over many flushes, keys once only, and keys that meet in different tasks."""
    rng = np.random.default_rng(2)
    keys = np.concatenate([np.full(30_000, 77), rng.integers(0, 1 << 63, 40_000), np.repeat(rng.integers(0, 1 << 63, 5000), 3)]).astype(np.uint64) * np.uint64(2)
    rng.shuffle(keys)
    rows = [(i, keys[a : a + 500].tobytes()) for i, a in enumerate(range(0, len(keys), 500))]
    df = spark.createDataFrame(rows, "row long, keys binary").repartition(3)
    seen = Counter(keys.tolist())
    want = Counter((k, i // 500) for i, k in enumerate(keys.tolist()) if seen[k] > 1)
    for flush in (700, 400_000):
        monkeypatch.setattr(packed, "FLUSH", flush)
        assert Counter((r.key % (1 << 64), r.row) for r in packed.repeated(df, ["row"], 5).collect()) == want


def test_anchor_keys_spread_over_the_parts(spark):
    """Least hashes are small numbers: dealt by their high bits, nine tenths of all entries went to one part."""
    rng = np.random.default_rng(2)
    texts = ["".join(map(chr, rng.integers(97, 123, size=20_000))) for _ in range(20)]
    batch = pa.RecordBatch.from_pydict({"doc_id": list(range(20)), "k2": [0] * 20, "text": texts})
    made = suffix_dedup.first_level(400, 128, 250)(iter([batch]))
    keys = np.concatenate([np.frombuffer(x, dtype=np.uint64) for b in made for x in b.column(0).to_pylist()])
    held = np.bincount(packed.home(keys, 20).astype(int), minlength=20)
    assert len(keys) > 5000 and held.max() < 2 * held.mean()


def test_exchange_packs_in_bounded_memory(spark, monkeypatch):
    """A million entries with five numbers each go out in pieces, and a piece costs little more than itself."""
    made = []

    class Plan:
        def mapInArrow(self, f, schema):
            made.append(f)
            return self

        def repartitionById(self, *_):
            return self

    monkeypatch.setattr(packed, "TaskContext", SimpleNamespace(get=lambda: SimpleNamespace(partitionId=lambda: 2)))

    def rows(_):
        for k in range(50):
            keys = (np.arange(20_000, dtype=np.uint64) + np.uint64(20_000 * (k % 45))) * np.uint64(0x9E3779B97F4A7C15)
            yield pa.RecordBatch.from_pydict({x: [keys.tobytes()] for x in "kabcde"})

    packed.repeated(Plan(), list("abcde"), 7, rows)
    tracemalloc.start()
    try:
        kinds, before = Counter(), pa.total_allocated_bytes()
        for batch in made[0](iter(())):
            assert pa.total_allocated_bytes() - before < 30e6
            for kind, keys, *more in zip(*(c.to_pylist() for c in batch.columns[1:])):
                assert {len(keys)} == {len(x) for x in more}
                kinds[kind] += len(keys) // 8
        assert sum(kinds.values()) == 1_000_000
        assert tracemalloc.get_traced_memory()[1] < 60e6
    finally:
        tracemalloc.stop()


def test_repeats_odd_rows(spark, odd, none):
    got = suffix_dedup.remove_repeats(odd).collect()
    assert len(got) == odd.count()
    assert sum(r.n_bytes > 0 and not r.kept for r in got) >= 3  # the two equal long texts and the run of one letter
    assert suffix_dedup.remove_repeats(none).count() == 0


# near duplicates


def plain_components(texts, n, num, den):
    sets = []
    for _, t in texts:
        w = words_of(t)
        sets.append({tuple(w[i : i + n]) for i in range(max(1, len(w) - n + 1))} if w else set())
    top = list(range(len(sets)))

    def find(i):
        while top[i] != i:
            i = top[i]
        return i

    for i, a in enumerate(sets):
        for j in range(i):
            b = sets[j]
            if a and b and den * len(a & b) >= num * len(a | b):
                x, y = sorted((find(i), find(j)))
                top[y] = x
    groups = defaultdict(list)
    for i in range(len(sets)):
        groups[find(i)].append(texts[i][0])
    return [(k, len(s), min(groups[find(i)])) for i, ((k, _), s) in enumerate(zip(texts, sets))]


@pytest.mark.parametrize("n, num, den", [(3, 90, 100), (5, 80, 100), (1, 60, 100)])
def test_components_against_plain(spark, n, num, den):
    rng = random.Random(n)
    vocab = [f"w{i}" for i in range(400)]
    base = [[rng.choice(vocab) for _ in range(rng.randint(5, 150))] for _ in range(12)]
    texts = []
    for i in range(110):
        w = list(rng.choice(base))
        for _ in range(rng.randint(0, 6)):
            w[rng.randrange(len(w))] = rng.choice(vocab)
        texts.append((i, " ".join(w).upper() if i % 9 == 0 else " ".join(w)))
    texts += [(200, ""), (201, ""), (202, "only two"), (203, "ONLY two")]
    df = spark.createDataFrame(texts, "doc_id long, text string")
    got = sorted((r.doc_id, r.n_shingles, r.component_id) for r in near_duplicates.jaccard_components(df, n, num, den, block_sets=7).collect())
    assert got == sorted(plain_components(texts, n, num, den))


def test_part_keys_never_lose_a_pair():
    rng = np.random.default_rng(0)
    for num, den in ((90, 100), (80, 100), (50, 100)):
        for _ in range(150):
            n = int(rng.integers(1, 300))
            a = np.unique(rng.integers(0, 1 << 62, size=n).astype(np.uint64))
            k = int(rng.integers(0, max(1, n // 4) + 1))
            b = np.unique(np.concatenate([a[k:], rng.integers(0, 1 << 62, size=int(rng.integers(0, k + 1))).astype(np.uint64)]))
            if near_duplicates.similar(a, b, num, den) and not np.array_equal(a, b):
                assert len(np.intersect1d(near_duplicates.part_keys(a, num, den), near_duplicates.part_keys(b, num, den)))


def test_large_sets_are_ruled_out_by_their_bitmaps():
    """Texts of thousands of words that share a passage alone: no pair of them may reach the proof, and similar ones of other widths must."""
    rng = np.random.default_rng(5)
    some = lambda n: rng.integers(0, 1 << 62, size=n).astype(np.uint64)
    passage = some(300)
    sets = [np.unique(np.concatenate([passage, some(int(n))])) for n in rng.integers(6500, 8200, size=24)]
    sets.append(np.unique(np.concatenate([sets[0][:-400], some(500)])))  # similar to the first one
    sets.append(near := np.unique(some(4096)))  # two of unequal widths
    sets.append(np.unique(np.concatenate([near, some(300)])))
    bits = [near_duplicates.bitmap(x) for x in sets]
    assert len(bits[-2]) < len(bits[-1]) and near_duplicates.folded(bits[-1], 512) == np.packbits(np.bincount((near_duplicates.mix(sets[-1], 21) % np.uint64(4096)).astype(int), minlength=4096) > 0).tobytes()
    asked = []
    near_duplicates.tree_pairs([len(x) for x in sets], bits, list(range(len(sets))), 80, 100, lambda i, j: bool(asked.append((min(i, j), max(i, j)))))
    assert sorted(asked) == [(0, 24), (25, 26)]


def test_only_disputed_buckets_are_searched_again(spark):
    left = spark.createDataFrame([(1, 10, 10), (1, 11, 11), (2, 10, 10), (2, 12, 12), (3, 13, 13), (3, 14, 14)], "key long, rid long, comp long")
    pairs = spark.createDataFrame([(10, 11), (10, 12), (13, 14)], "a long, b long")
    labels = spark.createDataFrame([(10, 10), (11, 10), (13, 13)], "id long, comp long")  # 10 and 12, 13 and 14 were refuted
    assert sorted(map(tuple, near_duplicates.disputed(left, pairs, labels).collect())) == [(2, 10), (2, 12), (3, 13), (3, 14)]


def test_near_duplicates_odd_rows(odd, none):
    got = near_duplicates.jaccard_components(odd, 3, 90, 100).collect()
    assert len(got) == odd.count()
    by = defaultdict(set)
    for r in got:
        by[r.doc_id].add(r.component_id)
    assert by[6] == {5} and by[10] == {9} and by[0] == {0} and by[1] == {1} and by[None] == {None}
    assert near_duplicates.drop_near_duplicates(odd).columns == odd.columns
    assert near_duplicates.jaccard_components(none, 3, 90, 100).count() == 0


# language model


def test_katz_sums_to_one_and_matches_plain(spark, sf):
    df = docs_of(spark, sf)
    rows = [(k, [*words_of(t), b""]) for k, t in texts_of(df)]
    train = [t for k, t in rows if zlib.crc32(str(k).encode()) % 7 != 2]
    c1, c2 = Counter(w for t in train for w in t), Counter((a, b) for t in train for a, b in zip([b" ", *t], t))
    total, kinds = sum(c1.values()), len(c1)
    nr = lambda c: [sum(v == r for v in c.values()) for r in range(1, katz.TOP + 2)]
    d1, d2 = katz.discounts(nr(c1)), katz.discounts(nr(c2))
    use = lambda c, d: c * (d[c] if c <= katz.TOP else 1)
    unknown = 1 - sum(use(c, d1) for c in c1.values()) / total
    p1 = lambda w: use(c1[w], d1) / total if c1[w] else unknown
    after = defaultdict(list)
    for (a, b), c in c2.items():
        after[a].append((b, c))
    seen = Counter(c1)
    seen[b" "] = len(train)
    alpha, size = {}, {}
    for h, f in after.items():
        a, b = sum(use(c, d2) for _, c in f), sum(p1(w) for w, _ in f)
        size[h] = seen[h] + (seen[h] - a <= 1e-9 * seen[h])
        alpha[h] = (1 - a / size[h]) / (1 - b)
        assert alpha[h] > 0 and math.isclose(a / size[h] + alpha[h] * (1 - b), 1)
    p = lambda h, w: use(c2[h, w], d2) / size[h] if c2[h, w] else alpha.get(h, 1) * p1(w)
    for chunk_tokens in (3_000_000, 5000):
        got = {r.doc_id: r for r in katz.katz_scores(df, chunk_tokens=chunk_tokens).collect()}
        assert len(got) == len(rows)
        for k, t in rows:
            r = got[k]
            assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (zlib.crc32(str(k).encode()) % 7 == 2, len(t), sum(c1[w] > 0 for w in t), total)
            assert math.isclose(r.base_score, sum(math.log10((c1[w] + 1) / (total + kinds + 1)) for w in t), rel_tol=1e-9)
            assert math.isclose(r.score, sum(math.log10(p(h, w)) for h, w in zip([b" ", *t], t)), rel_tol=1e-9)


def test_katz_odd_rows(odd, none):
    got = katz.katz_scores(odd).collect()
    assert len(got) == odd.count() and all(math.isfinite(r.score) for r in got)
    assert katz.katz_scores(none).count() == 0
    assert all(r.train_tokens == 0 for r in katz.katz_scores(odd, held_out=lambda k: True).collect())


# personal data


def plain_spans(text):
    out = []
    for kind, pattern in enumerate((r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", r"[0-9]([\x20-]?[0-9])+", r"\+[0-9][\x20().0-9-]+[0-9]")):
        for m in re.finditer(pattern, text):
            digits = "".join(c for c in m[0] if "0" <= c <= "9")
            ok = kind == 0 or kind == 1 and all(int(p) <= 255 for p in m[0].split(".")) or kind == 2 and 12 <= len(digits) <= 19 and pii.luhn(digits) or kind == 3 and 9 <= len(digits) <= 15
            if ok:
                out.append((m.start(), kind, m.end()))
    return sorted(out)


def test_pii_base_against_patterns(spark, sf):
    rng = random.Random(5)
    texts = [t for _, t in texts_of(docs_of(spark, sf))] + ["".join(rng.choice("ab1.@+-% 9(") for _ in range(rng.randint(0, 60))) for _ in range(4000)]
    texts += ["@a.b x@y.z@q.r..", "4111 1111-1111 1111", "1.2.3.4.5.6.7.8", "999.1.1.1", "+1 (555) 123-4567 8", "0001.2.3.255"]
    for t in texts:
        assert pii.base_spans(t) == plain_spans(t), t
    pii.base_spans("1" * 200_000 + "." + "a" * 200_000 + "@")  # linear


def plain_disclosure(rows, words, reach, alpha, support):
    """Term places by document number, from the whole-document counts."""
    ctx, holds, terms = defaultdict(set), defaultdict(set), []
    for i, (_, t) in enumerate(rows):
        base = plain_spans(t)
        terms.append([(h, a, b) for h, a, b in pii.term_places(t, [(s, e) for s, _, e in base])])
        for e, c in pii.mentions(t, base, words, reach):
            ctx[e].add(c)
            holds[e].add((i, c))
    df = Counter(h for x in terms for h in {h for h, _, _ in x})
    out = defaultdict(set)
    for e, mine in holds.items():
        if len(ctx[e]) < support:
            continue
        docs = {i for i, _ in mine}
        for h in {h for i in docs for h, _, _ in terms[i]}:
            both = len({c for i, c in mine if any(x[0] == h for x in terms[i])})
            told = math.log2(both / len(ctx[e]) / (df[h] / len(rows)))
            if both >= support and told > 0 and told >= alpha * math.log2(len(rows) / len(docs)):
                for i in docs:
                    out[i] |= {(a, b) for x, a, b in terms[i] if x == h}
    return out


def test_pii_marks_disclosing_terms(spark):
    rng = random.Random(2)
    vocab = [f"plain{i}" for i in range(50)]
    rows = []
    for i in range(300):
        w = [rng.choice(vocab) for _ in range(60)]
        if i % 30 == 0:
            w[8] = "joe@hill.org"
            w[9 if i % 60 else 40] = "mayor-of-hilltown,"  # by the mention, or far from it
            w[55] = "Mayor-of-Hilltown"
        if i % 50 == 1:
            w[3], w[30] = "+1 (555) 123-4567", f"rare{i % 4}"
        rows.append((i, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r for r in pii.personal_data(df).collect()}
    want = plain_disclosure(rows, 6, 120, 0.75, 3)
    for i, t in rows:
        assert {(s.start, s.stop) for s in got[i].spans if s.kind == 4} == want[i]
        if i % 30 == 0:
            assert [t[a:b] for a, b in sorted(want[i])] == ["mayor-of-hilltown", "Mayor-of-Hilltown"]
    clean = pii.sanitise(df, "remove").where("doc_id = 60").first().text
    assert "illtown" not in clean and "[EMAIL]" in clean
    small = {r.doc_id: r.spans for r in pii.personal_data(df, broadcast_rows=0).collect()}
    assert all(small[i] == got[i].spans for i, _ in rows)


def test_pii_odd_rows(odd, none):
    got = pii.personal_data(odd).collect()
    assert len(got) == odd.count() and all(r.base_sha256 == hashlib.sha256(b"").hexdigest() for r in got)
    assert pii.personal_data(none).count() == 0 and pii.sanitise(odd).columns == odd.columns


# chunks


def test_cuts_resist_shifts():
    rng = random.Random(1)
    t = " ".join("".join(rng.choice("etaoin") for _ in range(rng.randint(2, 9))) for _ in range(900)).encode()
    parts = lambda d: {d[a:b] for a, b in zip([0, *chunk_dedup.cuts(d)], chunk_dedup.cuts(d))}
    one, two = parts(t), parts(b"inserted " + t)
    assert len(one & two) > 0.9 * len(one)
    for d in (b"", b"x", t, "é".encode() * 500):
        c = chunk_dedup.cuts(d)
        assert (c[-1] if c else 0) == len(d) and all(b > a for a, b in zip([0, *c], c))
        for a, b in zip([0, *c], c):
            d[a:b].decode()


def test_chunk_dedup_keeps_one_copy(spark, sf, odd, none):
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("etaoinshrdlu") for _ in range(rng.randint(3, 9)))
    passage = " ".join(word() for _ in range(60))
    rows = [(i, " ".join(word() for _ in range(80)) + " " + (passage + " " if i % 3 == 0 else "") + " ".join(word() for _ in range(80))) for i in range(30)]
    rows += [(100, rows[1][1]), (101, rows[1][1])]
    got = {r.doc_id: r for r in chunk_dedup.chunk_dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for i, t in rows[:30]:
        if i % 3:
            assert got[i].n_removed == 0 and bytes(got[i].kept) == t.encode()
        elif i:
            assert got[i].n_removed > 100
    assert got[0].n_removed == 0 and got[0].n_dup_chunks > 0
    assert got[100].n_removed == got[100].n_bytes == got[101].n_removed
    assert chunk_dedup.chunk_dedup(odd).count() == odd.count() and chunk_dedup.chunk_dedup(none).count() == 0


def plain_chunk_dedup(rows, least, most, min_run):
    """Kept bytes of every row: all but the first of equal chunks go, in the order of id, hash of the text, place, where they run for min_run bytes."""
    first, count = {}, Counter()
    parts = []
    for i, (order, t) in enumerate(rows):
        ends = chunk_dedup.cuts(t.encode(), least, most)
        parts.append([(a, b, t.encode()[a:b]) for a, b in zip([0, *ends], ends)])
        for a, _, c in parts[-1]:
            count[c] += 1
            first[c] = min(first.get(c, (order, i, a)), (order, i, a))
    out = []
    for i, ((order, t), chunks) in enumerate(zip(rows, parts)):
        runs = []
        for a, b, c in chunks:
            if count[c] > 1 and first[c] != (order, i, a):
                if runs and runs[-1][1] == a:
                    runs[-1][1] = b
                else:
                    runs.append([a, b])
        gone = [r for r in runs if r[1] - r[0] >= min_run]
        out.append(b"".join(t.encode()[a:b] for a, b in zip([0, *(r[1] for r in gone)], [*(r[0] for r in gone), len(t.encode())])))
    return out


def test_chunks_against_plain(spark):
    rng = random.Random(6)
    word = lambda: "".join(rng.choice("etaoinshrdlu") for _ in range(rng.randint(3, 9)))
    base = [" ".join(word() for _ in range(40)) for _ in range(12)]
    rows = [(rng.choice([None, 1, 2, i]), " ".join(rng.choice(base) for _ in range(rng.randint(0, 5)))) for i in range(60)] + [(None, base[0] + base[1])] * 5 + [(3, base[2])] * 4
    df = spark.createDataFrame(rows, "doc_id long, text string")
    hashes = {r.text: r.h for r in df.selectExpr("text", "xxhash64(text) as h").collect()}
    order = [((chunk_dedup.NO_ID if k is None else k, hashes[t]), t) for k, t in rows]
    want = Counter((k, b) for (k, _), b in zip(rows, plain_chunk_dedup(order, 32, 128, 64)))
    assert Counter((r.doc_id, bytes(r.kept)) for r in chunk_dedup.chunk_dedup(df).collect()) == want


# decontamination


def test_leaks_odd_rows(spark, odd, none):
    items = spark.createDataFrame([(1, "word0 tail0 word1 tail1 word2 tail2 word3 tail3 word4 tail4 word5"), (2, "one"), (3, None), (4, "..."), (2, "one")], "item_id long, text string")
    got = decontaminate.contamination(odd, items).collect()
    assert len(got) == odd.count()
    for r in got:
        if r.doc_id in (5, 6):
            assert "1" in r["items"] and r.n_hit >= 11
        elif r.doc_id == 3:
            assert r["items"] == ["2"] and r.n_hit == 1
        else:
            assert not r.contaminated
    assert decontaminate.contamination(none, items).count() == 0
    assert decontaminate.contamination(odd, items.where("false")).where("contaminated").count() == 0
    assert {r.doc_id for r in decontaminate.drop_contaminated(odd, items).select("doc_id").collect()} & {3, 5, 6} == set()
    small = decontaminate.contamination(odd, items, broadcast_words=0)
    assert sorted(map(str, small.collect())) == sorted(map(str, got))


def test_phrase_and_proximity(spark):
    df = spark.createDataFrame([(1, "the quick brown fox and the quick red fox"), (2, "fox quick the")], "doc_id long, text string")
    index = decontaminate.postings(df)
    assert {(r.doc_id, r.start) for r in decontaminate.phrase(index, ["the", "quick"]).collect()} == {(1, 0), (1, 5)}
    assert {(r.doc_id, r.first, r.last) for r in decontaminate.proximity(index, ["quick", "fox"], 3).collect()} == {(1, 1, 3), (1, 6, 8), (2, 0, 1)}


# token files


def test_token_round_trip(spark, sf, odd, none, tmp_path):
    tok = token_files.tokenizer(token_files.default_tokenizer_path())
    more = spark.createDataFrame([(None, f"no id {i % 40}") for i in range(80)] + [(5, f"text {i}") for i in range(80)], "doc_id long, text string")
    for df in (docs_of(spark, sf), odd, more):
        asked = df.selectExpr("doc_id", "coalesce(text, '') as text", "xxhash64(coalesce(text, '')) as h").collect()
        rows = [(r.doc_id, r.text) for r in sorted(asked, key=lambda r: (r.doc_id is not None, r.doc_id or 0, r.h, r.text))]
        out = f"file://{tmp_path}/t{len(rows)}"
        manifest = token_files.write_tokens(df, out, partitions=3)
        got = sorted(token_files.read_tokens(manifest).collect(), key=lambda r: r.start)
        at = 0
        for (k, t), r in zip(rows, got, strict=True):
            ids = np.array([*tok.encode(t, add_special_tokens=False).ids, 0], dtype="<u4")
            assert (r.doc_id, r.start, r.n_tokens, r.ids_crc32, bytes(r.ids)) == (k, at, len(ids), zlib.crc32(ids.tobytes()), ids.tobytes())
            at += len(ids)
        for asked in (3, 5, None):
            assert len(token_files.lookup(manifest, [asked, 10**9])[asked]) == sum(k == asked for k, _ in rows)
    assert token_files.token_rows(spark, none).count() == 0


def test_pieces_encode_like_whole_texts():
    tok = token_files.tokenizer(token_files.default_tokenizer_path())
    rng = random.Random(4)
    texts = ["", "  a b", "a\n\n b", "x \n y  ", "\t\tq\r\n z'", "it's  they're", "\x1c a\x1fb", "<|endoftext|> a", " \n \n", "12 34a5!!  ??'s 's"] + ["".join(rng.choice(" \n\t\x0b\x1c\u00a0 a1é!'s-") for _ in range(rng.randint(0, 30))) for _ in range(3000)]
    assert [x[:-1].tolist() for x in token_files.encode(texts)] == [e.ids for e in tok.encode_batch(texts, add_special_tokens=False)]


def test_words_are_encoded_once_and_without_offsets():
    """The library's plain form keeps offsets, at a third more CPU; words stay known over both generations of the cache."""
    path = token_files.default_tokenizer_path()
    encoder = token_files.Encoder(path, cache_entries=50)
    real, asked = encoder.tok, []

    class Fast:
        def encode_batch_fast(self, texts, **kw):
            asked.extend(texts)
            return real.encode_batch_fast(texts, **kw)

    encoder.tok = Fast()
    texts = [" ".join(f"word{k}x{i}" for i in range(40)) + "\nline two" for k in (1, 2, 1, 3, 2)]
    got = [x for t in texts for x in encoder.raw([t])]
    assert got == [np.array(real.encode(t, add_special_tokens=False).ids, dtype="<u4").tobytes() for t in texts]
    words = Counter(w for t in asked for w in t.split() if "x7" in w)
    assert words["word1x7"] == words["word3x7"] == 1


def test_damage_is_found():
    raw = token_files.to_bytes([(k, np.arange(k + 5, dtype="<u4")) for k in range(4)])
    reader = token_files.Reader(io.BytesIO(raw), len(raw))
    assert [reader.of(2)[0].tolist(), reader.of(9)] == [list(range(7)), []]
    bad = bytearray(raw)
    bad[int(reader.starts[1]) + 10] ^= 1
    with pytest.raises(Exception):
        token_files.Reader(io.BytesIO(bytes(bad)), len(bad)).ids(1)
    with pytest.raises(ValueError):
        token_files.Reader(io.BytesIO(raw[:-1]), len(raw) - 1)


# mixing


def test_mixing_reaches_targets(spark, sf, odd, none):
    docs = docs_of(spark, sf)
    labels = mixing.label_domains(spark.read.parquet(f"{sf}/labels.parquet"))
    rates, fit = mixing.document_rates(docs, labels, {"good": 0.9, "poor": 0.09, "toxic": 0.01})
    assert np.abs(fit.reached - fit.targets).max() <= 0.02 * fit.budget
    rows = rates.collect()
    assert all(r.rate >= 0 and math.isclose(sum(r.p), 1) for r in rows)
    again = np.array([r.tokens * r.rate * np.array(r.p) for r in rows]).sum(0)
    assert np.allclose(again, fit.reached, rtol=1e-6)
    assert mixing.mix(odd, labels.where("false"), {"a": 0.5, "b": 0.5}).columns == odd.columns
    assert mixing.mix(none, labels, {"good": 0.9, "poor": 0.1}).count() == 0


def plain_least_squares(a, c, turns=30_000):
    """Distance of a @ r from c for the best r >= 0, by accelerated projected gradient with restarts."""
    step = 1 / np.linalg.norm(a @ a.T, 2)
    r = z = np.ones(a.shape[1])
    q = 1.0
    for _ in range(turns):
        new = np.maximum(0, z - step * (a.T @ (a @ z - c)))
        if (z - new) @ (new - r) > 0:
            q = 1.0
        more = (1 + math.sqrt(1 + 4 * q * q)) / 2
        z, r, q = new + (q - 1) / more * (new - r), new, more
    return np.linalg.norm(a @ r - c)


@pytest.mark.parametrize("soft, poor, weights", [(1.0, 0.2, (0.9, 0.09, 0.01)), (0.5, 0.6, (0.9, 0.09, 0.01)), (2.0, 0.6, (0.98, 0.01, 0.01)), (0.1, 0.6, (0.9, 0.09, 0.01))])
def test_rates_are_converged(spark, soft, poor, weights):
    rng = np.random.default_rng(8)
    n = 3000
    kind = rng.choice(3, n, p=(0.95 - poor, poor, 0.05))
    score = rng.standard_normal((n, 3)) * 0.7 + 2 * soft * np.eye(3)[kind]
    p = np.exp(score) / np.exp(score).sum(1, keepdims=True)
    t = rng.integers(20, 400, n)
    fit = mixing.fit_rates(spark.createDataFrame([(int(a), b.tolist()) for a, b in zip(t, p)], "tokens long, p array<double>"), list(weights))
    reached = (t * mixing.replay(p, fit.moves)) @ p
    assert np.allclose(reached, fit.reached)
    # the same distance by plain non-negative least squares
    scale = np.sqrt(1 / ((t[:, None] * p * p).sum(0)))
    best = plain_least_squares(scale[:, None] * (t[:, None] * p).T / np.sqrt(t), scale * fit.targets)
    miss = np.linalg.norm(scale * (reached - fit.targets))
    assert miss <= best + 1e-4 * fit.budget * np.linalg.norm(scale)
    if best < 1e-6 * fit.budget * scale.min():
        assert np.abs(reached - fit.targets).max() <= 1e-4 * fit.budget


def test_unfinished_rates_are_an_error(spark):
    post = spark.createDataFrame([(10, [0.6, 0.4]), (10, [0.4, 0.6]), (7, [0.9, 0.1])], "tokens long, p array<double>")
    with pytest.raises(RuntimeError, match="not optimal"):
        mixing.fit_rates(post, [0.1, 0.9], steps=0)


def test_classifier_is_held_out_accurate(spark, sf):
    docs = mixing.docs_view(spark.read.parquet(sf.replace("sf0.001", "sf0.01") + "/documents.parquet"))
    labels = mixing.label_domains(spark.read.parquet(sf.replace("sf0.001", "sf0.01") + "/labels.parquet"))
    train, test = labels.where("doc_id % 4 <> 0"), {r.doc_id: r.domain for r in labels.where("doc_id % 4 = 0").collect()}
    model = mixing.fit_classifier(docs, train, ("good", "poor", "toxic"))
    got = {r.doc_id: model.domains[int(np.argmax(r.p))] for r in mixing.posteriors(docs, model).collect()}
    right = np.mean([got[k] == d for k, d in test.items()])
    usual = Counter(test.values()).most_common(1)[0][1] / len(test)
    assert right >= usual


# the whole


def test_pipeline_stages(spark, sf):
    import corpus_pipeline

    docs = docs_of(spark, sf)
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["quality_rules", "ngram_jaccard", "decontaminate", "mixing", "token_files"]
    held = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        new = stage(spark, held, sf)
        assert new.columns == docs.columns, name
        new = new.persist()
        before, after = held.select("doc_id", "text").distinct(), new.select("doc_id", "text").distinct()
        assert after.subtract(before).count() == 0
        if name == "quality_rules":
            verdict = {r.doc_id: r.kept for r in quality_rules.judge(held).collect()}
            assert {r.doc_id for r in new.collect()} == {k for k, v in verdict.items() if v}
        if name == "ngram_jaccard":
            want = {c for _, _, c in plain_components(texts_of(held), 5, 80, 100)}
            assert sorted(r.doc_id for r in new.collect()) == sorted(want)
        if name == "decontaminate":
            bad = {r.doc_id for r in decontaminate.contamination(held, spark.read.parquet(f"{sf}/benchmark.parquet")).where("contaminated").collect()}
            assert {r.doc_id for r in new.collect()} == {r.doc_id for r in held.collect()} - bad
        held = new
    assert corpus_pipeline.STAGES[-1][1](spark, held, sf).count() == held.count()


def test_registered_queries():
    assert sorted(k for k in queries.queries() if k.startswith("op")) == sorted(f"op{i}_{n}" for i, n in enumerate(("mixing", "url_filters", "suffix_dedup", "ngram_jaccard", "katz_scores", "pii", "chunk_dedup", "decontaminate", "token_files", "quality_rules"), 1))


def test_decontamination_sql_with_items_of_every_length(spark):
    import duckdb

    words = [f"w{i}" for i in range(40)]
    items = [("a", " ".join(words[:12])), ("b", " ".join(words[20:23])), ("c", "Solo"), ("d", " ".join(words[5:14])), ("e", ""), ("f", None), ("g", " ".join(words[30:40]))]
    docs = [(1, " ".join(words)), (2, "x " + " ".join(words[19:24]) + " y solo, solo"), (3, " ".join(words[20:22])), (4, None), (5, ""), (6, " ".join(words[:9])), (7, "solo"), (7, "w30 " + " ".join(words[30:39]))]
    d, b = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id string, text string")
    con = duckdb.connect()
    con.register("documents", d.toArrow())
    con.register("benchmark", b.toArrow())
    want = sorted(con.execute(f"SELECT doc_id, n_words, n_hit, n_items, items_sha256, contaminated FROM ({queries.LEAK_SQL})").fetchall())
    got = decontaminate.contamination(d, b)
    rows = sorted((r.doc_id, r.n_words, r.n_hit, r.n_items, hashlib.sha256(",".join(r.items or []).encode()).hexdigest(), r.contaminated) for r in got.collect())
    assert rows == want
    assert {r[0]: r[2] for r in rows if r[0] != 7} == {1: 27, 2: 5, 3: 0, 4: 0, 5: 0, 6: 0}
