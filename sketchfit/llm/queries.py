"""The registered query of each operator, with production parameters, and SQL where it can express the result."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .common import table

Query = Callable[[SparkSession, str], DataFrame]

#: The rules of the url query, (verdict, rule).
URL_RULES = (("allow", "org/"), ("block", "example.org/es/"), ("block", "example.org/en/1"), ("allow", "com/fr/"), ("block", "com/de/"))


#: Target shares of tokens by domain for the mixing query.
MIX_TARGETS = {"good": 0.9, "poor": 0.09, "toxic": 0.01}


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import functions as F

    from .mixing import copies, document_rates, label_domains

    rates, _ = document_rates(table(spark, sf_dir, "documents"), label_domains(table(spark, sf_dir, "labels")), MIX_TARGETS)
    p = [F.col("p")[i].alias(f"p_{d}") for i, d in enumerate(MIX_TARGETS)]
    return rates.select("doc_id", F.col("tokens").alias("n_tokens"), *p, "rate", copies(F.col("rate"), F.col("doc_id"), F.col("h")).alias("n_copies"))


def op2_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .url_filters import filter_urls

    return filter_urls(table(spark, sf_dir, "pages").select("page_id", "url"), URL_RULES).select("page_id", "host", "path", "rule", "verdict")


def op3_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import functions as F

    from .suffix_dedup import remove_repeats

    done = remove_repeats(table(spark, sf_dir, "documents"), length=400)
    return done.select("doc_id", "n_bytes", (F.col("n_bytes") - F.octet_length("kept")).alias("n_removed"), F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"), "n_repeat_grams")


def op4_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .near_duplicates import jaccard_components

    return jaccard_components(table(spark, sf_dir, "documents"), n=3, num=90, den=100)


def op5_katz_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .katz import katz_scores

    return katz_scores(table(spark, sf_dir, "documents"))


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import functions as F

    from .pii import KINDS, personal_data

    found = personal_data(table(spark, sf_dir, "documents"))
    name = F.array(*[F.lit(k) for k in KINDS])
    spans = F.array_join(F.transform("spans", lambda s: F.concat_ws(":", F.get(name, s["kind"]), s["start"].cast("string"), s["stop"].cast("string"))), ",")
    return found.select("doc_id", *[F.col("n")[i].alias(f"n_{k}") for i, k in enumerate(KINDS[:4])], "base_sha256", spans.alias("spans"))


def op7_chunk_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import functions as F

    from .chunk_dedup import chunk_dedup

    done = chunk_dedup(table(spark, sf_dir, "documents"))
    return done.select("doc_id", "n_bytes", "n_dup_chunks", "n_removed", F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))


def op8_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import functions as F

    from .decontaminate import contamination

    found = contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", "n_items", F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), "contaminated")


def op9_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .token_files import token_rows

    return token_rows(spark, table(spark, sf_dir, "documents"))


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality_rules import judge

    return judge(table(spark, sf_dir, "documents"))


URL_SQL = """
WITH r(verdict, rule) AS (VALUES {rules}),
rules AS (SELECT verdict, rule, split_part(rule, '/', 1) AS rh, substr(rule, length(split_part(rule, '/', 1)) + 1) AS rp FROM r),
u AS (SELECT page_id, CASE WHEN url IS NULL OR strpos(url, '://') = 0 THEN '' ELSE substr(url, strpos(url, '://') + 3) END AS rest FROM pages),
p AS (SELECT page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
             regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM u),
f AS (SELECT page_id, max_by(struct_pack(rule := rule, verdict := verdict), length(rule) * 1000 + length(rh)) AS b FROM p JOIN rules
      ON (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp) GROUP BY page_id)
SELECT p.page_id, host, path, b.rule AS rule, coalesce(b.verdict, 'allow') AS verdict FROM p LEFT JOIN f USING (page_id)
"""


LEAK_SQL = r"""
WITH w(doc, k, pos, word) AS (
  SELECT doc_id, k, unnest(range(len(ws))), unnest(ws) FROM (
    SELECT doc_id, row_number() OVER () AS k, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents)),
b AS (SELECT CAST(item_id AS VARCHAR) AS item, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark),
bw AS (SELECT item, unnest(range(greatest(len(ws) - 9, 1))) AS s, ws FROM b WHERE len(ws) > 0),
win AS (SELECT item, list_aggregate(ws[s + 1 : least(s + 10, len(ws))], 'string_agg', ' ') AS phrase, least(10, len(ws)) AS n FROM bw),
lens AS (SELECT DISTINCT n FROM win),
f AS (SELECT k, pos, list(word) OVER (PARTITION BY k ORDER BY pos ROWS BETWEEN CURRENT ROW AND 9 FOLLOWING) AS l FROM w),
g AS (SELECT k, pos, n, array_to_string(l[1 : n], ' ') AS phrase FROM f, lens WHERE len(l) >= n),
h AS (SELECT DISTINCT g.k, g.pos, g.n, win.item FROM g JOIN win ON g.phrase = win.phrase AND g.n = win.n),
hp AS (SELECT k, count(DISTINCT pos + o) AS n_hit FROM h, range(10) t(o) WHERE o < n GROUP BY k),
hi AS (SELECT k, count(DISTINCT item) AS n_items, string_agg(DISTINCT item, ',' ORDER BY item) AS items FROM h GROUP BY k),
d AS (SELECT row_number() OVER () AS k, doc_id, len(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')) AS n_words FROM documents)
SELECT doc_id, n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items, sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN hp USING (k) LEFT JOIN hi USING (k)
"""


NEAR_SQL = r"""
WITH RECURSIVE d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (SELECT doc_id, list_distinct([CAST(ws[i : i + least(3, len(ws)) - 1] AS VARCHAR) FOR i IN range(1, greatest(len(ws) - 2, 1) + 1)]) AS sh FROM d WHERE len(ws) > 0),
f AS (SELECT doc_id, len(sh) AS n, unnest(sh) AS g FROM s),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, any_value(a.n) + any_value(b.n) AS sizes, count(*) AS i FROM f a JOIN f b ON a.g = b.g AND a.doc_id <> b.doc_id AND 10 * a.n >= 9 * b.n AND 10 * b.n >= 9 * a.n GROUP BY 1, 2),
e AS (SELECT a, b FROM p WHERE 100 * i >= 90 * (sizes - i)),
r(a, b) AS (SELECT a, b FROM e UNION SELECT r.a, e.b FROM r JOIN e ON r.b = e.a)
SELECT d.doc_id, CAST(coalesce(len(sh), 0) AS BIGINT) AS n_shingles, least(d.doc_id, coalesce(m, d.doc_id)) AS component_id
FROM d LEFT JOIN s ON d.doc_id = s.doc_id LEFT JOIN (SELECT a, min(b) AS m FROM r GROUP BY a) c ON c.a = d.doc_id
"""


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Query]:
    return {k: v for k, v in globals().items() if k.startswith("op") and k[2].isdigit()} | {"pipeline": pipeline}


def oracle_sql() -> dict[str, str]:
    return {"op2_url_filters": URL_SQL.format(rules=", ".join(f"('{v}', '{r}')" for v, r in URL_RULES)), "op4_ngram_jaccard": NEAR_SQL, "op8_decontaminate": LEAK_SQL}
