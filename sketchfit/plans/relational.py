"""The operators around the methods, one query each, with SQL that gives the same rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import features as X
from ..functions import keyed_random as K
from ..functions import vectors as V
from ..sources.tables import load_table, round_trip, written
from .registry import Registry

R = Registry()
M = "CAST(floor(({}) * 1e6 + 0.4637) AS BIGINT)"


def micro_sql(x: str) -> str:
    return M.format(x)


def t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return load_table(spark, d, name)


# sources and sinks


@R.add("scan_prune_filter", "SELECT l_orderkey, l_quantity, l_discount FROM lineitem WHERE l_discount >= 0.05 AND l_quantity < 10")
def _(s, d):
    return t(s, d, "lineitem").where("l_discount >= 0.05 AND l_quantity < 10").select("l_orderkey", "l_quantity", "l_discount")


@R.add("csv_json_orc_roundtrip", "SELECT fmt, count(*) AS n, CAST(sum(floor(o_totalprice * 100 + 0.5)) AS BIGINT) AS sum_cents FROM orders, (VALUES ('csv'), ('json'), ('orc')) f(fmt) GROUP BY fmt")
def _(s, d):
    o = t(s, d, "orders").select("o_orderkey", "o_totalprice", "o_orderpriority")
    out = None
    for fmt in ("csv", "json", "orc"):
        r = round_trip(o, fmt).agg(F.count(F.lit(1)).alias("n"), F.sum(F.floor(F.col("o_totalprice") * 100 + 0.5)).cast("bigint").alias("sum_cents")).select(F.lit(fmt).alias("fmt"), "n", "sum_cents")
        out = r if out is None else out.union(r)
    return out


@R.add("text_roundtrip", "SELECT count(*) AS n FROM customer")
def _(s, d):
    from ..sources.tables import shared_folder

    path = shared_folder(s, "text")
    t(s, d, "customer").select(F.col("c_name").alias("value")).write.text(path)
    return s.read.text(path).agg(F.count(F.lit(1)).alias("n"))


@R.add("sql_view_entry", "SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_orderstatus = 'F' GROUP BY o_orderpriority")
def _(s, d):
    t(s, d, "orders").createOrReplaceTempView("sketchfit_orders")
    return s.sql("SELECT o_orderpriority, count(*) AS n FROM sketchfit_orders WHERE o_orderstatus = 'F' GROUP BY o_orderpriority")


@R.add("vector_long_form", f"SELECT vec_id, CAST(j - 1 AS INTEGER) AS j, {micro_sql('CAST(embedding[j] AS DOUBLE)')} AS v_micro FROM embeddings, range(1, 65) r(j)")
def _(s, d):
    return t(s, d, "embeddings").select("vec_id", F.posexplode(V.as_doubles(F.col("embedding"))).alias("j", "v")).select("vec_id", "j", V.micro(F.col("v")).alias("v_micro"))


@R.add("vector_roundtrip", f"SELECT vec_id, {micro_sql('CAST(embedding[1] AS DOUBLE)')} AS first_micro, CAST(len(embedding) AS INTEGER) AS width FROM embeddings")
def _(s, d):
    long = t(s, d, "embeddings").select("vec_id", F.posexplode(V.as_doubles(F.col("embedding"))).alias("j", "v"))
    back = long.groupBy("vec_id").agg(F.array_sort(F.collect_list(F.struct("j", "v"))).alias("c")).select("vec_id", F.col("c.v").alias("e"))
    return back.select("vec_id", V.micro(F.get("e", F.lit(0))).alias("first_micro"), F.size("e").alias("width"))


# feature building


@R.add("assemble_features", f"SELECT l_orderkey, l_linenumber, CAST(j AS INTEGER) AS j, {micro_sql('[l_quantity, l_discount, l_tax, CAST(p_size AS DOUBLE)][j + 1]')} AS v_micro FROM lineitem JOIN part ON l_partkey = p_partkey, range(4) r(j)")
def _(s, d):
    r = t(s, d, "lineitem").join(t(s, d, "part"), F.col("l_partkey") == F.col("p_partkey"))
    v = r.select("l_orderkey", "l_linenumber", F.posexplode(X.assemble("l_quantity", "l_discount", "l_tax", "p_size")).alias("j", "v"))
    return v.select("l_orderkey", "l_linenumber", "j", V.micro(F.col("v")).alias("v_micro"))


@R.add("fit_width_pad", f"SELECT s_suppkey, CAST(j AS INTEGER) AS j, {micro_sql('CASE WHEN j = 0 THEN s_acctbal ELSE 0 END')} AS v_micro FROM supplier, range(4) r(j)")
def _(s, d):
    v = t(s, d, "supplier").select("s_suppkey", F.posexplode(X.fit_width(X.assemble("s_acctbal"), 1, 4)).alias("j", "v"))
    return v.select("s_suppkey", "j", V.micro(F.col("v")).alias("v_micro"))


def _subset() -> list[int]:
    return X.feature_subset(64, 5)


@R.add("fit_width_subset", f"SELECT vec_id, CAST(k - 1 AS INTEGER) AS j, {micro_sql('CAST(embedding[(' + str(_subset()) + ')[k] + 1] AS DOUBLE)')} AS v_micro FROM embeddings, range(1, 6) r(k)")
def _(s, d):
    v = t(s, d, "embeddings").select("vec_id", F.posexplode(X.fit_width(V.as_doubles(F.col("embedding")), 64, 5)).alias("j", "v"))
    return v.select("vec_id", "j", V.micro(F.col("v")).alias("v_micro"))


SUPP = "SELECT l_suppkey, l_orderkey, l_linenumber, {} AS v_micro FROM lineitem JOIN (SELECT l_suppkey AS k, min(l_quantity) AS lo, max(l_quantity) AS hi, avg(l_quantity) AS mu, stddev_pop(l_quantity) AS sd FROM lineitem GROUP BY 1) p ON l_suppkey = k"


def _line(s, d):
    return t(s, d, "lineitem").select(F.col("l_suppkey"), "l_orderkey", "l_linenumber", X.assemble("l_quantity").alias("features"))


def _scaled(s, d, how):
    return X.scaled(_line(s, d), 1, how, ["l_suppkey"]).select("l_suppkey", "l_orderkey", "l_linenumber", F.floor(F.get("features", F.lit(0)) * 1e4 + 0.5).cast("bigint").alias("v_micro"))


def _e4(x: str) -> str:
    return f"CAST(floor(({x}) * 1e4 + 0.5) AS BIGINT)"


@R.add("minmax_scaled", SUPP.format(_e4("CASE WHEN hi > lo THEN (l_quantity - lo) / (hi - lo) ELSE 0 END")))
def _(s, d):
    return _scaled(s, d, "minmax")


@R.add("zscored", SUPP.format(_e4("CASE WHEN sd > 0 THEN (l_quantity - mu) / sd ELSE 0 END")))
def _(s, d):
    return _scaled(s, d, "zscore")


@R.add("maxabs", SUPP.format(_e4("CASE WHEN greatest(abs(lo), abs(hi)) > 0 THEN l_quantity / greatest(abs(lo), abs(hi)) ELSE 0 END")))
def _(s, d):
    return _scaled(s, d, "maxabs")


@R.add("onehot_orders", "SELECT o_orderkey, CAST(o_orderstatus = 'F' AS INTEGER) AS f, CAST(o_orderstatus = 'O' AS INTEGER) AS o, CAST(o_orderstatus = 'P' AS INTEGER) AS p FROM orders")
def _(s, d):
    h = X.one_hot(F.col("o_orderstatus"), ("F", "O", "P"))
    return t(s, d, "orders").select("o_orderkey", h.alias("h")).select("o_orderkey", *[F.get("h", F.lit(i)).cast("int").alias(n) for i, n in enumerate("fop")])


@R.add("binarize_embedding", "SELECT vec_id, CAST(list_sum(list_transform(embedding, lambda x: CASE WHEN x > 0 THEN 1 ELSE 0 END)) AS BIGINT) AS ones FROM embeddings")
def _(s, d):
    return t(s, d, "embeddings").select("vec_id", F.aggregate("embedding", F.lit(0).cast("bigint"), lambda a, x: a + (x > 0).cast("bigint")).alias("ones"))


@R.add("quantile_bins", "SELECT o_orderkey, CAST(ntile(4) OVER (ORDER BY o_totalprice, o_orderkey) AS INTEGER) AS bin FROM orders")
def _(s, d):
    # exact quartiles without a single-partition window: rank borders from counts of a range-partitioned sort
    o = t(s, d, "orders").select("o_orderkey", "o_totalprice")
    part = written(o.repartitionByRange("o_totalprice", "o_orderkey").withColumn("p", F.spark_partition_id()), "bins")
    before = part.groupBy("p").count().collect()  # a row for each partition
    total, start, at = sum(r["count"] for r in before), {}, 0
    for r in sorted(before, key=lambda r: r.p):
        start[r.p] = at
        at += r["count"]
    offsets = s.createDataFrame(list(start.items()) or [(0, 0)], "p int, before long")
    rank = F.row_number().over(Window.partitionBy("p").orderBy("o_totalprice", "o_orderkey")) + F.col("before") - 1
    q, r = divmod(total, 4)
    big = F.lit(r * (q + 1))
    bin_ = F.when(F.col("k") < big, F.floor(F.col("k") / F.lit(q + 1))).otherwise(F.floor((F.col("k") - big) / F.lit(max(q, 1))) + r)
    return part.join(F.broadcast(offsets), "p").withColumn("k", rank).select("o_orderkey", (bin_ + 1).cast("int").alias("bin"))


@R.add("hashed_bigrams", "WITH g AS (SELECT doc_id, substr(x, i, 2) AS g FROM (SELECT doc_id, lower(text) AS x, unnest(range(1, length(text))) AS i FROM documents WHERE doc_id % 1 = 0) WHERE length(substr(x, i, 2)) = 2), c AS (SELECT doc_id, g, count(*) AS n FROM g WHERE g ~ '^[a-z]{2}$' GROUP BY 1, 2) SELECT doc_id, CAST(CAST('0x' || substr(md5(g), 1, 6) AS BIGINT) % 64 AS INTEGER) AS bucket, CAST(sum(n) AS BIGINT) AS n FROM c GROUP BY 1, 2".replace(" WHERE doc_id % 1 = 0", ""))
def _(s, d):
    chars = F.split(F.lower("text"), "")
    docs = t(s, d, "documents").select("doc_id", F.filter(chars, lambda c: c != "").alias("c"))
    pairs = docs.select("doc_id", F.explode(F.zip_with(F.slice("c", 1, F.greatest(F.size("c") - 1, F.lit(0))), F.slice("c", 2, F.greatest(F.size("c") - 1, F.lit(0))), lambda a, b: F.concat(a, b))).alias("g"))
    counted = pairs.where(F.col("g").rlike("^[a-z]{2}$")).groupBy("doc_id", "g").count()
    bucket = F.pmod(F.conv(F.substring(F.md5(F.col("g").cast("binary")), 1, 6), 16, 10).cast("bigint"), F.lit(64)).cast("int")
    return counted.groupBy("doc_id", bucket.alias("bucket")).agg(F.sum("count").cast("bigint").alias("n"))


@R.add("html_text_len", "SELECT page_id, CAST(length(regexp_replace(html, '<[^>]*>', '', 'g')) AS BIGINT) AS n FROM pages")
def _(s, d):
    return t(s, d, "pages").select("page_id", F.length(F.regexp_replace("html", "<[^>]*>", "")).cast("bigint").alias("n"))


@R.add("json_prop", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")
def _(s, d):
    return t(s, d, "events").select("event_id", F.from_json("props", "k int").getField("k").alias("k"))


@R.add("url_parts", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/]*/([a-z]{2})/', 1) AS lang FROM pages")
def _(s, d):
    return t(s, d, "pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.regexp_extract("url", "^[a-z]+://[^/]*/([a-z]{2})/", 1).alias("lang"))


@R.add("calendar_features", "SELECT event_id, CAST(hour(ts) AS INTEGER) AS h, CAST(dayofweek(ts) + 1 AS INTEGER) AS dow, CAST(dayofyear(ts) AS INTEGER) AS doy, strftime(ts, '%Y-%m-%d') AS day FROM events")
def _(s, d):
    return t(s, d, "events").select("event_id", F.hour("ts").alias("h"), F.dayofweek("ts").alias("dow"), F.dayofyear("ts").alias("doy"), F.date_format("ts", "yyyy-MM-dd").alias("day"))


@R.add("ship_lag", "SELECT l_orderkey, l_linenumber, l_partkey, CAST(date_diff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE)) AS INTEGER) AS lag FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def _(s, d):
    j = t(s, d, "lineitem").hint("merge").join(t(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return j.select("l_orderkey", "l_linenumber", "l_partkey", F.datediff("l_shipdate", "o_orderdate").alias("lag"))


def _perm_sql() -> str:
    order = sorted(range(8), key=lambda j: (K.uniform(f"perm3-{j}"), j))
    parts = [f"{'1 - ' if K.uniform(f'neg3-{j}') < 0.5 else ''}CAST(embedding[{j + 1}] > 0 AS INTEGER)" for j in order]
    return "SELECT vec_id, " + ", ".join(f"{p} AS b{i}" for i, p in enumerate(parts)) + " FROM embeddings"


@R.add("permute_negate", _perm_sql())
def _(s, d):
    bits = F.transform(F.slice("embedding", 1, 8), lambda x: (x > 0).cast("tinyint"))
    v = t(s, d, "embeddings").select("vec_id", X.permute_negate(bits, 8, 3).alias("b"))
    return v.select("vec_id", *[F.get("b", F.lit(i)).cast("int").alias(f"b{i}") for i in range(8)])


@R.add("keyed_uniform", f"SELECT i, j, {micro_sql(K.uniform_sql(chr(39) + 'u-' + chr(39) + ' || i || ' + chr(39) + '-' + chr(39) + ' || j'))} AS u_micro FROM range(40) a(i), range(8) b(j)")
def _(s, d):
    return s.range(40).select(F.col("id").alias("i"), F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(7).cast("bigint"))).alias("j")).select("i", "j", V.micro(K.uniform_col("u", F.col("i"), F.col("j"))).alias("u_micro"))


@R.add("keyed_normal", f"SELECT i, j, {micro_sql(K.normal_sql(chr(39) + 'g-' + chr(39) + ' || i || ' + chr(39) + '-' + chr(39) + ' || j'))} AS u_micro FROM range(40) a(i), range(8) b(j)")
def _(s, d):
    return s.range(40).select(F.col("id").alias("i"), F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(7).cast("bigint"))).alias("j")).select("i", "j", V.micro(K.normal_col("g", F.col("i"), F.col("j"))).alias("u_micro"))


# joins


@R.add("join_broadcast_inner", "SELECT p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand")
def _(s, d):
    return t(s, d, "lineitem").join(t(s, d, "part"), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"))


@R.add("join_merge", "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority")
def _(s, d):
    return t(s, d, "lineitem").hint("merge").join(t(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@R.add("join_shuffle_hash", "SELECT o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderstatus")
def _(s, d):
    return t(s, d, "lineitem").join(t(s, d, "orders").hint("shuffle_hash"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


@R.add("join_left_labels", "SELECT d.doc_id, coalesce(quality, -1) AS quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def _(s, d):
    return t(s, d, "documents").select("doc_id").join(t(s, d, "labels").select("doc_id", "quality"), "doc_id", "left").na.fill(-1, ["quality"])


@R.add("join_right", "SELECT l.doc_id, lang FROM documents d RIGHT JOIN labels l ON d.doc_id = l.doc_id")
def _(s, d):
    return t(s, d, "documents").select("doc_id", "lang").join(t(s, d, "labels").select("doc_id"), "doc_id", "right").select("doc_id", "lang")


@R.add("join_full", "SELECT coalesce(c_custkey, o_custkey) AS k, count(c_custkey) AS c, count(o_orderkey) AS o FROM customer FULL JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def _(s, d):
    j = t(s, d, "customer").join(t(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "full")
    return j.groupBy(F.coalesce("c_custkey", "o_custkey").alias("k")).agg(F.count("c_custkey").alias("c"), F.count("o_orderkey").alias("o"))


@R.add("join_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 400000)")
def _(s, d):
    return t(s, d, "customer").join(t(s, d, "orders").where("o_totalprice > 400000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@R.add("join_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_totalprice > 400000)")
def _(s, d):
    return t(s, d, "customer").join(t(s, d, "orders").where("o_totalprice > 400000"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


CENT = "(SELECT vec_id AS cid, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS c FROM embeddings WHERE vec_id < 5)"
D2 = "list_sum(list_transform(list_zip(e, c), lambda p: (p[1] - p[2]) * (p[1] - p[2])))"


@R.add("join_cross_centroids", f"WITH x AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e FROM embeddings), d AS (SELECT vec_id, cid, {D2} AS d2 FROM x, {CENT}) SELECT vec_id, min_by(cid, struct_pack(d := CAST(floor(d2 * 1e6 + 0.4637) AS BIGINT), c := cid)) AS cid FROM d GROUP BY vec_id")
def _(s, d):
    e = t(s, d, "embeddings").select("vec_id", V.as_doubles(F.col("embedding")).alias("e"))
    c = t(s, d, "embeddings").where("vec_id < 5").select(F.col("vec_id").alias("cid"), V.as_doubles(F.col("embedding")).alias("c"))  # five centroids
    d2 = V.micro(V.norm2(V.subtract(F.col("e"), F.col("c"))))
    return e.crossJoin(F.broadcast(c)).groupBy("vec_id").agg(F.min_by("cid", F.struct(d2, "cid")).alias("cid"))


@R.add("join_theta_bins", "SELECT lo, count(*) AS n FROM orders JOIN (SELECT k * 50000 AS lo, (k + 1) * 50000 AS hi FROM range(10) r(k)) b ON o_totalprice >= lo AND o_totalprice < hi GROUP BY lo")
def _(s, d):
    b = s.range(10).select((F.col("id") * 50000).alias("lo"), ((F.col("id") + 1) * 50000).alias("hi"))
    return t(s, d, "orders").join(F.broadcast(b), (F.col("o_totalprice") >= F.col("lo")) & (F.col("o_totalprice") < F.col("hi"))).groupBy("lo").agg(F.count(F.lit(1)).alias("n"))


@R.add("join_range_binned", "SELECT a.o_orderkey, count(*) AS n FROM orders a JOIN orders b ON b.o_custkey % 50 = a.o_custkey % 50 AND b.o_totalprice > a.o_totalprice AND b.o_totalprice <= a.o_totalprice + 500 GROUP BY a.o_orderkey")
def _(s, d):
    # a range condition as an equality on bins of the range's width and their neighbours
    o = t(s, d, "orders").select("o_orderkey", F.pmod("o_custkey", F.lit(50)).alias("g"), "o_totalprice")
    a = o.select("o_orderkey", "g", F.col("o_totalprice").alias("x")).withColumn("bin", F.explode(F.array(F.floor(F.col("x") / 500), F.floor(F.col("x") / 500) + 1)))
    b = o.select("g", F.col("o_totalprice").alias("y")).withColumn("bin", F.floor(F.col("y") / 500))
    return a.join(b, ["g", "bin"]).where("y > x AND y <= x + 500").groupBy("o_orderkey").agg(F.count(F.lit(1)).alias("n"))


@R.add("join_asof_sketch_version", "WITH v AS (SELECT date_trunc('day', ts) AS vts FROM events GROUP BY 1) SELECT e.event_id, strftime(v.vts, '%Y-%m-%d %H:%M:%S') AS version_ts FROM events e ASOF LEFT JOIN v ON e.ts >= v.vts")
def _(s, d):
    # the newest version at each event: both in one stream of each day's bucket, last version seen; versions start their day, so a bucket is a day
    e = t(s, d, "events").select("event_id", "ts", F.date_trunc("day", "ts").alias("b"))
    v = e.select("b").distinct().select(F.lit(None).cast("bigint").alias("event_id"), F.col("b").alias("ts"), "b", F.col("b").alias("vts"))
    both = e.withColumn("vts", F.lit(None).cast(e.schema["b"].dataType)).unionByName(v)
    w = Window.partitionBy("b").orderBy("ts", F.col("event_id").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("version_ts", F.last("vts", ignorenulls=True).over(w)).where("event_id IS NOT NULL").select("event_id", F.date_format("version_ts", "yyyy-MM-dd HH:mm:ss").alias("version_ts"))


@R.add("join_interval_after_signup", "SELECT s.event_id, count(*) AS n FROM events s JOIN events e ON e.user_id = s.user_id AND e.ts > s.ts AND e.ts <= s.ts + INTERVAL 1 DAY WHERE s.event_type = 'signup' GROUP BY s.event_id")
def _(s, d):
    e = t(s, d, "events")
    a = e.where("event_type = 'signup'").select(F.col("event_id").alias("sid"), F.col("user_id").alias("u"), F.col("ts").alias("s"))
    j = a.join(e, (F.col("u") == F.col("user_id")) & (F.col("ts") > F.col("s")) & (F.col("ts") <= F.col("s") + F.expr("INTERVAL 1 DAY")))
    return j.groupBy(F.col("sid").alias("event_id")).agg(F.count(F.lit(1)).alias("n"))


@R.add("join_lateral_topk", "SELECT r_regionkey, n_nationkey FROM region, LATERAL (SELECT n_nationkey FROM nation WHERE n_regionkey = r_regionkey ORDER BY n_nationkey DESC LIMIT 2)")
def _(s, d):
    r, n = t(s, d, "region"), t(s, d, "nation")
    top = n.where(F.col("n_regionkey") == F.col("r_regionkey").outer()).orderBy(F.col("n_nationkey").desc()).limit(2).select("n_nationkey")
    return r.lateralJoin(top).select("r_regionkey", "n_nationkey")


@R.add("salted_group_sum", "SELECT l_returnflag, count(*) AS n, CAST(sum(floor(l_quantity * 1048576 + 0.5)) AS BIGINT) AS s FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    li = t(s, d, "lineitem").select("l_returnflag", F.pmod(F.xxhash64("l_orderkey", "l_partkey"), F.lit(16)).alias("salt"), V.fixed(F.col("l_quantity")).alias("q"))
    first = li.groupBy("l_returnflag", "salt").agg(F.count(F.lit(1)).alias("n"), F.sum("q").alias("s"))
    return first.groupBy("l_returnflag").agg(F.sum("n").alias("n"), F.sum("s").alias("s"))


# aggregates


@R.add("agg_moments_native", "SELECT l_returnflag, count(*) AS n, min(l_quantity) AS lo, max(l_quantity) AS hi, round(avg(l_quantity), 6) AS mu, round(var_pop(l_quantity), 6) AS v, round(covar_pop(l_quantity, l_discount), 6) AS c, round(corr(l_quantity, l_tax), 6) AS r FROM lineitem GROUP BY 1")
def _(s, d):
    return t(s, d, "lineitem").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.min("l_quantity").alias("lo"), F.max("l_quantity").alias("hi"), F.round(F.avg("l_quantity"), 6).alias("mu"), F.round(F.var_pop("l_quantity"), 6).alias("v"), F.round(F.covar_pop("l_quantity", "l_discount"), 6).alias("c"), F.round(F.corr("l_quantity", "l_tax"), 6).alias("r"))


@R.add("agg_regr", "SELECT l_returnflag, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(regr_intercept(l_extendedprice, l_quantity), 3) AS cut FROM lineitem GROUP BY 1")
def _(s, d):
    return t(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"), F.round(F.regr_intercept("l_extendedprice", "l_quantity"), 3).alias("cut"))


@R.add("agg_distinct_exact", "SELECT event_type, count(DISTINCT user_id) AS n FROM events GROUP BY 1")
def _(s, d):
    return t(s, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("n"))


@R.add("agg_distinct_hll", "SELECT event_type, true AS ok FROM events GROUP BY 1")
def _(s, d):
    day = t(s, d, "events").groupBy("event_type", F.to_date("ts").alias("day")).agg(F.hll_sketch_agg("user_id", F.lit(12)).alias("h"), F.collect_set("user_id").alias("u"))
    got = day.groupBy("event_type").agg(F.hll_sketch_estimate(F.hll_union_agg("h")).alias("est"), F.size(F.array_distinct(F.flatten(F.collect_list("u")))).alias("n"))
    return got.select("event_type", (F.abs(F.col("est") - F.col("n")) <= 0.05 * F.col("n")).alias("ok"))


@R.add("agg_percentile_exact", "SELECT o_orderpriority, round(quantile_cont(o_totalprice, 0.5), 4) AS p50 FROM orders GROUP BY 1")
def _(s, d):
    return t(s, d, "orders").groupBy("o_orderpriority").agg(F.round(F.percentile("o_totalprice", F.lit(0.5)), 4).alias("p50"))


@R.add("agg_kll", "SELECT o_orderpriority, true AS ok FROM orders GROUP BY 1")
def _(s, d):
    o = t(s, d, "orders")
    k = o.groupBy("o_orderpriority").agg(F.kll_sketch_agg_double("o_totalprice").alias("k"))
    q = k.select("o_orderpriority", F.kll_sketch_get_quantile_double("k", F.lit(0.5)).alias("q"))
    r = o.join(q, "o_orderpriority").groupBy("o_orderpriority").agg(F.avg((F.col("o_totalprice") <= F.col("q")).cast("double")).alias("rank"))
    return r.select("o_orderpriority", (F.abs(F.col("rank") - 0.5) < 0.05).alias("ok"))


@R.add("agg_max_by", "SELECT o_custkey, max_by(o_orderkey, struct_pack(p := o_totalprice, k := o_orderkey)) AS top, min(o_totalprice) AS low FROM orders GROUP BY 1")
def _(s, d):
    return t(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("top"), F.min("o_totalprice").alias("low"))


@R.add("agg_collect", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
def _(s, d):
    return t(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"))


@R.add("agg_filter", "SELECT l_linestatus, count(*) FILTER (WHERE l_discount > 0.05) AS high, CAST(sum(CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END) AS BIGINT) AS returned FROM lineitem GROUP BY 1")
def _(s, d):
    return t(s, d, "lineitem").groupBy("l_linestatus").agg(F.count_if(F.col("l_discount") > 0.05).alias("high"), F.sum(F.when(F.col("l_returnflag") == "R", 1).otherwise(0)).cast("bigint").alias("returned"))


@R.add("agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 12")
def _(s, d):
    return t(s, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n")).where("n > 12")


@R.add("pivot_method_size", "SELECT user_id % 10 AS g, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS view FROM events GROUP BY 1")
def _(s, d):
    return t(s, d, "events").groupBy(F.pmod("user_id", F.lit(10)).alias("g")).pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).na.fill(0)


@R.add("unpivot_back", "SELECT g, event_type, n FROM (SELECT user_id % 10 AS g, event_type, count(*) AS n FROM events WHERE event_type IN ('click', 'view') GROUP BY 1, 2)")
def _(s, d):
    wide = t(s, d, "events").groupBy(F.pmod("user_id", F.lit(10)).alias("g")).pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1)))
    return wide.unpivot("g", ["click", "view"], "event_type", "n").where("n IS NOT NULL")


# windows, sorts, sets


@R.add("win_rank_family", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)")
def _(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    return t(s, d, "orders").select("o_orderkey", F.row_number().over(w).cast("bigint").alias("rn"), F.rank().over(w).cast("bigint").alias("rk"), F.dense_rank().over(w).cast("bigint").alias("dr"))


@R.add("win_lag_lead", "SELECT o_orderkey, coalesce(lag(o_orderkey) OVER w, -1) AS before, coalesce(lead(o_orderkey) OVER w, -1) AS after FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def _(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return t(s, d, "orders").select("o_orderkey", F.lag("o_orderkey", 1, -1).over(w).alias("before"), F.lead("o_orderkey", 1, -1).over(w).alias("after"))


@R.add("win_nth_value", "SELECT o_orderkey, first_value(o_orderkey) OVER w AS f, coalesce(nth_value(o_orderkey, 2) OVER w, -1) AS second FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def _(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return t(s, d, "orders").select("o_orderkey", F.first("o_orderkey").over(w).alias("f"), F.coalesce(F.nth_value("o_orderkey", 2).over(w), F.lit(-1)).alias("second"))


@R.add("win_ntile", "SELECT o_orderkey, ntile(3) OVER w AS n, round(percent_rank() OVER w, 6) AS p, round(cume_dist() OVER w, 6) AS c FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)")
def _(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    return t(s, d, "orders").select("o_orderkey", F.ntile(3).over(w).cast("bigint").alias("n"), F.round(F.percent_rank().over(w), 6).alias("p"), F.round(F.cume_dist().over(w), 6).alias("c"))


@R.add("sort_total", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey")
def _(s, d):
    return t(s, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.col("o_totalprice").desc(), "o_orderkey")


@R.add("sort_within", "SELECT o_orderkey, o_custkey FROM orders")
def _(s, d):
    return t(s, d, "orders").select("o_orderkey", "o_custkey").repartition("o_custkey").sortWithinPartitions("o_custkey", "o_orderkey")


@R.add("topk", "SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 20")
def _(s, d):
    return t(s, d, "customer").select("c_custkey", "c_acctbal").orderBy(F.col("c_acctbal").desc(), "c_custkey").limit(20)


@R.add("limit_offset", "SELECT c_custkey FROM customer ORDER BY c_custkey LIMIT 10 OFFSET 5")
def _(s, d):
    return t(s, d, "customer").select("c_custkey").orderBy("c_custkey").offset(5).limit(10)


@R.add("knn_bruteforce", f"WITH x AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e FROM embeddings), q AS (SELECT vec_id AS q, e AS c FROM x WHERE vec_id % 50 = 0) SELECT q AS vec_id, vec_id AS nb, CAST(r AS INTEGER) AS rank FROM (SELECT q, vec_id, row_number() OVER (PARTITION BY q ORDER BY CAST(floor({D2} * 1e6 + 0.4637) AS BIGINT), vec_id) AS r FROM x, q WHERE q <> vec_id) WHERE r <= 5")
def _(s, d):
    x = t(s, d, "embeddings").select("vec_id", V.as_doubles(F.col("embedding")).alias("e"))
    q = x.where(F.pmod("vec_id", F.lit(50)) == 0).select(F.col("vec_id").alias("q"), F.col("e").alias("c"))
    pairs = x.join(q, F.col("q") != F.col("vec_id")).select("q", "vec_id", V.micro(V.norm2(V.subtract(F.col("e"), F.col("c")))).alias("d2"))
    w = Window.partitionBy("q").orderBy("d2", "vec_id")
    return pairs.withColumn("rank", F.row_number().over(w)).where("rank <= 5").select(F.col("q").alias("vec_id"), F.col("vec_id").alias("nb"), "rank")


def _sets(name: str, op: str, f) -> None:
    @R.add(name, f"SELECT k FROM (SELECT c_nationkey AS k FROM customer {op} SELECT s_nationkey FROM supplier)")
    def _(s, d, f=f):
        return f(t(s, d, "customer").select(F.col("c_nationkey").alias("k")), t(s, d, "supplier").select(F.col("s_nationkey").alias("k")))


_sets("set_union_all", "UNION ALL", lambda a, b: a.unionAll(b))
_sets("set_union_distinct", "UNION", lambda a, b: a.union(b).distinct())
_sets("set_intersect", "INTERSECT", lambda a, b: a.intersect(b))
_sets("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b))
_sets("set_except", "EXCEPT", lambda a, b: a.subtract(b))
_sets("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))


@R.add("drop_duplicates", "SELECT DISTINCT o_custkey, o_orderpriority FROM orders")
def _(s, d):
    return t(s, d, "orders").select("o_custkey", "o_orderpriority").dropDuplicates()


# scalar functions


@R.add("fn_math", "SELECT o_orderkey, round(sqrt(o_totalprice), 6) AS a, round(ln(o_totalprice), 6) AS b, round(log10(o_totalprice), 6) AS c, round(cos(o_custkey), 6) AS d, round(sin(o_custkey), 6) AS e, CAST(sign(o_totalprice - 1000) AS DOUBLE) AS f, o_custkey % 7 AS g, greatest(o_custkey, o_orderkey) AS h, abs(o_custkey - o_orderkey) AS i FROM orders")
def _(s, d):
    return t(s, d, "orders").select("o_orderkey", F.round(F.sqrt("o_totalprice"), 6).alias("a"), F.round(F.ln("o_totalprice"), 6).alias("b"), F.round(F.log10("o_totalprice"), 6).alias("c"), F.round(F.cos("o_custkey"), 6).alias("d"), F.round(F.sin("o_custkey"), 6).alias("e"), F.signum(F.col("o_totalprice") - 1000).alias("f"), F.pmod("o_custkey", F.lit(7)).alias("g"), F.greatest("o_custkey", "o_orderkey").alias("h"), F.abs(F.col("o_custkey") - F.col("o_orderkey")).alias("i"))


@R.add("fn_vector", f"WITH x AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e FROM embeddings) SELECT vec_id, {micro_sql('list_sum(list_transform(e, lambda x: x * x))')} AS n2, {micro_sql('list_sum(list_transform(list_zip(e, list_reverse(e)), lambda p: p[1] * p[2]))')} AS mirror, CAST(list_position(e, list_min(e)) - 1 AS INTEGER) AS least, {micro_sql('e[2] * e[1]')} AS second FROM x")
def _(s, d):
    e = t(s, d, "embeddings").select("vec_id", V.as_doubles(F.col("embedding")).alias("e"))
    return e.select("vec_id", V.micro(V.norm2(F.col("e"))).alias("n2"), V.micro(V.dot(F.col("e"), F.reverse("e"))).alias("mirror"), V.argmin(F.col("e")).alias("least"), V.micro(F.get(V.outer_lt(F.col("e"), 2), F.lit(1))).alias("second"))


@R.add("fn_array_map", "SELECT n_nationkey, CAST(len(range(n_nationkey)) AS INTEGER) AS n, CAST(coalesce(list_sum(list_filter(range(n_nationkey), lambda x: x % 2 = 0)), 0) AS BIGINT) AS evens, n_nationkey > 10 AS big FROM nation")
def _(s, d):
    seq = F.when(F.col("n_nationkey") > 0, F.sequence(F.lit(0).cast("bigint"), (F.col("n_nationkey") - 1).cast("bigint"))).otherwise(F.array().cast("array<bigint>"))
    m = F.map_from_arrays(F.array(F.lit("big")), F.array(F.col("n_nationkey") > 10))
    return t(s, d, "nation").select("n_nationkey", F.size(seq).alias("n"), F.aggregate(F.filter(seq, lambda x: F.pmod(x, F.lit(2)) == 0), F.lit(0).cast("bigint"), lambda a, x: a + x).alias("evens"), F.element_at(m, "big").alias("big"))


@R.add("fn_string", "SELECT c_custkey, lower(c_name) AS l, CAST(length(c_name) AS INTEGER) AS n, substr(c_name, 10) AS tail, md5(c_name) AS m, sha256(c_name) AS h, regexp_replace(c_name, '[^0-9]', '', 'g') AS digits, split_part(c_name, '#', 1) AS head FROM customer")
def _(s, d):
    c = t(s, d, "customer")
    return c.select("c_custkey", F.lower("c_name").alias("l"), F.length("c_name").alias("n"), F.expr("substr(c_name, 10)").alias("tail"), F.md5(F.col("c_name").cast("binary")).alias("m"), F.sha2("c_name", 256).alias("h"), F.regexp_replace("c_name", "[^0-9]", "").alias("digits"), F.split_part("c_name", F.lit("#"), F.lit(1)).alias("head"))


@R.add("fn_date", "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS first, strftime(o_orderdate + INTERVAL 10 DAY, '%Y-%m-%d') AS later, strftime(last_day(o_orderdate), '%Y-%m-%d') AS last FROM orders")
def _(s, d):
    return t(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.trunc("o_orderdate", "month").cast("string").alias("first"), F.date_add(F.to_date("o_orderdate"), 10).cast("string").alias("later"), F.last_day("o_orderdate").cast("string").alias("last"))


@R.add("fn_json", "SELECT event_id, json_extract_string(props, '$.k') AS k, '{\"v\":' || CAST(CAST(json_extract_string(props, '$.k') AS INTEGER) AS VARCHAR) || '}' AS j FROM events")
def _(s, d):
    v = F.try_parse_json("props")
    return t(s, d, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"), F.to_json(F.struct(F.variant_get(v, "$.k", "int").alias("v"))).alias("j"))


@R.add("filters_predicates", "SELECT o_orderkey, CASE WHEN o_orderpriority LIKE '1%' THEN 'urgent' WHEN regexp_matches(o_orderpriority, '^[2-3]') THEN 'mid' ELSE 'low' END AS c FROM orders WHERE o_orderstatus IN ('F', 'O') AND o_totalprice BETWEEN 1000 AND 300000 AND o_custkey IS NOT DISTINCT FROM o_custkey")
def _(s, d):
    p = F.col("o_orderpriority")
    o = t(s, d, "orders").where(F.col("o_orderstatus").isin("F", "O") & F.col("o_totalprice").between(1000, 300000) & F.col("o_custkey").eqNullSafe(F.col("o_custkey")))
    return o.select("o_orderkey", F.when(p.like("1%"), "urgent").when(p.rlike("^[2-3]"), "mid").otherwise("low").alias("c"))


@R.add("split_by_dataset", f"SELECT o_custkey, CASE WHEN {K.uniform_sql(chr(39) + 'split0-' + chr(39) + ' || o_custkey')} < 0.5 THEN 'train' ELSE 'test' END AS split, count(*) AS n FROM orders GROUP BY 1, 2")
def _(s, d):
    from ..meta.train import split_datasets

    return split_datasets(t(s, d, "orders"), by="o_custkey").groupBy("o_custkey", "split").agg(F.count(F.lit(1)).alias("n"))
