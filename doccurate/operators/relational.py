"""Operators around the methods, one query each, on the given tables."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from doccurate.functions.text import norm
from doccurate.functions.web import canonical_url, to_plain
from doccurate.plans.registry import query


def _t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def _op(name: str, tables: str, sql: str | None = None):
    """Register op(tables...) as ``op_<name>``; tables by name, in order."""

    def add(f):
        query(f"op_{name}", sql)(lambda spark, d: f(*(_t(spark, d, t) for t in tables.split())))
        return f

    return add


def _sql(name: str, tables: str, template: str) -> None:
    """template names its tables in braces; DuckDB gets the bare names."""
    query(f"op_{name}", template.format_map({t: t for t in tables.split()}))(lambda spark, d: spark.sql(template, **{t: _t(spark, d, t) for t in tables.split()}))


_op("scan_prune", "documents", "SELECT doc_id, lang, n_chars FROM documents WHERE lang = 'fr' AND n_chars >= 100")(lambda d: d.select("doc_id", "lang", "n_chars").filter("lang = 'fr' AND n_chars >= 100"))
_op("project_case", "lineitem", "SELECT l_orderkey, l_linenumber, CASE WHEN l_discount < 0.03 THEN 'low' WHEN l_discount < 0.07 THEN 'middle' ELSE 'high' END AS band, round(l_extendedprice * (1 - l_discount), 4) AS price FROM lineitem")(
    lambda d: d.select("l_orderkey", "l_linenumber", F.when(F.col("l_discount") < 0.03, "low").when(F.col("l_discount") < 0.07, "middle").otherwise("high").alias("band"), F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("price"))
)
_op("filter_compound", "orders", "SELECT o_orderkey FROM orders WHERE o_orderdate BETWEEN TIMESTAMP '1995-01-01' AND TIMESTAMP '1996-12-31' AND o_orderstatus IN ('F', 'O') AND o_orderpriority IS DISTINCT FROM '5-LOW'")(
    lambda d: d.filter(F.col("o_orderdate").between(F.lit("1995-01-01").cast("timestamp_ntz"), F.lit("1996-12-31").cast("timestamp_ntz")) & F.col("o_orderstatus").isin("F", "O") & ~F.col("o_orderpriority").eqNullSafe("5-LOW")).select("o_orderkey")
)
_op("filter_regex", "documents", "SELECT doc_id, len(regexp_extract_all(text, '[A-Za-z]+[%#*$&]{3}')) AS marked, regexp_matches(text, '[a-z0-9.]+@[a-z0-9-]+[.][a-z]+') AS mail FROM documents WHERE regexp_matches(text, '[A-Za-z]+[%#*$&]{3}|[a-z0-9.]+@[a-z0-9-]+[.][a-z]+')")(
    lambda d: d.filter(F.col("text").rlike("[A-Za-z]+[%#*$&]{3}|[a-z0-9.]+@[a-z0-9-]+[.][a-z]+")).select("doc_id", F.regexp_count("text", F.lit("[A-Za-z]+[%#*$&]{3}")).cast("long").alias("marked"), F.col("text").rlike("[a-z0-9.]+@[a-z0-9-]+[.][a-z]+").alias("mail"))
)
# Joins
_op("join_broadcast", "customer nation region", "SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")(
    lambda c, n, r: c.join(F.broadcast(n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey)), c.c_nationkey == n.n_nationkey).groupBy("r_name").agg(F.count("*").alias("n"))  # 25 nations
)
for _hint, _name in (("merge", "sortmerge"), ("shuffle_hash", "shuffle_hash")):
    _op(f"join_{_name}", "orders lineitem", "SELECT o_orderstatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderstatus")(
        lambda o, li, h=_hint: o.select("o_orderkey", "o_orderstatus").join(li.select("l_orderkey", "l_quantity").hint(h), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))
    )
for _how in ("left", "right", "full"):
    _op(f"join_{_how}", "documents labels", f"SELECT doc_id, coalesce(n_chars, -1) AS n_chars, coalesce(quality, -1) AS quality FROM documents {_how.upper()} JOIN labels USING (doc_id)")(
        lambda d, x, how=_how: d.select("doc_id", "n_chars").join(x.select("doc_id", "quality"), "doc_id", how).select("doc_id", F.coalesce("n_chars", F.lit(-1)).alias("n_chars"), F.coalesce("quality", F.lit(-1)).alias("quality"))
    )
_op("join_semi", "documents labels", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")(lambda d, x: d.select("doc_id").join(x, "doc_id", "left_semi"))
_op("join_anti", "documents labels", "SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels x WHERE x.doc_id = d.doc_id)")(lambda d, x: d.select("doc_id").join(x, "doc_id", "left_anti"))
_op("join_theta", "nation region", "SELECT n_name, r_name FROM nation JOIN region ON n_nationkey < 3 * r_regionkey")(lambda n, r: n.join(F.broadcast(r), n.n_nationkey < 3 * r.r_regionkey).select("n_name", "r_name"))  # 5 regions


@_op("join_range", "events", "WITH e AS (SELECT event_id, floor(epoch(ts))::BIGINT AS s FROM events WHERE event_type = 'signup'), p AS (SELECT floor(epoch(ts))::BIGINT AS s FROM events WHERE event_type = 'purchase') SELECT e.event_id, count(*) AS purchases FROM e JOIN p ON p.s BETWEEN e.s AND e.s + 21600 GROUP BY e.event_id")
def _range(e):
    """Purchases in the six hours after each signup: equal six-hour bins, then the exact bounds."""
    s = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000).cast("long")
    left = e.filter("event_type = 'signup'").select("event_id", s.alias("s")).withColumn("bin", F.explode(F.array(F.floor(F.col("s") / 21600), F.floor(F.col("s") / 21600) + 1)))
    right = e.filter("event_type = 'purchase'").select(s.alias("t")).withColumn("bin", F.floor(F.col("t") / 21600))
    return left.join(right, "bin").filter("t between s and s + 21600").groupBy("event_id").agg(F.count("*").alias("purchases"))


_op("join_interval", "events", "SELECT a.event_id AS signup, b.event_id AS later FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'signup' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")(
    lambda e: e.filter("event_type = 'signup'").select("user_id", F.col("ts").alias("s"), F.col("event_id").alias("signup")).join(e.select("user_id", "ts", F.col("event_id").alias("later")), "user_id").filter("ts > s AND ts <= s + INTERVAL 1 HOUR").select("signup", "later")
)


@_op("join_asof", "events", "WITH v AS (SELECT user_id, ts, event_id FROM events WHERE event_type = 'view') SELECT p.event_id, coalesce((SELECT max_by(v.event_id, v.ts) FROM v WHERE v.user_id = p.user_id AND v.ts < p.ts), -1) AS seen FROM events p WHERE p.event_type = 'purchase'")
def _asof(e):
    """Each purchase with the user's last earlier view: one window over both kinds, no join."""
    w = W.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "purchase", 0).otherwise(1)).rowsBetween(W.unboundedPreceding, -1)
    rows = e.filter("event_type in ('view', 'purchase')").withColumn("seen", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w))
    return rows.filter("event_type = 'purchase'").select("event_id", F.coalesce("seen", F.lit(-1)).alias("seen"))


_op("join_self_pairs", "conversations", "SELECT a.conv_id, a.turn AS one, b.turn AS two FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND a.turn < b.turn AND a.role = 'user' AND b.role = 'user'")(
    lambda c: c.filter("role = 'user'").select("conv_id", F.col("turn").alias("one")).join(c.filter("role = 'user'").select("conv_id", F.col("turn").alias("two")), "conv_id").filter("one < two")
)


@_op("join_lateral", "documents", "SELECT doc_id, line FROM (SELECT doc_id, line, row_number() OVER (PARTITION BY doc_id ORDER BY md5(line), line) AS k FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents)) WHERE k <= 2")
def _lateral(d):
    """Two lines of each document in hash order, inside the row."""
    lines = F.array_sort(F.transform(F.split("text", "\n"), lambda x: F.struct(F.md5(x.cast("binary")).alias("h"), x.alias("line"))))
    return d.select("doc_id", F.explode(F.slice(lines, 1, 2)).alias("x")).select("doc_id", "x.line")


_op("join_cross", "region", "SELECT r_name, lang FROM region, (VALUES ('de'), ('fr')) AS t(lang)")(lambda r: r.select("r_name").crossJoin(r.sparkSession.createDataFrame([("de",), ("fr",)], "lang string")))  # 5 x 2 rows
# Aggregates
_op("agg_hash", "lineitem", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS q, round(avg(l_discount), 6) AS d, count(*) AS n FROM lineitem GROUP BY ALL")(
    lambda d: d.groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("q"), F.round(F.avg("l_discount"), 6).alias("d"), F.count("*").alias("n"))
)
_op("agg_distinct", "events", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")(lambda e: e.groupBy("event_type").agg(F.countDistinct("user_id").alias("users")))
_op("agg_conditional", "documents", "SELECT count(*) AS n, count(*) FILTER (n_chars < 100) AS short, sum(CASE WHEN lang = 'en' THEN n_chars ELSE 0 END)::BIGINT AS english FROM documents")(
    lambda d: d.agg(F.count("*").alias("n"), F.count_if(F.col("n_chars") < 100).alias("short"), F.sum(F.when(F.col("lang") == "en", F.col("n_chars")).otherwise(0)).alias("english"))
)
_op("agg_rollup", "documents", "SELECT lang, source, count(*) AS n, (grouping(lang) * 2 + grouping(source))::BIGINT AS g FROM documents GROUP BY ROLLUP (lang, source)")(lambda d: d.rollup("lang", "source").agg(F.count("*").alias("n"), F.grouping_id().alias("g")))
_op("agg_cube", "documents", "SELECT lang, source, count(*) AS n, (grouping(lang) * 2 + grouping(source))::BIGINT AS g FROM documents GROUP BY CUBE (lang, source)")(lambda d: d.cube("lang", "source").agg(F.count("*").alias("n"), F.grouping_id().alias("g")))
_sql("agg_grouping_sets", "documents", "SELECT lang, source, count(*) AS n FROM {documents} GROUP BY GROUPING SETS ((lang), (source), ())")
_op("agg_pivot", "events", "SELECT user_id, count(*) FILTER (event_type = 'view') AS view, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY user_id")(
    lambda e: e.groupBy("user_id").pivot("event_type", ["view", "purchase"]).agg(F.count(F.lit(1))).na.fill(0)
)
_op("unpivot", "part", "SELECT p_partkey, 'size' AS what, p_size::DOUBLE AS value FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")(
    lambda p: p.select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price")).unpivot("p_partkey", ["size", "price"], "what", "value")
)
_op("agg_collect", "conversations", "SELECT conv_id, md5(string_agg(text, '|' ORDER BY turn)) AS asked FROM conversations WHERE role = 'user' GROUP BY conv_id")(
    lambda c: c.filter("role = 'user'").groupBy("conv_id").agg(F.md5(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "text"))), lambda x: x.text), "|").cast("binary")).alias("asked"))
)
_op("agg_argmax", "documents", "SELECT lang, min(doc_id) AS doc_id FROM documents d WHERE n_chars = (SELECT max(n_chars) FROM documents e WHERE e.lang = d.lang) GROUP BY lang")(lambda d: d.groupBy("lang").agg(F.max_by("doc_id", F.struct("n_chars", -F.col("doc_id"))).alias("doc_id")))
_op("agg_percentile", "documents", "SELECT lang, round(quantile_cont(n_chars, 0.5), 4) AS mid, round(quantile_cont(n_chars, 0.9), 4) AS high FROM documents GROUP BY lang")(
    lambda d: d.groupBy("lang").agg(F.round(F.percentile("n_chars", F.lit(0.5)), 4).alias("mid"), F.round(F.percentile("n_chars", F.lit(0.9)), 4).alias("high"))
)
_op("agg_approx", "events")(lambda e: e.agg(F.approx_count_distinct("user_id", 0.02).alias("users"), F.percentile_approx("value", 0.5, 1000).alias("median"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("hll")))
_op("agg_corr", "lineitem", "SELECT round(corr(l_quantity, l_extendedprice), 6) AS r, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(covar_samp(l_quantity, l_discount), 6) AS c FROM lineitem")(
    lambda d: d.agg(F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"), F.round(F.covar_samp("l_quantity", "l_discount"), 6).alias("c"))
)
_op("agg_salted", "documents", "SELECT lang, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY lang")(
    lambda d: d.groupBy("lang", F.pmod(F.xxhash64("doc_id"), F.lit(16)).alias("salt")).agg(F.count("*").alias("n"), F.sum("n_chars").alias("c")).groupBy("lang").agg(F.sum("n").alias("n"), F.sum("c").alias("chars"))
)
# Windows
def _cw():
    return W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")


_op("win_rank", "orders", "SELECT o_orderkey, row_number() OVER w AS k, rank() OVER w AS r, dense_rank() OVER w AS d FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)")(
    lambda o: o.select("o_orderkey", F.row_number().over(_cw()).alias("k"), F.rank().over(_cw()).alias("r"), F.dense_rank().over(_cw()).alias("d"))
)
_op("win_frame_rows", "orders", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS running FROM orders")(
    lambda o: o.select("o_orderkey", F.round(F.sum("o_totalprice").over(W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(-2, 0)), 2).alias("running"))
)
_op("win_frame_range", "events", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY floor(epoch(ts))::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS day FROM events")(
    lambda e: e.select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy(F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000).cast("long")).rangeBetween(-86400, 0)).alias("day"))
)
def _ew():
    return W.partitionBy("user_id").orderBy("ts", "event_id")


_op("win_analytic", "events", "SELECT event_id, coalesce(lag(event_id) OVER w, -1) AS before, coalesce(lead(event_id) OVER w, -1) AS after, first_value(event_id) OVER w AS first, coalesce(nth_value(event_id, 2) OVER w, -1) AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")(
    lambda e: e.select("event_id", F.lag("event_id", 1, -1).over(_ew()).alias("before"), F.lead("event_id", 1, -1).over(_ew()).alias("after"), F.first("event_id").over(_ew()).alias("first"), F.coalesce(F.nth_value("event_id", 2).over(_ew()), F.lit(-1)).alias("second"))
)
def _pw():
    return W.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")


_op("win_ntile", "part", "SELECT p_partkey, ntile(4) OVER w AS q, round(percent_rank() OVER w, 6) AS p, round(cume_dist() OVER w, 6) AS c FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey)")(
    lambda p: p.select("p_partkey", F.ntile(4).over(_pw()).alias("q"), F.round(F.percent_rank().over(_pw()), 6).alias("p"), F.round(F.cume_dist().over(_pw()), 6).alias("c"))
)


@_op("sessionize", "events", "WITH g AS (SELECT user_id, event_id, ts, CASE WHEN ts - lag(ts) OVER w <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) SELECT user_id, session, count(*) AS n FROM (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id)::BIGINT AS session FROM g) GROUP BY ALL")
def _sessions(e):
    fresh = F.when(F.col("ts") <= F.lag("ts").over(_ew()) + F.expr("INTERVAL 30 MINUTE"), 0).otherwise(1)
    return e.withColumn("fresh", fresh).withColumn("session", F.sum("fresh").over(_ew())).groupBy("user_id", "session").agg(F.count("*").alias("n"))


_op("sort_limit", "orders", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")(lambda o: o.select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20))
_op("topk_group", "customer", "SELECT c_nationkey, c_custkey FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS k FROM customer) WHERE k <= 3")(
    lambda c: c.withColumn("k", F.row_number().over(W.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey"))).filter("k <= 3").select("c_nationkey", "c_custkey")
)
# Sets
for _name, _f, _s in (
    ("union", lambda a, b: a.union(b), "UNION ALL"), ("intersect", lambda a, b: a.intersect(b), "INTERSECT"), ("intersect_all", lambda a, b: a.intersectAll(b), "INTERSECT ALL"),
    ("except", lambda a, b: a.subtract(b), "EXCEPT"), ("except_all", lambda a, b: a.exceptAll(b), "EXCEPT ALL"),
):
    _op(_name, "documents conversations", f"SELECT lang AS x, length(text) % 50 AS k FROM documents {_s} SELECT 'en', length(text) % 50 FROM conversations")(
        lambda d, c, f=_f: f(d.select(F.col("lang").alias("x"), (F.length("text") % 50).cast("long").alias("k")), c.select(F.lit("en").alias("x"), (F.length("text") % 50).cast("long").alias("k")))
    )
_op("union_by_name", "documents benchmark", "SELECT doc_id, -1 AS item_id FROM documents UNION ALL SELECT -1, item_id FROM benchmark")(
    lambda d, b: d.select("doc_id").unionByName(b.select("item_id"), allowMissingColumns=True).na.fill(-1)
)
_op("distinct", "documents", "SELECT DISTINCT md5(text) AS h FROM documents")(lambda d: d.select("text").distinct().select(F.md5(F.col("text").cast("binary")).alias("h")))
_op("drop_duplicates", "documents", "SELECT min(doc_id) AS doc_id FROM documents GROUP BY text")(lambda d: d.groupBy("text").agg(F.min("doc_id").alias("doc_id")).select("doc_id"))
# Subqueries
_sql("scalar_subquery", "orders", "SELECT o_orderkey FROM {orders} WHERE o_totalprice > 2 * (SELECT avg(o_totalprice) FROM {orders})")
_sql("exists", "customer orders", "SELECT c_custkey FROM {customer} c WHERE EXISTS (SELECT 1 FROM {orders} o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 300000)")
_sql("in", "part lineitem", "SELECT p_partkey FROM {part} WHERE p_partkey IN (SELECT l_partkey FROM {lineitem} WHERE l_quantity >= 50)")
_sql("correlated", "orders", "SELECT o_orderkey FROM {orders} o WHERE o_totalprice > (SELECT 1.5 * avg(i.o_totalprice) FROM {orders} i WHERE i.o_custkey = o.o_custkey)")
_sql("cte", "documents", "WITH s AS (SELECT source, count(*) AS n FROM {documents} GROUP BY source) SELECT a.source, a.n, b.n AS other FROM s a JOIN s b ON a.n = b.n AND a.source < b.source")
# Scalars
_op("string", "documents", r"SELECT doc_id, md5(trim(regexp_replace(lower(text), '[^\p{L}\p{N}]+', ' ', 'g'))) AS n, translate(substr(text, 3, 5), 'aeiou', '12345') AS t, length(text) AS chars, strlen(text) AS bytes, len(string_split(text, ' ')) AS parts FROM documents")(
    lambda d: d.select("doc_id", F.md5(norm(F.col("text")).cast("binary")).alias("n"), F.translate(F.substring("text", 3, 5), "aeiou", "12345").alias("t"), F.length("text").cast("long").alias("chars"), F.octet_length("text").cast("long").alias("bytes"), F.size(F.split("text", " ", -1)).cast("long").alias("parts"))
)
_op("url", "pages", r"SELECT page_id, regexp_extract(url, '^([a-z]+):', 1) AS scheme, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]*([^?#]*)', 1) AS path FROM pages")(
    lambda p: p.select("page_id", F.try_parse_url("url", F.lit("PROTOCOL")).alias("scheme"), F.try_parse_url("url", F.lit("HOST")).alias("host"), F.try_parse_url("url", F.lit("PATH")).alias("path"))
)
_op("url_canonical", "pages")(lambda p: p.select("page_id", canonical_url(F.col("url")).alias("url")))
_op("html", "pages", "SELECT page_id, len(regexp_extract_all(html, '<p[ >]')) AS paragraphs, len(regexp_extract_all(html, 'href=\"([^\"]*)\"')) AS links, strlen(html) AS bytes FROM pages")(
    lambda p: p.select("page_id", F.regexp_count("html", F.lit("<p[ >]")).cast("long").alias("paragraphs"), F.size(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).cast("long").alias("links"), F.octet_length("html").cast("long").alias("bytes"))
)
_op("html_plain", "pages")(lambda p: p.select("page_id", F.length(to_plain(F.col("html"))).alias("n")))
_op("math", "part", "SELECT p_partkey, round(ln(p_retailprice), 6) AS l, round(sqrt(p_size), 6) AS s, p_size % 7 AS m, bit_count(p_partkey) AS b FROM part")(
    lambda p: p.select("p_partkey", F.round(F.ln("p_retailprice"), 6).alias("l"), F.round(F.sqrt("p_size"), 6).alias("s"), F.pmod("p_size", F.lit(7)).alias("m"), F.bit_count("p_partkey").alias("b"))
)
_op("date", "orders", "SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, date_diff('day', DATE '1992-01-01', o_orderdate::DATE) AS days, year(o_orderdate) AS y FROM orders")(
    lambda o: o.select("o_orderkey", F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1992-01-01").cast("date")).cast("long").alias("days"), F.year("o_orderdate").cast("long").alias("y"))
)
_op("array", "documents", "SELECT doc_id, len(w) AS n, len(list_distinct(w)) AS d, list_max(list_transform(w, lambda x: length(x))) AS longest, len(list_intersect(w, ['the', 'and', 'der'])) AS common FROM (SELECT doc_id, string_split(text, ' ') AS w FROM documents)")(
    lambda d: d.select("doc_id", F.split("text", " ", -1).alias("w")).select("doc_id", F.size("w").cast("long").alias("n"), F.size(F.array_distinct("w")).cast("long").alias("d"), F.array_max(F.transform("w", F.length)).cast("long").alias("longest"), F.size(F.array_intersect("w", F.array(*map(F.lit, ("the", "and", "der"))))).cast("long").alias("common"))
)
_op("map", "events", "SELECT user_id, count(DISTINCT event_type) AS kinds, count(*) FILTER (event_type = 'view') AS views FROM events GROUP BY user_id")(
    lambda e: e.groupBy("user_id", "event_type").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m")).select("user_id", F.size("m").cast("long").alias("kinds"), F.coalesce(F.col("m")["view"], F.lit(0)).alias("views"))
)
_op("struct", "documents", "SELECT doc_id, lang AS l, n_chars AS n FROM documents WHERE n_chars > 5000")(lambda d: d.select(F.struct("doc_id", F.col("lang").alias("l"), F.col("n_chars").alias("n")).alias("s")).filter("s.n > 5000").select("s.*"))
_op("json", "events", "SELECT event_id, json_extract(props, '$.k')::BIGINT AS k FROM events")(lambda e: e.select("event_id", F.from_json("props", "k bigint").k.alias("k")))
_op("variant", "events", "SELECT sum(json_extract(props, '$.k')::BIGINT)::BIGINT AS k FROM events")(lambda e: e.agg(F.sum(F.variant_get(F.parse_json("props"), "$.k", "bigint")).alias("k")))
_op("explode", "documents", "SELECT doc_id, unnest(range(len(string_split(text, chr(10))))) AS pos, unnest(list_transform(string_split(text, chr(10)), lambda x: length(x))) AS n FROM documents")(
    lambda d: d.select("doc_id", F.posexplode(F.split("text", "\n", -1)).alias("pos", "line")).select("doc_id", F.col("pos").cast("long").alias("pos"), F.length("line").cast("long").alias("n"))
)
@_op("vector_topk", "embeddings", "SELECT vec_id, other FROM (SELECT a.vec_id, b.vec_id AS other, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) DESC, b.vec_id) AS k FROM embeddings a, embeddings b WHERE a.vec_id % 100 = 0 AND a.vec_id <> b.vec_id) WHERE k <= 3")
def _vector(v):
    """Nearest three of every hundredth vector, by brute force: the queries, a stated set, meet all rows block by block."""
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)
    blocks = 64
    asked = v.filter("vec_id % 100 = 0").select("vec_id", F.col("embedding").alias("a"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("block"))
    rows = v.select(F.col("vec_id").alias("other"), F.col("embedding").alias("b"), F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).alias("block"))
    near = rows.join(asked, "block").filter("vec_id <> other")
    scored = near.select("vec_id", "other", F.round(dot("a", "b") / F.sqrt(dot("a", "a") * dot("b", "b")), 9).alias("c"))
    # The rank's limit reaches each task before the shuffle, so a task sends three rows a query.
    ranked = scored.withColumn("k", F.row_number().over(W.partitionBy("vec_id").orderBy(F.desc("c"), "other")))
    return ranked.filter("k <= 3").select("vec_id", "other")


# Python surfaces
@_op("udf_pandas", "documents", "SELECT doc_id, len(string_split(text, ' ')) AS parts FROM documents")
def _pandas(d):
    @F.pandas_udf("long")
    def parts(text: pd.Series) -> pd.Series:
        return text.str.count(" ") + 1

    return d.select("doc_id", parts("text").alias("parts"))


@_op("udaf", "documents", "SELECT lang, round(avg(n_chars), 4) AS mean FROM documents GROUP BY lang")
def _udaf(d):
    """Sums in Python per language and bucket of rows, so that no language is one task; the mean from the sums."""

    @F.pandas_udf("double")
    def total(v: pd.Series) -> float:
        return float(v.sum())

    @F.pandas_udf("long")
    def known(v: pd.Series) -> int:
        return int(v.count())

    parts = d.groupBy("lang", F.pmod(F.xxhash64("doc_id"), F.lit(64)).alias("salt")).agg(total("n_chars").alias("total"), known("n_chars").alias("n"))
    return parts.groupBy("lang").agg(F.round(F.try_divide(F.sum("total"), F.sum("n")), 4).alias("mean"))


@_op("map_arrow", "documents", "SELECT count(*) AS n FROM documents WHERE n_chars > 1000")
def _arrow(d):
    def run(batches):
        import pyarrow.compute as pc

        for b in batches:
            yield b.filter(pc.greater(b.column(0), 1000))

    return d.select("n_chars").mapInArrow(run, "n_chars long").agg(F.count("*").alias("n"))


@_op("cogroup", "documents labels", "SELECT lang, count(*) AS docs, count(quality) AS labelled FROM documents LEFT JOIN labels USING (doc_id) GROUP BY lang")
def _cogroup(d, x):
    """Per language and hash bucket (so that no language is one task), documents and those with a label."""
    labelled = x.select("doc_id").join(d.select("doc_id", "lang").alias("own"), "doc_id").select(F.col("doc_id").alias("id"), F.col("lang").alias("language"))
    salt = F.pmod(F.xxhash64("doc_id"), F.lit(32))

    def merge(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        some = a if len(a) else b
        return pd.DataFrame({"lang": [some.iloc[0, 1]], "docs": [len(a)], "labelled": [len(b)]})

    left = d.select("doc_id", "lang", salt.alias("salt")).groupBy("lang", "salt")
    both_ = left.cogroup(labelled.select("id", "language", F.pmod(F.xxhash64("id"), F.lit(32)).alias("part")).groupBy("language", "part")).applyInPandas(merge, "lang string, docs long, labelled long")
    return both_.groupBy("lang").agg(F.sum("docs").alias("docs"), F.sum("labelled").alias("labelled"))


@_op("udtf", "documents", "SELECT count(*) AS n FROM (SELECT unnest(string_split(text, chr(10))) FROM documents)")
def _udtf(d):
    @F.udtf(returnType="line string")
    class Lines:
        def eval(self, text: str):
            for line in (text or "").split("\n"):
                yield (line,)

    d.sparkSession.udtf.register("lines_of", Lines)
    return d.sparkSession.sql("SELECT count(*) AS n FROM {d}, LATERAL lines_of({d}.text)", d=d.select("text"))
