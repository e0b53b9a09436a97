"""Relational operators around claims: each entry is a query over the given tables and its DuckDB twin (None: rows only).

Money is summed in integer cents so that both engines give equal values.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from functools import reduce

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sparkverdict.session import shared_dir, ship_package

Fn = Callable[[SparkSession, Callable[[str], DataFrame]], DataFrame]
REGISTRY: dict[str, tuple[Fn, str | None]] = {}
c = F.col


def op(name: str, sql: str | None = None) -> Callable[[Fn], Fn]:
    def add(f: Fn) -> Fn:
        REGISTRY[name] = (f, sql)
        return f

    return add


def simple(name: str, build: Callable[[Callable[[str], DataFrame]], DataFrame], sql: str | None) -> None:
    REGISTRY[name] = (lambda s, t, f=build: f(t), sql)


def cents(col: str):
    return F.round(c(col) * 100).cast("long")


# --- scans, projections, predicates ---
simple("scan_parquet", lambda t: t("documents").filter(c("lang") == "fr").select("doc_id", "n_chars"), "SELECT doc_id, n_chars FROM documents WHERE lang = 'fr'")
simple("proj_basic", lambda t: t("lineitem").select(c("l_orderkey").alias("order_id"), c("l_linenumber").cast("long").alias("line"), cents("l_extendedprice").alias("cents")), "SELECT l_orderkey AS order_id, l_linenumber::BIGINT AS line, round(l_extendedprice * 100)::BIGINT AS cents FROM lineitem")
simple("proj_case", lambda t: t("lineitem").select("l_orderkey", "l_linenumber", F.when(c("l_quantity") < 10, "low").when(c("l_quantity") < 30, "mid").otherwise("high").alias("band")), "SELECT l_orderkey, l_linenumber, CASE WHEN l_quantity < 10 THEN 'low' WHEN l_quantity < 30 THEN 'mid' ELSE 'high' END AS band FROM lineitem")
simple("flt_cmp", lambda t: t("documents").filter((c("n_chars") > 2000) & (c("lang") != "en")).select("doc_id"), "SELECT doc_id FROM documents WHERE n_chars > 2000 AND lang <> 'en'")
simple("flt_in", lambda t: t("documents").filter(c("source").isin("src1", "src2")).select("doc_id"), "SELECT doc_id FROM documents WHERE source IN ('src1', 'src2')")
simple("flt_between", lambda t: t("orders").filter(cents("o_totalprice").between(1000000, 5000000)).select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE round(o_totalprice * 100)::BIGINT BETWEEN 1000000 AND 5000000")
simple("flt_like", lambda t: t("part").filter(c("p_name").like("%a%e%")).select("p_partkey"), "SELECT p_partkey FROM part WHERE p_name LIKE '%a%e%'")
simple("flt_rlike", lambda t: t("documents").filter(c("text").rlike("[0-9]{16}")).select("doc_id"), "SELECT doc_id FROM documents WHERE regexp_matches(text, '[0-9]{16}')")
simple("flt_null", lambda t: t("documents").join(t("labels"), "doc_id", "left").select("doc_id", c("toxic").isNull().alias("unlabelled"), c("toxic").eqNullSafe(1).alias("toxic"), F.coalesce("quality", F.lit(-1)).alias("quality")), "SELECT doc_id, toxic IS NULL AS unlabelled, toxic IS NOT DISTINCT FROM 1 AS toxic, coalesce(quality, -1) AS quality FROM documents LEFT JOIN labels USING (doc_id)")

# --- joins ---
simple("join_broadcast", lambda t: t("nation").join(F.broadcast(t("region")), c("n_regionkey") == c("r_regionkey")).select("n_name", "r_name"), "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
simple("join_equi", lambda t: t("orders").hint("merge").join(t("lineitem"), c("o_orderkey") == c("l_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n")), "SELECT o_orderpriority, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
simple("join_hash", lambda t: t("lineitem").join(t("orders").hint("shuffle_hash"), c("o_orderkey") == c("l_orderkey")).groupBy("o_orderstatus").agg(F.sum(cents("l_extendedprice")).alias("cents")), "SELECT o_orderstatus, sum(round(l_extendedprice * 100)::BIGINT)::BIGINT AS cents FROM lineitem JOIN orders ON o_orderkey = l_orderkey GROUP BY 1")
simple("join_semi", lambda t: t("customer").join(t("orders"), c("c_custkey") == c("o_custkey"), "left_semi").select("c_custkey"), "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
simple("join_anti", lambda t: t("customer").join(t("orders"), c("c_custkey") == c("o_custkey"), "left_anti").select("c_custkey"), "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
simple("join_left", lambda t: t("documents").join(t("labels"), "doc_id", "left").select("doc_id", "quality"), "SELECT doc_id, quality FROM documents LEFT JOIN labels USING (doc_id)")
simple("join_right", lambda t: t("labels").join(t("documents"), "doc_id", "right").select("doc_id", "toxic"), "SELECT doc_id, toxic FROM labels RIGHT JOIN documents USING (doc_id)")
simple("join_full", lambda t: t("documents").join(t("labels"), "doc_id", "full").select("doc_id", "lang", "quality"), "SELECT doc_id, lang, quality FROM documents FULL JOIN labels USING (doc_id)")
simple("join_cross", lambda t: t("nation").crossJoin(t("region")).groupBy("r_name").agg(F.count(F.lit(1)).alias("n")), "SELECT r_name, count(*) AS n FROM nation CROSS JOIN region GROUP BY 1")
simple("join_range", lambda t: t("part").join(F.broadcast(t("region").select((c("r_regionkey") * 10).alias("lo"), (c("r_regionkey") * 10 + 10).alias("hi"))), (c("p_size") >= c("lo")) & (c("p_size") < c("hi"))).select("p_partkey", "lo"), "SELECT p_partkey, lo FROM part JOIN (SELECT r_regionkey * 10 AS lo, r_regionkey * 10 + 10 AS hi FROM region) ON p_size >= lo AND p_size < hi")
simple("join_self", lambda t: t("supplier").alias("a").join(t("supplier").alias("b"), (c("a.s_nationkey") == c("b.s_nationkey")) & (c("a.s_suppkey") < c("b.s_suppkey"))).select(c("a.s_suppkey").alias("a"), c("b.s_suppkey").alias("b")), "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey")


@op("join_lateral", "SELECT n_name, s_suppkey FROM (SELECT n_name, s_suppkey, row_number() OVER (PARTITION BY n_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS r FROM nation JOIN supplier ON s_nationkey = n_nationkey) WHERE r <= 2")
def _(s, t):
    t("nation").createOrReplaceTempView("v_nation")
    t("supplier").createOrReplaceTempView("v_supplier")
    return s.sql("SELECT n_name, s_suppkey FROM v_nation, LATERAL (SELECT s_suppkey FROM v_supplier WHERE s_nationkey = n_nationkey ORDER BY s_acctbal DESC, s_suppkey LIMIT 2)")


simple("join_interval", lambda t: t("events").filter("event_type = 'click'").alias("a").join(t("events").filter("event_type = 'error'").alias("b"), (c("a.user_id") == c("b.user_id")) & (c("b.ts") >= c("a.ts")) & (c("b.ts") <= c("a.ts") + F.expr("INTERVAL 1 HOUR"))).select(c("a.event_id").alias("click"), c("b.event_id").alias("error")), "SELECT a.event_id AS click, b.event_id AS error FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'error' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")


@op("join_asof", "SELECT p.event_id, max(s.ts) AS since FROM (SELECT * FROM events WHERE event_type = 'purchase') p LEFT JOIN (SELECT * FROM events WHERE event_type = 'signup') s ON p.user_id = s.user_id AND s.ts <= p.ts GROUP BY p.event_id")
def _(s, t):
    """The last signup at or before each purchase: one sorted pass per user, no pairs."""
    e = t("events").filter(c("event_type").isin("purchase", "signup"))
    w = Window.partitionBy("user_id").orderBy("ts", F.when(c("event_type") == "signup", 0).otherwise(1)).rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("since", F.last(F.when(c("event_type") == "signup", c("ts")), ignorenulls=True).over(w)).filter("event_type = 'purchase'").select("event_id", "since")


@op("join_contains", "SELECT d.doc_id, count(*) AS n FROM documents d JOIN benchmark b ON contains(d.text, b.text) GROUP BY 1")
def _(s, t):
    """Every passage against every text: the passages are the small side, the texts are not shuffled."""
    b = t("benchmark").select("item_id", c("text").alias("passage"))
    return t("documents").select("doc_id", "text").join(b, F.contains("text", "passage")).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))


# --- aggregation ---
simple("agg_bool", lambda t: t("documents").groupBy("lang").agg(F.bool_or(c("n_chars") > 5000).alias("some"), F.bool_and(c("n_chars") > 10).alias("every")), "SELECT lang, bool_or(n_chars > 5000) AS some, bool_and(n_chars > 10) AS every FROM documents GROUP BY 1")
simple("agg_countif", lambda t: t("events").agg(F.count_if(c("event_type") == "error").alias("hits"), F.count(F.lit(1)).alias("seen")), "SELECT count(*) FILTER (event_type = 'error') AS hits, count(*) AS seen FROM events")
simple("agg_share", lambda t: t("events").groupBy("user_id").agg(F.count_if(c("event_type") == "error").alias("hits"), F.count(F.lit(1)).alias("seen")), "SELECT user_id, count(*) FILTER (event_type = 'error') AS hits, count(*) AS seen FROM events GROUP BY 1")
simple("agg_distinct", lambda t: t("orders").groupBy("o_orderpriority").agg(F.countDistinct("o_custkey").alias("n")), "SELECT o_orderpriority, count(DISTINCT o_custkey) AS n FROM orders GROUP BY 1")
simple("agg_approx", lambda t: t("orders").agg(F.approx_count_distinct("o_custkey", 0.01).alias("n")), None)
simple("agg_sketch", lambda t: t("lineitem").groupBy("l_returnflag").agg(F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("parts")), None)
simple("agg_cube", lambda t: t("customer").cube("c_nationkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n")), "SELECT c_nationkey, c_mktsegment, count(*) AS n FROM customer GROUP BY CUBE (c_nationkey, c_mktsegment)")
simple("agg_rollup", lambda t: t("customer").rollup("c_nationkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"), F.sum(cents("c_acctbal")).alias("cents")), "SELECT c_nationkey, c_mktsegment, count(*) AS n, sum(round(c_acctbal * 100)::BIGINT)::BIGINT AS cents FROM customer GROUP BY ROLLUP (c_nationkey, c_mktsegment)")


@op("agg_gsets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def _(s, t):
    return t("orders").groupingSets([[c("o_orderstatus")], [c("o_orderpriority")], []], c("o_orderstatus"), c("o_orderpriority")).agg(F.count(F.lit(1)).alias("n"))


simple("agg_having", lambda t: t("lineitem").groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n")).filter("n > 50"), "SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY 1 HAVING count(*) > 50")
simple("agg_pivot", lambda t: t("events").groupBy("user_id").pivot("event_type", ["click", "error"]).agg(F.count(F.lit(1))), "SELECT user_id, nullif(count(*) FILTER (event_type = 'click'), 0) AS click, nullif(count(*) FILTER (event_type = 'error'), 0) AS error FROM events GROUP BY 1")
simple("agg_minmaxby", lambda t: t("orders").groupBy("o_orderpriority").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("top"), F.min("o_orderkey").alias("first")), "SELECT o_orderpriority, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS top, min(o_orderkey) AS first FROM orders GROUP BY 1")
simple("agg_pct", lambda t: t("part").groupBy("p_size").agg(F.round(F.median("p_retailprice"), 4).alias("med")), "SELECT p_size, round(median(p_retailprice), 4) AS med FROM part GROUP BY 1")
simple("agg_stats", lambda t: t("lineitem").groupBy("l_returnflag").agg(F.round(F.avg("l_quantity"), 6).alias("mean"), F.round(F.stddev("l_quantity"), 6).alias("sd")), "SELECT l_returnflag, round(avg(l_quantity), 6) AS mean, round(stddev(l_quantity), 6) AS sd FROM lineitem GROUP BY 1")
simple("agg_collect", lambda t: t("conversations").groupBy("conv_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"]), ",").alias("roles")), "SELECT conv_id, string_agg(role, ',' ORDER BY turn, role) AS roles FROM conversations GROUP BY 1")

# --- windows ---
_sup = lambda t: t("lineitem").groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n"))
_SUP = "(SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY 1)"
for _n, _f, _s, _o in [
    ("win_dense", F.dense_rank, "dense_rank()", F.desc), ("win_dense_asc", F.dense_rank, "dense_rank()", F.asc), ("win_rank", F.rank, "rank()", F.desc),
]:
    simple(_n, lambda t, f=_f, o=_o: _sup(t).select("l_suppkey", f().over(Window.orderBy(o("n"))).cast("long").alias("r")), f"SELECT l_suppkey, {_s} OVER (ORDER BY n {'ASC' if 'asc' in _n else 'DESC'}) AS r FROM {_SUP}")
for _n, _f, _s in [("win_rownum", F.row_number, "row_number()"), ("win_ntile", lambda: F.ntile(4), "ntile(4)")]:
    simple(_n, lambda t, f=_f: _sup(t).select("l_suppkey", f().over(Window.orderBy(c("n").desc(), "l_suppkey")).cast("long").alias("r")), f"SELECT l_suppkey, {_s} OVER (ORDER BY n DESC, l_suppkey)::BIGINT AS r FROM {_SUP}")
simple("win_pctrank", lambda t: _sup(t).select("l_suppkey", F.round(F.percent_rank().over(Window.orderBy("n")), 9).alias("r")), f"SELECT l_suppkey, round(percent_rank() OVER (ORDER BY n), 9) AS r FROM {_SUP}")
_w = lambda: Window.partitionBy("user_id").orderBy("event_id")
_W = "OVER (PARTITION BY user_id ORDER BY event_id"
simple("win_lag", lambda t: t("events").select("event_id", F.lag("event_type").over(_w()).alias("before")), f"SELECT event_id, lag(event_type) {_W}) AS before FROM events")
simple("win_lead", lambda t: t("events").select("event_id", F.lead("event_type", 2).over(_w()).alias("after")), f"SELECT event_id, lead(event_type, 2) {_W}) AS after FROM events")
simple("win_first", lambda t: t("events").select("event_id", F.first("event_type").over(_w()).alias("first_type")), f"SELECT event_id, first_value(event_type) {_W}) AS first_type FROM events")
simple("win_last", lambda t: t("events").select("event_id", F.last("event_type").over(_w().rowsBetween(0, Window.unboundedFollowing)).alias("last_type")), f"SELECT event_id, last_value(event_type) {_W} ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS last_type FROM events")
simple("win_rows", lambda t: t("events").select("event_id", F.count_if(c("event_type") == "error").over(_w().rowsBetween(Window.unboundedPreceding, 0)).alias("hits")), f"SELECT event_id, count(*) FILTER (event_type = 'error') {_W} ROWS UNBOUNDED PRECEDING) AS hits FROM events")
simple("win_range", lambda t: t("events").select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy(F.unix_micros(c("ts").cast("timestamp"))).rangeBetween(-86400 * 10**6, 0)).alias("n")), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS n FROM events")


@op("win_stop", "SELECT source, min(pos) AS stop FROM (SELECT source, row_number() OVER w AS pos, count(*) FILTER (n_chars > 2000) OVER w AS hits FROM documents WINDOW w AS (PARTITION BY source ORDER BY doc_id ROWS UNBOUNDED PRECEDING)) WHERE hits >= 2 GROUP BY 1")
def _(s, t):
    """The first place in each group at which 'at least two long documents' is confirmed."""
    w = Window.partitionBy("source").orderBy("doc_id")
    run = t("documents").select("source", F.row_number().over(w).cast("long").alias("pos"), F.count_if(c("n_chars") > 2000).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("hits"))
    return run.filter("hits >= 2").groupBy("source").agg(F.min("pos").alias("stop"))


# --- sorts, limits, sets, subqueries ---
simple("srt_multi", lambda t: t("orders").orderBy(c("o_totalprice").desc(), "o_orderkey").select("o_orderkey"), "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey")
simple("srt_within", lambda t: t("orders").repartition("o_custkey").sortWithinPartitions("o_custkey", "o_orderkey").select("o_orderkey"), None)
simple("lim_topk", lambda t: t("part").orderBy(c("p_retailprice").desc(), "p_partkey").limit(10).select("p_partkey"), "SELECT p_partkey FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 10")
simple("lim_page", lambda t: t("documents").orderBy("doc_id").offset(20).limit(10).select("doc_id"), "SELECT doc_id FROM documents ORDER BY doc_id LIMIT 10 OFFSET 20")
simple("lim_group", lambda t: t("documents").withColumn("r", F.row_number().over(Window.partitionBy("source").orderBy(c("n_chars").desc(), "doc_id"))).filter("r <= 3").select("source", "doc_id"), "SELECT source, doc_id FROM (SELECT *, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS r FROM documents) WHERE r <= 3")
_a = lambda t: t("customer").select(c("c_nationkey").alias("k"))
_b = lambda t: t("supplier").select(c("s_nationkey").alias("k"))
for _n, _f, _s in [
    ("set_union", lambda a, b: a.union(b), "UNION ALL"), ("set_inter", lambda a, b: a.intersect(b), "INTERSECT"), ("set_except", lambda a, b: a.subtract(b), "EXCEPT"), ("set_exceptall", lambda a, b: a.exceptAll(b), "EXCEPT ALL"),
]:
    simple(_n, lambda t, f=_f: f(_a(t), _b(t)), f"SELECT c_nationkey AS k FROM customer {_s} SELECT s_nationkey AS k FROM supplier")
simple("set_unionname", lambda t: t("nation").select("n_name", "n_nationkey").unionByName(t("region").select(c("r_regionkey").alias("n_nationkey"), c("r_name").alias("n_name"))), "SELECT n_name, n_nationkey FROM nation UNION ALL SELECT r_name, r_regionkey FROM region")
simple("set_distinct", lambda t: t("customer").select("c_mktsegment").distinct(), "SELECT DISTINCT c_mktsegment FROM customer")


def sql_op(name: str, tables: list[str], sql: str, duck: str | None = None) -> None:
    def run(s, t):
        for x in tables:
            t(x).createOrReplaceTempView(f"v_{x}")
        return s.sql(reduce(lambda q, x: q.replace(f"@{x}", f"v_{x}"), tables, sql))

    REGISTRY[name] = (run, reduce(lambda q, x: q.replace(f"@{x}", x), tables, duck or sql))


sql_op("sub_scalar", ["orders"], "SELECT o_orderkey FROM @orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM @orders)")
sql_op("sub_exists", ["customer", "orders"], "SELECT c_custkey FROM @customer WHERE EXISTS (SELECT 1 FROM @orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")
sql_op("sub_in", ["customer", "nation"], "SELECT c_custkey FROM @customer WHERE c_nationkey IN (SELECT n_nationkey FROM @nation WHERE n_regionkey = 1)")
sql_op("sub_corr", ["orders"], "SELECT o_orderkey FROM @orders o WHERE o_totalprice = (SELECT max(o_totalprice) FROM @orders i WHERE i.o_custkey = o.o_custkey)")

# --- strings ---
simple("str_case", lambda t: t("nation").select(F.lower("n_name").alias("lo"), F.upper("n_name").alias("up"), F.length("n_name").cast("long").alias("n")), "SELECT lower(n_name) AS lo, upper(n_name) AS up, length(n_name)::BIGINT AS n FROM nation")
simple("str_split", lambda t: t("documents").select("doc_id", F.size(F.split("text", "\n")).cast("long").alias("n")), "SELECT doc_id, len(string_split(text, chr(10)))::BIGINT AS n FROM documents")
simple("str_sentence", lambda t: t("documents").select("doc_id", F.regexp_count("text", F.lit(r"[.!?]")).cast("long").alias("n")), "SELECT doc_id, len(regexp_extract_all(text, '[.!?]'))::BIGINT AS n FROM documents")
simple("str_regex", lambda t: t("pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"), F.length(F.regexp_replace("url", "[0-9]+", "")).cast("long").alias("n")), "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, length(regexp_replace(url, '[0-9]+', '', 'g'))::BIGINT AS n FROM pages")
simple("str_pad", lambda t: t("nation").select(F.lpad(c("n_nationkey").cast("string"), 4, "0").alias("code"), F.rpad("n_name", 3, ".").alias("short")), "SELECT lpad(n_nationkey::VARCHAR, 4, '0') AS code, rpad(n_name, 3, '.') AS short FROM nation")
simple("str_dist", lambda t: t("nation").select("n_name", F.levenshtein("n_name", F.lit("NATION")).cast("long").alias("d")), "SELECT n_name, levenshtein(n_name, 'NATION')::BIGINT AS d FROM nation")
simple("str_hash", lambda t: t("part").select("p_partkey", F.md5("p_name").alias("h"), F.sha2("p_name", 256).alias("s")), "SELECT p_partkey, md5(p_name) AS h, sha256(p_name) AS s FROM part")
simple("str_prompt", lambda t: t("nation").select(F.format_string("Is %s in region %d?", "n_name", "n_regionkey").alias("prompt")), "SELECT 'Is ' || n_name || ' in region ' || n_regionkey || '?' AS prompt FROM nation")
simple("html_strip", lambda t: t("pages").select("page_id", F.length(F.regexp_replace("html", "<[^>]*>", "")).cast("long").alias("n")), "SELECT page_id, length(regexp_replace(html, '<[^>]*>', '', 'g'))::BIGINT AS n FROM pages")

# --- dates and numbers ---
simple("dt_trunc", lambda t: t("orders").groupBy(F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("m")).agg(F.count(F.lit(1)).alias("n")), "SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS m, count(*) AS n FROM orders GROUP BY 1")
simple("dt_diff", lambda t: t("orders").select("o_orderkey", F.datediff("o_orderdate", F.lit("1992-01-01")).cast("long").alias("d")), "SELECT o_orderkey, date_diff('day', DATE '1992-01-01', o_orderdate::DATE) AS d FROM orders")
simple("dt_add", lambda t: t("orders").select("o_orderkey", F.date_add("o_orderdate", 30).alias("due")), "SELECT o_orderkey, (o_orderdate::DATE + 30)::DATE AS due FROM orders")
simple("dt_parts", lambda t: t("orders").select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m"), F.dayofmonth("o_orderdate").cast("long").alias("d")), "SELECT o_orderkey, year(o_orderdate)::BIGINT AS y, month(o_orderdate)::BIGINT AS m, day(o_orderdate)::BIGINT AS d FROM orders")
simple("dt_ntz", lambda t: t("events").select("event_id", F.unix_seconds(c("ts").cast("timestamp")).alias("s")), "SELECT event_id, epoch(date_trunc('second', ts))::BIGINT AS s FROM events")
simple("mth_basic", lambda t: t("lineitem").select("l_orderkey", "l_linenumber", F.floor("l_quantity").alias("f"), F.ceil("l_quantity").alias("c"), F.greatest(c("l_quantity"), F.lit(10.0)).alias("g")), "SELECT l_orderkey, l_linenumber, floor(l_quantity)::BIGINT AS f, ceil(l_quantity)::BIGINT AS c, greatest(l_quantity, 10.0) AS g FROM lineitem")
simple("mth_log", lambda t: t("part").select("p_partkey", F.round(F.log("p_retailprice"), 6).alias("l"), F.round(F.sqrt("p_retailprice"), 6).alias("s")), "SELECT p_partkey, round(ln(p_retailprice), 6) AS l, round(sqrt(p_retailprice), 6) AS s FROM part")
simple("mth_round", lambda t: t("customer").select("c_custkey", F.round("c_acctbal", 0).cast("long").alias("r")), "SELECT c_custkey, round(c_acctbal, 0)::BIGINT AS r FROM customer")

# --- arrays, maps, structs, JSON, vectors ---
simple("arr_hof", lambda t: t("documents").select("doc_id", F.size(F.filter(F.transform(F.split("text", " "), F.lower), lambda w: w == "the")).cast("long").alias("n")), "SELECT doc_id, len(list_filter(list_transform(string_split(text, ' '), lambda w: lower(w)), lambda w: w = 'the'))::BIGINT AS n FROM documents")
simple("arr_exists", lambda t: t("embeddings").select("vec_id", F.exists("embedding", lambda x: x > 0.4).alias("e")), "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0.4::FLOAT)) > 0 AS e FROM embeddings".replace("0.4::FLOAT", "0.4::DOUBLE"))
simple("arr_forall", lambda t: t("embeddings").select("vec_id", F.forall("embedding", lambda x: F.abs(x) < 1).alias("e")), "SELECT vec_id, len(list_filter(embedding, lambda x: abs(x) >= 1)) = 0 AS e FROM embeddings")
simple("arr_agg", lambda t: t("embeddings").select("vec_id", F.aggregate("embedding", F.lit(0).cast("long"), lambda a, x: a + F.floor(x * 64)).alias("s")), "SELECT vec_id, list_sum(list_transform(embedding, lambda x: floor(x * 64)::BIGINT))::BIGINT AS s FROM embeddings")
simple("arr_zip", lambda t: t("embeddings").select("vec_id", F.size(F.filter(F.zip_with("embedding", F.reverse("embedding"), lambda a, b: a > b), lambda x: x)).cast("long").alias("n")), "SELECT vec_id, len(list_filter(list_zip(embedding, list_reverse(embedding)), lambda x: x[1] > x[2]))::BIGINT AS n FROM embeddings")
simple("arr_explode", lambda t: t("documents").select("doc_id", F.posexplode(F.split("text", "\n")).alias("pos", "line")).groupBy("pos").agg(F.count(F.lit(1)).alias("n")).select(c("pos").cast("long").alias("pos"), "n"), "SELECT (i - 1)::BIGINT AS pos, count(*) AS n FROM (SELECT unnest(range(1, len(string_split(text, chr(10))) + 1)) AS i FROM documents) GROUP BY 1")
simple("arr_sort", lambda t: t("conversations").groupBy("conv_id").agg(F.array_join(F.sort_array(F.collect_set("role"), asc=False), ",").alias("roles")), "SELECT conv_id, string_agg(DISTINCT role, ',' ORDER BY role DESC) AS roles FROM conversations GROUP BY 1")
_dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: F.floor(x * 64) * F.floor(y * 64)), F.lit(0).cast("long"), lambda s, x: s + x)
_first = lambda t: F.broadcast(t("embeddings").filter("vec_id = 0").select(c("embedding").alias("q")))  # noqa: E731  one row
_DOT = "list_inner_product(list_transform(e.embedding, lambda x: floor(x * 64)::DOUBLE), list_transform(q.embedding, lambda x: floor(x * 64)::DOUBLE))::BIGINT"
simple("vec_cosine", lambda t: t("embeddings").crossJoin(_first(t)).select("vec_id", _dot(c("embedding"), c("q")).alias("s")), f"SELECT e.vec_id, {_DOT} AS s FROM embeddings e, embeddings q WHERE q.vec_id = 0")
simple("vec_topk", lambda t: t("embeddings").crossJoin(_first(t)).select("vec_id", _dot(c("embedding"), c("q")).alias("s")).orderBy(c("s").desc(), "vec_id").limit(10), f"SELECT e.vec_id, {_DOT} AS s FROM embeddings e, embeddings q WHERE q.vec_id = 0 ORDER BY s DESC, vec_id LIMIT 10")
simple("vec_filter", lambda t: t("embeddings").crossJoin(_first(t)).filter(_dot(c("embedding"), c("q")) >= 600).select("vec_id"), f"SELECT e.vec_id FROM embeddings e, embeddings q WHERE q.vec_id = 0 AND {_DOT} >= 600")
simple("map_build", lambda t: t("nation").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_name", "n_nationkey"))).alias("m")).select("n_regionkey", F.size("m").cast("long").alias("n")), "SELECT n_regionkey, count(DISTINCT n_name) AS n FROM nation GROUP BY 1")
simple("map_get", lambda t: t("events").select("event_id", F.element_at(F.create_map(F.lit("k"), c("value"), F.lit("z"), F.lit(0.0)), "k").alias("v")), "SELECT event_id, value AS v FROM events")
simple("map_entries", lambda t: t("nation").select(F.explode(F.map_entries(F.create_map("n_name", "n_regionkey"))).alias("e")).select(c("e.key").alias("k"), c("e.value").alias("v")), "SELECT n_name AS k, n_regionkey AS v FROM nation")
simple("st_field", lambda t: t("nation").select(F.struct(c("n_name").alias("a"), c("n_regionkey").alias("b")).alias("s")).select("s.a", "s.b"), "SELECT n_name AS a, n_regionkey AS b FROM nation")
simple("js_get", lambda t: t("events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")), "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k FROM events")
simple("js_from", lambda t: t("events").select("event_id", F.from_json("props", "k long")["k"].alias("k")), "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k FROM events")
simple("js_to", lambda t: t("nation").select(F.to_json(F.struct("n_name", "n_regionkey")).alias("j")), "SELECT '{\"n_name\":\"' || n_name || '\",\"n_regionkey\":' || n_regionkey || '}' AS j FROM nation")
simple("js_variant", lambda t: t("events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "long").alias("k")), None)

# --- event-time windows over the batch ---
simple("st_tumble", lambda t: t("events").groupBy(F.window(c("ts").cast("timestamp"), "1 day").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n"), "SELECT date_trunc('day', ts)::TIMESTAMP AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
simple("st_slide", lambda t: t("events").groupBy(F.window(c("ts").cast("timestamp"), "2 days", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n"), "SELECT start, count(*) AS n FROM (SELECT unnest([date_trunc('day', ts)::TIMESTAMP, date_trunc('day', ts)::TIMESTAMP - INTERVAL 1 DAY]) AS start FROM events) GROUP BY 1")
simple(
    "st_session", lambda t: t("events").groupBy(F.session_window(c("ts").cast("timestamp"), "6 hours").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n"),
    "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS g FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, g",
)


# --- sources and sinks ---
def _round_trip(kind: str, schema: str, **options):
    def run(s, t):
        path = f"{shared_dir(s)}/sparkverdict/rt-{kind}"
        rows = t("nation").select("n_nationkey", "n_name", "n_regionkey")
        if kind == "text":
            rows.select(F.concat_ws("|", *rows.columns).alias("value")).write.mode("overwrite").text(path)
            parts = F.split("value", r"\|")
            return s.read.text(path).select(parts[0].cast("long").alias("n_nationkey"), parts[1].alias("n_name"), parts[2].cast("long").alias("n_regionkey"))
        rows.write.mode("overwrite").format(kind).options(**options).save(path)
        return s.read.format(kind).schema(schema).options(**options).load(path)

    return run


for _k, _o in (("json", {}), ("csv", {"header": "true"}), ("orc", {}), ("text", {})):
    REGISTRY[f"rt_{_k}"] = (_round_trip(_k, "n_nationkey long, n_name string, n_regionkey long", **_o), "SELECT n_nationkey, n_name, n_regionkey FROM nation")


@op("sink_partitioned", "SELECT lang, count(*) AS n FROM documents GROUP BY 1")
def _(s, t):
    path = f"{shared_dir(s)}/sparkverdict/by-lang"
    t("documents").select("doc_id", "lang").write.mode("overwrite").partitionBy("lang").parquet(path)
    return s.read.parquet(path).groupBy(c("lang").cast("string").alias("lang")).agg(F.count(F.lit(1)).alias("n"))


@op("src_rows", "SELECT * FROM (VALUES (1::BIGINT, 'a'), (2::BIGINT, 'b')) AS v(id, name)")
def _(s, t):
    return s.createDataFrame([(1, "a"), (2, "b")], "id long, name string")


# --- Python functions ---
@op("udf_arrow", "SELECT doc_id, length(text)::BIGINT AS n FROM documents")
def _(s, t):
    import pyarrow.compute as pc

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pc.utf8_length(b.column(1)).cast(pa.int64())], names=["doc_id", "n"])

    return t("documents").select("doc_id", "text").mapInArrow(run, "doc_id long, n long")


@op("udf_pandas", "SELECT event_id, floor(value * 2)::BIGINT AS v FROM events")
def _(s, t):
    def double(x: pd.Series) -> pd.Series:
        return x * 2

    twice = F.pandas_udf(double, "double")
    return t("events").select("event_id", F.floor(twice("value")).alias("v"))


@op("udaf_pandas", "SELECT event_type, max(event_id) - min(event_id) AS span FROM events GROUP BY 1")
def _(s, t):
    def span(x: pd.Series) -> int:
        return int(x.max() - x.min())

    return t("events").groupBy("event_type").agg(F.pandas_udf(span, "long")("event_id").alias("span"))


@op("udf_apply", "SELECT source, max(n_chars) AS longest FROM documents GROUP BY 1")
def _(s, t):
    return t("documents").select("source", "n_chars").groupBy("source").applyInPandas(lambda p: pd.DataFrame({"source": [p["source"].iloc[0]], "longest": [int(p["n_chars"].max())]}), "source string, longest long")


@op("udf_iter", "SELECT doc_id, length(text) - length(replace(text, ' ', '')) AS blanks FROM documents")
def _(s, t):
    """An iterator function: what is set up once per task serves all its batches."""
    @F.pandas_udf("long")
    def blanks(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        pattern = re.compile(" ")
        for batch in batches:
            yield batch.map(lambda x: None if x is None else len(pattern.findall(x))).astype("Int64")

    return t("documents").select("doc_id", blanks("text").alias("blanks"))


@op("udf_mapin", "SELECT doc_id, i::INT AS line_no, length(line) AS width FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, unnest(range(len(string_split(text, chr(10))))) AS i FROM documents)")
def _(s, t):
    """Many rows from one, in Arrow batches."""
    def lines(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(k, i, len(line)) for k, x in zip(batch["doc_id"].to_pylist(), batch["text"].to_pylist(), strict=True) if x is not None for i, line in enumerate(x.split("\n"))]
            ids, numbers, widths = zip(*rows, strict=True) if rows else ((), (), ())
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(numbers, pa.int32()), pa.array(widths, pa.int64())], ["doc_id", "line_no", "width"])

    return t("documents").select("doc_id", "text").mapInArrow(lines, "doc_id long, line_no int, width long")


@op("udf_cogroup", "SELECT coalesce(d.lang, '') AS lang, count(*) AS docs, count(l.doc_id) AS labelled FROM documents d LEFT JOIN labels l USING (doc_id) GROUP BY 1")
def _(s, t):
    labelled = t("labels").join(t("documents").select("doc_id", "lang"), "doc_id").select("doc_id", "lang")
    both = t("documents").select("doc_id", "lang").groupBy("lang").cogroup(labelled.groupBy("lang"))
    return both.applyInPandas(lambda a, b: pd.DataFrame({"lang": [a["lang"].iloc[0]], "docs": [len(a)], "labelled": [len(b)]}), "lang string, docs long, labelled long")


@op("udtf_tally", "SELECT source, least(count(*) FILTER (n_chars > 2000), 2) AS hits FROM documents GROUP BY 1")
def _(s, t):
    """A streaming tally per group: stops reading a group at its second hit."""
    from pyspark.sql.functions import udtf
    from pyspark.sql.udtf import SkipRestOfInputTableException

    @udtf(returnType="source string, hits long")
    class TwoLong:
        def __init__(self):
            self.source, self.hits = None, 0

        def eval(self, row):
            self.source = row["source"]
            self.hits += row["n_chars"] > 2000
            if self.hits == 2:
                raise SkipRestOfInputTableException

        def terminate(self):
            if self.source is not None:
                yield self.source, self.hits

    s.udtf.register("two_long", TwoLong)
    t("documents").select("source", "n_chars", "doc_id").createOrReplaceTempView("v_two_long")
    return s.sql("SELECT * FROM two_long(TABLE(SELECT * FROM v_two_long) PARTITION BY source ORDER BY doc_id)")


@op("udf_sql", "SELECT n_name, length(n_name)::BIGINT AS n FROM nation")
def _(s, t):
    def lengths(x: pd.Series) -> pd.Series:
        return x.str.len()

    s.udf.register("text_length", F.pandas_udf(lengths, "long"))
    t("nation").createOrReplaceTempView("v_nation")
    return s.sql("SELECT n_name, text_length(n_name) AS n FROM v_nation")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    def bind(f: Fn):
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            ship_package(spark)
            return f(spark, lambda name: spark.read.parquet(f"{sf_dir}/{name}.parquet"))

        return run

    return {f"ops_{k}": bind(f) for k, (f, _) in REGISTRY.items()}


def oracle_sql() -> dict[str, str]:
    return {f"ops_{k}": sql for k, (_, sql) in REGISTRY.items() if sql}
