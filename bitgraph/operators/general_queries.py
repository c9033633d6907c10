"""Queries for what a user needs around the methods: scans, filters, joins, aggregations, windows, sets and functions."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from bitgraph.catalog import add, query
from bitgraph.sources.graphs import TABLES


class Tables:
    """Tables of a folder as attributes."""

    def __init__(self, spark, sf_dir):
        self.spark, self.sf_dir = spark, sf_dir

    def __getattr__(self, name):
        return self.spark.read.parquet(f"{self.sf_dir}/{name}.parquet")


def q(name: str, sql: str):
    def keep(f):
        add(name, lambda spark, sf_dir: f(Tables(spark, sf_dir)), sql)
        return f

    return keep


day = lambda c: F.date_format(c, "yyyy-MM-dd")
_SCANS = {"lineitem": "l_orderkey, l_partkey, l_suppkey, l_linenumber", "orders": "o_orderkey, o_custkey, o_orderstatus", "customer": "c_custkey, c_name, c_nationkey", "supplier": "s_suppkey, s_name, s_nationkey", "part": "p_partkey, p_name, p_brand, p_type, p_size", "nation": "n_nationkey, n_name, n_regionkey", "region": "r_regionkey, r_name", "events": "event_id, user_id, event_type, props", "documents": "doc_id, lang, source, n_chars", "labels": "doc_id, quality, toxic", "pages": "page_id, url", "conversations": "conv_id, turn, role", "embeddings": "vec_id, label", "benchmark": "item_id, text"}
for _t in TABLES:
    add(f"scan_{_t}", lambda spark, d, t=_t: spark.read.parquet(f"{d}/{t}.parquet").select(*_SCANS[t].split(", ")), f"SELECT {_SCANS[_t]} FROM {_t}")

# Projections and filters -----------------------------------------------------------------------------------------------------
q("op_project", "SELECT DISTINCT upper(p_brand) AS brand, p_size + 1 AS size1 FROM part")(lambda t: t.part.select(F.upper("p_brand").alias("brand"), (F.col("p_size") + 1).alias("size1")).distinct())
q("op_filter_eq", "SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F'")(lambda t: t.orders.where("o_orderstatus = 'F'").select("o_orderkey"))
q("op_filter_range", "SELECT o_orderkey FROM orders WHERE o_custkey BETWEEN 10 AND 20 AND o_orderkey >= 100")(lambda t: t.orders.where(F.col("o_custkey").between(10, 20) & (F.col("o_orderkey") >= 100)).select("o_orderkey"))
q("op_filter_in", "SELECT c_custkey FROM customer WHERE c_mktsegment IN ('BUILDING', 'MACHINERY')")(lambda t: t.customer.where(F.col("c_mktsegment").isin("BUILDING", "MACHINERY")).select("c_custkey"))
q("op_filter_like", "SELECT p_partkey FROM part WHERE p_brand LIKE '%1_' OR regexp_matches(p_type, '^[A-M]')")(lambda t: t.part.where(F.col("p_brand").like("%1_") | F.col("p_type").rlike("^[A-M]")).select("p_partkey"))
q("op_filter_null", "SELECT d.doc_id FROM documents d LEFT JOIN labels l ON l.doc_id = d.doc_id WHERE l.quality IS NULL")(lambda t: t.documents.join(t.labels, "doc_id", "left").where(F.col("quality").isNull()).select("doc_id"))
q("op_filter_bool", "SELECT s_suppkey FROM supplier WHERE NOT (s_nationkey < 5 AND s_suppkey % 2 = 0) OR s_nationkey = 3")(lambda t: t.supplier.where(~((F.col("s_nationkey") < 5) & (F.col("s_suppkey") % 2 == 0)) | (F.col("s_nationkey") == 3)).select("s_suppkey"))
q("op_case", "SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS class FROM part")(lambda t: t.part.select("p_partkey", F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "medium").otherwise("large").alias("class")))
q("op_exists", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_orderstatus = 'P')")(lambda t: t.customer.join(t.orders.where("o_orderstatus = 'P'"), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("c_custkey"))
q("op_not_exists", "SELECT c_custkey FROM customer c WHERE NOT EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey)")(lambda t: t.customer.join(t.orders, F.col("o_custkey") == F.col("c_custkey"), "left_anti").select("c_custkey"))
q("op_scalar_subq", "SELECT p_partkey FROM part WHERE p_size = (SELECT max(p_size) FROM part)")(lambda t: t.spark.sql("SELECT p_partkey FROM {p} WHERE p_size = (SELECT max(p_size) FROM {p})", p=t.part))
q("op_unpivot", "SELECT doc_id, name, value FROM (SELECT doc_id, 'quality' AS name, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels) x")(lambda t: t.labels.unpivot("doc_id", ["quality", "toxic"], "name", "value"))
q("op_filter_literal_range", "SELECT o_orderkey, CAST(CAST(o_orderdate AS DATE) AS VARCHAR) AS d FROM orders WHERE CAST(o_orderdate AS DATE) BETWEEN DATE '1996-01-01' AND DATE '1996-02-01'")(lambda t: t.orders.where(F.col("o_orderdate").cast("date").between("1996-01-01", "1996-02-01")).select("o_orderkey", day("o_orderdate").alias("d")))

# Joins -----------------------------------------------------------------------------------------------------------------------
_CN = "SELECT c_custkey, n_name FROM customer JOIN nation ON n_nationkey = c_nationkey"
_on = lambda t: F.col("c_nationkey") == F.col("n_nationkey")
q("join_broadcast", _CN)(lambda t: t.customer.join(F.broadcast(t.nation), _on(t)).select("c_custkey", "n_name"))
q("join_shuffle_hash", _CN)(lambda t: t.customer.join(t.nation.hint("shuffle_hash"), _on(t)).select("c_custkey", "n_name"))
q("join_sort_merge", _CN)(lambda t: t.customer.join(t.nation.hint("merge"), _on(t)).select("c_custkey", "n_name"))
_pairs = lambda how: lambda t: t.customer.select("c_custkey").join(t.orders.select("o_orderkey", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), how).select(*(["c_custkey", "o_orderkey"] if "left_" not in how else ["c_custkey"]))
for _how, _sql in (("left", "LEFT JOIN"), ("right", "RIGHT JOIN"), ("full", "FULL JOIN")):
    q(f"join_{_how}", f"SELECT c_custkey, o_orderkey FROM customer {_sql} orders ON c_custkey = o_custkey")(_pairs(_how))
for _how, _sql in (("semi", "EXISTS"), ("anti", "NOT EXISTS")):
    q(f"join_{_how}", f"SELECT c_custkey FROM customer WHERE {_sql} (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")(_pairs(f"left_{_how}"))
q("join_theta", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")(lambda t: t.nation.select(F.col("n_nationkey").alias("a"), F.col("n_regionkey").alias("r")).join(t.nation.select(F.col("n_nationkey").alias("b"), F.col("n_regionkey").alias("r")), "r").where("a < b").select("a", "b"))
q("join_cross", "SELECT r_regionkey, n_nationkey FROM region, nation")(lambda t: t.region.select("r_regionkey").crossJoin(F.broadcast(t.nation.select("n_nationkey"))))
q("join_nullsafe", "SELECT a.doc_id FROM (SELECT d.doc_id, l.toxic FROM documents d LEFT JOIN labels l ON l.doc_id = d.doc_id) a JOIN (SELECT CAST(NULL AS INT) AS x UNION ALL SELECT 1) b ON a.toxic IS NOT DISTINCT FROM b.x")(lambda t: t.documents.join(t.labels, "doc_id", "left").join(F.broadcast(t.spark.sql("SELECT CAST(NULL AS INT) AS x UNION ALL SELECT 1")), F.col("toxic").eqNullSafe(F.col("x"))).select("doc_id"))
q("join_lateral_topk", "SELECT n_nationkey, c_custkey FROM (SELECT n_nationkey, c_custkey, row_number() OVER (PARTITION BY n_nationkey ORDER BY c_custkey DESC) AS k FROM nation JOIN customer ON c_nationkey = n_nationkey) x WHERE k <= 2")(lambda t: t.spark.sql("SELECT n_nationkey, c_custkey FROM {n}, LATERAL (SELECT c_custkey FROM {c} WHERE c_nationkey = n_nationkey ORDER BY c_custkey DESC LIMIT 2)", n=t.nation, c=t.customer))

_BUCKET = 600


@q("join_range", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def _range_join(t):
    """Events of a user within ten minutes: both sides fall in buckets of that length, and meet in their own or the next."""
    e = t.events.select("event_id", "user_id", "ts", F.floor(F.unix_seconds(F.col("ts").cast("timestamp")) / _BUCKET).alias("k"))
    later = e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("ts2"), F.explode(F.array("k", F.col("k") - 1)).alias("k"))
    return e.join(later, ["user_id", "k"]).where((F.col("ts2") > F.col("ts")) & (F.col("ts2") <= F.col("ts") + F.expr("INTERVAL 10 MINUTES"))).select(F.col("event_id").alias("a"), "b")


@q("join_asof", "SELECT event_id, last_view AS before FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS last_view FROM events) x WHERE event_type = 'click'")
def _asof(t):
    """The last view before each click of a user: one sort a user, no pairs."""
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, 0)
    seen = t.events.withColumn("before", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w))
    return seen.where("event_type = 'click'").select("event_id", "before")


# Aggregations ------------------------------------------------------------------------------------------------------------------
q("agg_order_value", "SELECT o_orderstatus, count(*) AS n, CAST(sum(o_custkey) AS BIGINT) AS total, min(o_custkey) AS low, max(o_custkey) AS high FROM orders GROUP BY o_orderstatus")(lambda t: t.orders.groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum("o_custkey").alias("total"), F.min("o_custkey").alias("low"), F.max("o_custkey").alias("high")))
q("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_returnflag")(lambda t: t.lineitem.groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers")))
_GS = "SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY "
q("agg_grouping_sets", _GS + "GROUPING SETS ((p_brand), (p_type), ())")(lambda t: t.spark.sql(_GS.replace("part", "{p}") + "GROUPING SETS ((p_brand), (p_type), ())", p=t.part))
q("agg_rollup", _GS + "ROLLUP (p_brand, p_type)")(lambda t: t.part.rollup("p_brand", "p_type").agg(F.count("*").alias("n")))
q("agg_cube", _GS + "CUBE (p_brand, p_type)")(lambda t: t.part.cube("p_brand", "p_type").agg(F.count("*").alias("n")))
q("agg_adjacency", "SELECT l_partkey, array_to_string(list_sort(list(DISTINCT l_suppkey)), ',') AS suppliers FROM lineitem GROUP BY l_partkey")(lambda t: t.lineitem.groupBy("l_partkey").agg(F.array_join(F.sort_array(F.collect_set("l_suppkey")), ",").alias("suppliers")))
q("agg_max_by", "SELECT c_nationkey, max(c_custkey) AS k, arg_max(c_name, c_custkey) AS name FROM customer GROUP BY c_nationkey")(lambda t: t.customer.groupBy("c_nationkey").agg(F.max("c_custkey").alias("k"), F.max_by("c_name", "c_custkey").alias("name")))
q("agg_masks", "SELECT o_orderstatus, bit_or(1 << CAST(o_custkey % 8 AS INT)) AS any, bit_and(o_custkey % 16) AS every FROM orders GROUP BY o_orderstatus")(lambda t: t.orders.groupBy("o_orderstatus").agg(F.bit_or(F.expr("1 << CAST(o_custkey % 8 AS INT)")).alias("any"), F.bit_and(F.expr("o_custkey % 16")).alias("every")))
q("agg_filter", "SELECT c_mktsegment, count(*) FILTER (WHERE c_nationkey < 5) AS low, count(*) FILTER (WHERE c_nationkey >= 5) AS high FROM customer GROUP BY c_mktsegment")(lambda t: t.customer.groupBy("c_mktsegment").agg(F.count_if(F.col("c_nationkey") < 5).alias("low"), F.count_if(F.col("c_nationkey") >= 5).alias("high")))
q("agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 12")(lambda t: t.orders.groupBy("o_custkey").agg(F.count("*").alias("n")).where("n > 12"))
q("agg_pivot", "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS \"F\", count(*) FILTER (WHERE o_orderstatus = 'O') AS \"O\" FROM orders GROUP BY o_orderpriority")(lambda t: t.orders.groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O"]).count().na.fill(0))
q("agg_stats", "SELECT p_brand, round(stddev_samp(p_size), 6) AS sd, round(var_pop(p_size), 6) AS v, median(p_size) AS med, round(corr(p_size, p_partkey), 6) AS c FROM part GROUP BY p_brand")(lambda t: t.part.groupBy("p_brand").agg(F.round(F.stddev_samp("p_size"), 6).alias("sd"), F.round(F.var_pop("p_size"), 6).alias("v"), F.median("p_size").alias("med"), F.round(F.corr("p_size", "p_partkey"), 6).alias("c")))


@query("agg_approx")
def _approx(spark, sf_dir):
    """Sketches: distinct parts by HyperLogLog two ways, a quantile, and the exact values beside them."""
    return Tables(spark, sf_dir).lineitem.agg(F.approx_count_distinct("l_partkey", 0.02).alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", F.lit(14))).alias("hll"), F.countDistinct("l_partkey").alias("exact"), F.percentile_approx("l_partkey", 0.5, 10_000).alias("median_approx"), F.percentile("l_partkey", 0.5).alias("median"))


# Windows, order, sets ------------------------------------------------------------------------------------------------------------
q("win_ranking", "SELECT c_custkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_mktsegment, c_custkey)")(lambda t: (lambda w: t.customer.select("c_custkey", F.row_number().over(w).cast("bigint").alias("rn"), F.rank().over(w).cast("bigint").alias("rk"), F.dense_rank().over(w).cast("bigint").alias("dr"), F.ntile(4).over(w).cast("bigint").alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd")))(W.partitionBy("c_nationkey").orderBy("c_mktsegment", "c_custkey")))
q("win_gaps", "SELECT DISTINCT l_partkey, l_suppkey, l_suppkey - lag(l_suppkey) OVER (PARTITION BY l_partkey ORDER BY l_suppkey) AS gap FROM (SELECT DISTINCT l_partkey, l_suppkey FROM lineitem) x")(lambda t: t.lineitem.select("l_partkey", "l_suppkey").distinct().withColumn("gap", F.col("l_suppkey") - F.lag("l_suppkey").over(W.partitionBy("l_partkey").orderBy("l_suppkey"))))
q("win_running", "SELECT o_orderkey, CAST(sum(o_custkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS s FROM orders")(lambda t: t.orders.select("o_orderkey", F.sum("o_custkey").over(W.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(-2, 0)).alias("s")))
q("win_range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey RANGE BETWEEN 500 PRECEDING AND 500 FOLLOWING) AS n FROM orders")(lambda t: t.orders.select("o_orderkey", F.count("*").over(W.partitionBy("o_custkey").orderBy("o_orderkey").rangeBetween(-500, 500)).alias("n")))
q("win_values", "SELECT o_orderkey, first_value(o_orderkey) OVER w AS f, last_value(o_orderkey) OVER w AS l, nth_value(o_orderkey, 2) OVER w AS n FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")(lambda t: (lambda w: t.orders.select("o_orderkey", F.first("o_orderkey").over(w).alias("f"), F.last("o_orderkey").over(w).alias("l"), F.nth_value("o_orderkey", 2).over(w).alias("n")))(W.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)))


@q("win_sessions", "SELECT user_id, session, count(*) AS n FROM (SELECT user_id, CAST(sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS BIGINT) AS session FROM (SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events) x) y GROUP BY ALL")
def _sessions(t):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    new = F.when(F.col("ts") - F.lag("ts").over(w) <= F.expr("INTERVAL 6 HOURS"), 0).otherwise(1)
    return t.events.withColumn("new", new).withColumn("session", F.sum("new").over(w)).groupBy("user_id", "session").agg(F.count("*").alias("n"))


q("sort_ids", "SELECT s_suppkey FROM supplier ORDER BY s_suppkey")(lambda t: t.supplier.select("s_suppkey").orderBy("s_suppkey"))
q("sort_nulls", "SELECT d.doc_id, toxic FROM documents d LEFT JOIN labels l ON l.doc_id = d.doc_id ORDER BY toxic NULLS LAST, d.doc_id")(lambda t: t.documents.join(t.labels, "doc_id", "left").select("doc_id", "toxic").orderBy(F.asc_nulls_last("toxic"), "doc_id"))
q("topk_global", "SELECT o_orderkey, o_custkey FROM orders ORDER BY o_custkey DESC, o_orderkey LIMIT 25")(lambda t: t.orders.select("o_orderkey", "o_custkey").orderBy(F.desc("o_custkey"), "o_orderkey").limit(25))
q("limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 5")(lambda t: t.orders.select("o_orderkey").orderBy("o_orderkey").offset(5).limit(10))
for _n, _sql, _f in (("union_all", "UNION ALL", lambda a, b: a.union(b)), ("union", "UNION", lambda a, b: a.union(b).distinct()), ("intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)), ("except", "EXCEPT", lambda a, b: a.subtract(b)), ("except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))):
    q(f"set_{_n}", f"SELECT l_partkey AS k FROM lineitem {_sql} SELECT l_suppkey AS k FROM lineitem")(lambda t, f=_f: f(t.lineitem.select(F.col("l_partkey").alias("k")), t.lineitem.select(F.col("l_suppkey").alias("k"))))

# Functions ------------------------------------------------------------------------------------------------------------------------
q("fn_string", "SELECT c_custkey, concat(c_name, '!') AS a, substr(c_name, 2, 3) AS b, lower(c_name) AS c, lpad(c_mktsegment, 12, '*') AS d, replace(c_name, 'C', 'K') AS e, length(c_name) AS f, split_part(c_name, '#', 2) AS g, instr(c_name, '#') AS h FROM customer")(lambda t: t.customer.select("c_custkey", F.concat("c_name", F.lit("!")).alias("a"), F.substring("c_name", 2, 3).alias("b"), F.lower("c_name").alias("c"), F.lpad("c_mktsegment", 12, "*").alias("d"), F.replace("c_name", F.lit("C"), F.lit("K")).alias("e"), F.length("c_name").cast("bigint").alias("f"), F.split_part("c_name", F.lit("#"), F.lit(2)).alias("g"), F.instr("c_name", "#").cast("bigint").alias("h")))
q("fn_date", "SELECT o_orderkey, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(month(o_orderdate) AS BIGINT) AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS t, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS d, strftime(CAST(o_orderdate AS DATE) + INTERVAL 1 MONTH, '%Y-%m-%d') AS n FROM orders")(lambda t: t.orders.select("o_orderkey", F.year("o_orderdate").cast("bigint").alias("y"), F.month("o_orderdate").cast("bigint").alias("m"), day(F.date_trunc("month", "o_orderdate")).alias("t"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).cast("bigint").alias("d"), day(F.add_months(F.col("o_orderdate").cast("date"), 1)).alias("n")))
q("fn_math", "SELECT p_partkey, p_partkey % 7 AS m, CAST(ceil(log2(p_partkey + 1)) AS BIGINT) AS h, round(sqrt(p_partkey), 6) AS r, abs(p_size - 25) AS a FROM part")(lambda t: t.part.select("p_partkey", (F.col("p_partkey") % 7).alias("m"), F.ceil(F.log2(F.col("p_partkey") + 1)).alias("h"), F.round(F.sqrt("p_partkey"), 6).alias("r"), F.abs(F.col("p_size") - 25).alias("a")))
q("fn_bits", "SELECT p_partkey, p_partkey << 3 AS l, p_partkey >> 2 AS r, p_partkey & 12 AS a, p_partkey | 5 AS o, xor(p_partkey, 9) AS x, CAST(bit_count(p_partkey) AS INT) AS c FROM part")(lambda t: t.part.select("p_partkey", F.shiftleft("p_partkey", 3).alias("l"), F.shiftright("p_partkey", 2).alias("r"), F.col("p_partkey").bitwiseAND(12).alias("a"), F.col("p_partkey").bitwiseOR(5).alias("o"), F.col("p_partkey").bitwiseXOR(9).alias("x"), F.bit_count("p_partkey").alias("c")))
q("fn_array", "SELECT l_orderkey, array_to_string(list_sort(list(l_partkey)), ',') AS sorted, list_sum(list(l_partkey))::BIGINT AS total, len(list_distinct(list(l_suppkey)))::BIGINT AS suppliers FROM lineitem GROUP BY l_orderkey")(lambda t: t.lineitem.groupBy("l_orderkey").agg(F.collect_list("l_partkey").alias("p"), F.collect_list("l_suppkey").alias("s")).select("l_orderkey", F.array_join(F.array_sort("p"), ",").alias("sorted"), F.aggregate("p", F.lit(0).cast("bigint"), lambda a, x: a + x).alias("total"), F.size(F.array_distinct("s")).cast("bigint").alias("suppliers")))
q("fn_gap_decode", "SELECT l_partkey, array_to_string(list_sort(list(DISTINCT l_suppkey)), ',') AS suppliers FROM lineitem GROUP BY l_partkey")(lambda t: t.lineitem.groupBy("l_partkey").agg(F.sort_array(F.collect_set("l_suppkey")).alias("l")).withColumn("g", F.transform("l", lambda x, i: F.when(i == 0, x).otherwise(x - F.get("l", i - 1)))).select("l_partkey", F.array_join(F.transform("g", lambda x, i: F.aggregate(F.slice("g", F.lit(1), i + 1), F.lit(0).cast("bigint"), lambda a, y: a + y)), ",").alias("suppliers")))
q("fn_map", "SELECT o_custkey, count(*) FILTER (WHERE o_orderstatus = 'F') AS f, count(DISTINCT o_orderstatus) AS k FROM orders GROUP BY o_custkey")(lambda t: t.orders.groupBy("o_custkey", "o_orderstatus").agg(F.count("*").alias("n")).groupBy("o_custkey").agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "n"))).alias("m")).select("o_custkey", F.coalesce(F.try_element_at("m", F.lit("F")), F.lit(0)).alias("f"), F.size(F.map_keys("m")).cast("bigint").alias("k")))
q("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")(lambda t: t.events.select("event_id", F.from_json("props", "k bigint")["k"].alias("k")))
q("fn_hash", "SELECT c_custkey, md5(c_name) AS m, sha256(c_name) AS s, to_hex(c_custkey) AS h, base64(encode(c_name)) AS b FROM customer")(lambda t: t.customer.select("c_custkey", F.md5("c_name").alias("m"), F.sha2("c_name", 256).alias("s"), F.hex("c_custkey").alias("h"), F.base64(F.encode("c_name", "UTF-8")).alias("b")))


@q("fn_cell_code", "SELECT l_partkey, l_suppkey, CAST(" + " + ".join(f"(((l_partkey >> {i}) & 1) << {2 * i + 1}) + (((l_suppkey >> {i}) & 1) << {2 * i})" for i in range(16)) + " AS BIGINT) AS code FROM lineitem")
def _cell_code(t):
    from bitgraph.functions.geometry import Schedule, cell_code

    return t.lineitem.select("l_partkey", "l_suppkey", cell_code(F.col("l_partkey"), F.col("l_suppkey"), Schedule.uniform(2, 1 << 16)).alias("code"))


@q("fn_cosine_top", "SELECT a, b FROM (SELECT a.vec_id AS a, b.vec_id AS b, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) DESC, b.vec_id) AS k FROM embeddings a, embeddings b WHERE a.vec_id <> b.vec_id AND a.vec_id % 20 = 0) x WHERE k <= 5")
def _nearest(t):
    """The five nearest vectors of a stated query set, block by block."""
    from bitgraph.sources.graphs import nearest

    found = nearest(t.embeddings)
    number = lambda c: F.substring(c, 5, 20).cast("bigint")
    return found.select(number("s").alias("a"), number("o").alias("b")).where("a % 20 = 0")
