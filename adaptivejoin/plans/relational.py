"""Relational operators around the adaptive joins, one query each, with their SQL."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from adaptivejoin.functions.hashing import portable_hash, row_id
from adaptivejoin.plans import sqltext as S
from adaptivejoin.plans import workloads as X
from adaptivejoin.tables import table

QUERIES: dict = {}
ORACLES: dict = {}


def op(name: str, sql: str | None = None):
    def add(f):
        QUERIES[f"op_{name}"] = f
        if sql:
            ORACLES[f"op_{name}"] = sql
        return f

    return add


t = table
MONEY = "decimal(18,2)"


def money(c: str):
    return F.sum(F.col(c).cast(MONEY)).cast("decimal(38,2)")


def money_sql(c: str) -> str:
    return f"CAST(sum(CAST({c} AS DECIMAL(18,2))) AS DECIMAL(38,2))"


# Scans, projections, filters

op("scan_parquet_pruned", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45 AND l_returnflag = 'R'")(
    lambda s, d: t(s, d, "lineitem").where("l_quantity > 45 and l_returnflag = 'R'").select("l_orderkey", "l_quantity"))
op("project_cast", "SELECT l_orderkey, CAST(floor(l_extendedprice) AS BIGINT) AS whole, CAST(l_quantity AS INTEGER) AS qty FROM lineitem")(
    lambda s, d: t(s, d, "lineitem").select("l_orderkey", F.floor("l_extendedprice").cast("long").alias("whole"), F.col("l_quantity").cast("int").alias("qty")))
op("case_when", "SELECT CASE WHEN l_quantity < 10 THEN 'few' WHEN l_quantity < 30 THEN 'some' ELSE 'many' END AS size, count(*) AS n FROM lineitem GROUP BY 1")(
    lambda s, d: t(s, d, "lineitem").groupBy(F.when(F.col("l_quantity") < 10, "few").when(F.col("l_quantity") < 30, "some").otherwise("many").alias("size")).agg(F.count("*").alias("n")))
op("filter_predicates", "SELECT p_partkey, p_name FROM part WHERE p_size BETWEEN 5 AND 20 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#13') AND p_type LIKE '%A%' AND p_name IS NOT NULL AND regexp_matches(p_name, '[a-e]')")(
    lambda s, d: t(s, d, "part").where(F.col("p_size").between(5, 20) & F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#13") & F.col("p_type").like("%A%") & F.col("p_name").isNotNull() & F.col("p_name").rlike("[a-e]")).select("p_partkey", "p_name"))


def holes(s, d):
    return t(s, d, "events").select("event_id", F.when(F.col("user_id") % 3 != 0, F.col("user_id")).alias("k"))


@op("null_safe_eq", "WITH e AS (SELECT CASE WHEN user_id % 3 <> 0 THEN user_id END AS k FROM events), c AS (SELECT CASE WHEN c_custkey % 3 <> 0 THEN c_custkey END AS k, count(*) AS n FROM customer GROUP BY 1) SELECT e.k, max(n) AS n, count(*) AS m FROM e JOIN c ON e.k IS NOT DISTINCT FROM c.k GROUP BY 1")
def null_safe_eq(s, d):
    c = t(s, d, "customer").groupBy(F.when(F.col("c_custkey") % 3 != 0, F.col("c_custkey")).alias("ck")).agg(F.count("*").alias("n"))
    return holes(s, d).join(c, F.col("k").eqNullSafe(F.col("ck"))).groupBy("k").agg(F.max("n").alias("n"), F.count("*").alias("m"))


# Joins

BRANDS = "SELECT p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand"


def _join(hint: str, kind: str):
    op(f"join_{kind}", BRANDS)(lambda s, d: t(s, d, "lineitem").select("l_partkey").join(t(s, d, "part").select("p_partkey", "p_brand").hint(hint), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.count("*").alias("n")))


for _hint, _kind in (("shuffle_hash", "hash"), ("merge", "merge"), ("broadcast", "broadcast")):
    _join(_hint, _kind)
op("join_nested_loop", "SELECT s_suppkey, count(*) AS n FROM supplier JOIN nation ON s_nationkey < n_nationkey GROUP BY s_suppkey")(
    lambda s, d: t(s, d, "supplier").join(F.broadcast(t(s, d, "nation")), F.col("s_nationkey") < F.col("n_nationkey")).groupBy("s_suppkey").agg(F.count("*").alias("n")))
op("join_cross", "SELECT r_name, n_name FROM region CROSS JOIN nation")(lambda s, d: t(s, d, "region").select("r_name").crossJoin(F.broadcast(t(s, d, "nation").select("n_name"))))


def _outer(how: str):
    """Keys moved by seven: both sides have rows without a partner."""
    op(f"join_outer_{how}", f"SELECT c_custkey, o_orderkey FROM customer {how} JOIN orders ON c_custkey = o_custkey + 7")(
        lambda s, d: t(s, d, "customer").join(t(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey") + 7, how).select("c_custkey", "o_orderkey"))


for _how in ("left", "right", "full"):
    _outer(_how)
op("join_semi", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")(lambda s, d: t(s, d, "documents").select("doc_id").join(t(s, d, "labels"), "doc_id", "left_semi"))
op("join_anti", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")(lambda s, d: t(s, d, "documents").select("doc_id").join(t(s, d, "labels"), "doc_id", "left_anti"))


@op("join_range", "WITH b AS (SELECT o_custkey AS k, 1000 * (o_orderkey % 50) AS lo FROM orders) SELECT k, lo, count(*) AS n FROM b JOIN customer ON c_acctbal >= lo AND c_acctbal < lo + 1500 GROUP BY k, lo")
def join_range(s, d):
    """Intervals meet values in cells as wide as they are, so the range join is an equi-join with a filter. Equal intervals are
    joined once; what they count goes back to the orders that ask for them."""
    cell = 1500
    orders = t(s, d, "orders").select(F.col("o_custkey").alias("k"), (1000 * (F.col("o_orderkey") % 50)).alias("lo")).groupBy("k", "lo").agg(F.count("*").alias("times"))
    b = orders.select("lo").distinct().withColumn("cell", F.explode(F.sequence(F.floor(F.col("lo") / cell), F.floor((F.col("lo") + 1500) / cell))))
    c = t(s, d, "customer").select("c_acctbal", F.floor(F.col("c_acctbal") / cell).alias("cell"))
    held = b.join(c, "cell").where("c_acctbal >= lo and c_acctbal < lo + 1500").groupBy("lo").agg(F.count("*").alias("held"))
    return orders.join(held, "lo").select("k", "lo", (F.col("times") * F.col("held")).alias("n"))


@op("join_asof", "SELECT a.event_id, max(u.event_id) AS last_update FROM (SELECT * FROM events WHERE event_type <> 'purchase') a ASOF LEFT JOIN (SELECT user_id, ts, event_id FROM events WHERE event_type = 'purchase') u ON a.user_id = u.user_id AND a.ts >= u.ts GROUP BY a.event_id")
def join_asof(s, d):
    """The last update at or before each access: a union and a running last value."""
    e = t(s, d, "events").select("user_id", "ts", "event_id", (F.col("event_type") == "purchase").alias("u"))
    w = W.partitionBy("user_id").orderBy("ts", F.desc("u")).rowsBetween(W.unboundedPreceding, 0)
    return e.withColumn("last_update", F.last(F.when(F.col("u"), F.col("event_id")), ignorenulls=True).over(w)).where("not u").select("event_id", "last_update")


op("join_interval", "SELECT a.user_id, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND b.ts - a.ts <= INTERVAL 1 HOUR AND b.ts >= a.ts GROUP BY a.user_id")(
    lambda s, d: t(s, d, "events").alias("a").join(t(s, d, "events").alias("b"), F.expr("a.user_id = b.user_id and a.event_id < b.event_id and b.ts <= a.ts + interval 1 hour and b.ts >= a.ts")).groupBy("a.user_id").agg(F.count("*").alias("n")))
op("join_self", "SELECT a.n_name AS x, b.n_name AS y FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")(
    lambda s, d: t(s, d, "nation").alias("a").join(t(s, d, "nation").alias("b"), F.expr("a.n_regionkey = b.n_regionkey and a.n_nationkey < b.n_nationkey")).select(F.col("a.n_name").alias("x"), F.col("b.n_name").alias("y")))


@op("join_lateral", "SELECT n_nationkey, c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 3)")
def join_lateral(s, d):
    mine = t(s, d, "customer").where(F.col("c_nationkey") == F.col("n_nationkey").outer()).orderBy(F.desc("c_acctbal"), "c_custkey").limit(3)
    return t(s, d, "nation").lateralJoin(mine.select("c_custkey")).select("n_nationkey", "c_custkey")


STAR = "SELECT r_name, {m} AS price FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name"
op("join_multi", STAR.format(m=money_sql("o_totalprice")))(
    lambda s, d: t(s, d, "orders").join(t(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(t(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(money("o_totalprice").alias("price")))

# Aggregates

op("agg_hash", f"SELECT l_returnflag, l_linestatus, {money_sql('l_extendedprice')} AS price, count(*) AS n, max(l_quantity) AS top FROM lineitem GROUP BY 1, 2")(
    lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(money("l_extendedprice").alias("price"), F.count("*").alias("n"), F.max("l_quantity").alias("top")))
op("agg_sort", "SELECT l_partkey, max(l_returnflag || l_linestatus) AS top FROM lineitem GROUP BY l_partkey")(lambda s, d: t(s, d, "lineitem").groupBy("l_partkey").agg(F.max(F.concat("l_returnflag", "l_linestatus")).alias("top")))
op("agg_object", "SELECT o_custkey, string_agg(CAST(o_orderkey AS VARCHAR), ',' ORDER BY o_orderkey) AS ids FROM orders GROUP BY o_custkey")(
    lambda s, d: t(s, d, "orders").groupBy("o_custkey").agg(F.array_join(F.array_sort(F.collect_list("o_orderkey")), ",").alias("ids")))
op("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1")(lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts")))
op("agg_multi_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps FROM lineitem GROUP BY 1")(
    lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("supps")))
op("agg_filtered", "SELECT user_id, count(*) FILTER (event_type = 'click') AS clicks, count(*) FILTER (event_type = 'purchase') AS buys FROM events GROUP BY user_id")(
    lambda s, d: t(s, d, "events").groupBy("user_id").agg(F.count_if(F.col("event_type") == "click").alias("clicks"), F.count_if(F.col("event_type") == "purchase").alias("buys")))
op("agg_approx_distinct")(lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts")))
op("agg_percentile", "SELECT lang, CAST(quantile_disc(n_chars, 0.5) AS BIGINT) AS mid FROM documents GROUP BY lang")(
    lambda s, d: t(s, d, "documents").groupBy("lang").agg(F.expr("percentile_disc(0.5) within group (order by n_chars)").cast("long").alias("mid")))
op("agg_percentile_approx")(lambda s, d: t(s, d, "documents").groupBy("lang").agg(F.percentile_approx("n_chars", 0.5, 1000).alias("mid")))


def _grouped(name: str, clause: str):
    sql = f"SELECT o_orderstatus, o_orderpriority, count(*) AS n, grouping(o_orderstatus) * 2 + grouping(o_orderpriority) AS gid FROM orders GROUP BY {clause}"

    @op(name, sql)
    def grouped(s, d):
        o = t(s, d, "orders")
        n = (F.count("*").alias("n"), F.grouping_id().cast("int").alias("gid"))
        cols = ("o_orderstatus", "o_orderpriority")
        if name == "rollup":
            return o.rollup(*cols).agg(*n)
        if name == "cube":
            return o.cube(*cols).agg(*n)
        return o.groupingSets([["o_orderstatus"], ["o_orderpriority"], []], *cols).agg(*n)


_grouped("rollup", "ROLLUP (o_orderstatus, o_orderpriority)")
_grouped("cube", "CUBE (o_orderstatus, o_orderpriority)")
_grouped("grouping_sets", "GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
op("pivot", "SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS view_, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY user_id")(
    lambda s, d: t(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "view", "purchase"]).agg(F.count(F.lit(1))).na.fill(0).withColumnRenamed("view", "view_"))
op("unpivot", "SELECT s_suppkey, 'nation' AS what, CAST(s_nationkey AS BIGINT) AS v FROM supplier UNION ALL SELECT s_suppkey, 'balance', CAST(floor(s_acctbal) AS BIGINT) FROM supplier")(
    lambda s, d: t(s, d, "supplier").select("s_suppkey", F.col("s_nationkey").cast("long").alias("nation"), F.floor("s_acctbal").cast("long").alias("balance")).unpivot("s_suppkey", ["nation", "balance"], "what", "v"))
# Among equal prices the smallest key is taken; a row without a price or a key is none, as in the SQL.
op("max_by", "SELECT o_custkey, arg_max(o_orderkey, o_totalprice) AS top FROM orders GROUP BY o_custkey")(
    lambda s, d: t(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.when(F.col("o_orderkey").isNotNull() & F.col("o_totalprice").isNotNull(), F.struct("o_totalprice", F.bitwise_not("o_orderkey")))).alias("top")))
op("having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 14")(lambda s, d: t(s, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).where("n > 14"))

# Windows

RANKS = "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS nt FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderpriority)"


@op("window_rank", RANKS)
def window_rank(s, d):
    w, v = W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"), W.partitionBy("o_custkey").orderBy("o_orderpriority")
    long = lambda c, n: c.cast("long").alias(n)
    return t(s, d, "orders").select("o_orderkey", long(F.row_number().over(w), "rn"), long(F.rank().over(v), "rk"), long(F.dense_rank().over(v), "dr"), long(F.ntile(4).over(w), "nt"))


@op("window_dist", "SELECT c_custkey, round(percent_rank() OVER w, 6) AS p, round(cume_dist() OVER w, 6) AS c FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal)")
def window_dist(s, d):
    w = W.partitionBy("c_nationkey").orderBy("c_acctbal")
    return t(s, d, "customer").select("c_custkey", F.round(F.percent_rank().over(w), 6).alias("p"), F.round(F.cume_dist().over(w), 6).alias("c"))


@op("window_offset", "SELECT event_id, lag(event_id) OVER w AS a, lead(event_id, 2) OVER w AS b, first_value(event_id) OVER w AS f, last_value(event_id) OVER v AS l, nth_value(event_id, 2) OVER v AS n FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id), v AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def window_offset(s, d):
    w = W.partitionBy("user_id").orderBy("event_id")
    v = w.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    e = F.col("event_id")
    return t(s, d, "events").select("event_id", F.lag(e).over(w).alias("a"), F.lead(e, 2).over(w).alias("b"), F.first(e).over(w).alias("f"), F.last(e).over(v).alias("l"), F.nth_value(e, 2).over(v).alias("n"))


op("window_rows_frame", "SELECT event_id, CAST(sum(event_id) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS s FROM events")(
    lambda s, d: t(s, d, "events").select("event_id", F.sum("event_id").over(W.partitionBy("user_id").orderBy("event_id").rowsBetween(-2, 0)).alias("s")))
op("window_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 500 PRECEDING AND 500 FOLLOWING) AS n FROM events")(
    lambda s, d: t(s, d, "events").select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy("event_id").rangeBetween(-500, 500)).alias("n")))
op("window_running_epoch", "SELECT event_id, CAST(sum(CASE WHEN event_type = 'purchase' THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY event_id) AS BIGINT) AS epoch FROM events")(
    lambda s, d: t(s, d, "events").select("event_id", F.sum((F.col("event_type") == "purchase").cast("int")).over(W.partitionBy("user_id").orderBy("event_id")).alias("epoch")))
op("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")(lambda s, d: t(s, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20))
op("topk_per_group", "SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 3")(
    lambda s, d: t(s, d, "orders").withColumn("r", F.row_number().over(W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("r <= 3").select("o_custkey", "o_orderkey"))
op("sort_offset_limit", "SELECT o_orderkey FROM orders ORDER BY o_totalprice, o_orderkey LIMIT 15 OFFSET 10")(lambda s, d: t(s, d, "orders").orderBy("o_totalprice", "o_orderkey").offset(10).limit(15).select("o_orderkey"))


def _set(name: str, f, sql: str):
    keys = "(SELECT l_partkey AS k FROM lineitem WHERE l_quantity > 25) {} (SELECT l_suppkey FROM lineitem WHERE l_quantity < 10)"

    @op(name, f"SELECT k, count(*) AS n FROM ({keys.format(sql)}) GROUP BY k")
    def sets(s, d):
        li = t(s, d, "lineitem")
        a, b = li.where("l_quantity > 25").select(F.col("l_partkey").alias("k")), li.where("l_quantity < 10").select(F.col("l_suppkey").alias("k"))
        return f(a, b).groupBy("k").agg(F.count("*").alias("n"))


_set("union", lambda a, b: a.union(b).distinct(), "UNION")
_set("union_all", DataFrame.unionAll, "UNION ALL")
_set("intersect", DataFrame.intersect, "INTERSECT")
_set("intersect_all", DataFrame.intersectAll, "INTERSECT ALL")
_set("except", DataFrame.subtract, "EXCEPT")
_set("except_all", DataFrame.exceptAll, "EXCEPT ALL")
op("dedup", "SELECT md5(text) AS h, min(doc_id) AS doc_id FROM documents GROUP BY 1")(lambda s, d: t(s, d, "documents").groupBy(F.md5("text").alias("h")).agg(F.min("doc_id").alias("doc_id")))

# Strings, dates, numbers, nested values

op("string_tokens", "SELECT w, count(*) AS n FROM (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS w FROM documents) GROUP BY w")(
    lambda s, d: t(s, d, "documents").select(F.explode(F.expr("regexp_extract_all(lower(text), '[a-z]+', 0)")).alias("w")).groupBy("w").agg(F.count("*").alias("n")))
op("string_misc", "SELECT p_partkey, substr(p_name, 2, 3) AS a, lpad(CAST(p_size AS VARCHAR), 4, '0') AS b, instr(p_name, 'a') AS c, translate(p_brand, '#', '-') AS d, regexp_replace(p_type, '[AEIOU]', '', 'g') AS e, upper(p_name) || '/' || length(p_name) AS f FROM part")(
    lambda s, d: t(s, d, "part").select("p_partkey", F.substring("p_name", 2, 3).alias("a"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("b"), F.instr("p_name", "a").cast("long").alias("c"), F.translate("p_brand", "#", "-").alias("d"), F.regexp_replace("p_type", "[AEIOU]", "").alias("e"), F.concat_ws("/", F.upper("p_name"), F.length("p_name").cast("string")).alias("f")))
op("html_strip", "SELECT page_id, trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[ \\n\\t]+', ' ', 'g')) AS text FROM pages")(
    lambda s, d: t(s, d, "pages").select("page_id", F.trim(F.regexp_replace(F.regexp_replace("html", "<[^>]*>", " "), "[ \\n\\t]+", " ")).alias("text")))
op("date_misc", "SELECT o_orderkey, date_trunc('month', o_orderdate) AS m, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(date_diff('day', CAST(o_orderdate AS DATE), DATE '2000-01-01') AS INTEGER) AS d, epoch_us(o_orderdate) AS us FROM orders")(
    lambda s, d: t(s, d, "orders").select("o_orderkey", F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("m"), F.year("o_orderdate").alias("y"), F.datediff(F.lit("2000-01-01").cast("date"), F.col("o_orderdate").cast("date")).alias("d"), F.unix_micros(F.col("o_orderdate").cast("timestamp")).alias("us")))
op("math_bits", "SELECT l_orderkey, l_partkey, greatest(l_partkey, l_suppkey) AS g, ((l_partkey - 5000) % 7 + 7) % 7 AS p, CAST(floor(sqrt(CAST(l_partkey AS DOUBLE))) AS BIGINT) AS q, xor(l_partkey, l_suppkey) AS x, l_partkey >> 2 AS h FROM lineitem")(
    lambda s, d: t(s, d, "lineitem").select("l_orderkey", "l_partkey", F.greatest("l_partkey", "l_suppkey").alias("g"), F.pmod(F.col("l_partkey") - 5000, F.lit(7)).alias("p"), F.floor(F.sqrt(F.col("l_partkey").cast("double"))).cast("long").alias("q"), F.col("l_partkey").bitwiseXOR(F.col("l_suppkey")).alias("x"), F.shiftright("l_partkey", 2).alias("h")))
op("array_hof", "SELECT vec_id, CAST(list_sum(list_transform(embedding, lambda x: CAST(floor(CAST(x AS DOUBLE) * 1024) AS BIGINT) * CAST(floor(CAST(x AS DOUBLE) * 1024) AS BIGINT))) AS BIGINT) AS dot FROM embeddings")(
    lambda s, d: t(s, d, "embeddings").select("vec_id", F.aggregate(F.transform("embedding", lambda x: F.floor(x.cast("double") * 1024).cast("long")), F.lit(0).cast("long"), lambda a, v: a + v * v).alias("dot")))
op("array_window_slice", "SELECT doc_id, array_to_string(string_split(text, ' ')[3:6], '|') AS ctx FROM documents WHERE len(string_split(text, ' ')) >= 6")(
    lambda s, d: t(s, d, "documents").where(F.size(F.split("text", " ")) >= 6).select("doc_id", F.array_join(F.slice(F.split("text", " "), 3, 4), "|").alias("ctx")))
op("map_ops", "SELECT user_id, string_agg(event_type || ':' || n, ',' ORDER BY event_type) AS m FROM (SELECT user_id, event_type, count(*) * 2 AS n FROM events GROUP BY 1, 2) GROUP BY user_id")(
    lambda s, d: t(s, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.transform_values(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))), lambda k, v: v * 2).alias("m")).select("user_id", F.array_join(F.transform(F.array_sort(F.map_entries("m")), lambda e: F.concat_ws(":", e["key"], e["value"].cast("string"))), ",").alias("m")))
op("struct_nested", "SELECT p_partkey, p_size + 1 AS a, p_brand AS b FROM part")(
    lambda s, d: t(s, d, "part").select("p_partkey", F.named_struct(F.lit("size"), F.col("p_size"), F.lit("in"), F.named_struct(F.lit("brand"), F.col("p_brand"))).alias("v")).select("p_partkey", (F.col("v.size") + 1).alias("a"), F.col("v.in.brand").alias("b")))
op("json_extract", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")(lambda s, d: t(s, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k")))
op("json_build", "SELECT event_id, '{\"u\":' || user_id || '}' AS j FROM events")(lambda s, d: t(s, d, "events").select("event_id", F.to_json(F.struct(F.col("user_id").alias("u"))).alias("j")))
op("hash_portable", f"SELECT {S.h(S.ROW_ID)} % 64 AS cell, count(*) AS n FROM lineitem GROUP BY 1")(
    lambda s, d: t(s, d, "lineitem").groupBy((portable_hash(row_id(*X.SEQ)) % 64).alias("cell")).agg(F.count("*").alias("n")))

# User code

UDF_SQL = "SELECT p_partkey, (p_size * 31 + p_partkey) % 97 AS r FROM part"


@op("udf_scalar", UDF_SQL)
def udf_scalar(s, d):
    f = F.udf(lambda a, b: (a * 31 + b) % 97, "long")
    return t(s, d, "part").select("p_partkey", f("p_size", "p_partkey").alias("r"))


@op("udf_pandas", UDF_SQL)
def udf_pandas(s, d):
    @F.pandas_udf("long")
    def f(a: pd.Series, b: pd.Series) -> pd.Series:
        return (a.astype("int64") * 31 + b) % 97

    return t(s, d, "part").select("p_partkey", f("p_size", "p_partkey").alias("r"))


@op("udf_arrow", UDF_SQL)
def udf_arrow(s, d):
    @F.arrow_udf("long")
    def f(a: pa.Array, b: pa.Array) -> pa.Array:
        return pa.array((a.to_numpy(zero_copy_only=False).astype("int64") * 31 + b.to_numpy(zero_copy_only=False)) % 97)

    return t(s, d, "part").select("p_partkey", f("p_size", "p_partkey").alias("r"))


@op("udaf", "SELECT l_returnflag, CAST(sum(l_partkey % 10) AS BIGINT) AS s FROM lineitem GROUP BY 1")
def udaf(s, d):
    @F.pandas_udf("long")
    def f(x: pd.Series) -> int:
        return int(x.sum())

    return t(s, d, "lineitem").groupBy("l_returnflag").agg(f(F.col("l_partkey") % 10).alias("s"))


@op("map_in_arrow", "SELECT l_orderkey, l_partkey * 2 AS twice FROM lineitem")
def map_in_arrow(s, d):
    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pc.multiply(b.column(1), 2)], names=["l_orderkey", "twice"])

    return t(s, d, "lineitem").select("l_orderkey", "l_partkey").mapInArrow(run, "l_orderkey long, twice long")


@op("apply_grouped", "SELECT c_nationkey, count(*) AS n FROM customer GROUP BY 1")
def apply_grouped(s, d):
    return t(s, d, "customer").select("c_nationkey", "c_custkey").groupBy("c_nationkey").applyInPandas(lambda g: pd.DataFrame({"c_nationkey": [g.c_nationkey.iloc[0]], "n": [len(g)]}), "c_nationkey int, n long")


@op("cogroup", "SELECT n_nationkey AS k, (SELECT count(*) FROM customer WHERE c_nationkey = n_nationkey) AS c, (SELECT count(*) FROM supplier WHERE s_nationkey = n_nationkey) AS s FROM nation WHERE n_nationkey IN (SELECT c_nationkey FROM customer UNION SELECT s_nationkey FROM supplier)")
def cogroup(s, d):
    a = t(s, d, "customer").select(F.col("c_nationkey").alias("k")).groupBy("k")
    b = t(s, d, "supplier").select(F.col("s_nationkey").alias("k")).groupBy("k")
    return a.cogroup(b).applyInPandas(lambda x, y: pd.DataFrame({"k": [(x if len(x) else y).k.iloc[0]], "c": [len(x)], "s": [len(y)]}), "k int, c long, s long")


@op("udtf", "WITH r AS (SELECT event_id, user_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS c FROM events) SELECT event_id, CASE WHEN c <= 2 THEN 'ship' WHEN c = 3 THEN 'fetch' ELSE 'local' END AS route FROM r")
def udtf(s, d):
    """Routes from SQL: a table function over partitions of a table, in order."""
    from pyspark.sql.functions import udtf as make

    class RouteRequests:
        def __init__(self):
            self.c = 0

        def eval(self, row):
            self.c += 1
            yield row["event_id"], "ship" if self.c <= 2 else "fetch" if self.c == 3 else "local"

    s.udtf.register("route_requests", make(RouteRequests, returnType="event_id bigint, route string"))
    t(s, d, "events").select("event_id", "user_id", "ts").createOrReplaceTempView("route_events")
    return s.sql("SELECT * FROM route_requests(TABLE(route_events) PARTITION BY user_id ORDER BY (ts, event_id))")
