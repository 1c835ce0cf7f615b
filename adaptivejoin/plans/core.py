"""Queries of the call model, the cost terms, the routing family and the hybrid joins, with their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from adaptivejoin.functions.costs import CostProfile, smoothed, with_costs
from adaptivejoin.functions.hashing import SKEWS, row_id
from adaptivejoin.operators import joins, routing
from adaptivejoin.operators.routing import Access
from adaptivejoin.plans import sqltext as S
from adaptivejoin.plans import workloads as X
from adaptivejoin.tables import table

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


PROFILE = CostProfile(home_cpu_us=48, lane_cpu_us=20)
C = S.costs(PROFILE)
RESULT = ("row_id", "key", "result")
PLAIN = f"WITH {S.probe(1.0)}, store AS (SELECT p_partkey AS skey, p_size, p_retailprice FROM part)\nSELECT row_id, key, {S.CALL} AS result FROM probe JOIN store ON key = skey"


def priced(spark, folder: str, z: float, moving: bool = False) -> DataFrame:
    """Accesses with the size of their value, for traces that report costs and bytes; the joins learn sizes from replies instead."""
    probe = X.zipf_probe(spark, folder, z, moving=moving)
    return probe.join(X.part_store(spark, folder).select("skey", "value_bytes"), F.col("key") == F.col("skey")).drop("skey")


def terms(profile: CostProfile = PROFILE):
    return profile.rent(), profile.buy(F.col("value_bytes")), profile.use_memory()


def trace(spark, folder: str, z: float = 1.0, first_ships: bool = True, use=None, moving: bool = False) -> DataFrame:
    rent, buy, mem = terms()
    return routing.ski_route(priced(spark, folder, z, moving), X.ACCESS, rent, buy, use if use is not None else mem, first_ships)


@query("call_lookup_only", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, p_size, p_brand FROM lineitem JOIN part ON l_partkey = p_partkey")
def call_lookup_only(spark, folder):
    out = joins.keyed_join(table(spark, folder, "lineitem").select(*X.SEQ), table(spark, folder, "part"), "l_partkey", "p_partkey", joins.lookup("p_size", "p_brand"))
    return out.select(*X.SEQ, "value.p_size", "value.p_brand")


@query("call_with_udf", PLAIN)
def call_with_udf(spark, folder):
    return joins.keyed_join(X.zipf_probe(spark, folder, 1.0), X.part_store(spark, folder), "key", "skey", X.PART_CALL).select(*RESULT)


@query("fetch_join_dedup", PLAIN)
def fetch_join_dedup(spark, folder):
    return joins.fetch_join(X.zipf_probe(spark, folder, 1.0), X.part_store(spark, folder), "key", "skey", X.PART_CALL).select(*RESULT)


@query("fetch_join_every_time", PLAIN)
def fetch_join_every_time(spark, folder):
    return joins.fetch_join(X.zipf_probe(spark, folder, 1.0), X.part_store(spark, folder), "key", "skey", X.PART_CALL, dedupe=False).select(*RESULT)


@query("fetch_counts", f"WITH {S.probe(1.0)} SELECT lane, count(*) AS every_time, count(DISTINCT key) AS deduped FROM probe GROUP BY lane")
def fetch_counts(spark, folder):
    return X.zipf_probe(spark, folder, 1.0).groupBy("lane").agg(F.count("*").alias("every_time"), F.countDistinct("key").alias("deduped"))


@query("ship_join", PLAIN)
def ship_join(spark, folder):
    return joins.ship_join(X.zipf_probe(spark, folder, 1.0), X.part_store(spark, folder), "key", "skey", X.PART_CALL).select(*RESULT)


def adaptive(spark, folder, how="inner", probe=None, z=1.0) -> DataFrame:
    """The flagship: routes from what the first replies bring, and the hybrid join."""
    rent, buy, mem = terms()
    store = X.part_store(spark, folder)
    probe = X.zipf_probe(spark, folder, z) if probe is None else probe
    routed = routing.online_route(probe, store, X.ACCESS, "skey", "value_bytes", rent, buy, mem)
    return joins.adaptive_join(routed, store, X.ACCESS, "skey", X.PART_CALL, how)


@query("adaptive_join_result", PLAIN)
def adaptive_join_result(spark, folder):
    return adaptive(spark, folder).select(*RESULT)


def holed(spark, folder) -> DataFrame:
    """Accesses of which some have keys that no store holds, or none at all."""
    key = F.when(F.col("qty") % 10 == 0, F.lit(-1)).when(F.col("qty") % 11 == 0, F.lit(None)).otherwise(F.col("key")).cast("long")
    return X.zipf_probe(spark, folder, 1.0).withColumn("key", key)


HOLED = f"WITH {S.probe(1.0)}, holed AS (SELECT row_id, qty, CASE WHEN qty % 10 = 0 THEN -1 WHEN qty % 11 = 0 THEN NULL ELSE key END AS key FROM probe), store AS (SELECT p_partkey AS skey, p_size, p_retailprice FROM part)"


@query("adaptive_join_left", f"{HOLED} SELECT row_id, key, {S.CALL} AS result FROM holed LEFT JOIN store ON key = skey")
def adaptive_join_left(spark, folder):
    return adaptive(spark, folder, "left", holed(spark, folder)).select(*RESULT)


@query("adaptive_join_semi", f"{HOLED} SELECT row_id, key FROM holed WHERE key IN (SELECT skey FROM store)")
def adaptive_join_semi(spark, folder):
    return adaptive(spark, folder, "left_semi", holed(spark, folder)).select("row_id", "key")


@query("adaptive_join_anti", f"{HOLED} SELECT row_id, key FROM holed WHERE NOT EXISTS (SELECT 1 FROM store WHERE skey = key)")
def adaptive_join_anti(spark, folder):
    return adaptive(spark, folder, "left_anti", holed(spark, folder)).select("row_id", "key")


@query("unpushable_call_join", PLAIN)
def unpushable_call_join(spark, folder):
    from dataclasses import replace

    rent, buy, mem = terms()
    routed = routing.ski_route(priced(spark, folder, 1.0), X.ACCESS, rent, buy, mem)
    return joins.adaptive_join(routed, X.part_store(spark, folder), X.ACCESS, "skey", replace(X.PART_CALL, pushable=False)).select(*RESULT)


@query("lane_assignment", f"SELECT {S.h(S.ROW_ID)} % 8 AS lane, count(*) AS n FROM lineitem GROUP BY 1")
def lane_assignment(spark, folder):
    rows = routing.assign_lanes(table(spark, folder, "lineitem").select(*X.SEQ), S.LANES, row_id(*X.SEQ))
    return rows.groupBy(F.col("lane").cast("long").alias("lane")).agg(F.count("*").alias("n"))


@query("relane_elastic", PLAIN)
def relane_elastic(spark, folder):
    """Lanes grow from 4 to 12 and shrink to 6 during the run; results stay."""
    rent, buy, mem = terms()
    rows = routing.relane(priced(spark, folder, 1.0), [(0, 4), (300, 12), (900, 6)], "l_orderkey", F.col("row_id"))
    routed = routing.ski_route(rows, X.ACCESS, rent, buy, mem)
    return joins.adaptive_join(routed, X.part_store(spark, folder), X.ACCESS, "skey", X.PART_CALL).select(*RESULT)


_BLOCKING = S.costs(CostProfile(home_cpu_us=48, lane_cpu_us=20, overlap=False))


@query("cost_terms", f"WITH store AS (SELECT p_partkey AS skey, {S.STORE_BYTES} AS value_bytes FROM part) SELECT skey, {C['rent']} AS rent_us, {C['buy']} AS buy_us, {C['mem']} AS mem_us, {C['disk']} AS disk_us, {_BLOCKING['rent']} AS rent_blocking_us, {_BLOCKING['buy']} AS buy_blocking_us FROM store")
def cost_terms(spark, folder):
    from dataclasses import replace

    slow = replace(PROFILE, overlap=False)
    out = with_costs(X.part_store(spark, folder), PROFILE)
    return out.select("skey", "rent_us", "buy_us", "mem_us", "disk_us", slow.rent().alias("rent_blocking_us"), slow.buy(F.col("value_bytes")).alias("buy_blocking_us"))


@query("ewma_cost", "WITH x AS (SELECT user_id, list(CAST(floor(value * 100) AS BIGINT) ORDER BY ts, event_id) AS v FROM events GROUP BY user_id) SELECT user_id, list_reduce(list_prepend(CAST(100 * 1024 AS BIGINT), v), lambda a, x: (x * 1024 + a) // 2) AS smoothed FROM x")
def ewma_cost(spark, folder):
    """Smoothed cost of each user's events, alpha 1/2 in fixed point; a series is one key's measurements."""
    e = table(spark, folder, "events").select("user_id", F.struct("ts", "event_id", F.floor(F.col("value") * 100).cast("long").alias("v")).alias("m"))
    series = e.groupBy("user_id").agg(F.array_sort(F.collect_list("m")).alias("ms"))
    return series.select("user_id", smoothed(F.transform("ms", lambda m: m["v"]), 1, 2, 100, 1024).alias("smoothed"))


def _counts(name: str, first_ships: bool, use_sql: str, use) -> None:
    sql = f"WITH {S.routed(PROFILE, 1.0, first_ships, use_sql)} SELECT key, count(*) FILTER (route = 'ship') AS ship, count(*) FILTER (route = 'fetch') AS fetch, count(*) FILTER (route = 'local') AS local FROM trace GROUP BY key"

    @query(name, sql)
    def counts(spark, folder):
        n = lambda r: F.count_if(F.col("route") == r).alias(r)
        return trace(spark, folder, 1.0, first_ships, use() if use else None).groupBy("key").agg(n("ship"), n("fetch"), n("local"))


_counts("ski_classic", False, "0", lambda: F.lit(0))
_counts("ski_recurring", False, C["mem"], None)
_counts("ski_never_buy", False, C["rent"], PROFILE.rent)


@query("tiered_trace_unbounded", f"WITH {S.routed(PROFILE, 1.0)} SELECT key, count(*) FILTER (route = 'ship') AS ship, count(*) FILTER (route = 'fetch') AS fetch, count(*) FILTER (route = 'local') AS local FROM trace GROUP BY key")
def tiered_trace_unbounded(spark, folder):
    """The bounded router with memory for everything: the closed form's counts."""
    from adaptivejoin.operators.router import CacheBudget, tiered_route

    routed = tiered_route(priced(spark, folder, 1.0), X.ACCESS, PROFILE, CacheBudget(1 << 60, 0))
    n = lambda r, name: F.count_if(F.col("route") == r).alias(name)
    return routed.groupBy("key").agg(n("ship", "ship"), n("fetch_mem", "fetch"), n("local_mem", "local"))


@query("online_trace", f"WITH {S.routed(PROFILE, 1.0)} SELECT row_id, c, route FROM trace")
def online_trace(spark, folder):
    """Routes when sizes are learned from first replies: those of full knowledge."""
    rent, buy, mem = terms()
    return routing.online_route(X.zipf_probe(spark, folder, 1.0), X.part_store(spark, folder), X.ACCESS, "skey", "value_bytes", rent, buy, mem).select("row_id", "c", "route")


@query("measured_costs", "SELECT * FROM (VALUES ('home_cpu_us'), ('lane_cpu_us'), ('home_disk_us'), ('bandwidth')) v(resource), (SELECT true AS measured)")
def measured_costs(spark, folder):
    """The cost profile as measured on the machines that run this: whether each figure is a positive time or rate."""
    from adaptivejoin.functions.measure import measured_profile

    p = measured_profile(spark, X.part_store(spark, folder), "skey", ("p_size", "p_retailprice"))
    rows = [(n, getattr(p, n) > 0) for n in ("home_cpu_us", "lane_cpu_us", "home_disk_us", "bandwidth")]
    return spark.createDataFrame(rows, "resource string, measured boolean")


@query("adaptive_join_measured", PLAIN)
def adaptive_join_measured(spark, folder):
    """The hybrid join with rent, buy and use from measured costs; whatever they are, the result is that of the plain join."""
    from adaptivejoin.functions.measure import measured_profile

    store = X.part_store(spark, folder)
    p = measured_profile(spark, store, "skey", ("p_size", "p_retailprice"))
    routed = routing.online_route(X.zipf_probe(spark, folder, 1.0), store, X.ACCESS, "skey", "value_bytes", p.rent(), p.buy(F.col("value_bytes")), p.use_memory())
    return joins.adaptive_join(routed, store, X.ACCESS, "skey", X.PART_CALL).select(*RESULT)

@query("tiered_trace_zero", f"WITH {S.routed(PROFILE, 1.0)} SELECT key, count(*) AS ship FROM trace GROUP BY key")
def tiered_trace_zero(spark, folder):
    """Without memory and disk every access ships."""
    from adaptivejoin.operators.router import CacheBudget, tiered_route

    routed = tiered_route(priced(spark, folder, 1.0), X.ACCESS, PROFILE, CacheBudget(0, 0))
    return routed.where("route = 'ship'").groupBy("key").agg(F.count("*").alias("ship"))


@query("ski_trace", f"WITH {S.routed(PROFILE, 1.0)} SELECT row_id, lane, key, c, route FROM trace")
def ski_trace(spark, folder):
    return trace(spark, folder).select("row_id", "lane", "key", "c", "route")


@query("ski_first_ships", f"WITH {S.probe(1.0)} SELECT count(DISTINCT (lane, key)) AS first_calls FROM probe")
def ski_first_ships(spark, folder):
    return trace(spark, folder).where("c = 1 and route = 'ship'").agg(F.count("*").alias("first_calls"))


@query("competitive_ratio", f"""WITH {S.routed(PROFILE, 1.5, False)}, per AS (
SELECT lane, key, CAST(sum(CASE route WHEN 'ship' THEN rent WHEN 'fetch' THEN buy + use ELSE use END) AS BIGINT) AS cost, count(*) AS n, max(rent) AS r, max(buy) AS b, max(use) AS u FROM trace GROUP BY lane, key)
SELECT lane, key, cost, least(n * r, b + n * u) AS optimum, cost * r <= (2 * r - u) * least(n * r, b + n * u) AS within FROM per""")
def competitive_ratio(spark, folder):
    """Online and clairvoyant cost of each (lane, key), and whether the ratio keeps its bound 2 - use / rent."""
    rent, buy, mem = terms()
    t = trace(spark, folder, 1.5, first_ships=False).withColumn("cost", routing.route_cost(rent, buy, mem))
    per = t.groupBy("lane", "key").agg(F.sum("cost").alias("cost"), F.count("*").alias("n"), F.max("value_bytes").alias("value_bytes"))
    best = routing.offline_optimum(rent, buy, mem, F.col("n"))
    return per.select("lane", "key", "cost", best.alias("optimum"), (F.col("cost") * rent <= (2 * rent - mem) * best).alias("within"))


ACCESSES = """acc AS (SELECT event_id, CAST(event_id % 4 AS INTEGER) AS lane, user_id AS key, ts FROM events WHERE event_type <> 'purchase'),
upd AS (SELECT user_id AS ukey, ts AS uts FROM events WHERE event_type = 'purchase'),
both_ AS (SELECT event_id, lane, key, ts, 0 AS u FROM acc UNION ALL SELECT NULL, NULL, ukey, uts, 1 FROM upd),
epochs AS (SELECT * FROM (SELECT *, CAST(sum(u) OVER (PARTITION BY key ORDER BY ts, u DESC ROWS UNBOUNDED PRECEDING) AS BIGINT) AS epoch FROM both_) WHERE u = 0)"""


def accesses(spark, folder) -> tuple[DataFrame, DataFrame]:
    e = table(spark, folder, "events")
    a = e.where("event_type != 'purchase'").select("event_id", (F.col("event_id") % 4).cast("int").alias("lane"), F.col("user_id").alias("key"), "ts")
    return a, e.where("event_type = 'purchase'").select(F.col("user_id").alias("key"), F.col("ts").alias("updated_at"))


EVENT_ACCESS = Access("key", "lane", ("ts", "event_id"))
R, B, M = 10, 16, 2


def updated_trace(spark, folder, reset: bool = True) -> DataFrame:
    a, u = accesses(spark, folder)
    return routing.route_with_updates(routing.with_epochs(a, u, "key", "ts", "updated_at"), EVENT_ACCESS, F.lit(R), F.lit(B), F.lit(M), reset)


@query("updates_broadcast", f"WITH {ACCESSES}, t AS (SELECT *, row_number() OVER (PARTITION BY lane, key, epoch ORDER BY ts, event_id) AS c FROM epochs) SELECT event_id, epoch, CASE WHEN c <= 2 THEN 'ship' WHEN c = 3 THEN 'fetch' ELSE 'local' END AS route FROM t")
def updates_broadcast(spark, folder):
    return updated_trace(spark, folder).select("event_id", "epoch", "route")


@query("updates_no_reset", f"""WITH {ACCESSES}, t AS (SELECT *, row_number() OVER (PARTITION BY lane, key ORDER BY ts, event_id) AS c FROM epochs),
b AS (SELECT *, coalesce(max(CASE WHEN c > 2 THEN 1 ELSE 0 END) OVER (PARTITION BY lane, key, epoch ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS had FROM t)
SELECT event_id, epoch, CASE WHEN c <= 2 THEN 'ship' WHEN had = 0 THEN 'fetch' ELSE 'local' END AS route FROM b""")
def updates_no_reset(spark, folder):
    return updated_trace(spark, folder, reset=False).select("event_id", "epoch", "route")


@query("updates_holders", f"""WITH {ACCESSES}, t AS (SELECT *, row_number() OVER (PARTITION BY lane, key, epoch ORDER BY ts, event_id) AS c FROM epochs),
holders AS (SELECT key, epoch, count(DISTINCT lane) AS n FROM t WHERE c = 3 GROUP BY key, epoch),
ups AS (SELECT ukey, row_number() OVER (PARTITION BY ukey ORDER BY uts) - 1 AS epoch FROM upd)
SELECT count(*) * 4 AS broadcast_messages, CAST(coalesce(sum(n), 0) AS BIGINT) AS holder_messages FROM ups LEFT JOIN holders h ON ukey = key AND ups.epoch = h.epoch""")
def updates_holders(spark, folder):
    """Messages if every lane hears of each update, and if only the lanes that hold the key do."""
    _, u = accesses(spark, folder)
    holders = updated_trace(spark, folder).where("route = 'fetch'").groupBy("key", "epoch").agg(F.countDistinct("lane").alias("n"))
    ends = u.withColumn("epoch", (F.row_number().over(W.partitionBy("key").orderBy("updated_at")) - 1).cast("long"))
    return ends.join(holders, ["key", "epoch"], "left").agg((F.count("*") * 4).alias("broadcast_messages"), F.coalesce(F.sum("n"), F.lit(0)).alias("holder_messages"))


LEARN = "10 * l_orderkey < (SELECT max(l_orderkey) + 1 FROM lineitem)"
FROZEN = f"""early AS (SELECT *, row_number() OVER (PARTITION BY lane, key ORDER BY {S.SEQ}) AS c, {S.threshold('rent', 'buy', 'use')} AS m FROM priced WHERE {LEARN}),
bought AS (SELECT DISTINCT lane, key FROM early WHERE c = m + 1),
frozen AS (SELECT row_id, lane, key, {S.SEQ}, value_bytes, rent, buy, use, CASE WHEN c <= m THEN 'ship' WHEN c = m + 1 THEN 'fetch' ELSE 'local' END AS route FROM early
UNION ALL SELECT row_id, p.lane, p.key, {S.SEQ}, value_bytes, rent, buy, use, CASE WHEN b.key IS NOT NULL THEN 'local' ELSE 'ship' END FROM priced p LEFT JOIN bought b ON p.lane = b.lane AND p.key = b.key WHERE NOT ({LEARN}))"""


def frozen(spark, folder, z: float, moving: bool) -> DataFrame:
    rent, buy, mem = terms()
    top = table(spark, folder, "lineitem").agg(F.max("l_orderkey")).first()[0] + 1
    return routing.frozen_route(priced(spark, folder, z, moving), X.ACCESS, rent, buy, mem, F.col("l_orderkey") * 10 < top)


@query("frozen_after_prefix", f"WITH {S.routed(PROFILE, 1.0)}, {FROZEN} SELECT row_id, route FROM frozen")
def frozen_after_prefix(spark, folder):
    return frozen(spark, folder, 1.0, False).select("row_id", "route")


def _cost_sql(rel: str) -> str:
    return f"(SELECT CAST(sum(CASE route WHEN 'ship' THEN rent WHEN 'fetch' THEN buy + use ELSE use END) AS BIGINT) FROM {rel})"


def _frozen_vs_adaptive(z: float) -> None:
    name = f"frozen_vs_adaptive_z{str(z).replace('.', '')}"

    @query(name, f"WITH {S.routed(PROFILE, z, moving=True)}, {FROZEN} SELECT {_cost_sql('frozen')} AS frozen_cost, {_cost_sql('trace')} AS adaptive_cost")
    def compare(spark, folder):
        """Cost over a moving distribution, of decisions frozen after a tenth of the rows, and of continuous ones."""
        rent, buy, mem = terms()
        total = lambda t, n: t.agg(F.sum(routing.route_cost(rent, buy, mem)).alias(n))
        return total(frozen(spark, folder, z, True), "frozen_cost").crossJoin(total(trace(spark, folder, z, moving=True), "adaptive_cost"))


for _z in SKEWS:
    _frozen_vs_adaptive(_z)


def _zipf(z: float) -> None:
    @query(f"zipf_keys_z{str(z).replace('.', '')}", f"WITH {S.probe(z)} SELECT key, count(*) AS n FROM probe GROUP BY key")
    def keys(spark, folder):
        return X.zipf_probe(spark, folder, z).groupBy("key").agg(F.count("*").alias("n"))


for _z in SKEWS:
    _zipf(_z)


@query("moving_hot_keys", f"WITH {S.probe(1.5, moving=True)}, n AS (SELECT phase, key, count(*) AS n FROM probe GROUP BY phase, key) SELECT phase, key, n FROM (SELECT *, row_number() OVER (PARTITION BY phase ORDER BY n DESC, key) AS r FROM n) WHERE r = 1")
def moving_hot_keys(spark, folder):
    n = X.zipf_probe(spark, folder, 1.5, moving=True).groupBy("phase", "key").agg(F.count("*").alias("n"))
    return n.withColumn("r", F.row_number().over(W.partitionBy("phase").orderBy(F.desc("n"), "key"))).where("r = 1").drop("r")


@query("cached_keys_by_lane", f"WITH {S.routed(PROFILE, 1.0)} SELECT key, count(DISTINCT lane) AS lanes_caching FROM trace WHERE route = 'fetch' GROUP BY key")
def cached_keys_by_lane(spark, folder):
    """Heavy hitters end up on every lane, rare keys on none."""
    return trace(spark, folder).where("route = 'fetch'").groupBy("key").agg(F.countDistinct("lane").alias("lanes_caching"))

