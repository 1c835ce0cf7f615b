"""Queries of the bounded router, frequency tracking, batching and the split of batches, with their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adaptivejoin.operators import balance, batching, frequency, router, routing
from adaptivejoin.operators.cache import CacheBudget
from adaptivejoin.plans import core
from adaptivejoin.plans import sqltext as S
from adaptivejoin.plans import workloads as X
from adaptivejoin.plans.core import PROFILE
from adaptivejoin.tables import table

QUERIES: dict = {}
ORACLES: dict = {}
EPS, SUPPORT = 0.002, 0.01


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def budgets(spark, folder, share: float) -> CacheBudget:
    stored = X.part_store(spark, folder).agg(F.sum("value_bytes")).first()[0]
    return CacheBudget(int(stored * share), int(stored * share * 4))


@query("tiered_trace_bounded")
def tiered_trace_bounded(spark, folder):
    """Route counts with memory for a twentieth of the stored bytes."""
    t = router.tiered_route(core.priced(spark, folder, 1.0), X.ACCESS, PROFILE, budgets(spark, folder, 0.05))
    return t.groupBy("lane", "route").agg(F.count("*").alias("n"), F.sum("size").alias("bytes"))


@query("tiered_trace_lossy")
def tiered_trace_lossy(spark, folder):
    t = router.tiered_route(core.priced(spark, folder, 1.0), X.ACCESS, PROFILE, budgets(spark, folder, 0.05), eps=EPS)
    return t.groupBy("lane", "route").agg(F.count("*").alias("n"), F.sum("size").alias("bytes"))


@query("eviction_modes")
def eviction_modes(spark, folder):
    """Share of accesses that memory answers, by eviction policy and weight."""
    out: DataFrame | None = None
    for mode, weight in (("lfu_da", "unit"), ("lfu_da", "cost"), ("lfu_da", "cost_per_byte"), ("lfu", "unit"), ("lru", "unit")):
        t = router.tiered_route(core.priced(spark, folder, 1.0, True), X.ACCESS, PROFILE, budgets(spark, folder, 0.01), mode, weight)
        one = t.agg(F.lit(mode).alias("mode"), F.lit(weight).alias("weight"), F.count_if(F.col("route") == "local_mem").alias("hits"), F.count("*").alias("n"))
        out = one if out is None else out.unionAll(one)
    return out


@query("cache_budgets")
def cache_budgets(spark, folder):
    """The same for budgets of 1, 5 and 25 per cent of the stored bytes."""
    out: DataFrame | None = None
    for share in (0.01, 0.05, 0.25):
        t = router.tiered_route(core.priced(spark, folder, 1.0), X.ACCESS, PROFILE, budgets(spark, folder, share))
        one = t.agg(F.lit(share).alias("share"), F.count_if(F.col("route").startswith("local")).alias("hits"), F.count_if(F.col("route") == "ship").alias("ships"), F.count("*").alias("n"))
        out = one if out is None else out.unionAll(one)
    return out


@query("updates_piggyback")
def updates_piggyback(spark, folder):
    """Counts are set back when a reply shows a later time of change; lanes that hold a key are told at once."""
    import pyarrow as pa

    a, u = core.accesses(spark, folder)
    rows = routing.with_epochs(a, u, "key", "ts", "updated_at").select("lane", "key", "epoch", "ts", "event_id")
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = rows.repartition(n, "lane").sortWithinPartitions("lane", "ts", "event_id")
    rent, buy, use = core.R, core.B, core.M

    def run(batches):
        lane, r, held = None, None, {}
        for batch in batches:
            routes = []
            for lane_, key, epoch in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                if lane_ != lane:
                    lane, r, held = lane_, router.LaneRouter(router.RouterOptions(CacheBudget(1 << 60, 0))), {}
                if key in r.cache.memory and held.get(key) != epoch:
                    r.invalidate(key)  # the owner has told this lane
                route = r.decide(key, 1, rent, buy, use, use, updated_at=epoch)
                if route == router.FETCH_MEM:
                    held[key] = epoch
                routes.append(route)
            yield pa.RecordBatch.from_arrays([batch.column(4), batch.column(0), batch.column(1), pa.array(routes)], names=["event_id", "lane", "key", "route"])

    return dealt.mapInArrow(run, "event_id long, lane int, key long, route string").groupBy("lane", "route").agg(F.count("*").alias("n"))


@query("freq_exact", f"WITH {S.probe(1.0)} SELECT lane, key, count(*) AS n FROM probe GROUP BY lane, key")
def freq_exact(spark, folder):
    return X.zipf_probe(spark, folder, 1.0).groupBy("lane", "key").agg(F.count("*").alias("n"))


@query("freq_lossy_bounds")
def freq_lossy_bounds(spark, folder):
    """Whether for every key the estimate lies within its bounds, a forgotten key being estimated as 0."""
    probe = X.zipf_probe(spark, folder, 1.0)
    exact = probe.groupBy("lane", "key").agg(F.count("*").alias("n"))
    sizes = probe.groupBy("lane").agg(F.count("*").alias("seen"))
    est = frequency.lossy_count(probe, "key", "lane", X.SEQ, EPS).select("lane", "key", "est")
    j = exact.join(est, ["lane", "key"], "left").join(sizes, "lane").withColumn("est", F.coalesce("est", F.lit(0)))
    ok = (F.col("est") <= F.col("n")) & (F.col("est") >= F.col("n") - EPS * F.col("seen") - 1)
    return j.groupBy("lane").agg(F.count("*").alias("keys"), F.min(ok).alias("within"))


@query("freq_heavy_two_pass", f"WITH {S.probe(1.0)} SELECT key, count(*) AS n FROM probe GROUP BY key HAVING count(*) >= {SUPPORT} * (SELECT count(*) FROM probe)")
def freq_heavy_two_pass(spark, folder):
    """A key over the support overall is over it in some lane."""
    return frequency.heavy_two_pass(X.zipf_probe(spark, folder, 1.0), "key", "lane", X.SEQ, SUPPORT, EPS)


@query("freq_sketch_topk")
def freq_sketch_topk(spark, folder):
    X.zipf_probe(spark, folder, 1.0).createOrReplaceTempView("zipf_probe_z1")
    return spark.sql("SELECT explode(approx_top_k(key, 10, 1000)) AS top FROM zipf_probe_z1").select("top.item", "top.count")


@query("sketch_error")
def sketch_error(spark, folder):
    """Error of the estimates against exact counts: never above, and every key over the error bound is kept."""
    probe = X.zipf_probe(spark, folder, 1.0)
    exact = probe.groupBy("lane", "key").agg(F.count("*").alias("n"))
    j = exact.join(frequency.lossy_count(probe, "key", "lane", X.SEQ, EPS).select("lane", "key", "est"), ["lane", "key"], "left")
    sizes = probe.groupBy("lane").agg(F.count("*").alias("seen"))
    j = j.join(sizes, "lane")
    return j.agg(F.min(F.coalesce(F.col("est") <= F.col("n"), F.lit(True))).alias("never_above"), F.min(F.col("est").isNotNull() | (F.col("n") <= EPS * F.col("seen") + 1)).alias("heavy_kept"))


SHIPS = f"""hm AS (SELECT *, CAST({S.h("CAST(key AS VARCHAR)")} % {S.HOMES} AS INTEGER) AS home FROM priced),
ships AS (SELECT *, (row_number() OVER (PARTITION BY lane, home ORDER BY {S.SEQ}) - 1) // {S.BATCH} AS batch_no, 0 AS local_before, 0 AS asked_before FROM hm)"""


def all_ships(spark, folder, z: float = 1.0) -> DataFrame:
    """Every access shipped, in batches of its lane and home."""
    rows = routing.assign_home(core.priced(spark, folder, z), "key", S.HOMES)
    return batching.by_size(rows, ("lane", "home"), X.SEQ, S.BATCH).withColumns({"local_before": F.lit(0), "asked_before": F.lit(0)})


@query("batch_by_size", f"WITH {S.routed(PROFILE, 1.0)}, {SHIPS} SELECT lane, home, batch_no, count(*) AS members FROM ships GROUP BY lane, home, batch_no")
def batch_by_size(spark, folder):
    return all_ships(spark, folder).groupBy("lane", "home", "batch_no").agg(F.count("*").alias("members"))


WAIT_US, SIZE = 6 * 3600 * 1_000_000, 5


@query("batch_by_wait", f"""WITH RECURSIVE e AS (SELECT user_id AS key, epoch_us(ts) AS t, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS i FROM events),
walk AS (SELECT key, i, t, t AS begun, 1 AS members, CAST(0 AS BIGINT) AS batch_no FROM e WHERE i = 1
UNION ALL SELECT e.key, e.i, e.t, CASE WHEN w.members = {SIZE} OR e.t > w.begun + {WAIT_US} THEN e.t ELSE w.begun END,
 CASE WHEN w.members = {SIZE} OR e.t > w.begun + {WAIT_US} THEN 1 ELSE w.members + 1 END, w.batch_no + CASE WHEN w.members = {SIZE} OR e.t > w.begun + {WAIT_US} THEN 1 ELSE 0 END
 FROM walk w JOIN e ON e.key = w.key AND e.i = w.i + 1),
closed AS (SELECT key, batch_no, count(*) AS members, max(begun) AS begun, max(t) AS ended FROM walk GROUP BY key, batch_no),
finals AS (SELECT *, max(batch_no) OVER (PARTITION BY key) AS final FROM closed)
SELECT key, batch_no, members, CASE WHEN members = {SIZE} OR batch_no = final THEN ended - begun ELSE {WAIT_US} END AS waited FROM finals""")
def batch_by_wait(spark, folder):
    """Batches of at most five events of a user that wait at most six hours."""
    e = table(spark, folder, "events").select("user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))
    return batching.by_wait(e, "user_id", "at", SIZE, WAIT_US)




def batches_sql(p, ships: str = "ships", to: str = "tried") -> str:
    """Relations that end in ``to``, the time of every d of every batch of ``ships``."""
    back = f"half * val + (b - half) * {p.result_bytes}"
    return f"""{to}_grouped AS (SELECT lane, home, batch_no, count(*) AS b, CAST(sum(value_bytes) AS BIGINT) AS bytes, max(local_before) AS local, max(asked_before) AS asked FROM {ships} GROUP BY lane, home, batch_no),
{to}_halved AS (SELECT *, bytes // b AS val, b // 2 AS half FROM {to}_grouped),
{to}_before AS (SELECT *, CAST(coalesce(sum(half) OVER l, 0) AS BIGINT) AS lane_returned, CAST(coalesce(sum(b) OVER l, 0) AS BIGINT) AS lane_calls, CAST(coalesce(sum({back}) OVER l, 0) AS BIGINT) AS lane_bytes,
  CAST(coalesce(sum(b - half) OVER h, 0) AS BIGINT) AS home_kept, CAST(coalesce(sum({back}) OVER h, 0) AS BIGINT) AS home_bytes FROM {to}_halved
  WINDOW l AS (PARTITION BY lane ORDER BY batch_no RANGE BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), h AS (PARTITION BY home ORDER BY batch_no RANGE BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
{to} AS (SELECT lane, home, batch_no, b, d, greatest({p.lane_cpu_us * p.bandwidth} * (local + lane_returned + b - d), {p.key_bytes + p.param_bytes} * (lane_calls + b) + asked + lane_bytes + d * {p.result_bytes} + (b - d) * val,
  {p.home_cpu_us * p.bandwidth} * (home_kept + d), home_bytes + d * {p.result_bytes} + (b - d) * val) AS time FROM (SELECT *, unnest(range(0, b + 1)) AS d FROM {to}_before))"""


BATCHES = batches_sql(PROFILE)
SPLIT = f"WITH {S.routed(PROFILE, 1.0)}, {SHIPS}, {BATCHES}"


@query("split_exact", f"{SPLIT} SELECT lane, home, batch_no, b, min(time) AS time, arg_min(d, time * 1000 + d) AS d FROM tried GROUP BY lane, home, batch_no, b")
def split_exact(spark, folder):
    return balance.split_exact(balance.batch_lines(all_ships(spark, folder), PROFILE)).select("lane", "home", "batch_no", "b", "time", "d")


@query("split_descent", f"{SPLIT} SELECT lane, home, batch_no, min(time) AS time FROM tried GROUP BY lane, home, batch_no")
def split_descent(spark, folder):
    return balance.split_descent(balance.batch_lines(all_ships(spark, folder), PROFILE)).select("lane", "home", "batch_no", "time")


@query("split_limits", f"{SPLIT} SELECT lane, home, batch_no, max(time) FILTER (d = 0) AS none, max(time) FILTER (d = b) AS all_, min(time) AS best FROM tried GROUP BY lane, home, batch_no")
def split_limits(spark, folder):
    lines = balance.split_exact(balance.batch_lines(all_ships(spark, folder), PROFILE))
    return lines.select("lane", "home", "batch_no", balance.time_at(F.lit(0)).alias("none"), balance.time_at(F.col("b")).alias("all_"), F.col("time").alias("best"))


@query("load_by_node", f"{SPLIT}, chosen AS (SELECT lane, home, b, arg_min(d, time * 1000 + d) AS d FROM tried GROUP BY lane, home, batch_no, b) SELECT home, CAST(sum(b) AS BIGINT) AS before_split, CAST(sum(d) AS BIGINT) AS after_split FROM chosen GROUP BY home")
def load_by_node(spark, folder):
    """Calls computed at each owner, all of them and after the split."""
    s = balance.split_exact(balance.batch_lines(all_ships(spark, folder), PROFILE))
    return s.groupBy("home").agg(F.sum("b").alias("before_split"), F.sum("d").alias("after_split"))


@query("split_balances", f"{SPLIT}, chosen AS (SELECT home, b, arg_min(d, time * 1000 + d) AS d FROM tried GROUP BY lane, home, batch_no, b), n AS (SELECT home, CAST(sum(b) AS BIGINT) AS x, CAST(sum(d) AS BIGINT) AS y FROM chosen GROUP BY home) SELECT max(x) AS busiest_before, max(y) AS busiest_after, CAST(sum(x) AS BIGINT) AS total_before, CAST(sum(y) AS BIGINT) AS total_after FROM n")
def split_balances(spark, folder):
    n = load_by_node(spark, folder)
    return n.agg(F.max("before_split").alias("busiest_before"), F.max("after_split").alias("busiest_after"), F.sum("before_split").alias("total_before"), F.sum("after_split").alias("total_after"))
