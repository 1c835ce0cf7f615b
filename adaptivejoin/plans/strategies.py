"""The compared strategies: each one's join, checked against the plain join, and the modelled time of a run of each.

The model charges every access to the resources of its lane and of its key's owner; a run takes as long as its busiest resource.
It is integer arithmetic over aggregates, so that any SQL engine can repeat it; it is no wall clock.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from adaptivejoin.functions.costs import BOTH_HEAVY, COMPUTE_HEAVY, DATA_HEAVY, CostProfile
from adaptivejoin.functions.hashing import SKEWS, portable_hash
from adaptivejoin.operators import balance, batching, joins, routing
from adaptivejoin.plans import core
from adaptivejoin.plans import kernels as K
from adaptivejoin.plans import sqltext as S
from adaptivejoin.plans import workloads as X
from adaptivejoin.sources.store import spooled
from adaptivejoin.tables import table

QUERIES: dict = {}
ORACLES: dict = {}
SALTS = 8
HEAVY_SHARE = 100  # a key is heavy from one in so many accesses


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


SHARED = f"SELECT key, count(*) AS n, CAST(sum(result) AS BIGINT) AS total FROM ({core.PLAIN}) GROUP BY key"


def strategy(name: str):
    """A strategy's rows, summed by key: the same for all of them."""

    def add(f):
        QUERIES[f"strategy_{name}_result"] = lambda spark, folder: f(spark, folder).groupBy("key").agg(F.count("*").alias("n"), F.sum("result").alias("total"))
        ORACLES[f"strategy_{name}_result"] = SHARED
        return f

    return add


def _probe(spark, folder):
    return X.zipf_probe(spark, folder, 1.0), X.part_store(spark, folder)


def _coin():
    return F.pmod(portable_hash(F.concat("row_id", F.lit("!"))), F.lit(2))


@strategy("naive_fetch")
def naive_fetch(spark, folder):
    """One blocking fetch for each access, through the store client."""
    from adaptivejoin.sources.prefetch import AccessMode
    from adaptivejoin.sources.store import client_join

    return client_join(spark, folder, AccessMode("sync", 1, 1))


@strategy("batched_fetch")
def batched_fetch(spark, folder):
    p, s = _probe(spark, folder)
    return joins.fetch_join(p, s, "key", "skey", X.PART_CALL, dedupe=False)


@strategy("always_ship")
def always_ship(spark, folder):
    p, s = _probe(spark, folder)
    return joins.ship_join(p, s, "key", "skey", X.PART_CALL)


@strategy("coin_flip")
def coin_flip(spark, folder):
    """Half of the accesses ship, by a hash of the row, so that a repeated task decides alike."""
    p, s = _probe(spark, folder)
    far = joins.ship_join(p.where(_coin() == 0), s, "key", "skey", X.PART_CALL)
    return far.unionByName(joins.fetch_join(p.where(_coin() == 1), s, "key", "skey", X.PART_CALL, dedupe=False))


@strategy("cache_only")
def cache_only(spark, folder):
    return core.adaptive(spark, folder)


def batched_ships(routed: DataFrame, profile: CostProfile) -> DataFrame:
    """What of the routed rows ships, in batches of its lane and home, with the other work of the lanes up to each row."""
    ships = balance.with_lane_work(routed, X.SEQ, profile).where(F.col("route") == "ship")
    return batching.by_size(routing.assign_home(ships, "key", S.HOMES), ("lane", "home"), X.SEQ, S.BATCH)


def split_join(routed: DataFrame, store: DataFrame) -> DataFrame:
    """Shipped calls in batches; of each batch the owner computes ``d`` and sends the values of the others back to their lanes. The
    routed rows are narrow and are saved once: four steps read them."""
    routed = spooled(routed.select("row_id", "key", "qty", "lane", *X.SEQ, "route", "value_bytes"), "routed")
    rows = batched_ships(routed, core.PROFILE)
    place = (F.row_number().over(W.partitionBy("lane", "home").orderBy(*X.SEQ)) - 1) % S.BATCH + 1
    rows = spooled(rows.withColumn("in_batch", place), "batched")
    d = balance.split_exact(balance.batch_lines(rows, core.PROFILE)).select("lane", "home", "batch_no", "d")
    rows = rows.join(d, ["lane", "home", "batch_no"])
    keep = ["row_id", "key", "qty", "lane"]
    at_home = joins.ship_join(rows.where("in_batch <= d").select(*keep), store, "key", "skey", X.PART_CALL)
    back = joins.fetch_join(rows.where("in_batch > d").select(*keep), store, "key", "skey", X.PART_CALL, dedupe=False)
    near = joins.fetch_join(routed.where(F.col("route") != "ship").select(*keep), store, "key", "skey", X.PART_CALL)
    return at_home.unionByName(back).unionByName(near)


@strategy("split_only")
def split_only(spark, folder):
    rows = core.priced(spark, folder, 1.0).withColumn("route", F.lit("ship"))
    return split_join(rows, X.part_store(spark, folder))


@strategy("full_adaptive")
def full_adaptive(spark, folder):
    """Routing by frequency, and the split of what ships."""
    return split_join(core.trace(spark, folder), X.part_store(spark, folder))


@strategy("frozen_adaptive")
def frozen_adaptive(spark, folder):
    """Decisions of the first tenth are kept; what ships is still split."""
    return split_join(core.frozen(spark, folder, 1.0, False), X.part_store(spark, folder))


@strategy("plain_reduce")
def plain_reduce(spark, folder):
    p, s = _probe(spark, folder)
    return joins.keyed_join(p, s, "key", "skey", X.PART_CALL, hint="shuffle_hash")


def _heavy(spark, folder, weight, least, sample=None):
    p, s = _probe(spark, folder)
    return joins.heavy_hitter_join(p, s, "key", "skey", X.PART_CALL, weight, least, sample)


@strategy("cost_aware_replicate")
def cost_aware_replicate(spark, folder):
    """Known statistics: a key's frequency times the cost of its calls, here the bytes that a call reads. A key is heavy if it has one
    in so many of the bytes of all calls."""
    p, s = _probe(spark, folder)
    per = p.groupBy("key").agg(F.count("*").alias("n")).join(s.select("skey", "value_bytes"), F.col("key") == F.col("skey"))
    cost = spooled(per.select(F.col("key").alias("of"), (F.col("n") * F.col("value_bytes")).alias("bytes")), "costs")
    least = max(1, (cost.agg(F.sum("bytes")).first()[0] or 0) // HEAVY_SHARE)
    heavy = cost.where(F.col("bytes") >= least).select("of")
    marked = p.join(F.broadcast(heavy), F.col("key") == F.col("of"), "left")  # at most HEAVY_SHARE keys are heavy
    return joins.heavy_hitter_join(marked.withColumn("heavy", F.col("of").isNotNull()).drop("of"), s, "key", "skey", X.PART_CALL, F.max(F.col("heavy").cast("int")), 1).drop("heavy")


@strategy("full_stats_heavy_hitter")
def full_stats_heavy_hitter(spark, folder):
    return _heavy(spark, folder, F.count("*"), max(1, table(spark, folder, "lineitem").count() // HEAVY_SHARE))


@strategy("sampled_heavy_hitter")
def sampled_heavy_hitter(spark, folder):
    """Frequencies from a tenth of the accesses."""
    sample = F.pmod(portable_hash(F.concat("row_id", F.lit("?"))), F.lit(10)) == 0
    return _heavy(spark, folder, F.count("*"), max(1, table(spark, folder, "lineitem").count() // HEAVY_SHARE // 10), sample)


@strategy("sql_engine_join")
def sql_engine_join(spark, folder):
    p, s = _probe(spark, folder)
    p.createOrReplaceTempView("strategy_probe")
    s.createOrReplaceTempView("strategy_store")
    return spark.sql("SELECT row_id, key, (key * 31 + qty * 7 + p_size * CAST(floor(p_retailprice) AS BIGINT)) % 1000003 AS result FROM strategy_probe JOIN strategy_store ON key = skey")


@strategy("salted_join")
def salted_join(spark, folder):
    p, s = _probe(spark, folder)
    return joins.salted_join(p, s, "key", "skey", X.PART_CALL, portable_hash(F.col("row_id")), SALTS)


# Modelled times

LOADS = {"data_heavy": (DATA_HEAVY, 100_000), "compute_heavy": (COMPUTE_HEAVY, 1_000), "both_heavy": (BOTH_HEAVY, 100_000)}
ROUTES = ("naive_fetch", "batched_fetch", "always_ship", "coin_flip", "cache_only")
SPLITS = ("split_only", "full_adaptive", "frozen_adaptive")
#: The reduce-side plan has the callers' nodes for its reducers as well.
REDUCERS = S.LANES + S.HOMES


def _transfers(p: CostProfile, value: int) -> tuple[int, int]:
    """Time on the wire of a value and of a shipped call with its result."""
    return -(-(value + p.key_bytes) // p.bandwidth), -(-(p.result_bytes + p.key_bytes + p.param_bytes) // p.bandwidth)


def _split_time_sql(name: str, p: CostProfile, value: int, routed: str) -> tuple[str, str]:
    """(relations, select) of a strategy that splits its shipped batches."""
    val, res = _transfers(p, value)
    over = f"OVER (PARTITION BY lane ORDER BY {S.SEQ} ROWS UNBOUNDED PRECEDING)"
    work = f"""{name}_work AS (SELECT *, CAST({S.h("CAST(key AS VARCHAR)")} % {S.HOMES} AS INTEGER) AS home, CAST(sum(CASE WHEN route <> 'ship' THEN 1 ELSE 0 END) {over} AS BIGINT) AS local_before,
  CAST(sum(CASE WHEN route = 'fetch' THEN {p.key_bytes} + value_bytes ELSE 0 END) {over} AS BIGINT) AS asked_before FROM {routed}),
{name}_ships AS (SELECT *, (row_number() OVER (PARTITION BY lane, home ORDER BY {S.SEQ}) - 1) // {S.BATCH} AS batch_no FROM {name}_work WHERE route = 'ship'),
{K.batches_sql(p, f"{name}_ships", f"{name}_tried")},
{name}_parts AS (SELECT lane, home, (b - d) * {p.lane_cpu_us} AS cpu_l, d * {p.home_cpu_us} AS cpu_h, b * {p.home_disk_us} AS disk, d * {res} + (b - d) * {val} AS net
    FROM (SELECT lane, home, b, arg_min(d, time * 1000 + d) AS d FROM {name}_tried GROUP BY lane, home, batch_no, b)
  UNION ALL SELECT lane, home, {p.lane_cpu_us}, 0, CASE WHEN route = 'fetch' THEN {p.home_disk_us} ELSE 0 END, CASE WHEN route = 'fetch' THEN {val} ELSE 0 END FROM {name}_work WHERE route <> 'ship')"""
    lanes = f"(SELECT max(x) FROM (SELECT greatest(sum(cpu_l), sum(net)) AS x FROM {name}_parts GROUP BY lane))"
    homes = f"(SELECT max(x) FROM (SELECT greatest(sum(cpu_h), sum(net), sum(disk)) AS x FROM {name}_parts GROUP BY home))"
    return work, f"SELECT '{name}' AS strategy, CAST(greatest({lanes}, {homes}) AS BIGINT) AS time_us"


def _time_sql(p: CostProfile, value: int, z: float) -> str:
    val, res = _transfers(p, value)
    c = S.costs(p, str(value))
    ships = {"naive_fetch": "false", "batched_fetch": "false", "always_ship": "true", "coin_flip": "coin = 0", "cache_only": "route = 'ship'"}
    parts = []
    for name in ROUTES:
        store = "route <> 'local'" if name == "cache_only" else "true"
        net = f"CASE WHEN {ships[name]} THEN {res} WHEN {store} THEN {val} ELSE 0 END"
        cpu_l, cpu_h, disk = f"CASE WHEN {ships[name]} THEN 0 ELSE {p.lane_cpu_us} END", f"CASE WHEN {ships[name]} THEN {p.home_cpu_us} ELSE 0 END", f"CASE WHEN {store} THEN {p.home_disk_us} ELSE 0 END"
        lane = f"sum({cpu_l}) + sum({net}) + sum({disk})" if name == "naive_fetch" else f"greatest(sum({cpu_l}), sum({net}))"
        parts.append(f"SELECT '{name}' AS strategy, CAST(greatest((SELECT max(x) FROM (SELECT {lane} AS x FROM t GROUP BY lane)), (SELECT max(x) FROM (SELECT greatest(sum({cpu_h}), sum({net}), sum({disk})) AS x FROM t GROUP BY home))) AS BIGINT) AS time_us")
    splits = [_split_time_sql(n, p, value, r) for n, r in zip(SPLITS, ("all_ship", "routed", "frozen"), strict=True)]
    reducer = f"SELECT {S.h('CAST(key AS VARCHAR)')} % {REDUCERS} AS node, key, count(*) AS n FROM probe GROUP BY key"
    parts += [x for _, x in splits]
    parts.append(f"SELECT 'plain_reduce' AS strategy, CAST(max(greatest(cpu, net, disk)) AS BIGINT) AS time_us FROM (SELECT sum(n) * {p.home_cpu_us} AS cpu, sum(n) * {res} + count(*) * {val} AS net, count(*) * {p.home_disk_us} AS disk FROM ({reducer}) GROUP BY node)")
    return f"""WITH {S.probe(z)}, priced AS (SELECT *, CAST({value} AS BIGINT) AS value_bytes, {c['rent']} AS rent, {c['buy']} AS buy, {c['mem']} AS use FROM probe),
counted AS (SELECT *, row_number() OVER (PARTITION BY lane, key ORDER BY {S.SEQ}) AS c, {S.threshold('rent', 'buy', 'use')} AS m FROM priced),
routed AS (SELECT *, CASE WHEN c <= m THEN 'ship' WHEN c = m + 1 THEN 'fetch' ELSE 'local' END AS route FROM counted),
all_ship AS (SELECT *, 'ship' AS route FROM priced), {core.FROZEN},
t AS (SELECT lane, {S.h("CAST(key AS VARCHAR)")} % {S.HOMES} AS home, {S.h("row_id || '!'")} % 2 AS coin, route FROM routed),
{', '.join(w for w, _ in splits)}
{' UNION ALL '.join(parts)}"""


def modelled(spark, folder, load: str, z: float) -> DataFrame:
    p, value = LOADS[load]
    probe = X.zipf_probe(spark, folder, z).select("row_id", "lane", *X.SEQ, "key").withColumn("value_bytes", F.lit(value).cast("long"))
    probe = spooled(probe, "accesses")  # nine strategies read them
    rent, buy, use = p.rent(), p.buy(F.col("value_bytes")), p.use_memory()
    rows = spooled(routing.ski_route(probe, X.ACCESS, rent, buy, use).drop("c"), "routed")
    t = routing.assign_home(rows, "key", S.HOMES).withColumn("coin", _coin()).select("lane", "home", "coin", "route")
    # The five strategies read one aggregate: a row for each combination, not for each access.
    t = t.groupBy("lane", "home", "coin", "route").agg(F.count("*").alias("n"))
    top = table(spark, folder, "lineitem").agg(F.max("l_orderkey")).first()[0] + 1
    frozen = routing.frozen_route(probe, X.ACCESS, rent, buy, use, F.col("l_orderkey") * 10 < top)
    out = node_times(t, p, value)
    for name, routed in zip(SPLITS, (probe.withColumn("route", F.lit("ship")), rows, frozen), strict=True):
        out = out.unionByName(split_time(routed, p, value).select(F.lit(name).alias("strategy"), "time_us"))
    return out.unionByName(reduce_time(probe, p, value).select(F.lit("plain_reduce").alias("strategy"), "time_us"))


def _busiest(parts: DataFrame) -> DataFrame:
    """time_us of the busiest resource, from the work of (lane, home) pairs."""
    sums = parts.groupBy("lane", "home").agg(*[F.sum(c).alias(c) for c in ("cpu_l", "cpu_h", "disk", "net")])
    lanes = sums.groupBy("lane").agg(F.greatest(F.sum("cpu_l"), F.sum("net")).alias("x")).agg(F.max("x").alias("a"))
    homes = sums.groupBy("home").agg(F.greatest(F.sum("cpu_h"), F.sum("net"), F.sum("disk")).alias("x")).agg(F.max("x").alias("b"))
    return lanes.crossJoin(homes).select(F.greatest("a", "b").cast("long").alias("time_us"))


def split_time(routed: DataFrame, p: CostProfile, value: int) -> DataFrame:
    """Modelled time when what ships is split batch by batch."""
    val, res = _transfers(p, value)
    d = balance.split_exact(balance.batch_lines(batched_ships(routed, p), p))
    back = F.col("b") - F.col("d")
    split = d.select("lane", "home", (back * p.lane_cpu_us).alias("cpu_l"), (F.col("d") * p.home_cpu_us).alias("cpu_h"), (F.col("b") * p.home_disk_us).alias("disk"), (F.col("d") * res + back * val).alias("net"))
    own = routing.assign_home(routed.where("route != 'ship'"), "key", S.HOMES).groupBy("lane", "home").agg(F.count("*").alias("n"), F.count_if(F.col("route") == "fetch").alias("fetched"))
    own = own.select("lane", "home", (F.col("n") * p.lane_cpu_us).alias("cpu_l"), F.lit(0).cast("long").alias("cpu_h"), (F.col("fetched") * p.home_disk_us).alias("disk"), (F.col("fetched") * val).alias("net"))
    return _busiest(split.unionByName(own))


def reduce_time(probe: DataFrame, p: CostProfile, value: int) -> DataFrame:
    """Modelled time when accesses and values are dealt by key over all nodes."""
    val, res = _transfers(p, value)
    keys = routing.assign_home(probe, "key", REDUCERS).groupBy("home", "key").agg(F.count("*").alias("n"))
    nodes = keys.groupBy("home").agg(F.greatest(F.sum("n") * p.home_cpu_us, F.sum("n") * res + F.count("*") * val, F.count("*") * p.home_disk_us).alias("x"))
    return nodes.agg(F.max("x").cast("long").alias("time_us"))


def node_times(t: DataFrame, p: CostProfile, value: int) -> DataFrame:
    val, res = _transfers(p, value)
    rows = t.withColumn("strategy", F.explode(F.array(*[F.lit(x) for x in ROUTES])))
    s = F.col("strategy")
    ship = (s == "always_ship") | ((s == "coin_flip") & (F.col("coin") == 0)) | ((s == "cache_only") & (F.col("route") == "ship"))
    store = (s != "cache_only") | (F.col("route") != "local")
    n = F.col("n")
    rows = rows.select(s.alias("strategy"), "lane", "home", (n * F.when(ship, 0).otherwise(p.lane_cpu_us)).alias("cpu_l"), (n * F.when(ship, p.home_cpu_us).otherwise(0)).alias("cpu_h"), (n * F.when(store, p.home_disk_us).otherwise(0)).alias("disk"), (n * F.when(ship, res).when(store, val).otherwise(0)).alias("net"))
    total = lambda *c: [F.sum(x).alias(x) for x in c]
    serial = F.col("cpu_l") + F.col("net") + F.col("disk")
    lanes = rows.groupBy("strategy", "lane").agg(*total("cpu_l", "net", "disk")).groupBy("strategy").agg(F.max(F.when(F.col("strategy") == "naive_fetch", serial).otherwise(F.greatest("cpu_l", "net"))).alias("a"))
    homes = rows.groupBy("strategy", "home").agg(*total("cpu_h", "net", "disk")).groupBy("strategy").agg(F.max(F.greatest("cpu_h", "net", "disk")).alias("b"))
    return lanes.join(homes, "strategy").select("strategy", F.greatest("a", "b").cast("long").alias("time_us"))


def _times(load: str, z: float) -> None:
    @query(f"strategy_time_{load}_z{str(z).replace('.', '')}", _time_sql(*LOADS[load], z))
    def times(spark, folder):
        return modelled(spark, folder, load, z)


def _normalised(load: str) -> None:
    each = " UNION ALL ".join(f"SELECT CAST({z} AS DOUBLE) AS z, strategy, time_us FROM ({_time_sql(*LOADS[load], z)})" for z in SKEWS)

    @query(f"normalised_time_{load}", f"WITH every_time AS ({each}) SELECT z, strategy, time_us * 1000 // (SELECT time_us FROM every_time WHERE z = 0 AND strategy = 'naive_fetch') AS permille FROM every_time")
    def normalised(spark, folder):
        """Times of all strategies and skews over that of naive fetching without skew, in thousandths."""
        every = None
        for z in SKEWS:
            one = modelled(spark, folder, load, z).withColumn("z", F.lit(z))
            every = one if every is None else every.unionByName(one)
        every = spooled(every, "times")
        unit = every.where("z = 0 and strategy = 'naive_fetch'").select(F.col("time_us").alias("unit"))
        return every.crossJoin(F.broadcast(unit)).select("z", "strategy", F.floor(F.col("time_us") * 1000 / F.col("unit")).cast("long").alias("permille"))


for _load in LOADS:
    _normalised(_load)
for _load in LOADS:
    for _z in SKEWS:
        _times(_load, _z)


@query("bytes_moved", f"WITH {S.routed(core.PROFILE, 1.0)} SELECT route, count(*) AS requests, CAST(sum(CASE route WHEN 'ship' THEN 104 WHEN 'fetch' THEN value_bytes + 8 ELSE 0 END) AS BIGINT) AS bytes FROM trace GROUP BY route")
def bytes_moved(spark, folder):
    """Requests and bytes by kind."""
    p = core.PROFILE
    size = F.when(F.col("route") == "ship", p.key_bytes + p.param_bytes + p.result_bytes).when(F.col("route") == "fetch", F.col("value_bytes") + p.key_bytes).otherwise(0)
    return core.trace(spark, folder).groupBy("route").agg(F.count("*").alias("requests"), F.sum(size).alias("bytes"))


@query("request_counts", f"WITH {S.routed(core.PROFILE, 1.0)} SELECT lane, count(*) FILTER (route = 'ship') AS ship, count(*) FILTER (route = 'fetch') AS fetch, count(*) FILTER (route = 'local') AS local FROM trace GROUP BY lane")
def request_counts(spark, folder):
    n = lambda r: F.count_if(F.col("route") == r).alias(r)
    return core.trace(spark, folder).groupBy("lane").agg(n("ship"), n("fetch"), n("local"))


@query("offline_optimum", f"WITH {S.routed(core.PROFILE, 1.0)}, per AS (SELECT lane, key, count(*) AS n, max(rent) AS r, max(buy) AS b, max(use) AS u FROM trace GROUP BY lane, key) SELECT lane, CAST(sum(least(n * r, b + n * u)) AS BIGINT) AS optimum FROM per GROUP BY lane")
def offline_optimum(spark, folder):
    rent, buy, mem = core.terms()
    per = core.priced(spark, folder, 1.0).groupBy("lane", "key").agg(F.count("*").alias("n"), F.max("value_bytes").alias("value_bytes"))
    return per.groupBy("lane").agg(F.sum(routing.offline_optimum(rent, buy, mem, F.col("n"))).alias("optimum"))


def pack(loads: list[tuple[int, int]], nodes: int) -> dict[int, int]:
    """Partitions on nodes, longest first on the least loaded; a partition is never divided, so a hot key stays whole."""
    import heapq

    heap = [(0, i) for i in range(nodes)]
    out = {}
    for load, p in sorted(((n, p) for p, n in loads), key=lambda x: (-x[0], x[1])):
        total, node = heapq.heappop(heap)
        out[p] = node
        heapq.heappush(heap, (total + load, node))
    return out


@query("partition_migration")
def partition_migration(spark, folder):
    """Whole partitions moved to even out owners: 64 partitions, a fixed number, on 8 nodes."""
    loads = X.zipf_probe(spark, folder, 1.5).groupBy(F.pmod(portable_hash(F.col("key")), F.lit(64)).cast("int").alias("p")).agg(F.count("*").alias("n")).collect()
    placed = pack([(r.p, r.n) for r in loads], S.HOMES)
    rows = [(r.p, placed[r.p], r.n) for r in loads]
    return spark.createDataFrame(rows, "part int, node int, n long").groupBy("node").agg(F.sum("n").alias("load"))
