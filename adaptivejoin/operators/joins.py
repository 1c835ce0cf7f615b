"""Joins of a probe with a stored relation, by fetching values, by shipping calls, or by both."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from adaptivejoin.operators.routing import FETCH, SHIP, Access


@dataclass(frozen=True)
class CallSpec:
    """A function of (key, parameters, value): ``result`` builds its column from the joined row; it must be deterministic.

    ``value`` names the stored columns it reads, so that nothing else travels. A call that cannot run at the data is not
    ``pushable`` and is always fetched for.
    """

    value: tuple[str, ...]
    result: Callable[[], Column]
    name: str = "result"
    pushable: bool = True
    deterministic: bool = field(default=True)

    def __post_init__(self):
        if not self.deterministic:
            raise ValueError("a call without side effects must give equal results wherever and however often it runs")


def lookup(*value: str) -> CallSpec:
    """The empty call: the stored value itself."""
    return CallSpec(value, lambda: F.struct(*value), "value")


def _stored(stored: DataFrame, key: str, call: CallSpec) -> DataFrame:
    return stored.select(F.col(key).alias("__key"), *call.value)


def _finish(joined: DataFrame, probe: DataFrame, call: CallSpec, how: str) -> DataFrame:
    if how in ("left_semi", "left_anti"):
        return joined.select(*probe.columns)
    result = call.result()
    if how == "left":
        result = F.when(F.col("__key").isNotNull(), result)
    return joined.select(*[F.col(c) for c in probe.columns], result.alias(call.name))


def keyed_join(probe: DataFrame, stored: DataFrame, key: str, stored_key: str, call: CallSpec, how: str = "inner", hint: str | None = None) -> DataFrame:
    """The plain join; which algorithm runs is left to the planner, or to a hint."""
    right = _stored(stored, stored_key, call)
    right = right.hint(hint) if hint else right
    return _finish(probe.join(right, F.col(key) == F.col("__key"), how), probe, call, how)


def ship_join(probe: DataFrame, stored: DataFrame, key: str, stored_key: str, call: CallSpec, how: str = "inner") -> DataFrame:
    """Calls travel to the owner of their key: both sides are dealt by key and the call runs there. AQE splits a key that is too hot."""
    return keyed_join(probe, stored, key, stored_key, call, how, "merge")


def fetch_join(probe: DataFrame, stored: DataFrame, key: str, stored_key: str, call: CallSpec, how: str = "inner", lane: str = "lane", dedupe: bool = True) -> DataFrame:
    """Values travel to the lanes: each lane's list of distinct keys meets the stored side, and comes back as (lane, key) with the
    value. Without ``dedupe`` every access fetches for itself, as when nothing is kept: its value travels to its lane, and the call
    runs there."""
    if not dedupe:
        right = _stored(stored, stored_key, call).hint("shuffle_hash")
        return _finish(probe.join(right, F.col(key) == F.col("__key"), how).repartition(lane), probe, call, how)
    needs = probe.where(F.col(key).isNotNull()).select(F.col(lane).alias("__lane"), F.col(key).alias("__need"))
    values = needs.distinct().join(_stored(stored, stored_key, call), F.col("__need") == F.col("__key")).drop("__need")
    joined = probe.join(values, (F.col(lane) == F.col("__lane")) & (F.col(key) == F.col("__key")), how)
    return _finish(joined, probe, call, how)


#: The place of a value with its owner, where those of lanes have the lane's number.
OWNER = -1


def adaptive_join(routed: DataFrame, stored: DataFrame, access: Access, stored_key: str, call: CallSpec, how: str = "inner") -> DataFrame:
    """Rows routed to ship meet the value at its owner; the others meet the copy that their lane has bought, which it gets once.

    Both are one join on (place, key), so the probe is read and routed once; the bought keys, one row of each (lane, key), come from
    the same exchange of the routed rows. A hot key's rows are spread over the lanes, what ships of it can be split.
    """
    if not call.pushable:
        return fetch_join(routed, stored, access.key, stored_key, call, how, access.lane)
    lane = F.col(access.lane).cast("int")
    values = _stored(stored, stored_key, call)
    needs = routed.where(F.col("route") == FETCH).select(lane.alias("__place"), F.col(access.key).alias("__need"))
    bought = needs.join(values, F.col("__need") == F.col("__key")).drop("__need")
    copies = values.withColumn("__place", F.lit(OWNER)).unionByName(bought)
    # A frozen router knows keys as local whose purchase is in another part of its input; every route but ship has one in its lane.
    place = F.when(F.col(access.key).isNull() | (F.col("route") == SHIP), F.lit(OWNER)).otherwise(lane)
    return _finish(routed.withColumn("__at", place).join(copies, (F.col("__at") == F.col("__place")) & (F.col(access.key) == F.col("__key")), how), routed, call, how)


def heavy_hitter_join(probe: DataFrame, stored: DataFrame, key: str, stored_key: str, call: CallSpec, weight: Column, least: Column | int, sample: Column | None = None, most_bytes: int = 64 << 20, most_keys: int = 100_000) -> DataFrame:
    """Known statistics: keys whose weight reaches ``least`` are replicated and their rows stay where they are; the rest is dealt by key.

    At most ``total / least`` keys can be heavy. The replicated side is broadcast only where its values are measured to fit
    ``most_bytes`` (and its keys ``most_keys``); otherwise the heavy keys' rows are salted, so no row is lost and none is hot.
    """
    counted = probe.where(sample) if sample is not None else probe
    heavy = counted.where(F.col(key).isNotNull()).groupBy(F.col(key).alias("__heavy")).agg(weight.alias("w")).where(F.col("w") >= least).select("__heavy")
    right = _stored(stored, stored_key, call)
    heavy_values = right.join(heavy, F.col("__key") == F.col("__heavy"), "left_semi")
    found = heavy_values.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.octet_length(F.to_json(F.struct(*call.value)))), F.lit(0)).alias("bytes")).first()
    if found["n"] > most_keys or found["bytes"] > most_bytes:
        return salted_join(probe, stored, key, stored_key, call, F.xxhash64(*probe.columns), 16)
    a = _finish(probe.join(F.broadcast(heavy_values), F.col(key) == F.col("__key")), probe, call, "inner")
    rest = probe.join(F.broadcast(heavy_values.select(F.col("__key").alias("__heavy"))), F.col(key) == F.col("__heavy"), "left_anti")
    return a.unionByName(keyed_join(rest, stored, key, stored_key, call, "inner", "shuffle_hash"))


def salted_join(probe: DataFrame, stored: DataFrame, key: str, stored_key: str, call: CallSpec, salt: Column, salts: int) -> DataFrame:
    """Every key over ``salts`` partitions: stored rows are repeated, probe rows draw one. Both sides are dealt and sorted: the planner
    takes the repeated side for as small as it was, and would send all of it through the driver."""
    right = _stored(stored, stored_key, call).withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)))).hint("merge")
    left = probe.withColumn("__mine", F.pmod(salt, F.lit(salts)).cast("int"))
    return _finish(left.join(right, (F.col(key) == F.col("__key")) & (F.col("__mine") == F.col("__salt"))), probe, call, "inner")


@dataclass(frozen=True)
class Stage:
    """One join of a chain: the stored relation, its key, the probe column that holds the key, the call."""

    stored: DataFrame
    stored_key: str
    key: str
    call: CallSpec
    rent: int = 40
    buy: int = 160
    use: int = 20


def estimated_bytes(df: DataFrame) -> int:
    """The planner's estimate of a relation's size, from file sizes and column types; no job runs."""
    return int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())


def chain_join(probe: DataFrame, stages: list[Stage], lanes: int, by: Column, seq: tuple[str, ...], small: int = 0) -> DataFrame:
    """Left-deep: each stage routes and joins the rows of the one before, with counts of its own. Rows keep their lanes throughout.
    Each stage reads the one before once. With ``small``, a stored side under so many bytes by the planner's estimate goes to every
    lane at once and needs no routing: each would buy all of it after a few accesses."""
    from adaptivejoin.operators.routing import assign_lanes, ski_route

    rows = assign_lanes(probe, lanes, by)
    for s in stages:
        if estimated_bytes(_stored(s.stored, s.stored_key, s.call)) <= small:
            rows = keyed_join(rows, s.stored, s.key, s.stored_key, s.call, hint="broadcast")
            continue
        access = Access(s.key, "lane", seq)
        routed = ski_route(rows, access, F.lit(s.rent), F.lit(s.buy), F.lit(s.use))
        rows = adaptive_join(routed, s.stored, access, s.stored_key, s.call).drop("c", "route")
    return rows


def chain_shuffle(probe: DataFrame, stages: list[Stage]) -> DataFrame:
    """The alternative that deals all rows anew by each stage's key."""
    for s in stages:
        probe = keyed_join(probe, s.stored, s.key, s.stored_key, s.call, "inner", "shuffle_hash")
    return probe
