"""Where each access is computed: rent or buy by frequency, without statistics known beforehand.

Routes depend on earlier accesses of the same key in the same lane only, so lanes decide independently and a hot key is spread
over all of them: no window is partitioned by the key alone.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from adaptivejoin.functions.hashing import portable_hash

SHIP, FETCH, LOCAL = "ship", "fetch", "local"
NEVER = (1 << 62) - 1


@dataclass(frozen=True)
class Access:
    """Columns of a probe: its key, its lane, and its order within the lane."""

    key: str = "key"
    lane: str = "lane"
    seq: tuple[str, ...] = ("seq",)


def reserved(df: DataFrame, *names: str) -> None:
    """Refuse a relation whose own columns an operator would overwrite."""
    taken = [n for n in names if n in df.columns]
    if taken:
        raise ValueError(f"columns {taken} are set here: rename the relation's own")


def assign_lanes(df: DataFrame, lanes: int, by: Column) -> DataFrame:
    """A lane for each row, evenly, by a hash of the row's identity."""
    reserved(df, "lane")
    return df.withColumn("lane", F.pmod(portable_hash(by), F.lit(lanes)).cast("int"))


def assign_home(df: DataFrame, key: str, homes: int) -> DataFrame:
    return df.withColumn("home", F.pmod(portable_hash(F.col(key)), F.lit(homes)).cast("int"))


def relane(df: DataFrame, schedule: list[tuple[int, int]], seq: str, by: Column) -> DataFrame:
    """Lanes that change during the run: from each position on, so many lanes. A new lane starts with a cold cache."""
    lane = F.lit(None).cast("int")
    for start, lanes in schedule:
        lane = F.when(F.col(seq) >= start, F.pmod(portable_hash(by), F.lit(lanes)).cast("int")).otherwise(lane)
    return df.withColumn("lane", lane)


def threshold(rent: Column, buy: Column, use: Column, first_ships: bool = True) -> Column:
    """How many accesses are rented before the buy: while ``c * (rent - use) <= buy``. Never buy if renting isn't dearer than using;
    the first call always ships, as it brings the key's costs; after it a value that isn't dearer than a call is fetched."""
    gap = F.when(rent > use, rent - use)
    by_cost = F.when(rent <= use, F.lit(NEVER)).otherwise(F.floor(buy / gap).cast("long"))
    if not first_ships:
        return by_cost
    return F.when(rent <= use, F.lit(NEVER)).when(buy <= rent, F.lit(1)).otherwise(F.greatest(by_cost, F.lit(1))).cast("long")


def ski_route(probe: DataFrame, access: Access, rent: Column, buy: Column, use: Column, first_ships: bool = True, epoch: tuple[str, ...] = ()) -> DataFrame:
    """``probe`` with the access count ``c`` and the ``route``: ship, then fetch once, then local."""
    reserved(probe, "c", "route")
    order = W.partitionBy(access.lane, access.key, *epoch).orderBy(*access.seq)
    m = threshold(rent, buy, use, first_ships)
    c = F.col("c")
    return probe.withColumn("c", F.row_number().over(order).cast("long")).withColumn("route", F.when(c <= m, SHIP).when(c == m + 1, FETCH).otherwise(LOCAL))


def online_route(probe: DataFrame, stored: DataFrame, access: Access, stored_key: str, size: str, rent: Column, buy: Column, use: Column) -> DataFrame:
    """Routes without knowing anything beforehand. The first call of a key in a lane ships and its reply brings the value's size,
    from which ``rent``, ``buy`` and ``use`` follow (expressions over ``size``). So only one row of each (lane, key) with a second
    access meets the store, and only its narrow size column; keys that the store lacks always ship."""
    reserved(probe, "c", "route")
    order = W.partitionBy(access.lane, access.key).orderBy(*access.seq)
    counted = probe.withColumn("c", F.row_number().over(order).cast("long"))
    again = counted.where((F.col("c") == 2) & F.col(access.key).isNotNull()).select(F.col(access.lane).alias("__lane"), F.col(access.key).alias("__key"))
    sizes = stored.select(F.col(stored_key).alias("__stored"), F.col(size).alias(size))
    replies = again.join(sizes, F.col("__key") == F.col("__stored")).select("__lane", "__key", threshold(rent, buy, use).alias("__m"))
    known = counted.join(replies, (F.col(access.lane) == F.col("__lane")) & (F.col(access.key) == F.col("__key")), "left")
    route = F.when(F.col("__m").isNull() | (F.col("c") <= F.col("__m")), SHIP).when(F.col("c") == F.col("__m") + 1, FETCH).otherwise(LOCAL)
    return known.withColumn("route", route).drop("__lane", "__key", "__m")


def route_cost(rent: Column, buy: Column, use: Column) -> Column:
    """What an access on its route costs; the access that buys also uses the value."""
    return F.when(F.col("route") == SHIP, rent).when(F.col("route") == FETCH, buy + use).otherwise(use)


def offline_optimum(rent: Column, buy: Column, use: Column, n: Column) -> Column:
    """The least cost of ``n`` accesses if their number were known."""
    return F.least(n * rent, buy + n * use)


def with_epochs(accesses: DataFrame, updates: DataFrame, key: str, at: str, updated_at: str) -> DataFrame:
    """``accesses`` with the number of updates of their key up to their time: a union and a running count, no range join."""
    a = accesses.withColumn("__update", F.lit(0))
    u = updates.select(F.col(key), F.col(updated_at).alias(at), F.lit(1).alias("__update"))
    both = a.unionByName(u, allowMissingColumns=True)
    w = W.partitionBy(key).orderBy(at, F.col("__update").desc()).rowsBetween(W.unboundedPreceding, 0)
    return both.withColumn("epoch", F.sum("__update").over(w)).where("__update = 0").drop("__update")


def route_with_updates(accesses: DataFrame, access: Access, rent: Column, buy: Column, use: Column, reset: bool = True) -> DataFrame:
    """Routes when updates discard bought values (column ``epoch``). With ``reset`` an update also sets the count back; without,
    a key past its threshold is bought again at its first access in each epoch."""
    if reset:
        return ski_route(accesses, access, rent, buy, use, epoch=("epoch",))
    routed = ski_route(accesses, access, rent, buy, use)
    m = threshold(rent, buy, use)
    past = W.partitionBy(access.lane, access.key, "epoch").orderBy(*access.seq).rowsBetween(W.unboundedPreceding, -1)
    bought = F.coalesce(F.max((F.col("c") > m).cast("int")).over(past), F.lit(0))
    return routed.withColumn("route", F.when(F.col("c") <= m, SHIP).when(bought == 0, FETCH).otherwise(LOCAL))


def frozen_route(probe: DataFrame, access: Access, rent: Column, buy: Column, use: Column, learning: Column) -> DataFrame:
    """Decide on the rows where ``learning`` holds, then keep the set of bought keys: they stay local, all others ship."""
    marked = probe.withColumn("__learn", learning)
    early = ski_route(marked.where("__learn"), access, rent, buy, use)
    late = marked.where("not __learn")
    bought = early.where(F.col("route") == FETCH).select(access.lane, access.key).distinct().withColumn("__bought", F.lit(True))
    late = late.join(bought, [access.lane, access.key], "left").withColumn("route", F.when(F.col("__bought"), LOCAL).otherwise(SHIP)).withColumn("c", F.lit(None).cast("long")).drop("__bought")
    return early.unionByName(late).drop("__learn")
