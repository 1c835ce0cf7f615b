"""Routing with a bounded cache: a fold over the accesses of each lane.

Lanes are independent, so they are dealt over the tasks; a lane's rows stream past in order and only its counters and cache
residents are held. Residents are bounded by the budget, counters by ``eps``; exact counts (no ``eps``) grow with the keys of a
lane and are there for comparison. A task may hold several lanes, one after the other.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adaptivejoin.functions.costs import CostProfile
from adaptivejoin.operators.cache import CacheBudget, Priorities, TwoTierCache
from adaptivejoin.operators.frequency import ExactCounter, LossyCounter
from adaptivejoin.operators.routing import Access

LOCAL_MEM, LOCAL_DISK, FETCH_MEM, FETCH_DISK, SHIP = "local_mem", "local_disk", "fetch_mem", "fetch_disk", "ship"


@dataclass(frozen=True)
class RouterOptions:
    budget: CacheBudget
    policy: str = "lfu_da"
    weight: str = "unit"
    eps: float | None = None  # None: exact counts
    first_ships: bool = True


class LaneRouter:
    """Decides the accesses of one lane one after the other."""

    def __init__(self, options: RouterOptions):
        self.options = options
        self.policy = Priorities(options.policy, options.weight)
        self.cache = TwoTierCache(options.budget, self.policy)
        self.counter = ExactCounter() if options.eps is None else LossyCounter(options.eps)
        self.updated: dict = {}

    def invalidate(self, key) -> None:
        """An update of the stored value: a bought copy is discarded, a rented key is new again."""
        self.cache.discard(key)
        self.counter.reset(key)

    def decide(self, key, size: int, rent: int, buy: int, use_mem: int, use_disk: int, updated_at=None) -> str:
        """Route of an access. ``updated_at`` is the value's time of change that a reply would carry: a count that was begun before
        it is set back once a reply shows it."""
        cache, count = self.cache, self.counter.add(key)
        priority = self.policy.of(count, rent - use_mem, size)
        if key in cache.memory:
            cache.memory.touch(key, priority)
            return LOCAL_MEM
        if key in cache.disk:
            cache.disk.touch(key, priority)
            if cache.admit(key, size, priority):
                cache.promoted += 1
            return LOCAL_DISK
        route = self._miss(key, size, count, rent, buy, use_mem, use_disk, priority)
        if route == SHIP and updated_at is not None:
            if self.updated.get(key, updated_at) != updated_at:
                self.counter.reset(key)
                self.counter.add(key)
            self.updated[key] = updated_at
            if len(self.updated) > 2 * len(self.counter.table) + 1024:  # times of keys that are no longer counted
                self.updated = {k: v for k, v in self.updated.items() if k in self.counter.table}
        return route

    def _miss(self, key, size, count, rent, buy, use_mem, use_disk, priority) -> str:
        if self.options.first_ships and count == 1:
            return SHIP
        eager = self.options.first_ships and buy <= rent and rent > use_mem
        if not eager and (rent <= use_mem or count * (rent - use_mem) <= buy):
            return SHIP
        if self.cache.admit(key, size, priority):
            return FETCH_MEM
        if (not eager or rent <= use_disk) and (rent <= use_disk or count * (rent - use_disk) <= buy):
            return SHIP
        if size <= self.cache.disk.budget and self.cache.to_disk(key, size, priority):
            return FETCH_DISK
        return SHIP


def tiered_route(priced: DataFrame, access: Access, profile: CostProfile, budget: CacheBudget, policy: str = "lfu_da", weight: str = "unit", eps: float | None = None, size: str = "value_bytes") -> DataFrame:
    """(lane, key, seq columns, route) of every access under a bounded cache; ``size`` is the value's bytes."""
    options = RouterOptions(budget, policy, weight, eps)
    n = int(priced.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    cols = [F.col(access.lane).cast("int").alias("lane"), F.col(access.key).cast("long").alias("key"), F.col(size).cast("long").alias("size"), profile.rent().alias("rent"), profile.buy(F.col(size)).alias("buy"), profile.use_memory().alias("mem"), profile.use_disk().alias("disk")]
    rows = priced.select(*cols, *access.seq).repartition(n, "lane").sortWithinPartitions("lane", *access.seq)
    kinds = ", ".join(f"{c} {priced.schema[c].dataType.simpleString()}" for c in access.seq)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lane, router = None, None
        for batch in batches:
            routes = []
            for lane_, *row in zip(*(batch.column(i).to_pylist() for i in range(7)), strict=True):
                if lane_ != lane:
                    lane, router = lane_, LaneRouter(options)
                routes.append(router.decide(*row))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), *(batch.column(i) for i in range(7, batch.num_columns)), pa.array(routes)], names=["lane", "key", "size", *access.seq, "route"])

    return rows.mapInArrow(run, f"lane int, key long, size long, {kinds}, route string")
