"""A two-tier cache with byte budgets, and the order in which it gives up what it holds."""

from __future__ import annotations

import heapq
from dataclasses import dataclass, field


@dataclass(frozen=True)
class CacheBudget:
    memory: int
    disk: int


class Priorities:
    """Benefit of keys. ``lfu_da``: the cache's age plus the count, with a weight; ``lfu``: the count; ``lru``: the last access."""

    def __init__(self, mode: str = "lfu_da", weight: str = "unit"):
        if mode not in ("lfu_da", "lfu", "lru") or weight not in ("unit", "cost", "cost_per_byte"):
            raise ValueError(f"unknown policy {mode}, {weight}")
        self.mode, self.weight, self.age, self.clock = mode, weight, 0.0, 0

    def of(self, count: int, gain: float = 1.0, size: int = 1) -> float:
        self.clock += 1
        if self.mode == "lru":
            return float(self.clock)
        worth = {"unit": 1.0, "cost": gain, "cost_per_byte": gain / max(size, 1)}[self.weight]
        return (self.age if self.mode == "lfu_da" else 0.0) + count * worth

    def gave_up(self, priority: float) -> None:
        """What is given up sets the age, so that keys that were frequent long ago lose to recent ones."""
        if self.mode == "lfu_da":
            self.age = max(self.age, priority)


@dataclass
class Tier:
    """Resident keys with sizes and priorities; the heap may hold outdated entries, which are skipped."""

    budget: int
    sizes: dict = field(default_factory=dict)
    priority: dict = field(default_factory=dict)
    heap: list = field(default_factory=list)
    used: int = 0

    def __contains__(self, key) -> bool:
        return key in self.sizes

    def put(self, key, size: int, priority: float) -> None:
        self.remove(key)
        self.sizes[key] = size
        self.used += size
        self.touch(key, priority)

    def touch(self, key, priority: float) -> None:
        self.priority[key] = priority
        heapq.heappush(self.heap, (priority, key))
        if len(self.heap) > 64 + 4 * len(self.sizes):
            self.heap = [(p, k) for k, p in self.priority.items()]
            heapq.heapify(self.heap)

    def remove(self, key) -> None:
        if key in self.sizes:
            self.used -= self.sizes.pop(key)
            del self.priority[key]

    def victims(self, need: int, below: float) -> list | None:
        """The least valuable residents that free ``need`` bytes, all under ``below``; None if there aren't enough."""
        out, free, put_back = [], self.budget - self.used, []
        while free < need:
            while self.heap and self.priority.get(self.heap[0][1]) != self.heap[0][0]:
                heapq.heappop(self.heap)
            if not self.heap or self.heap[0][0] >= below:
                out = None
                break
            entry = heapq.heappop(self.heap)
            put_back.append(entry)
            if entry[1] in out:
                continue
            out.append(entry[1])
            free += self.sizes[entry[1]]
        for entry in put_back:
            heapq.heappush(self.heap, entry)
        return out


class TwoTierCache:
    """Memory first; what memory gives up goes to disk, and what disk gives up is gone."""

    def __init__(self, budget: CacheBudget, policy: Priorities):
        self.memory, self.disk, self.policy = Tier(budget.memory), Tier(budget.disk), policy
        self.evicted = self.promoted = self.demoted = 0

    def discard(self, key) -> None:
        self.memory.remove(key)
        self.disk.remove(key)

    def admit(self, key, size: int, priority: float) -> bool:
        """Whether the key goes into memory: free bytes suffice, or residents of strictly lower priority free enough."""
        if size > self.memory.budget:
            return False
        out = self.memory.victims(size, priority)
        if out is None:
            return False
        self.disk.remove(key)
        for k in out:
            s, p = self.memory.sizes[k], self.memory.priority[k]
            self.memory.remove(k)
            self.policy.gave_up(p)
            self.demoted += 1
            self.to_disk(k, s, p)
        self.memory.put(key, size, priority)
        return True

    def to_disk(self, key, size: int, priority: float) -> bool:
        if size > self.disk.budget:
            self.evicted += 1
            return False
        out = self.disk.victims(size, float("inf"))
        for k in out or ():
            self.policy.gave_up(self.disk.priority[k])
            self.disk.remove(k)
            self.evicted += 1
        self.disk.put(key, size, priority)
        return True
