"""Costs of the two ways to compute a call, in whole microseconds.

*Rent* is to ship a call to the owner of its key; *buy* is to fetch the value; after that a call costs the *use* of the value from
memory or from disk. Stages of asynchronous calls overlap, so the slowest counts; blocking calls add them up.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class CostProfile:
    """Sizes in bytes, bandwidth in bytes a microsecond, times in microseconds."""

    bandwidth: int = 125
    key_bytes: int = 8
    param_bytes: int = 32
    result_bytes: int = 64
    home_disk_us: int = 40
    lane_disk_us: int = 30
    home_cpu_us: int = 24
    lane_cpu_us: int = 20
    overlap: bool = True
    #: The owner's CPU time grows with its backlog over the caller's, up to this factor; 1 switches that off.
    load_feedback: int = 1

    def transfer(self, size: Column) -> Column:
        return F.floor((size + self.bandwidth - 1) / self.bandwidth).cast("long")

    def _both(self, *parts: Column) -> Column:
        if self.overlap:
            return F.greatest(*parts).cast("long")
        total = parts[0]
        for p in parts[1:]:
            total = total + p
        return total.cast("long")

    def rent(self) -> Column:
        return self._both(F.lit(self.home_disk_us), self.transfer(F.lit(self.key_bytes + self.param_bytes + self.result_bytes)), F.lit(self.home_cpu_us))

    def buy(self, value_bytes: Column) -> Column:
        return self._both(F.lit(self.home_disk_us), self.transfer(value_bytes + self.key_bytes))

    def use_memory(self) -> Column:
        return F.lit(self.lane_cpu_us).cast("long")

    def use_disk(self) -> Column:
        return self._both(F.lit(self.lane_cpu_us), F.lit(self.lane_disk_us))


#: Kinds of load: values are large, calls are slow, or both.
DATA_HEAVY = CostProfile(home_disk_us=400, lane_disk_us=200, home_cpu_us=20, lane_cpu_us=20)
COMPUTE_HEAVY = CostProfile(home_disk_us=40, lane_disk_us=20, home_cpu_us=100_000, lane_cpu_us=100_000)
BOTH_HEAVY = CostProfile(home_disk_us=400, lane_disk_us=200, home_cpu_us=100_000, lane_cpu_us=100_000)
DEFAULT = CostProfile()


def with_costs(df: DataFrame, profile: CostProfile, value_bytes: str = "value_bytes") -> DataFrame:
    v = F.col(value_bytes)
    return df.withColumns({"rent_us": profile.rent(), "buy_us": profile.buy(v), "mem_us": profile.use_memory(), "disk_us": profile.use_disk()})


def smoothed(values: Column, alpha_num: int, alpha_den: int, start: int, scale: int) -> Column:
    """Exponential smoothing of an ordered array, next = a * measured + (1 - a) * last, in fixed point with ``scale`` units."""
    step = lambda acc, v: F.floor((alpha_num * v * scale + (alpha_den - alpha_num) * acc) / alpha_den).cast("long")
    return F.aggregate(values, F.lit(start * scale).cast("long"), step)
