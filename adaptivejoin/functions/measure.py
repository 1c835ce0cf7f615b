"""Costs measured while running: time of stored reads and of calls in the workers, smoothed, and bandwidth by a probe."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from adaptivejoin.functions.costs import DEFAULT, CostProfile

#: Weight of a new measurement, and how many values of the store are read and called for it.
ALPHA, SAMPLE = 0.25, 20_000


def ewma(values: list[float], alpha: float = ALPHA, start: float | None = None) -> float:
    """Smoothed mean of a series; with alpha 1 its last value, with 0 the first."""
    now = start
    for v in values:
        now = v if now is None else alpha * v + (1 - alpha) * now
    return now or 0.0


def plain_call(columns: list[np.ndarray]) -> np.ndarray:
    """A call that stands for those whose code is not given: one pass over the numbers of a value."""
    total = np.zeros(len(columns[0]) if columns else 0)
    for c in columns:
        if c.dtype.kind in "if":
            total = total * 31 + np.nan_to_num(c)
    return total


def probe_bandwidth(spark: SparkSession, megabytes: int = 8) -> float:
    """Bytes a microsecond through an exchange of rows, written and read."""
    rows = megabytes * 1024
    wide = spark.range(rows).select("id", F.repeat(F.md5(F.col("id").cast("string")), 32).alias("v"))
    began = time.perf_counter()
    wide.repartition(4, "id").agg(F.sum(F.octet_length("v"))).first()
    return rows * 1024 / max((time.perf_counter() - began) * 1e6, 1.0)


def measured_profile(spark: SparkSession, stored: DataFrame, key: str, value: tuple[str, ...], call: Callable[[list[np.ndarray]], np.ndarray] = plain_call, base: CostProfile = DEFAULT) -> CostProfile:
    """``base`` with measured times in whole microseconds (1 at least): of a stored read, of a call, and the bandwidth.

    Values are read until each task has seen its share of ``SAMPLE``; every batch gives one measurement of both, a task sends its
    smoothed ones, and these are smoothed again: as many rows as tasks, not as values.
    """
    columns = list(value)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reads, calls, seen, began = [], [], 0, time.perf_counter()
        for batch in batches:
            n = max(batch.num_rows, 1)
            reads.append((time.perf_counter() - began) * 1e6 / n)
            at = time.perf_counter()
            call([batch.column(i).to_numpy(zero_copy_only=False) for i in range(len(columns))])
            calls.append((time.perf_counter() - at) * 1e6 / n)
            seen, began = seen + n, time.perf_counter()
            if seen >= SAMPLE:
                break
        if seen:
            yield pa.RecordBatch.from_arrays([pa.array([ewma(reads)]), pa.array([ewma(calls)])], names=["read_us", "call_us"])

    got = stored.where(F.col(key).isNotNull()).select(*columns).mapInArrow(run, "read_us double, call_us double").agg(F.avg("read_us").alias("read_us"), F.avg("call_us").alias("call_us")).first()
    whole = lambda x: max(1, round(x or 0.0))
    return replace(base, home_disk_us=whole(got["read_us"]), lane_disk_us=whole(got["read_us"]), home_cpu_us=whole(got["call_us"]), lane_cpu_us=whole(got["call_us"]), bandwidth=whole(probe_bandwidth(spark)))
