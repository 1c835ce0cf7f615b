"""Counts of accesses in bounded memory."""

from __future__ import annotations

import math
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


class LossyCounter:
    """Counts with an error of at most ``eps`` times the accesses: after each bucket of ``1/eps`` accesses, keys that may have
    been seen no more often than their slack are forgotten. An estimate is never above the true count."""

    def __init__(self, eps: float):
        self.width, self.seen, self.table = math.ceil(1 / eps), 0, {}

    def add(self, key) -> int:
        """Count an access; the key's estimate."""
        bucket = self.seen // self.width
        count, slack = self.table.get(key, (0, bucket))
        self.table[key] = (count + 1, slack)
        self.seen += 1
        if self.seen % self.width == 0:
            self.table = {k: (c, s) for k, (c, s) in self.table.items() if c + s > bucket + 1}
        return count + 1

    def reset(self, key) -> None:
        self.table.pop(key, None)


class ExactCounter:
    def __init__(self):
        self.table: dict = {}

    def add(self, key) -> int:
        self.table[key] = self.table.get(key, 0) + 1
        return self.table[key]

    def reset(self, key) -> None:
        self.table.pop(key, None)


def lossy_count(df: DataFrame, key: str, lane: str, seq: tuple[str, ...], eps: float) -> DataFrame:
    """(lane, key, est, slack, n) after all accesses of each lane; a lane's rows stream past, its table is bounded."""
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = df.select(F.col(lane).cast("int").alias("lane"), F.col(key).cast("long").alias("key"), *seq).repartition(n, "lane").sortWithinPartitions("lane", *seq)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lane_now, counter = None, None

        def out() -> pa.RecordBatch:
            t = counter.table
            return pa.RecordBatch.from_arrays(
                [pa.array([lane_now] * len(t), pa.int32()), pa.array(list(t), pa.int64()), pa.array([c for c, _ in t.values()], pa.int64()), pa.array([s for _, s in t.values()], pa.int64()), pa.array([counter.seen] * len(t), pa.int64())],
                names=["lane", "key", "est", "slack", "n"],
            )

        for batch in batches:
            for lane_, k in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if lane_ != lane_now:
                    if counter:
                        yield out()
                    lane_now, counter = lane_, LossyCounter(eps)
                counter.add(k)
        if counter:
            yield out()

    return rows.mapInArrow(run, "lane int, key long, est long, slack long, n long")


def heavy_two_pass(df: DataFrame, key: str, lane: str, seq: tuple[str, ...], support: float, eps: float) -> DataFrame:
    """Exact counts of the keys with at least ``support`` of all accesses: candidates by lossy counting, then a count of those alone."""
    est = lossy_count(df, key, lane, seq, eps)
    candidates = est.where(F.col("est") >= (support - eps) * F.col("n")).select("key").distinct()
    total = df.agg(F.count("*").alias("total"))
    exact = df.select(F.col(key).alias("key")).join(candidates, "key", "left_semi").groupBy("key").agg(F.count("*").alias("n"))
    return exact.crossJoin(F.broadcast(total)).where(F.col("n") >= support * F.col("total")).select("key", "n")
