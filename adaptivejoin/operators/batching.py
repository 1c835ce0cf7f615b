"""Batches of requests by size and by waiting time."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def by_size(df: DataFrame, by: tuple[str, ...], seq: tuple[str, ...], size: int) -> DataFrame:
    """``batch_no`` of each request: so many of a (lane, home) at a time."""
    return df.withColumn("batch_no", F.floor((F.row_number().over(W.partitionBy(*by).orderBy(*seq)) - 1) / size).cast("long"))


def cut(times: list[int], size: int, wait: int) -> list[tuple[int, int]]:
    """(members, close time) of the batches of one queue: closed when full, or when its first member has waited long enough."""
    out, first, n, last = [], None, 0, None
    for t in times:
        if n and t > first + wait:
            out.append((n, first + wait))
            n = 0
        if not n:
            first = t
        n, last = n + 1, t
        if n == size:
            out.append((n, t))
            n = 0
    if n:
        out.append((n, last))
    return out


def by_wait(df: DataFrame, key: str, at: str, size: int, wait: int) -> DataFrame:
    """(key, batch_no, members, waited) with ``at`` in whole units of time; queues stream past in order."""
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = df.select(F.col(key).cast("long").alias("key"), F.col(at).cast("long").alias("at")).repartition(n, "key").sortWithinPartitions("key", "at")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        k, first, members, last, no = None, 0, 0, 0, 0
        for batch in batches:
            out: list[tuple] = []
            for key_, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if key_ != k:
                    if members:
                        out.append((k, no, members, last - first))
                    k, members, no = key_, 0, 0
                elif members and t > first + wait:
                    out.append((k, no, members, wait))
                    members, no = 0, no + 1
                if not members:
                    first = t
                members, last = members + 1, t
                if members == size:
                    out.append((k, no, members, t - first))
                    members, no = 0, no + 1
            if out:
                yield _rows(out)
        if members:
            yield _rows([(k, no, members, last - first)])

    def _rows(out):
        return pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], pa.int64()) for i in range(4)], names=["key", "batch_no", "members", "waited"])

    return rows.mapInArrow(run, "key long, batch_no long, members long, waited long")
