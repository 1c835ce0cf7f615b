"""Hashes and draws that any SQL engine can repeat."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: Keys whose interval ends are sent to the workers (8 bytes each); more keys are looked up by a join.
SENT_KEYS = 1 << 20
SKEWS = (0.0, 0.5, 1.0, 1.5)


def portable_hash(x: Column) -> Column:
    """60 bits of MD5 as a long: for traces that are compared across engines. Joins use Spark's own hashes."""
    return F.conv(F.substring(F.md5(x.cast("string")), 1, 15), 16, 10).cast("long")


def row_id(*cols: str) -> Column:
    return F.concat_ws("-", *[F.col(c).cast("string") for c in cols])


def zipf_bounds(keys: int, z: float) -> np.ndarray:
    """Upper ends of the intervals of draws: key k has floor(1e9 / k^z) of them. Only square root, product and quotient are used."""
    k = np.arange(1, keys + 1, dtype=np.float64)
    power = {0.0: np.ones_like, 0.5: np.sqrt, 1.0: np.copy, 1.5: lambda x: x * np.sqrt(x)}[z]
    return np.cumsum(np.floor(1e9 / power(k)).astype(np.int64))


def zipf_key(draw: Column, keys: int, z: float) -> Column:
    """Rank from 0 of the key that a draw falls on: binary search in a table of at most ``SENT_KEYS``, no join."""
    if keys > SENT_KEYS:
        raise ValueError("more keys than are sent to the workers: use with_zipf_key")
    bounds = zipf_bounds(keys, z)

    @F.pandas_udf("long")
    def rank(h: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(bounds, h.to_numpy() % bounds[-1], side="right").astype(np.int64))

    return rank(draw)


#: Ranks that are summed at a time, and interval cells a key.
STRIDE, CELLS = 1 << 16, 4


def zipf_intervals(spark, keys: int, z: float) -> DataFrame:
    """(k, lo, hi) of all ranks from 0, in any number: sums within strides, and over the few totals of strides."""
    k = (F.col("id") + 1).cast("double")
    power = {0.0: F.lit(1.0), 0.5: F.sqrt(k), 1.0: k, 1.5: k * F.sqrt(k)}[z]
    own = spark.range(keys).select(F.col("id").alias("k"), F.floor(F.lit(1e9) / power).cast("long").alias("w"), F.floor(F.col("id") / STRIDE).alias("stride"))
    within = F.sum("w").over(W.partitionBy("stride").orderBy("k").rowsBetween(W.unboundedPreceding, 0))
    before = own.groupBy("stride").agg(F.sum("w").alias("all")).withColumn("before", F.coalesce(F.sum("all").over(W.orderBy("stride").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    rows = own.withColumn("hi", within).join(before.select("stride", "before"), "stride")
    return rows.select("k", (F.col("before") + F.col("hi") - F.col("w")).alias("lo"), (F.col("before") + F.col("hi")).alias("hi"))


def with_zipf_key(df: DataFrame, draw: Column, keys: int, z: float, name: str = "key") -> DataFrame:
    """``df`` with the rank that each draw falls on. A table of many keys is joined by cells of equal width: an interval is in the cells
    that it touches, a draw in one."""
    if keys <= SENT_KEYS:
        return df.withColumn(name, zipf_key(draw, keys, z))
    intervals = zipf_intervals(df.sparkSession, keys, z)
    total = intervals.agg(F.max("hi")).first()[0]
    width = max(1, total // (CELLS * keys))
    cells = intervals.select("k", "lo", "hi", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor((F.col("hi") - 1) / width))).alias("cell"))
    drawn = df.withColumn("__u", draw % total).withColumn("__cell", F.floor(F.col("__u") / width))
    joined = drawn.join(cells, (F.col("__cell") == F.col("cell")) & (F.col("__u") >= F.col("lo")) & (F.col("__u") < F.col("hi")))
    return joined.select(*df.columns, F.col("k").alias(name))
