"""Probes and stored relations of the experiment workloads, on the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from adaptivejoin.functions.hashing import portable_hash, row_id, with_zipf_key
from adaptivejoin.operators.joins import CallSpec
from adaptivejoin.operators.routing import Access
from adaptivejoin.plans.sqltext import LANES
from adaptivejoin.tables import table

SEQ = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
ACCESS = Access("key", "lane", SEQ)
#: Distance that the frequent keys move at each change, and how many changes there are.
STRIDE, PHASES = 97, 10


def universe(spark: SparkSession, folder: str) -> int:
    """Keys of the generator, all of the store's: parquet footers give the count."""
    return table(spark, folder, "part").count()


def zipf_probe(spark: SparkSession, folder: str, z: float, lanes: int = LANES, moving: bool = False) -> DataFrame:
    """lineitem rows as accesses with a skewed key; lanes by hash of the row. With ``moving`` the frequent keys change ten times."""
    rows = table(spark, folder, "lineitem").select(row_id(*SEQ).alias("row_id"), *SEQ, F.col("l_quantity").cast("long").alias("qty"))
    n = universe(spark, folder)
    rows = rows.withColumn("lane", F.pmod(portable_hash(F.concat("row_id", F.lit("#"))), F.lit(lanes)).cast("int"))
    rows = with_zipf_key(rows, portable_hash(F.col("row_id")), n, z)
    if not moving:
        return rows
    top = table(spark, folder, "lineitem").agg(F.max("l_orderkey")).first()[0]
    rows = rows.withColumn("phase", F.floor(PHASES * F.col("l_orderkey") / F.lit(top + 1)).cast("long"))
    return rows.withColumn("key", (F.col("key") + F.col("phase") * STRIDE) % n)


def part_store(spark: SparkSession, folder: str) -> DataFrame:
    """part as the store; a value's size grows with the length of the name and the part's size."""
    size = (2 * F.octet_length("p_name") * (1 + F.col("p_size"))).cast("long")
    return table(spark, folder, "part").select(F.col("p_partkey").alias("skey"), "p_size", "p_retailprice", size.alias("value_bytes"))


def call_result() -> Column:
    return (F.col("key") * 31 + F.col("qty") * 7 + F.col("p_size") * F.floor("p_retailprice").cast("long")) % 1000003


PART_CALL = CallSpec(("p_size", "p_retailprice"), call_result)
