"""Mixing sources to target weights, in DataFrame operations only.

Tokens are aggregated per source, a target is derived for each source from its weight, and every document is emitted
``floor(rate)`` times plus one more time with the probability of the rate's fraction, decided by a hash of its id, source, text and,
where rows agree in all of these, its number among them.

Defined results: a null text or one without words has size 0 and is never taken; a null source is a source of its own
that sorts last; rows that share an id, or have none, draw for themselves; of equal rows it is settled how many are taken, not which;
an empty table gives an empty result; further columns pass through ``mix`` and do not matter to ``plan``.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from adaptivejoin.llm.common import Workspace, words

#: Weights of the sources in order, repeating, and the most often that a source may be repeated.
WEIGHTS = (5, 2, 1)
MOST_REPEATS = 3
SEED = "mix-1"


def source_targets(sized: DataFrame, weights: Sequence[int] = WEIGHTS, most: int = MOST_REPEATS) -> DataFrame:
    """Rows (source, source_size, target) from rows (source, size).

    A source that would exceed ``most`` times its size gets just that, and what it leaves is shared again by weight. The
    fixed point needs no iteration: in the order of ``most * size / weight`` the capped sources come first, so running sums
    over the sources tell which are capped. There is one row per source, so the one-partition windows see few rows.
    """
    # Sources are partially aggregated before the shuffle: a source with a third of all rows is one row a task.
    per = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    by_name = W.orderBy(F.col("source").asc_nulls_last())
    n = len(weights)
    turn = (F.row_number().over(by_name) - 1) % n
    per = per.withColumn("weight", F.element_at(F.array(*[F.lit(int(w)) for w in weights]), (turn + 1).cast("int")).cast("long"))
    ratio = F.col("source_size") / F.col("weight")
    order = W.orderBy(ratio, F.col("source").asc_nulls_last()).rowsBetween(W.unboundedPreceding, -1)
    every = W.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    per = per.select(
        "*",
        F.sum("source_size").over(every).alias("total"),
        F.sum("weight").over(every).alias("all_weight"),
        F.coalesce(F.sum("source_size").over(order), F.lit(0)).alias("size_before"),
        F.coalesce(F.sum("weight").over(order), F.lit(0)).alias("weight_before"),
    )
    # A source is capped if, with every source before it capped, its share of the rest would still exceed its cap.
    left = F.col("total") - most * F.col("size_before")
    weight_left = F.col("all_weight") - F.col("weight_before")
    capped = left * F.col("weight") >= most * F.col("source_size") * weight_left
    per = per.withColumn("capped", capped)
    rest = F.col("total") - most * F.coalesce(F.sum(F.when(F.col("capped"), F.col("source_size"))).over(every), F.lit(0))
    rest_weight = F.sum(F.when(~F.col("capped"), F.col("weight"))).over(every)
    share = F.when(F.col("capped"), (most * F.col("source_size")).cast("double")).otherwise(rest * F.col("weight") / rest_weight)
    return per.select("source", "source_size", share.alias("target"))


def _sized(docs: DataFrame, id_col: str, text_col: str, source_col: str, *more) -> DataFrame:
    """Rows with their size, ``same`` (equal for rows that agree in id, source and text) and the partition they are read in."""
    text, source = F.col(f"`{text_col}`"), F.col(f"`{source_col}`")
    same = F.concat_ws(":", F.coalesce(F.col(f"`{id_col}`").cast("string"), F.lit("")), F.coalesce(F.concat(F.lit("="), source), F.lit("")), F.md5(F.coalesce(text, F.lit(""))))
    return docs.select(*more, F.col(f"`{id_col}`").alias("doc_id"), source.alias("source"), F.size(words(text)).cast("long").alias("size"), same.alias("same"), F.spark_partition_id().alias("part"))


def plan(docs: DataFrame, weights: Sequence[int] = WEIGHTS, most: int = MOST_REPEATS, seed: str = SEED, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """How often each document is taken: (doc_id, source, size, source_size, target, copies, taken). Texts are read once."""
    narrow = Workspace(docs.sparkSession, "mix").save(_sized(docs, id_col, text_col, source_col), "sizes")
    return _with_copies(narrow, narrow, weights, most, seed).drop("same", "part")


def _numbered(rows: DataFrame, repeated: DataFrame) -> DataFrame:
    """``rows`` with ``number``, 1 for the first of those that agree. Only rows that repeat are dealt, by partition as well, so that
    a group of a third of all rows is spread; what the partitions before hold is added."""
    marked = rows.join(repeated.withColumn("again", F.lit(True)), "same", "left")
    one = marked.where("again is null").withColumn("number", F.lit(1).cast("long"))
    several = marked.where("again")
    before = several.groupBy("same", "part").agg(F.count("*").alias("n"))
    before = before.select("same", "part", F.coalesce(F.sum("n").over(W.partitionBy("same").orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    own = F.row_number().over(W.partitionBy("same", "part").orderBy("size"))
    several = several.withColumn("own", own).join(before, ["same", "part"]).withColumn("number", F.col("own") + F.col("before")).drop("own", "before")
    return one.unionByName(several).drop("again")


def _with_copies(rows: DataFrame, narrow: DataFrame, weights: Sequence[int], most: int, seed: str) -> DataFrame:
    """``rows`` with their source's figures and their copies; ``narrow`` holds the same rows' sizes."""
    repeated = narrow.groupBy("same").agg(F.count("*").alias("n")).where("n > 1").select("same")
    rows = rows.withColumn("number", F.lit(1).cast("long")) if repeated.isEmpty() else _numbered(rows, repeated)
    targets = source_targets(narrow, weights, most).withColumnRenamed("source", "of_source")
    joined = rows.join(targets, F.col("source").eqNullSafe(F.col("of_source")), "left").drop("of_source")
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    draw = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), "same", F.col("number").cast("string"))), 1, 12), 16, 10).cast("double") / F.lit(float(1 << 48))
    copies = (F.floor(rate) + F.when(draw < rate - F.floor(rate), 1).otherwise(0)).cast("long")
    return joined.withColumn("copies", copies).drop("number").withColumn("taken", F.col("copies") * F.col("size"))


def mix(docs: DataFrame, weights: Sequence[int] = WEIGHTS, most: int = MOST_REPEATS, seed: str = SEED) -> DataFrame:
    """The mixture itself: every document as often as the plan says, with its own columns.

    Texts are not shuffled, but for rows that repeat: the per-source plan is a row per source, joined to the documents, and copies
    are generated in place.
    """
    own = docs.columns
    # The plan's own column names live outside the struct, so clashing names in the input do no harm.
    marked = _sized(docs, "doc_id", "text", "source", F.struct(*[F.col(f"`{c}`") for c in own]).alias("row"))
    narrow = Workspace(docs.sparkSession, "mix").save(_sized(docs, "doc_id", "text", "source"), "sizes")
    taken = _with_copies(marked, narrow, weights, most, seed).where(F.col("copies") > 0)
    return taken.select(F.col("row"), F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))).alias("copy")).select(*[F.col("row").getField(c).alias(c) for c in own])


def query(spark, sf_dir: str) -> DataFrame:
    from adaptivejoin.llm.common import table

    return plan(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


ORACLE = r"""
WITH sized AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size,
    coalesce(CAST(doc_id AS VARCHAR), '') || ':' || coalesce('=' || source, '') || ':' || md5(coalesce(text, '')) AS same FROM documents
), numbered AS (
  SELECT *, row_number() OVER (PARTITION BY same) AS number FROM sized
), per AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sized GROUP BY source
), weighed AS (
  SELECT *, CASE (row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS weight FROM per
), running AS (
  SELECT *, CAST(sum(source_size) OVER () AS BIGINT) AS total, CAST(sum(weight) OVER () AS BIGINT) AS all_weight,
    CAST(coalesce(sum(source_size) OVER before, 0) AS BIGINT) AS size_before, CAST(coalesce(sum(weight) OVER before, 0) AS BIGINT) AS weight_before
  FROM weighed WINDOW before AS (ORDER BY source_size / weight, source ASC NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)
), capped AS (
  SELECT *, (total - 3 * size_before) * weight >= 3 * source_size * (all_weight - weight_before) AS capped FROM running
), rest AS (
  SELECT *, total - 3 * CAST(coalesce(sum(CASE WHEN capped THEN source_size END) OVER (), 0) AS BIGINT) AS rest,
    CAST(sum(CASE WHEN NOT capped THEN weight END) OVER () AS BIGINT) AS rest_weight FROM capped
), targets AS (
  SELECT source, source_size, CASE WHEN capped THEN CAST(3 * source_size AS DOUBLE) ELSE CAST(rest * weight AS DOUBLE) / rest_weight END AS target FROM rest
), rated AS (
  SELECT doc_id, size, source_size, target, CASE WHEN source_size > 0 THEN target / source_size ELSE 0 END AS rate,
    CAST(CAST('0x' || substr(md5('mix-1:' || same || ':' || number), 1, 12) AS BIGINT) AS DOUBLE) / 281474976710656.0 AS draw
  FROM numbered JOIN targets ON numbered.source IS NOT DISTINCT FROM targets.source
)
SELECT doc_id, size, source_size, target,
  CAST((floor(rate) + CASE WHEN draw < rate - floor(rate) THEN 1 ELSE 0 END) * size AS BIGINT) AS taken
FROM rated
"""
