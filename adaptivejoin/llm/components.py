"""Connected components of a graph given as edges, without collecting nodes or edges.

Alternating star operations: every node links its larger neighbours to the smallest node it sees, then its smaller ones. The
edges shrink towards stars whose centres are the components' smallest nodes, in about the logarithm of the longest path.
Each round is written to the shared folder; the previous one is deleted.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adaptivejoin.llm.common import Workspace


def _smallest(arcs: DataFrame) -> DataFrame:
    """(u, m): the smallest neighbour of each node. The key is computed anew, so that the join with the arcs deals both of its
    sides out by itself and can split a node with a great many arcs."""
    return arcs.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").bitwiseXOR(F.lit(1)).alias("key"), "m")


def _star(arcs: DataFrame) -> DataFrame:
    keyed = arcs.select(F.col("u").bitwiseXOR(F.lit(1)).alias("key"), "u", "v")
    return keyed.join(_smallest(arcs), "key")


def _large(edges: DataFrame) -> DataFrame:
    both = edges.unionAll(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    seen = _star(both)
    return seen.where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.least("m", "u").alias("v")).distinct()


def _small(edges: DataFrame) -> DataFrame:
    seen = _star(edges)
    own = F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))
    return seen.select(F.explode(own).alias("e")).select("e.u", "e.v").where(F.col("u") > F.col("v")).distinct()


#: Edges are few beside the rows they come from: so many shuffle partitions go into one file.
PARTITIONS_A_FILE = 16


def components(edges: DataFrame, work: Workspace) -> DataFrame:
    """(node, root) for every node of an edge (a, b) of longs; root is the smallest node it is connected with.

    Edges may repeat, point either way and join a node with itself (such a node has a root only through other edges).
    """
    files = max(1, int(work.spark.conf.get("spark.sql.shuffle.partitions")) // PARTITIONS_A_FILE)
    now = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u > v").distinct()
    sign = None
    while True:
        new = work.save(_small(_large(now)).coalesce(files), "edges")
        work.drop(now)
        now = new
        # A fixed point is a set of stars; equal counts and hash sums of two rounds mean equal sets.
        row = now.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        if (row["n"], row["h"]) == sign:
            return now.select(F.col("u").alias("node"), F.col("v").alias("root"))
        sign = (row["n"], row["h"])
