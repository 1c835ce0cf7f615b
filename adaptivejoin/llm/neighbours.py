"""Approximate nearest neighbours by counting collisions in single projections.

Vectors are normalised, so the largest cosine is the smallest distance. The table is dealt by hash into blocks of about
``BLOCK_BYTES``. A block sorts its vectors along each of ``PROJECTIONS`` random directions and cuts every order into at most
``LEAVES`` leaves; a vector is held by its leaf numbers, a byte each. A query looks at a window centred on its own projection in
every order, which is a run of leaves, and counts in how many windows each vector collides; the windows grow with the radius, by
virtual rehashing, without hashing anything again. Vectors that reach the collision threshold are verified with the exact cosine.
The search of a block ends once the k-th best verified distance lies within the radius: a vector at least as near would have
reached the threshold but with a small probability, set by ``Z``. A window takes whole leaves, so it holds a little more than its
radius asks for and never less.

A large block does not begin at the first radius but at the one that half of a sample of its own vectors need; a query that
needs less verifies more than it must. Of equal vectors a block keeps as many as one answer can name.

Queries meet all blocks; each block returns its k best, and the k best of these are the answer. Where there are fewer blocks than
cores, a block's queries are dealt over several tasks. A block also says how many vectors it verified. Recall and that share are
measured in the tests: on vectors without structure the nearest of 64 dimensions has a cosine of about 0.4, where the counts of
near and far vectors overlap, so that a share has to be verified; on clustered ones it is small.

Defined results: vectors that are null, zero, or hold a null or a number that isn't finite take no part, nor do rows without an
id; rows that repeat an id count once (the vector that sorts first); vectors of another length than the query's are no
candidates; equal scores go to the smaller id; fewer than k candidates are all returned; an empty table gives an empty result;
further columns do not matter.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from adaptivejoin.llm.common import table

NEAREST = 5
#: Bytes of a block's vectors as they are held: a larger block means fewer copies of the queries.
BLOCK_BYTES = 1 << 24
PROJECTIONS = 160
FIRST_RADIUS = 0.4
GROWTH = 1.05
#: The collision threshold lies so many standard deviations under what a vector at the radius is expected to reach.
Z = 1.0
#: Leaves of an order: their numbers are bytes, and one byte is no leaf's.
LEAVES = 255
#: Vectors whose collisions are counted at a time.
STRIP = 1 << 12
#: Vectors that say at which radius a block begins; a block of fewer begins at the first.
SAMPLE = 1 << 10
ASKED = 64
INSIDE = 0.6826894921370859  # the probability that a normal variable lies within its deviation: a window is two radii wide
SEED = 7


class Index:
    """Leaf numbers of one block's vectors in sorted projections."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, projections: int = PROJECTIONS):
        self.ids, self.vectors = ids, vectors
        self.norms = np.sqrt((vectors * vectors).sum(axis=1))
        self.unit = (vectors / self.norms[:, None]).astype(np.float32)
        self.verified = 0
        n, self.radii = len(ids), radii_up_to(2.0)
        self.directions = np.random.default_rng(SEED).standard_normal((projections, vectors.shape[1])).astype(np.float32)
        count = min(LEAVES, n)
        begins = np.arange(count) * n // count
        ends = np.append(begins[1:], n) - 1
        self.least, self.most = (np.empty((projections, count), np.float32) for _ in range(2))  # of each leaf
        self.leaves = np.empty((projections, n), np.uint8)
        for j, direction in enumerate(self.directions):
            p = self.unit @ direction
            ordered = np.sort(p)
            self.least[j], self.most[j] = ordered[begins], ordered[ends]
            self.leaves[j] = np.searchsorted(self.least[j, 1:], p, side="right")  # equal projections share a leaf
        self.threshold = max(1, int(INSIDE * projections - Z * np.sqrt(projections * INSIDE * (1 - INSIDE))))
        self.buffer = np.empty((projections, min(n, STRIP)), np.uint8)
        self.starts: dict[int, int] = {}

    def first_step(self, k: int) -> int:
        """The step at which the radius is that of the k-th nearest of half of a sample; 0 in a small block."""
        n = len(self.ids)
        if k not in self.starts:
            self.starts[k] = 0
            if n > max(SAMPLE, k + 1):
                own = np.arange(ASKED) * n // ASKED
                at = self.unit @ self.unit[own].T
                at[own, np.arange(ASKED)] = -2
                kth = np.sqrt(np.maximum(0, 2 - 2 * np.partition(at, n - k, axis=0)[n - k]))
                self.starts[k] = min(int(np.searchsorted(self.radii, np.median(kth))), len(self.radii) - 1)
        return self.starts[k]

    def collisions(self, at: np.ndarray, radius: float) -> np.ndarray:
        """In how many windows of a radius around ``at`` each vector lies."""
        low = (self.most < (at - np.float32(radius))[:, None]).sum(axis=1)
        high = (self.least <= (at + np.float32(radius))[:, None]).sum(axis=1) - 1
        none = high < low
        low, width = np.where(none, LEAVES, low).astype(np.uint8)[:, None], np.where(none, 0, high - low).astype(np.uint8)[:, None]
        n, out = len(self.ids), np.empty(len(self.ids), np.uint16)
        for lo in range(0, n, STRIP):
            inside = self.buffer[:, : min(STRIP, n - lo)]
            np.subtract(self.leaves[:, lo : lo + STRIP], low, out=inside)  # leaves below the window wrap to beyond it
            np.less_equal(inside, width, out=inside.view(bool))
            out[lo : lo + STRIP] = inside.sum(axis=0, dtype=np.uint8 if len(at) < 256 else np.uint16)
        return out

    def search(self, own: int, q: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids and cosines of the k best found, best first."""
        n, norm = len(self.ids), np.sqrt((q * q).sum())
        unit = (q / norm).astype(np.float32)
        at = self.directions @ unit
        slack = (len(q) + 16) * 2.0**-22  # more than single precision errs by
        rough = np.full(n, np.nan, np.float32)
        todo = self.ids != own
        best, scores = np.zeros(0, np.int64), np.zeros(0)
        for step in range(self.first_step(k), len(self.radii) + 1):  # the windows grow until the k-th best lies within their radius, or to the end
            last = step == len(self.radii)
            new = np.flatnonzero(todo if last else todo & (self.collisions(at, self.radii[step]) >= self.threshold))
            if len(new):
                todo[new] = False
                self.verified += len(new)
                rough[new] = self.unit[new] @ unit
                found = np.concatenate((best, new))
                least = np.partition(rough[found], len(found) - k)[len(found) - k] - slack if len(found) > k else -np.inf
                found = found[rough[found] >= least]
                exact = (self.vectors[found] * q).sum(axis=1) / (self.norms[found] * norm)
                order = np.lexsort((self.ids[found], -exact))[:k]
                best, scores = found[order], exact[order]
            if len(best) == k and not last and 2 - 2 * scores[-1] <= self.radii[step] ** 2:
                break
        return self.ids[best], scores


def radii_up_to(most: float) -> np.ndarray:
    """Window radii by virtual rehashing, each ``GROWTH`` times the one before; no two unit vectors are farther apart than 2."""
    steps = int(np.ceil(np.log(most / FIRST_RADIUS) / np.log(GROWTH))) + 1
    return FIRST_RADIUS * GROWTH ** np.arange(steps)


def search(vectors: DataFrame, every: int, k: int = NEAREST, block: int | None = None, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score, verified): the k nearest found of each row whose id is divisible by ``every``, and how many
    vectors were compared with it in full. ``block``: vectors of a block; by default as many as ``BLOCK_BYTES`` hold."""
    v = F.col(vector_col)
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    single = vectors.schema[vector_col].dataType.elementType.typeName() == "float"
    kept = v if single else v.cast("array<double>")
    valid = vectors.where(F.col(id_col).isNotNull() & v.isNotNull() & finite & F.exists(v, lambda x: x != 0)).select(F.col(id_col).cast("long").alias("id"), kept.alias("v"))
    held = valid.agg(F.count("*").alias("n"), F.sum(F.size("v").cast("long") * 8).alias("bytes")).first()
    blocks = max(1, -(-held["n"] // block) if block else -(-(held["bytes"] or 0) // BLOCK_BYTES))
    groups = -(-vectors.sparkSession.sparkContext.defaultParallelism // blocks) if held["n"] > SAMPLE else 1
    cell = lambda b, g: (b * groups + g).cast("int").alias("cell")
    every_of = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    rows = valid.withColumn("g", every_of(groups)).select(cell(F.pmod(F.xxhash64("id"), F.lit(blocks)), F.col("g")), F.size("v").alias("dim"), F.lit(0).alias("kind"), "id", "v")
    asked = valid.where(F.col("id") % every == 0).withColumn("b", every_of(blocks))
    asked = asked.select(cell(F.col("b"), F.pmod(F.xxhash64("id", F.lit(1)), F.lit(groups))), F.size("v").alias("dim"), F.lit(1).alias("kind"), "id", "v")
    dealt = rows.unionAll(asked).repartitionById(blocks * groups, "cell").sortWithinPartitions("cell", "dim", "kind", "id", "v")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, ids, vecs, copies, index, last = None, [], [], {}, None, None
        for batch in batches:
            cells, dims, kinds, row_ids = (batch.column(i).to_numpy() for i in range(4))
            out: list[tuple] = []
            flat, at = batch.column(4).flatten().to_numpy().astype(np.float64), 0
            for i in range(batch.num_rows):
                d = int(dims[i])
                vec, at = flat[at : at + d], at + d
                if (cells[i], d) != key:
                    key, ids, vecs, copies, index, last = (cells[i], d), [], [], {}, None, None
                own = int(row_ids[i])
                if (kinds[i], own) == last:
                    continue
                last = (kinds[i], own)
                if kinds[i] == 0:
                    same = vec.tobytes()
                    copies[same] = copies.get(same, 0) + 1
                    if copies[same] <= k + 1:  # the smallest ids: rows come in their order, and one of them may be the query's own
                        ids.append(own), vecs.append(vec)
                elif ids:
                    if index is None:
                        index, vecs, copies = Index(np.array(ids, np.int64), np.array(vecs)), [], {}
                    before = index.verified
                    got, scores = index.search(own, vec, k)
                    work = np.zeros(len(got), np.int64)
                    work[:1] = index.verified - before
                    out.append((np.full(len(got), own), got, scores, work))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*out, strict=True)], names=["query_id", "vec_id", "score", "verified"])

    best = W.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    found = dealt.mapInArrow(run, "query_id long, vec_id long, score double, verified long")
    ranked = found.withColumn("rank", F.row_number().over(best)).withColumn("verified", F.sum("verified").over(W.partitionBy("query_id")))
    return ranked.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score", "verified")


def query(spark, sf_dir: str) -> DataFrame:
    return search(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"), every=50)
