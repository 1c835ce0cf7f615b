"""Near duplicates by SimHash fingerprints, with candidates from chains of fingerprint segments.

A fingerprint of 64 bits is cut into ``SEGMENTS`` segments on a ring. If two fingerprints differ in at most ``most`` bits, then
from some segment on, every chain of consecutive segments keeps within its share of the differences, ``length * most /
SEGMENTS``. Integer differences make this a condition on which segments of the chain are equal: the first one, one of the next
two, and so on. Each way to meet it for a chain of a given length is a set of equal segments, so candidates meet in buckets of
an equi-key: the set and the bits of its segments. Within a bucket the rest of the chain is checked, then the full distance.

Buckets are read as a sorted stream. Only links to the smallest member of a connected group are emitted, so a bucket of n
members yields less than n links, however many pairs it holds. A bucket that exceeds a block is passed on and dealt out by pairs
of blocks. Documents with equal fingerprints are one node.

Defined results: a null text counts as empty; texts without words have the fingerprint zero and are linked like any others;
texts shorter than a shingle are one shingle; whole texts are hashed, in pieces of fixed size; rows that repeat an id or have none
are rows like any others, each with its own fingerprint; a component of null ids alone has a null id; an empty table gives an
empty result; further columns do not matter to ``near_duplicates`` and pass through ``deduplicate``.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adaptivejoin.llm.common import Workspace, columns_of_row, release_memory, row_keyed, table
from adaptivejoin.llm.components import components

SEED = 42
SHINGLE = 5
MOST_BITS = 4
SEGMENTS = 8
#: Lengths of chains: the key of a longer one has more bits, and there are more of them.
CHAINS = (5, 7, 8)
#: Words hashed at a time, and the members of a bucket that are compared with one another at a time.
PIECE = 1 << 16
BLOCK = 2048
#: Pairs checked at a time.
STRETCH = 1 << 14


def fingerprint(text: bytes, width: int = SHINGLE, seed: int = SEED) -> int:
    """64-bit SimHash of the word shingles of a text, every occurrence counted; signed."""
    from xxhash import xxh64_intdigest

    ws = text.lower().split()  # of bytes: the six ASCII white-space characters, and A-Z only
    if not ws:
        return 0
    n = max(1, len(ws) - width + 1)
    set_in = np.zeros(64, np.int64)
    for at in range(0, n, PIECE):
        part = ws[at : min(at + PIECE, n) + width - 1]
        joined = b" ".join(part)
        ends = np.cumsum(np.fromiter(map(len, part), np.int64, len(part)) + 1) - 1
        begins = np.concatenate(([0], ends[:-1] + 1))
        reach = min(width, len(part)) - 1
        spans = zip(begins[: len(part) - reach].tolist(), ends[reach:].tolist(), strict=True)
        hashes = np.array([xxh64_intdigest(joined[a:b], seed) for a, b in spans], np.uint64)
        bits = np.unpackbits(hashes.astype("<u8").view(np.uint8), bitorder="little").reshape(-1, 64)
        for lo in range(0, len(bits), 65535):
            set_in += bits[lo : lo + 65535].sum(axis=0, dtype=np.uint16)
    return int(np.packbits((2 * set_in > n).astype(np.uint8), bitorder="little").view("<u8")[0].astype(np.int64))


def fingerprints(docs: DataFrame, width: int = SHINGLE, seed: int = SEED, id_col: str = "doc_id", text_col: str = "text", row_col: str | None = None) -> DataFrame:
    """(doc_id, fp[, row_key]) of every row."""
    more = [F.col(row_col).alias("row_key")] if row_col else []
    extra = len(more)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release_memory()
        for batch in batches:
            fps = [fingerprint((t.as_py() or "").encode("utf-8", "replace"), width, seed) for t in batch.column(0)]
            yield pa.RecordBatch.from_arrays([batch.column(1).cast(pa.int64()), pa.array(fps, pa.int64()), *(batch.column(2 + i) for i in range(extra))], names=["doc_id", "fp", *["row_key"] * extra])

    return docs.select(F.col(text_col).alias("text"), F.col(id_col).cast("long").alias("doc_id"), *more).mapInArrow(run, "doc_id long, fp long" + ", row_key long" * extra)


def chain_of(fingerprints: int, most: int = MOST_BITS, segments: int = SEGMENTS) -> int:
    """The shortest chain whose equal segments have at least as many bits as the number of fingerprints: buckets of unrelated ones
    then stay small however many there are."""
    for chain in CHAINS:
        if (chain - chain * most // segments) * 64 // segments >= np.log2(max(fingerprints, 1)):
            return chain
    return CHAINS[-1]


def chain_masks(most: int = MOST_BITS, segments: int = SEGMENTS, chain: int = CHAINS[0]) -> list[int]:
    """Masks of the segments that are equal, over all starts and all ways to keep a chain of ``chain`` segments in budget.

    Within the first ``k`` segments of the chain at most ``k * most // segments`` may differ, so at least the rest is equal.
    """
    edges = [round(i * 64 / segments) for i in range(segments + 1)]
    bits = [((1 << edges[i + 1]) - 1) ^ ((1 << edges[i]) - 1) for i in range(segments)]
    need = [k - k * most // segments for k in range(1, chain + 1)]
    masks = set()
    for equal in combinations(range(chain), need[-1]):
        if all(sum(e < k for e in equal) >= need[k - 1] for k in range(1, chain + 1)):
            for start in range(segments):
                mask = 0
                for e in equal:
                    mask |= bits[(start + e) % segments]
                masks.add(mask)
    return sorted(masks)


def _chain_holds(diff: np.ndarray, most: int, segments: int) -> np.ndarray:
    """Whether some chain over the whole ring keeps every prefix within its share."""
    edges = [round(i * 64 / segments) for i in range(segments + 1)]
    counts = np.stack([np.bitwise_count((diff >> np.uint64(edges[i])) & np.uint64((1 << (edges[i + 1] - edges[i])) - 1)) for i in range(segments)]).astype(np.int16)
    good = np.zeros(diff.shape, bool)
    for start in range(segments):
        total, fine = np.zeros(diff.shape, np.int16), np.ones(diff.shape, bool)
        for k in range(1, segments + 1):
            total += counts[(start + k - 1) % segments]
            fine &= total * segments <= k * most
        good |= fine
    return good


def _linked(a: np.ndarray, b: np.ndarray, most: int, segments: int) -> np.ndarray:
    """Which of the pairs are within ``most`` bits; the chain condition goes first and leaves few for the full check."""
    diff = a ^ b
    flat = diff.ravel()
    found = np.zeros(flat.shape, bool)
    for at in range(0, len(flat), STRETCH):
        part = flat[at : at + STRETCH]
        left = np.flatnonzero(_chain_holds(part, most, segments))
        found[at + left] = np.bitwise_count(part[left]) <= most
    return found.reshape(diff.shape)


def bucket_links(fps: np.ndarray, most: int, segments: int) -> tuple[np.ndarray, np.ndarray]:
    """Links (member, smallest member) of the connected groups within one bucket of distinct fingerprints."""
    n = len(fps)
    label = np.arange(n)
    todo = np.ones(n, bool)
    for seed in range(n):
        if not todo[seed]:
            continue
        todo[seed] = False
        frontier, group = np.array([seed]), [seed]
        while len(frontier):
            others = np.flatnonzero(todo)
            if not len(others):
                break
            near = np.zeros(len(others), bool)
            for at in range(0, len(frontier), 64):
                near |= _linked(fps[frontier[at : at + 64], None], fps[None, others], most, segments).any(axis=0)
            frontier = others[near]
            todo[frontier] = False
            group.extend(frontier.tolist())
        if len(group) > 1:
            label[group] = group[int(np.argmin(fps[group].view(np.int64)))]
    moved = np.flatnonzero(label != np.arange(n))
    return fps[moved], fps[label[moved]]


def _groups(batches: Iterator[pa.RecordBatch], keys: int, most_rows: int) -> Iterator[tuple[tuple, np.ndarray, bool]]:
    """(key, values, whole) of a stream sorted by its first ``keys`` columns; groups over ``most_rows`` come in parts, not whole.

    The stream is cut at batches; at most ``most_rows`` values of one group and one batch are held.
    """
    held_key, held, over = None, [], False
    for batch in batches:
        if not batch.num_rows:
            continue
        cols = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(keys + 1)]
        change = np.zeros(batch.num_rows - 1, bool)
        for c in cols[:keys]:
            change |= c[1:] != c[:-1]
        cuts = np.concatenate(([0], np.flatnonzero(change) + 1, [batch.num_rows]))
        for i in range(len(cuts) - 1):
            key = tuple(c[cuts[i]] for c in cols[:keys])
            values = cols[keys][cuts[i] : cuts[i + 1]]
            if key != held_key:
                if held:
                    yield held_key, np.concatenate(held), not over
                held_key, held, over = key, [], False
            held.append(values)
            if sum(map(len, held)) > most_rows:
                over = True
                yield key, np.concatenate(held), False
                held = []
    if held:
        yield held_key, np.concatenate(held), not over


def _small_buckets(masks: list[int], most: int, segments: int, block: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows (a, b, mask): a link has mask -1, a member of an overfull bucket its mask and the bucket's key in b."""
        for a, b, m in _walk(batches):
            yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64)), pa.array(m)], names=["a", "b", "mask"])

    def _walk(batches):
        out_a, out_b, out_m, size = [], [], [], 0
        tail: list[np.ndarray] | None = None  # rows of the last, unfinished bucket: mask, key, fp
        over = None  # (mask, key) of a bucket that has exceeded a block

        def emit(a, b, m):
            nonlocal size
            if len(a):
                out_a.append(a.view(np.uint64)), out_b.append(b.view(np.uint64)), out_m.append(np.broadcast_to(np.int32(m), a.shape))
                size += len(a)

        def closed(mask, key, fp):
            """Whole buckets, each in adjacent rows."""
            cut = np.flatnonzero((mask[1:] != mask[:-1]) | (key[1:] != key[:-1])) + 1
            begin, end = np.concatenate(([0], cut)), np.concatenate((cut, [len(fp)]))
            several = end - begin > 1
            begin, end = begin[several], end[several]
            pairs = end - begin == 2
            if pairs.any():
                a, b = fp[begin[pairs]], fp[begin[pairs] + 1]
                good = _linked(a, b, most, segments)
                emit(a[good], b[good], -1)
            for s, e in zip(begin[~pairs].tolist(), end[~pairs].tolist(), strict=True):
                if e - s > block:
                    emit(fp[s:e], key[s:e], mask[s])
                else:
                    emit(*bucket_links(fp[s:e], most, segments), -1)

        for batch in batches:
            if not batch.num_rows:
                continue
            rows = [batch.column(0).to_numpy(), batch.column(1).to_numpy().view(np.uint64), batch.column(2).to_numpy().view(np.uint64)]
            if tail is not None:
                rows = [np.concatenate(x) for x in zip(tail, rows, strict=True)]
            mask, key, fp = rows
            last = np.flatnonzero((mask[1:] != mask[:-1]) | (key[1:] != key[:-1]))
            cut = int(last[-1]) + 1 if len(last) else 0
            if over is not None and (mask[0], key[0]) == over:
                stop = int(np.flatnonzero((mask != over[0]) | (key != over[1]))[0]) if cut else len(fp)
                emit(fp[:stop], key[:stop], mask[0])
                mask, key, fp, cut = mask[stop:], key[stop:], fp[stop:], max(0, cut - stop)
            if cut:
                closed(mask[:cut], key[:cut], fp[:cut])
                mask, key, fp = mask[cut:], key[cut:], fp[cut:]
            over_now = (mask[0], key[0]) if len(fp) else over
            if len(fp) > block:
                emit(fp, key, mask[0])
                over, tail = over_now, None
            elif len(fp):
                if over_now != over:
                    over = None
                tail = [mask, key, fp]
            else:
                tail = None
            if size:
                yield np.concatenate(out_a), np.concatenate(out_b), np.concatenate(out_m)
                out_a, out_b, out_m, size = [], [], [], 0
        if tail is not None:
            closed(*tail)
        if size:
            yield np.concatenate(out_a), np.concatenate(out_b), np.concatenate(out_m)

    return run


def links(nodes: DataFrame, work: Workspace, most: int = MOST_BITS, segments: int = SEGMENTS, chain: int | None = None, block: int = BLOCK) -> DataFrame:
    """Links (a, b) that connect all distinct fingerprints ``fp`` within ``most`` bits, directly or through others."""
    masks = chain_masks(most, segments, chain or chain_of(nodes.count(), most, segments))
    signed = [m - (1 << 64) if m >> 63 else m for m in masks]
    keys = F.explode(F.array(*[F.struct(F.lit(i).alias("mask"), F.col("fp").bitwiseAND(F.lit(m)).alias("key")) for i, m in enumerate(signed)]))
    buckets = nodes.select("fp", keys.alias("k")).select("k.mask", "k.key", "fp")
    dealt = buckets.repartition("mask", "key").sortWithinPartitions("mask", "key", "fp")
    found = work.save(dealt.mapInArrow(_small_buckets(signed, most, segments, block), "a long, b long, mask int"), "links")
    direct = found.where("mask < 0").select("a", "b")
    return direct.unionAll(_overfull(found.where("mask >= 0"), work, most, segments, block))


def _overfull(members: DataFrame, work: Workspace, most: int, segments: int, block: int) -> DataFrame:
    """Links of the buckets that exceed a block. Members are dealt into blocks by hash, and each pair of blocks is a group."""
    sizes = members.groupBy("mask", "b").agg(F.count("*").alias("n"))
    blocks = members.join(sizes, ["mask", "b"]).select("mask", F.col("b").alias("key"), F.col("a").alias("fp"), F.ceil(F.col("n") / block).cast("int").alias("of")).withColumn("own", F.pmod(F.xxhash64("fp"), F.col("of")).cast("int"))
    others = F.explode(F.sequence(F.lit(0), F.col("of") - 1))
    paired = blocks.withColumn("other", others).select(F.xxhash64("mask", "key").alias("bucket"), F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "fp")
    dealt = paired.repartition("bucket", "i", "j").sortWithinPartitions("bucket", "i", "j", "fp")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, fps, _ in _groups(batches, 3, 1 << 62):
            a, b = bucket_links(np.unique(fps).view(np.uint64), most, segments)
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

    return dealt.mapInArrow(run, "a long, b long")


def _rooted(of_doc: DataFrame, work: Workspace, most: int) -> DataFrame:
    """(fp, root) of every distinct fingerprint."""
    nodes = work.save(of_doc.select("fp").distinct(), "nodes")
    roots = components(links(nodes, work, most), work)
    return nodes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))


def _mixed(c: str):
    """A key that is computed anew, so that a join deals out both sides by itself and can split a hot value."""
    return F.col(c).bitwiseXOR(F.lit(1))


def near_duplicates(docs: DataFrame, width: int = SHINGLE, most: int = MOST_BITS, seed: int = SEED) -> DataFrame:
    """(doc_id, fp, component_id) of every row; component_id is the smallest doc_id that links reach, its own included."""
    work = Workspace(docs.sparkSession, "simhash")
    of_doc = work.save(fingerprints(docs, width, seed), "fingerprints")
    of_node = work.save(_rooted(of_doc, work, most), "roots")
    firsts = of_doc.groupBy("fp").agg(F.min("doc_id").alias("first"))
    of_root = firsts.join(of_node, "fp").groupBy("root").agg(F.min("first").alias("component_id"))
    ids = of_node.select("fp", _mixed("root").alias("k")).join(of_root.select(_mixed("root").alias("k"), "component_id"), "k").select(_mixed("fp").alias("key"), "component_id")
    return of_doc.withColumn("key", _mixed("fp")).join(ids, "key").select("doc_id", "fp", "component_id")


def deduplicate(docs: DataFrame, width: int = SHINGLE, most: int = MOST_BITS, seed: int = SEED) -> DataFrame:
    """One row of ``docs`` of each component: of those with the smallest id (rows without one last), the one with the smallest row key."""
    work = Workspace(docs.sparkSession, "simhash")
    rows = row_keyed(docs, work)
    of_doc = work.save(fingerprints(rows.select("row.doc_id", "row.text", "row_key"), width, seed, row_col="row_key"), "fingerprints")
    rooted = of_doc.withColumn("k", _mixed("fp")).join(_rooted(of_doc, work, most).select(_mixed("fp").alias("k"), "root"), "k")
    first = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "row_key")
    kept = rooted.groupBy("root").agg(F.min(first).alias("first")).select(F.col("first.row_key").alias("row_key"))
    return rows.join(kept, "row_key", "left_semi").select(*columns_of_row(docs.columns))


def query(spark, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"), width=4)
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
