import random

import numpy as np
import xxhash
from adaptivejoin.llm import simhash
from adaptivejoin.llm.common import Workspace
from adaptivejoin.llm.components import components
from pyspark.sql import functions as F


def brute_fingerprint(text, width, seed=42):
    ws = [w.decode() for w in (text or "").encode().lower().split()]
    if not ws:
        return 0
    shingles = [" ".join(ws[i : i + width]) for i in range(max(1, len(ws) - width + 1))]
    hashes = [xxhash.xxh64_intdigest(s.encode(), seed) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute_components(rows, width, most=4):
    """rows: (doc_id, text); smallest reachable id of each."""
    fps = [(d, brute_fingerprint(t, width)) for d, t in rows]
    label = {d: d for d, _ in fps}
    arr = np.array([f for _, f in fps], np.uint64)
    ids = np.array([d for d, _ in fps])
    for i, d in enumerate(ids.tolist()):  # breadth first from the smallest
        pass
    seen, out = set(), {}
    order = np.argsort(ids)
    for i in order.tolist():
        if i in seen:
            continue
        todo, seen_now = [i], {i}
        while todo:
            j = todo.pop()
            near = np.flatnonzero(np.bitwise_count(arr ^ arr[j]) <= most)
            for k in near.tolist():
                if k not in seen_now:
                    seen_now.add(k)
                    todo.append(k)
        for j in seen_now:
            out[int(ids[j])] = int(ids[i])
        seen |= seen_now
    del label
    return dict(fps), out


def test_fingerprint_matches_brute_force():
    rng = random.Random(1)
    for n in (0, 1, 3, 4, 5, 50, 300):
        text = " \t".join(rng.choice(["The", "cat", "É", "z\x85z", "on"]) + str(rng.random()) for _ in range(n))
        for width in (4, 5):
            assert simhash.fingerprint(text.encode(), width) % (1 << 64) == brute_fingerprint(text, width)


def test_pieces_do_not_change_a_fingerprint(monkeypatch):
    text = " ".join(str(i * i) for i in range(5000)).encode()
    whole = simhash.fingerprint(text, 4)
    monkeypatch.setattr(simhash, "PIECE", 7)
    assert simhash.fingerprint(text, 4) == whole


def test_masks_miss_no_pair_within_the_distance():
    rng = random.Random(2)
    masks = simhash.chain_masks()
    assert len(masks) == 40 and all(bin(m).count("1") == 24 for m in masks)
    for _ in range(3000):
        diff = 0
        for b in rng.sample(range(64), 4):
            diff |= 1 << b
        assert any(diff & m == 0 for m in masks)


def test_query_matches_brute_force(spark, sf_dir):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").collect()]
    fps, comp = brute_components(rows, 4)
    got = simhash.query(spark, sf_dir).collect()
    assert {r.doc_id: r.fingerprint for r in got} == {d: f"{f:016x}" for d, f in fps.items()}
    assert {r.doc_id: r.component_id for r in got} == comp


def test_dense_buckets_in_blocks_match_brute_force(spark):
    rng = random.Random(3)
    base = rng.getrandbits(64)
    fps = {base}
    for _ in range(400):
        f = base
        for b in rng.sample(range(64), rng.randint(1, 7)):
            f ^= 1 << b
        fps.add(f)
    fps |= {rng.getrandbits(64) for _ in range(200)}
    fps = sorted(fps)
    arr = np.array(fps, np.uint64)
    signed = arr.view(np.int64)
    for block in (8, 2048):
        work = Workspace(spark, "test")
        nodes = spark.createDataFrame([(int(x),) for x in signed], "fp long")
        found = simhash.links(nodes, work, block=block).collect()
        for r in found[:2000]:
            assert r.a != r.b
        root = {r.node: r.root for r in components(spark.createDataFrame([(r.a, r.b) for r in found], "a long, b long"), work).collect()}
        near = np.bitwise_count(arr[:, None] ^ arr[None]) <= 4
        label = np.arange(len(arr))
        while True:
            new = np.where(near, label[None], len(arr)).min(axis=1)
            if (new == label).all():
                break
            label = new
        groups, own = {}, {}
        for i, x in enumerate(signed.tolist()):
            groups.setdefault(int(label[i]), set()).add(x)
            own.setdefault(root.get(x, x), set()).add(x)
        assert sorted(map(sorted, groups.values())) == sorted(map(sorted, own.values()))


def test_nulls_ties_repeats_and_other_columns(spark):
    rows = [(1, None, "a"), (2, "", "b"), (3, " \n", "c"), (4, "one two", "d"), (4, "one two", "d"), (5, "ONE  two", "f"), (None, "three", "g"), (6, "word " * 30000, "h")]
    df = spark.createDataFrame(rows, "doc_id long, text string, fp string").withColumn("row_key", F.lit("k"))
    got = {(r.doc_id, r.component_id) for r in simhash.near_duplicates(df, 4).collect()}
    assert got == {(1, 1), (2, 1), (3, 1), (4, 4), (5, 4), (None, None), (6, 6)}
    kept = simhash.deduplicate(df, 4)
    assert kept.columns == df.columns
    assert sorted(r.fp for r in kept.collect()) == ["a", "d", "g", "h"] and {r.row_key for r in kept.collect()} == {"k"}
    assert simhash.near_duplicates(df.limit(0), 4).collect() == []
    assert simhash.deduplicate(df.limit(0), 4).collect() == []


def test_one_id_on_two_texts_and_null_ids(spark):
    """Rows are judged one by one: other texts under a removed id stay, copies under one id or none go."""
    t, u, v = ("the same few words in a row here", "quite another text with its own words", "a third one that nothing else resembles")
    rows = [(3, t), (5, t), (5, u), (None, v), (None, v), (None, t), (7, v), (8, "x"), (8, "x")]
    kept = simhash.deduplicate(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted((r.doc_id, r.text) for r in kept) == sorted([(3, t), (5, u), (7, v), (8, "x")])


def test_chain_follows_the_number_of_fingerprints():
    """Longer chains miss nothing either."""
    assert [simhash.chain_of(n) for n in (0, 1 << 20, 1 << 24, 1 << 25, 1 << 31, 1 << 40)] == [5, 5, 5, 7, 7, 8]
    rng = random.Random(5)
    for chain in simhash.CHAINS:
        masks = simhash.chain_masks(chain=chain)
        for _ in range(1000):
            diff = sum(1 << b for b in rng.sample(range(64), 4))
            assert any(diff & m == 0 for m in masks)


def test_chain_condition_goes_before_the_full_check_at_any_size():
    rng = np.random.default_rng(6)
    a = rng.integers(0, 1 << 63, 40_000, np.uint64)
    flips = np.array([sum(1 << b for b in random.Random(i).sample(range(64), i % 8)) for i in range(40_000)], np.uint64)
    assert (simhash._linked(a, a ^ flips, 4, 8) == (np.bitwise_count(flips) <= 4)).all()


def test_components_of_a_long_path(spark):
    work = Workspace(spark, "test")
    edges = spark.createDataFrame([(i, i + 1) for i in range(100)] + [(200, 201), (201, 200), (7, 7)], "a long, b long")
    got = {r.node: r.root for r in components(edges, work).collect()}
    assert got == {i: 0 for i in range(1, 101)} | {201: 200}
