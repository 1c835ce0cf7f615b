import math

import numpy as np
from adaptivejoin.llm import neighbours


def brute(rows, every, k=5):
    ids = np.array([i for i, _ in rows])
    v = np.array([x for _, x in rows], float)
    norm = np.sqrt((v * v).sum(1))
    out = {}
    for i in np.flatnonzero(ids % every == 0):
        s = (v * v[i]).sum(1) / (norm * norm[i])
        s[i] = -np.inf
        out[int(ids[i])] = [(int(ids[j]), s[j]) for j in np.lexsort((ids, -s))[:k] if s[j] > -np.inf]
    return out


def test_recall_and_scores(spark, sf_dir):
    rows = [(r.vec_id, r.embedding) for r in spark.read.parquet(f"{sf_dir.replace('0.001', '0.1')}/embeddings.parquet").collect()]
    want = brute(rows, 50)
    found = {}
    for r in neighbours.query(spark, sf_dir.replace("0.001", "0.1")).collect():
        found.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    assert found.keys() == want.keys()
    hits = 0
    vectors = {i: np.array(x, float) for i, x in rows}
    for q, got in found.items():
        got.sort()
        assert [g[0] for g in got] == [1, 2, 3, 4, 5]
        assert all(a[2] > b[2] or (a[2] == b[2] and a[1] < b[1]) for a, b in zip(got, got[1:], strict=False))
        for _, i, s in got:
            assert i != q and math.isclose(s, vectors[i] @ vectors[q] / np.linalg.norm(vectors[i]) / np.linalg.norm(vectors[q]), rel_tol=1e-12)
        hits += len({g[1] for g in got} & {i for i, _ in want[q]})
    assert hits / (5 * len(want)) >= 0.95
    # Vectors without structure: a part is verified.
    share = sum({r.query_id: r.verified for r in neighbours.query(spark, sf_dir.replace("0.001", "0.1")).collect()}.values()) / len(want) / len(rows)
    assert 0 < share < 0.25


def test_few_are_verified_on_clustered_vectors(spark):
    rng = np.random.default_rng(4)
    centres = rng.standard_normal((40, 64))
    rows = [(i, (centres[rng.integers(0, 40)] + 0.3 * rng.standard_normal(64)).tolist()) for i in range(3000)]
    want = brute(rows, 50)
    got = neighbours.search(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), every=50).collect()
    hits = sum(r.vec_id in {i for i, _ in want[r.query_id]} for r in got)
    assert hits / (5 * len(want)) >= 0.95
    assert sum({r.query_id: r.verified for r in got}.values()) / len(want) / len(rows) < 0.2


def test_windows_and_counts_are_those_of_a_plain_loop():
    """Every vector is first verified at the radius at which enough single windows hold it."""
    rng = np.random.default_rng(5)
    v = rng.standard_normal((200, 8))
    index = neighbours.Index(np.arange(200), v, 12)
    unit = v / np.linalg.norm(v, axis=1)[:, None]
    at = index.directions.astype(float) @ unit.T
    got, scores = index.search(0, v[0], 5)
    found = set()
    for r in [*neighbours.radii_up_to(2.0), np.inf]:
        found |= {i for i in range(1, 200) if (np.abs(at[:, i] - at[:, 0]) <= r).sum() >= index.threshold}
        best = sorted(((unit[i] @ unit[0], -i) for i in found), reverse=True)[:5]
        if len(best) == 5 and 2 - 2 * best[-1][0] <= r * r:
            break
    assert got.tolist() == [-i for _, i in best] and np.allclose(scores, [s for s, _ in best])
    assert index.verified == len(found)


def test_many_small_blocks(spark):
    rng = np.random.default_rng(0)
    rows = [(i, rng.standard_normal(8).tolist()) for i in range(300)]
    got = neighbours.search(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), every=10, block=40).collect()
    want = brute(rows, 10)
    assert len(got) == 5 * len(want)
    hits = sum(r.vec_id in {i for i, _ in want[r.query_id]} for r in got)
    assert hits / len(got) >= 0.9


def test_invalid_tied_repeated_and_few(spark):
    nan, inf = float("nan"), float("inf")
    rows = [
        (0, [1.0, 0.0], "a"), (0, [1.0, 0.0], "b"), (3, [2.0, 0.0], "c"), (2, [1.0, 0.0], "d"), (1, [0.0, 1.0], "e"), (50, None, "f"), (51, [0.0, 0.0], "g"),
        (52, [nan, 1.0], "h"), (53, [None, 1.0], "i"), (54, [inf, 1.0], "j"), (100, [1.0, 0.0, 0.0], "k"), (None, [1.0, 0.0], "l"), (55, [], "m"),
    ]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, score string")
    got = sorted((r.query_id, r["rank"], r.vec_id, r.score) for r in neighbours.search(df, every=50).collect())
    assert got == [(0, 1, 2, 1.0), (0, 2, 3, 1.0), (0, 3, 1, 0.0)]
    assert neighbours.search(df.limit(0), every=50).collect() == []


def test_leaves_and_a_large_block_cost_little():
    """Leaves hold every vector that a plain window holds, and a query of a large block counts few windows."""
    rng = np.random.default_rng(6)
    n = 8000
    v = rng.standard_normal((n, 16))
    index = neighbours.Index(np.arange(n), v, 40)
    unit = v / np.linalg.norm(v, axis=1)[:, None]
    at = index.directions @ unit[7].astype(np.float32)
    plain = (np.abs(index.directions @ unit.T.astype(np.float32) - at[:, None]) <= 0.7).sum(axis=0)
    counted = index.collisions(at, 0.7)
    assert (counted >= plain - 1).all() and (counted - plain.astype(int)).mean() < 40 * 2 / neighbours.LEAVES
    calls = []
    count, index.collisions = index.collisions, lambda *a: calls.append(a) or count(*a)
    hits = 0
    for q in range(0, n, 100):
        got, _ = index.search(q, v[q], 5)
        s = unit @ unit[q]
        s[q] = -2
        hits += len({*got.tolist()} & {*np.argsort(-s)[:5].tolist()})
    assert len(calls) <= 3 * 80 and hits / 400 >= 0.9


def test_copies_beyond_an_answer_are_not_held(spark):
    """Many equal vectors: the smallest ids are the answer, in a task that holds k + 1 of them."""
    rng = np.random.default_rng(8)
    rows = [(i, [1.0, 2.0] if i % 3 else rng.standard_normal(2).tolist()) for i in range(600)]
    got = neighbours.search(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), every=50).collect()
    same = [i for i in range(600) if i % 3]
    for q in (50, 100, 200):
        assert [r.vec_id for r in sorted((r for r in got if r.query_id == q), key=lambda r: r["rank"])] == [i for i in same if i != q][:5]
    assert max(r.verified for r in got) < 250
