import random

import numpy as np
import pyarrow as pa
from adaptivejoin.llm import lines, tokens
from pyspark.sql import functions as F


def brute(rows, least=lines.LEAST_WORDS):
    """{doc: lines kept} by comparing every line with all earlier ones."""
    seen, out = [], {}
    index = {}
    for d, text in sorted(rows):
        kept = []
        for line in (text or "").split("\n"):
            s = frozenset(line.encode().lower().split())
            dup = False
            if len(s) >= least:
                shared = {}
                for w in s:
                    for i in index.get(w, ()):
                        shared[i] = shared.get(i, 0) + 1
                dup = any(9 * c >= 4 * (len(s) + len(seen[i])) for i, c in shared.items())
                if s not in index.setdefault("sets", set()):
                    index["sets"].add(s)
                    seen.append(s)
                    for w in s:
                        index.setdefault(w, []).append(len(seen) - 1)
            if not dup:
                kept.append(line)
        out[d] = "\n".join(kept)
    return out


def test_lines_and_words_match_split():
    rng = random.Random(1)
    for _ in range(300):
        texts = ["".join(rng.choice(["a", "B", "é", " ", "\n", "\t", "\x0b"]) for _ in range(rng.randint(0, 12))) for _ in range(rng.randint(1, 6))]
        want = [(r, k, line.encode().lower().split()) for r, t in enumerate(texts) for k, line in enumerate(t.split("\n"))]
        for size in (1, 1 << 20):
            got, names = [], {}
            for lo, p in tokens.pieces(pa.array(texts), size):
                of = [[] for _ in p.row]
                for w, li in zip(p.word.tolist(), p.line.tolist(), strict=True):
                    of[li].append(w)
                got += [(lo + int(r), int(k), ws) for r, k, ws in zip(p.row, p.number, of, strict=True)]
            assert [x[:2] for x in got] == [x[:2] for x in want]
            for (_, _, a), (_, _, b) in zip(got, want, strict=True):
                assert len(a) == len(b) and all(names.setdefault(y, x) == x for x, y in zip(a, b, strict=True))
            assert len(set(names.values())) == len(names)


def test_word_hashes_tell_words_apart():
    """Words of 1024 letters, bytes swapped 4096 apart, order, padding: hashes of all bytes in their order."""
    rng = random.Random(4)
    a, b = ("".join(rng.choice("abcdefgh") for _ in range(1024)) for _ in range(2))
    body = "x" * 5000
    c, d = (body[:100] + u + body[102:4196] + v + body[4198:] for u, v in (("ab", "cd"), ("cd", "ab")))
    words = [a, b, c, d, a[:200], b[:200], a[8:16] + a[:8], a[:16], "ab", "ba", "a\x00", "a", "abcdefgh", "abcdefghabcdefgh", "é"]
    got = next(tokens.pieces(pa.array([" ".join(words)])))[1].word
    assert len(set(got.tolist())) == len(words)
    again = next(tokens.pieces(pa.array(["zz " + " ".join(w.upper() if w.isascii() else w for w in words)])))[1].word
    assert again[1:].tolist() == got.tolist()


def test_lines_of_long_similar_words(spark):
    """Eight of twelve words shared is 0.5: nothing goes, however alike the others look; eleven shared is 11/13."""
    swap = lambda w: w[:100] + w[4196:4198] + w[102:4196] + w[100:102] + w[4198:]
    own = [f"{i}" + "x" * 99 + "ab" + "x" * 4094 + "cd" + "x" * 50 for i in range(4)]
    same = [f"w{i}" for i in range(8)]
    rows = [(1, " ".join(same + own)), (2, " ".join(same + [swap(w) for w in own])), (3, " ".join(same + own[:3] + [swap(own[3])]))]
    got = {r.row.doc_id: r.n_removed for r in lines.deduplicate(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: 0, 2: 0, 3: 1}


def test_sketch_never_exceeds_the_difference():
    rng = random.Random(2)
    for _ in range(200):
        a = [str(rng.randint(0, 40)) for _ in range(30)]
        b = [str(rng.randint(0, 40)) for _ in range(30)]
        p = next(iter(tokens.pieces(pa.array([" ".join(a), " ".join(b)]))))[1]
        word, line, _ = lines.ordered_sets(p, np.zeros(1 << 16, np.uint8))
        _, size, _, s0 = lines.describe(word, line, 2)
        assert size.tolist() == [len(set(a)), len(set(b))]
        assert np.bitwise_count(s0[0] ^ s0[1]).max() <= len(set(a) ^ set(b))
    for extra in (0, 90):  # the three parts of a wide sketch together
        a, b = ({str(rng.randint(0, 400)) for _ in range(70 + extra)} for _ in range(2))
        p = next(iter(tokens.pieces(pa.array([" ".join(a), " ".join(b)]))))[1]
        word, line, _ = lines.ordered_sets(p, np.zeros(1 << 16, np.uint8))
        s0 = lines.describe(word, line, 2)[3]
        assert np.bitwise_count(s0[0, 1:] ^ s0[1, 1:]).sum() <= len(a ^ b) and np.bitwise_count(s0[0, 0] ^ s0[1, 0]) <= len(a ^ b)


def test_query_matches_brute_force(spark, sf_dir):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").collect()]
    want = brute(rows)
    got = {r.doc_id: r.text for r in lines.query(spark, sf_dir).collect()}
    assert got == want and sum(want[d] != t for d, t in rows) > 10


def test_near_copies_in_small_blocks_match_brute_force(spark, monkeypatch):
    rng = random.Random(3)
    base = [f"w{i}" for i in range(25)]
    rows = []
    for d in range(120):
        mine = [w if rng.random() > 0.06 else f"x{rng.randint(0, 60)}" for w in base]
        common = " ".join(rng.choice(["the", "of", "and", "to", "in", "is", "on", "at"]) for _ in range(rng.randint(5, 9)))
        rows.append((d, " ".join(mine) + "\n" + common + "\n" + " ".join(f"u{d}-{k % 9}" for k in range(12))))
    want = brute(rows)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    # The least reserve and few lines held at a time: many lines are looked up again.
    for first, block, short, reserve, held in ((3, 2048, 48, 64, 4096), (1, 7, 2, 1, 5), (2, 60, 3, 2, 3)):
        monkeypatch.setattr(lines, "SHORT", short)
        monkeypatch.setattr(lines, "RESERVE", reserve)
        monkeypatch.setattr(lines, "HELD", held)
        got = {r.row.doc_id: r.text for r in lines.deduplicate(df, first=first, block=block).collect()}
        assert got == want


def test_nulls_blank_repeated_and_other_columns(spark):
    long = " ".join(f"w{i}" for i in range(50_000))
    p = "one two three four five six"
    rows = [(5, f"{p}\n\nshort line\n{p} ", "k"), (5, f"{p}\n\nshort line\n{p} ", "k"), (6, None, "k"), (7, "", "k"), (None, f"{p}\nshort line", "k"), (8, long, "k"), (9, "x\n" + long, "k"), (4, "SIX five four three two one", "k")]
    df = spark.createDataFrame(rows, "doc_id long, text string, gone string")
    got = sorted((r.row.doc_id or 99, r.text, r.n_removed) for r in lines.deduplicate(df).select("row", F.substring("text", 1, 30).alias("text"), "n_removed").collect() if r.row.doc_id != 6)
    assert got == [(4, "SIX five four three two one", 0), (5, "", 3), (5, "\nshort line", 2), (7, "", 0), (8, long[:30], 0), (9, "x", 1), (99, "", 2)]
    assert lines.deduplicate(df.where("doc_id = 6")).first().text is None
    assert lines.deduplicate(df.limit(0)).collect() == []


def test_rows_that_share_an_id_keep_their_first_lines(spark):
    p, q, r = ("one two three four five six", "a b c d e f g", "h i j k l m n")
    near = "one two three four five six seven"
    rows = [(5, f"{p}\n{q}", "k"), (5, f"{p}\n{q}", "k"), (None, f"{q}\n{r}", "m"), (None, f"{p} \n{r} o", "m"), (None, f"u v w x y z\n{near}", "m")]
    df = spark.createDataFrame(rows, "doc_id long, text string, k string")
    for part in (df, df.repartition(3)):
        out = lines.deduplicate(part).collect()
        left = sorted(line for x in out for line in x.text.split("\n") if line)
        assert left in (sorted([p, q, kept, "u v w x y z"]) for kept in (r, f"{r} o"))
        assert sorted(x.n_removed for x in out if x.row.k == "k") in ([0, 2], [1, 1])


def test_one_of_similar_lines_at_the_same_place_stays(spark):
    """Different lines of rows without id, each similar to the others: the order between them is the same in all lists."""
    base = [f"w{i}" for i in range(30)]
    rows = [(None, " ".join([*base[:i], f"x{i}", *base[i + 1 :]])) for i in range(20)]
    out = lines.deduplicate(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sum(x.text != "" for x in out) == 1


def test_one_id_on_two_texts_and_null_ids(spark):
    """Only the row that repeats a line loses it, whatever ids the rows share."""
    p = "one two three four five six"
    rows = [(1, p), (7, p), (7, "totally unrelated words that nothing else holds"), (None, "a line of its own here"), (None, f"{p}\nanother line of its own")]
    got = sorted(r.text for r in lines.deduplicate(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got == sorted([p, "", "totally unrelated words that nothing else holds", "a line of its own here", "another line of its own"])


def test_frequent_words_are_dealt_out(spark, monkeypatch):
    """Salted words and small blocks: the same result."""
    rng = random.Random(9)
    rows = [(d, "\n".join(" ".join(["hot", *(rng.choice("abcdefghij") * 3 for _ in range(rng.randint(3, 7)))]) for _ in range(4))) for d in range(150)]
    want = brute(rows)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    got = {r.row.doc_id: r.text for r in lines.deduplicate(df, block=8).collect()}
    assert got == want


def test_short_lines_take_part(spark):
    """One to four distinct words; four match five that hold them, three do not match four."""
    few = " ".join(["a", "b", "c", "d"] * 15)
    rows = [(1, f"x\n{few}\np q r\n \ne f g h"), (2, f"x\n{few}\nq p r s\n\ne f g h i"), (3, "r q p\nX\nx y\n\ne f g")]
    want = {1: f"x\n{few}\np q r\n \ne f g h", 2: "q p r s\n", 3: "x y\n\ne f g"}
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert {r.row.doc_id: r.text for r in lines.deduplicate(df).collect()} == want == brute(rows, 1)


def test_only_pairs_within_reach_are_compared():
    """Pairs that lengths or places rule out are never made; all others are, once."""
    rng = np.random.default_rng(3)
    n = 600
    size = rng.integers(4, 60, n)
    group = rng.integers(0, 9, n)
    order = np.lexsort((size, group))
    size, group = size[order], group[order]
    pos = rng.integers(0, size // 5 + 1)
    rows = np.zeros((n, lines.OF_LINE), np.uint64)
    rows[:, lines.SIZE], rows[:, lines.AT] = size.astype(np.uint64) | np.uint64(7 << 32), pos.astype(np.uint64) | np.uint64(5 << 32)
    most, reach = lines._reach(rows)
    assert (most == size).all()
    enough = lambda i, j: 9 * min(size[i] - pos[i], size[j] - pos[j]) >= 4 * (size[i] + size[j]) and 5 * min(size[i], size[j]) >= 4 * max(size[i], size[j])
    want = [(i, j) for i in range(n) for j in range(i + 1, n) if group[i] == group[j] and enough(i, j)]
    got = [p for i, j in lines.fitting_pairs(size, reach, group) for p in zip(i.tolist(), j.tolist(), strict=True)]
    assert sorted(got) == want and 2 * len(want) < sum(int(c) * (int(c) - 1) // 2 for c in np.bincount(group))


def test_turns_share_the_keys(spark, sf_dir):
    """Rows of all turns together are those of one, and no key falls to two turns."""
    texts = pa.array([r.text for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()], pa.string())
    ids = pa.array(range(len(texts)), pa.int64())
    table = type("Table", (), {"value": np.full(1 << 10, 2, np.uint8)})

    def rows(**turn):
        run = lines._nodes(table, hot=9, parts=4, **turn)(iter([pa.RecordBatch.from_arrays([ids, texts, ids], names=["doc", "text", "row_key"])]))
        return sorted((k, v) for b in run for k, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True))

    one, parts = rows(), [rows(turn=t, turns=3) for t in range(3)]
    assert sorted(sum(parts, [])) == one and all(parts)
    keys = [{k for k, _ in p} for p in parts]
    assert sum(map(len, keys)) == len(set().union(*keys))


def _bundles_of(texts, bits=7):
    """What a worker sends of texts: batches of bundles."""
    table = type("Table", (), {"value": np.full(1 << 10, 2, np.uint8)})
    ids = pa.array(range(len(texts)), pa.int64())
    batch = pa.RecordBatch.from_arrays([ids, pa.array(texts, pa.string()), ids], names=["doc", "text", "row_key"])
    rows = lines._nodes(table, hot=9, parts=4)
    return [batch], rows, list(lines._bundled(rows, bits)(iter([batch])))


def test_bundles_hold_all_rows_in_few(spark, sf_dir):
    """The shuffle deals bundles, not rows; buckets are in the order of keys, and no row is lost or changed."""
    texts = [r.text for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()]
    batches, rows, sent = _bundles_of(texts)
    want = sorted((k, v) for b in rows(iter(batches)) for k, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True) if k >= 0)
    got, seen = [], set()
    for bucket, _, values in lines._by_bucket(iter(sent)):
        whole = lines._unbundled(values, lines.OF_SET if bucket < 0 else lines.OF_LINE)
        keys = whole[:, 0].copy().view(np.int64)
        assert (lines._bucket(keys, 7) == bucket).all()
        seen.update((int(x[1]), int(x[4])) for x in whole if bucket < 0)
        got += [(k, x[1:].tobytes()) for k, x in zip(keys.tolist(), whole, strict=True) if bucket >= 0]
    assert sorted(got) == want and 10 * sum(b.num_rows for b in sent) < len(want)
    sets = [v for b in rows(iter(batches)) for k, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True) if k < 0]
    assert seen == {tuple(np.frombuffer(v, np.uint64)[[0, 3]].tolist()) for v in sets}
    keys = np.sort(np.array([k for k, _ in want] + [-(1 << 63), -5, 0, lines.HOT, (1 << 63) - 1]))
    assert (np.diff(lines._bucket(keys, 7)) >= 0).all()


def test_a_very_common_line_is_one_row_under_its_key():
    """A worker sends one place of a set under its key; the other places are marked as later ones and dealt by row."""
    _, _, sent = _bundles_of([f"a common line here\nown line number {i}" for i in range(300)])
    rows = np.concatenate([lines._unbundled(v, lines.OF_SET) for bucket, _, v in lines._by_bucket(iter(sent)) if bucket < 0])
    own, count = np.unique(rows[:, 1], return_counts=True)
    common = rows[rows[:, 1] == own[count.argmax()]]
    marked = (common[:, 1 + lines.AT] & lines.LATE) > 0
    assert len(common) == 300 and marked.sum() == 299 and common[~marked][0, 1 + lines.DOC] == 0
    assert len(np.unique(common[:, 0])) == 300


def test_buckets_over_the_limit_lose_nothing(spark, monkeypatch):
    """Buckets are thinned while they come in: common lines and long lists, the same result."""
    rng = random.Random(12)
    base = [f"w{i}" for i in range(20)]
    rows = [(d, "the same line\n" + " ".join(w if rng.random() > 0.05 else f"x{rng.randint(0, 40)}" for w in base) + f"\none of ten {d % 10}") for d in range(200)]
    want = brute(rows)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    bundled, meet = lines._bundled, lines._meet_bundles
    for bits in (7, 1):
        monkeypatch.setattr(lines, "_bundled", lambda nodes, _, bits=bits: _small(bundled(nodes, bits), lines))
        monkeypatch.setattr(lines, "_meet_bundles", lambda first, block, _, bits=bits: _small(meet(first, block, bits), lines))
        for block in (2048, 5):
            assert {r.row.doc_id: r.text for r in lines.deduplicate(df, block=block).collect()} == want


def _small(run, module):
    """Run in a worker with bundles and limits of few rows."""

    def small(batches):
        before = module.BUNDLED, module.BUNDLE, module.GATHERED
        module.BUNDLED, module.BUNDLE, module.GATHERED = 40, 4, 8
        try:
            yield from run(batches)
        finally:
            module.BUNDLED, module.BUNDLE, module.GATHERED = before

    return small
