import math
import random
import zlib
from collections import Counter, defaultdict

import pyarrow as pa
import pytest
from adaptivejoin.llm import language


def brute_bits(train_texts, least_seen=language.LEAST_SEEN):
    """Code length function of PPM by recursion over dictionaries; train_texts: {lang: [text]}."""
    counts = {l: defaultdict(Counter) for l in train_texts}
    for l, texts in train_texts.items():
        for t in texts:
            b = bytes([0, 0, 0]) + t.lower().encode()
            for i in range(3, len(b)):
                for k in range(4):
                    counts[l][b[i - k : i]][b[i]] += 1
    total = Counter()
    for l in counts:
        for ctx, c in counts[l].items():
            total[ctx] += sum(c.values())
    seen = {0} | {x for l in counts for ctx in counts[l] for x in [*ctx, *counts[l][ctx]]}

    def dist(l, ctx):
        """Probability of every byte after a context that is known, however short."""
        if ctx is None:
            return {x: 1 / 256 for x in range(256)}
        lower = dist(l, shorter(ctx))
        c = counts[l].get(ctx)
        if not c:
            return lower
        n, q = sum(c.values()), len(c)
        left = sum(p for x, p in lower.items() if x not in c)
        if left <= 0:
            return {x: c[x] / n for x in range(256)}
        return {x: c[x] / (n + q) if x in c else q / (n + q) * lower[x] / left for x in range(256)}

    def shorter(ctx):
        while ctx:
            ctx = ctx[1:]
            if not ctx or total[ctx] >= least_seen:
                return ctx
        return None

    memo = {}

    def bits(l, text):
        b = bytes([0, 0, 0]) + text.lower().encode()
        out = 0.0
        for i in range(3, len(b)):
            ctx = b[i - 3 : i]
            while ctx and total[ctx] < least_seen:
                ctx = ctx[1:]
            if (l, ctx) not in memo:
                memo[l, ctx] = dist(l, ctx)
            out -= math.log2(memo[l, ctx][b[i]])
        return out

    assert seen
    return bits


def trained(train_texts):
    import numpy as np

    langs = sorted(train_texts)
    parts = [language.grams(pa.array(train_texts[l])) for l in langs]
    lang = np.concatenate([np.full(len(g), i) for i, (g, _) in enumerate(parts)])
    return language.build(langs, lang, np.concatenate([g for g, _ in parts]), np.concatenate([n for _, n in parts]).astype(float))


def test_code_lengths_match_brute_force():
    train = {"a": ["the cat sat on the mat and the hat", "that is the thing", ""], "b": ["der hund und die katze", "das ist gut, nicht wahr"]}
    model, bits = trained(train), brute_bits(train)
    texts = ["the thing", "und das", "", "ÄÖ zz 99 the", "The Cat\nund", "x" * 50]
    got = language.code_lengths(pa.array(texts), model)
    small = language.code_lengths(pa.array(texts), model, piece=5)
    for i, t in enumerate(texts):
        for j, l in enumerate(model.langs):
            assert got[i, j] == pytest.approx(bits(l, t), rel=1e-5, abs=1e-4)
            assert small[i, j] == pytest.approx(got[i, j], rel=1e-6, abs=1e-6)


def test_distributions_sum_to_one():
    import numpy as np

    model = trained({"a": ["the cat sat on the mat"] * 3, "b": ["der hund und die katze"] * 3})
    size = round(len(model.row) ** (1 / 3))
    members = np.ones(size)
    members[-1] = 256 - (size - 1)
    p = np.exp2(-model.bits.reshape(-1, size, 2).astype(float)) * members[None, :, None]
    assert np.allclose(p.sum(1), 1, atol=1e-5)


def test_held_out_accuracy(spark, sf_dir):
    got = {r.doc_id: r for r in language.query(spark, sf_dir.replace("sf0.001", "sf0.01")).collect()}
    truth = spark.read.parquet(f"{sf_dir.replace('sf0.001', 'sf0.01')}/documents.parquet").select("doc_id", "lang").collect()
    assert len(got) == len(truth)
    out = [(r.lang, got[r.doc_id].lang_pred) for r in truth if zlib.crc32(str(r.doc_id).encode()) % 5 == 0]
    assert all(got[r.doc_id].held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in truth)
    assert len(out) > 150 and sum(a == b for a, b in out) / len(out) > 0.97
    assert all(0 <= r.score <= 1 for r in got.values())


def test_held_out_labels_are_not_read(spark):
    rows = [(i, "aaa bbb ccc" if i % 2 else "xxx yyy zzz", ("p" if i % 2 else "q") if zlib.crc32(str(i).encode()) % 5 else "secret") for i in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    counts = language.train(df)
    assert counts[0] == ["p", "q"]
    got = language.predict(df, counts).collect()
    assert {r.lang_pred for r in got} == {"p", "q"}


def test_texts_that_no_language_explains_are_rejected(spark, sf_dir):
    """Random letters, a script never seen, and a language that was not learned go; learned ones stay."""
    folder = sf_dir.replace("sf0.001", "sf0.01")
    docs = spark.read.parquet(f"{folder}/documents.parquet").select("doc_id", "text", "lang")
    rng = random.Random(3)
    noise = ["".join(rng.choice("qwxzkjvybpfgmud ") for _ in range(900)), "Пример текста на другом языке. " * 30, "".join(rng.choice("abcdefghijklmnopqrstuvwxyz0123456789") for _ in range(2000))]
    df = docs.unionAll(spark.createDataFrame([(10**6 + i, t, None) for i, t in enumerate(noise)], docs.schema))
    kept = {r.doc_id for r in language.accepted(df).select("doc_id").collect()}
    assert not {10**6 + i for i in range(len(noise))} & kept
    clean = docs.where("lang is not null and length(text) > 200")
    assert len(kept & {r.doc_id for r in clean.collect()}) / clean.count() > 0.99


def test_nulls_empty_repeats_and_other_columns(spark):
    rows = [(1, "the cat", "en", "k"), (1, "the cat", "en", "k"), (2, None, "en", "k"), (3, "", None, "k"), (4, "12 34 !", "de", "k"), (None, "der hund", "de", None), (6, "the " * 200000, "en", "k")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, score string")
    counts = language.train(df)
    got = language.predict(df, counts).collect()
    assert len(got) == 7
    assert [r.lang_pred for r in got if r.doc_id in (2, 3, 4)] == ["und"] * 3
    kept = language.accepted(df, counts)
    assert kept.columns == df.columns and {r.doc_id for r in kept.collect()} <= {1, None, 6}
    empty = df.limit(0)
    assert language.train(empty)[0] == []
    assert language.accepted(empty).collect() == []
    assert {r.lang_pred for r in language.predict(df, language.train(empty)).collect()} == {"und"}
