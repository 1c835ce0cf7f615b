import itertools
import random
import re

import numpy as np
from adaptivejoin.llm import personal


def brute_base(text):
    """The patterns as they are stated, without shortcuts."""
    out = []
    for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text):
        out.append((m.start(), 0, m.end()))
    for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text):
        parts = [x.lstrip("0") for x in m[0].split(".")]
        if all(len(x) <= 3 and int(x or "0") <= 255 for x in parts):
            out.append((m.start(), 1, m.end()))
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        d = [int(c) for c in m[0] if c in "0123456789"]
        s = sum(x if i % 2 == 0 else sum(divmod(2 * x, 10)) for i, x in enumerate(reversed(d)))
        if 12 <= len(d) <= 19 and s % 10 == 0:
            out.append((m.start(), 2, m.end()))
    for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text):
        if 9 <= sum(c in "0123456789" for c in m[0]) <= 15:
            out.append((m.start(), 3, m.end()))
    return sorted(out)


def test_patterns_match_their_statement():
    rng = random.Random(9)
    pieces = ["a@b.c", "_", ".", "@", "x.y", "1.2.3.4", "999.1.1.1", "4111 1111 1111 1111", "+1 (555) 123-4567", "-", " ", "é", "\n", "12", "+", "%", "foo", "4111111111111111", "0" * 22, "..", "@@", "b-c.d"]
    for _ in range(5000):
        t = "".join(rng.choice(pieces) for _ in range(rng.randint(1, 14)))
        assert personal.base_spans(t) == brute_base(t), t


def test_query(spark, sf_dir):
    folder = sf_dir.replace("0.001", "0.01")
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{folder}/documents.parquet").select("doc_id", "text").collect()}
    got = personal.query(spark, folder).collect()
    assert len(got) == len(texts)
    secrets = found = 0
    for r in got:
        base = brute_base(texts[r.doc_id])
        assert [r.n_email, r.n_ip, r.n_card, r.n_phone] == [sum(k == i for _, k, _ in base) for i in range(4)]
        assert r.base_sha256 == personal.sha_of(base)
        spans = r.spans.split(",") if r.spans else []
        assert set(personal.written(base).split(",")) - {""} <= set(spans)
        for m in re.finditer(r'token = "([0-9a-f]{40})"', texts[r.doc_id]):
            secrets += 1
            found += f"secret:{m.start(1)}:{m.end(1)}" in spans
    assert secrets > 10 and found / secrets > 0.9


FILL = "the cat sat on the mat and then left " * 80


def test_long_runs_of_digits_in_an_address():
    for text in ("1" * 5000 + ".1.1.1", "0" * 5000 + "1.2.3.4", "1.1.1." + "9" * 5000):
        assert personal.base_spans(text) == brute_base(text)


def test_only_a_repetition_finds_weak_mentions(spark, sf_dir):
    """A weak mention alone is not found; near a strong one of the same content it is, and not without skip potentials."""
    weights = personal.learn(spark.read.parquet(f"{sf_dir.replace('0.001', '0.01')}/documents.parquet").select("doc_id", "text"))
    chain_only = weights | {"skip": np.zeros_like(weights["skip"])}
    key = "0a1b2c3d4e5f60718293a4b5c6d7e8f901234567"
    for strong, weak, kind in ((f'token = "{key}"', key, "secret"), ("+1 (743) 555-3824", "743 555 3824", "phone"), ("+1 (743) 555-3824", "(743) 555-3824", "phone"), ("re.46@mail8.example.com", "re.46(at)mail8.example.com", "email")):
        kinds = lambda text, w: [personal.KINDS[k] for _, k, _ in personal.find(text, w)[1]]
        assert kinds(f"{FILL}{weak} {FILL}", weights) == []
        assert kinds(f"{strong} {FILL}{weak} {FILL}", weights) == [kind, kind]
        assert kinds(f"{FILL}{weak} {FILL}{strong}", weights) == [kind, kind]
        assert kinds(f"{strong} {FILL}{weak} {FILL}", chain_only) == [kind]
        other = weak.replace("4", "9").replace("re", "si")
        assert kinds(f"{strong} {FILL}{other} {FILL}", weights) == [kind]


def exhaustive(u, keys, w):
    """Marginals by summing over all labels of the nodes and of a hidden one for each content."""
    n, k = u.shape
    hubs = sorted(set(x for x in keys if keys.count(x) > 1))
    want = np.zeros((n, k))
    for y in itertools.product(range(k), repeat=n):
        p = np.exp(sum(u[i, y[i]] for i in range(n)) + sum(w["chain"][y[i], y[i + 1]] for i in range(n - 1)))
        for h in hubs:
            p *= sum(np.exp(sum(w["skip"][y[i], z] for i in range(n) if keys[i] == h)) for z in range(k))
        for i in range(n):
            want[i, y[i]] += p
    return want / want.sum(1, keepdims=True)


def test_messages_equal_exhaustive_sums_where_there_is_no_loop():
    """A chain alone, and stars alone, of two to four equal mentions."""
    rng = np.random.default_rng(0)
    k = len(personal.LABELS)
    pair = rng.normal(size=(k, k))
    for keys, w in (("abcd", {"chain": rng.normal(size=(k, k)), "skip": np.zeros((k, k))}), ("aaaa", {"chain": np.zeros((k, k)), "skip": pair + pair.T}), ("abab", {"chain": np.zeros((k, k)), "skip": pair + pair.T})):
        u = rng.normal(size=(4, k))
        assert np.allclose(personal.beliefs(u, list(keys), w, rounds=6), exhaustive(u, list(keys), w), atol=1e-6)


def test_messages_come_near_exhaustive_sums_on_loops():
    rng = np.random.default_rng(1)
    k = len(personal.LABELS)
    for keys in ("abca", "aaba", "abab"):
        pair = 0.5 * rng.normal(size=(k, k))
        w = {"chain": 0.5 * rng.normal(size=(k, k)), "skip": pair + pair.T}
        u = 2 * rng.normal(size=(4, k))
        got, want = personal.beliefs(u, list(keys), w, rounds=20), exhaustive(u, list(keys), w)
        assert np.abs(got - want).max() < 0.1 and (got.argmax(1) == want.argmax(1)).mean() >= 0.75


def test_nulls_empty_long_and_repeated(spark):
    df = spark.createDataFrame([(1, None, "x"), (2, "", "x"), (3, "a@b.cc " * 3000 + "1" * 100000, "x"), (3, "a@b.cc", "x"), (None, "+1 555 123 4567", "x")], "doc_id long, text string, spans string")
    got = personal.digests(personal.detect(df, personal.learn(df))).collect()
    assert sorted((r.doc_id or 0, r.n_email, r.n_phone) for r in got) == [(0, 0, 1), (1, 0, 0), (2, 0, 0), (3, 1, 0), (3, 3000, 0)]
    empty = df.limit(0)
    assert personal.digests(personal.detect(empty, personal.learn(empty))).collect() == []
    assert personal.redact("me a@b.cc you", [(3, 0, 9)]) == "me [email] you"
