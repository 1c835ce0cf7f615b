import hashlib
import random

import numpy as np
import pytest
from adaptivejoin.llm import byte_pairs

PATH = byte_pairs.default_vocabulary()


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(PATH)


def odd_texts():
    rng = random.Random(4)
    letters = "abc THE the  \n\t'sré日本語🙂0123!?#<|endoftext|>​ \x85\x1c½²ſḰ"
    texts = ["", "a<|endoftext|>b", "<|endoftext|><|endoftext|>", "  lead", "trail   ", "\t\t\n", "it's we'll I'M", "a" * 5000, "ab " * 20000]
    return texts + ["".join(rng.choice(letters) for _ in range(rng.randint(1, 200))) for _ in range(300)]


def test_ids_and_text_match_the_library(library):
    own = byte_pairs.Codec(PATH)
    for t in odd_texts():
        want = library.encode(t, add_special_tokens=False).ids
        assert list(own.encode(t)) == want, t
        assert own.decode(want) == library.decode(want, skip_special_tokens=False)


def test_forgetting_changes_nothing(monkeypatch):
    monkeypatch.setattr(byte_pairs, "REMEMBERED", 3)
    a, b = byte_pairs.Codec(PATH), byte_pairs.Codec(PATH)
    for t in odd_texts()[:80]:
        assert a.encode(t) == b.encode(t) and len(a.known) <= 3


def test_query_matches_the_library(spark, sf_dir, library):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").collect()
    got = {r.doc_id: r for r in byte_pairs.query(spark, sf_dir).collect()}
    assert len(got) == len(docs)
    for d in docs:
        ids = library.encode(d.text or "", add_special_tokens=False).ids
        r = got[d.doc_id]
        assert r.n_tokens == len(ids) and r.ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()


def test_frames_with_nulls_repeats_and_other_columns(spark):
    df = spark.createDataFrame([(1, None, 5), (1, None, 5), (2, "", 6), (3, "hello world", 7)], "doc_id long, text string, ids int")
    out = byte_pairs.encode(df)
    assert out.columns == ["doc_id", "text", "ids", "n_tokens"]
    assert sorted((r.doc_id, r.n_tokens) for r in out.collect()) == [(1, 0), (1, 0), (2, 0), (3, 2)]
    back = byte_pairs.decode(out)
    assert {(r.text or "", r.decoded) for r in back.collect()} == {("", ""), ("hello world", "hello world")}
    assert byte_pairs.encode(df.limit(0)).collect() == []


def test_a_worker_remembers_as_many_pre_tokens_as_it_is_given():
    own = byte_pairs.Codec(byte_pairs.default_vocabulary(), 3)
    text = " ".join(f"w{c}" for c in "abcdefghij")
    first = own.encode(text)
    assert len(own.known) <= 3 and len(own.before) <= 3 and own.encode(text) == first


def test_remembered_ids_are_packed_and_outlive_a_generation():
    own = byte_pairs.Codec(PATH, 50)
    pieces = [f" w{i}x" for i in range(120)]
    want = {p: tuple(own.merge(p.encode())) for p in pieces}
    assert list(own.encode("".join(pieces))) == [i for p in pieces for i in want[p]]
    assert own.before and all(type(v) is bytes for v in [*own.known.values(), *own.before.values()])
    assert all(tuple(np.frombuffer(v, np.uint32)) == tuple(own.merge(k.encode())) for k, v in [*own.known.items(), *own.before.items()])
    assert not any(len(k) > byte_pairs.LONGEST for k in own.known) and list(own.encode("a" * 500)) == list(own.merge(b"a" * 500))
