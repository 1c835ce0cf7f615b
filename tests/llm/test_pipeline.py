import zlib
from collections import Counter

import corpus_pipeline as cp
import pyarrow as pa
from adaptivejoin.llm import byte_pairs, language
from pyspark.sql import functions as F
from tests.llm.test_lines import brute as brute_lines
from tests.llm.test_near_copies import brute_groups


def test_stages_match_brute_force(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    rows = {r.doc_id: r for r in docs.collect()}
    predicted = {r.doc_id: r for r in language.predict(docs, language.train(docs)).collect()}
    size = {d: len((r.text or "").encode()) for d, r in rows.items()}
    cost = lambda d: (predicted[d].bits_per_byte or 0) * size[d] / (size[d] + language.SPARE)
    dearest = max(cost(d) for d, r in rows.items() if r.lang is not None and zlib.crc32(str(d).encode()) % 5)
    kept = {d for d, r in predicted.items() if r.lang_pred != "und" and r.score >= 0.5 and cost(d) <= language.DEAREST * dearest}
    one = cp.language_id(spark, docs, sf_dir)
    assert tuple(one.columns) == cp.COLUMNS and {r.doc_id for r in one.collect()} == kept
    texts = brute_lines([(d, rows[d].text) for d in kept])
    two = cp.line_dedup(spark, one, sf_dir)
    assert tuple(two.columns) == cp.COLUMNS
    assert {(r.doc_id, r.text, r.n_chars) for r in two.collect()} == {(d, t, len(t)) for d, t in texts.items()}
    ordered = sorted(texts.items())
    first = {ordered[i][0] for i, root in enumerate(brute_groups(ordered)) if i == root}
    three = cp.near_dedup(spark, two, sf_dir)
    assert tuple(three.columns) == cp.COLUMNS and {r.doc_id for r in three.collect()} == first
    four = cp.source_mix(spark, three, sf_dir)
    times = Counter(r.doc_id for r in four.collect())
    assert tuple(four.columns) == cp.COLUMNS and set(times) <= first and max(times.values()) <= 3
    five = cp.encode(spark, four, sf_dir).collect()
    codec = byte_pairs.Codec(byte_pairs.default_vocabulary())
    assert Counter(r.doc_id for r in five) == times
    assert all(codec.decode(r.ids) == texts[r.doc_id] and len(r.ids) == r.n_tokens for r in five)
    whole = cp.run(spark, sf_dir).collect()
    assert Counter((r.doc_id, r.ids_sha256) for r in whole) == Counter((r.doc_id, r.ids_sha256) for r in five)


def test_labelled_documents_survive(spark, sf_dir):
    """Of documents called good, language identification rejects none."""
    folder = sf_dir.replace("0.001", "0.01")
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    good = spark.read.parquet(f"{folder}/labels.parquet").where("quality = 1").select("doc_id")
    one = cp.language_id(spark, docs, folder)
    assert one.join(good, "doc_id", "left_semi").count() == good.join(docs, "doc_id", "left_semi").count()


def test_nulls_repeats_long_texts_and_clashing_names(spark, sf_dir):
    """Odd rows among ordinary ones, through all stages."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select(*cp.COLUMNS)
    base = [r for r in docs.collect() if r.text and len(r.text) > 400][:2]
    long = "\n".join(f"{line} number {i} of the long text" for i, line in enumerate((base[0].text + " ") .split(" ")[:50] * 100))
    own = "this line stands in one document alone and is kept"
    odd = [(None, None, "en", "a", 0), (None, base[0].text + "\n" + own, None, None, None), (900, base[1].text, base[1].lang, "b", 1), (900, base[1].text, base[1].lang, "b", 1), (901, "", "en", "a", 0), (902, "1234 5678", None, "a", 9), (903, long, "en", None, None)]
    df = docs.unionByName(spark.createDataFrame(odd, docs.schema)).withColumns({"row_key": F.lit(1), "ids": F.lit("x"), "copies": F.lit(2), "gone": F.lit(None).cast("string")})
    now = df
    counts = []
    for name, stage in cp.STAGES:
        now = stage(spark, now, sf_dir)
        if name != "encode":
            assert tuple(now.columns) == cp.COLUMNS
            now = spark.createDataFrame(now.collect(), docs.schema)
        counts.append(now.count())
    got = now.collect()
    assert all(r.n_tokens == len(r.ids) for r in got)
    assert counts[1] == counts[0] > counts[2] > 0
    two = cp.line_dedup(spark, cp.language_id(spark, df, sf_dir), sf_dir).collect()
    assert any(own in r.text for r in two if r.doc_id is None)
    assert sorted(len(r.text) for r in two if r.doc_id == 900)[0] == 0


def test_empty(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").limit(0)
    for _, stage in cp.STAGES:
        docs = stage(spark, docs, sf_dir)
    assert docs.collect() == []


def test_encode_gives_its_workers_few_texts_at_a_time(spark, sf_dir, monkeypatch):
    def sizes(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([b.num_rows] * b.num_rows)], names=["doc_id", "n_tokens"])

    def spy(df, **_):
        found = df.select("doc_id").mapInArrow(sizes, "doc_id long, n_tokens long")
        return found.withColumns({c: F.lit("") for c in ("lang", "source", "ids", "ids_sha256", "decoded_sha256")})

    monkeypatch.setattr(byte_pairs, "digests", spy)
    docs = spark.range(0, 1500, 1, 1).select(F.col("id").alias("doc_id"), *[F.lit("").alias(c) for c in ("text", "lang", "source")], F.lit(0).alias("n_chars"))
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    rows = cp.encode(spark, docs, sf_dir).collect()
    assert len(rows) == 1500 and max(r.n_tokens for r in rows) <= byte_pairs.ROWS_A_BATCH
    assert spark.conf.get(name) == before
