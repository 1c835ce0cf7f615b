"""Language identification by prediction by partial matching over bytes.

Each language has a tree of byte contexts of up to ``ORDER`` bytes with the counts of the bytes that followed. A byte is
predicted from its longest known context; a byte that was never seen there costs an escape to the next shorter context, whose
distribution is renormalised over the bytes not yet excluded; below the empty context all 256 bytes are alike. The counts are
frozen after training, so a text's code length in each language is a sum of table entries, and the shortest one wins.

The counts are turned into one table: a row for each context of any language (a text position finds its row by an index over
byte triples that falls back to shorter contexts), a column for each byte, with the code lengths of all languages side by side.
Texts are scored as arrays, whole, in pieces of fixed size.

Training reads a sample of labelled rows: of each language those whose hash falls under ``SAMPLE_ROWS / rows``, so about
``SAMPLE_ROWS`` documents of each language however large the table is. Rows with ``crc32(id) mod 5 = 0`` are held out.

Defined results: ``und`` with score 0 for a null text, a text without a letter, or if nothing could be learned; equal code
lengths go to the language that sorts first; rows are independent, so repeated rows agree; a null id is not held out; a null
label is no language; an empty table gives an empty result; further columns pass through ``accepted``.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from adaptivejoin.llm.common import held, release_memory, table

ORDER = 3
SAMPLE_ROWS = 1000
#: A text is rejected if its bytes cost so many times what those of the dearest training document cost, ``SPARE`` bytes being added to
#: the length of both: short texts vary more.
DEAREST = 1.25
SPARE = 64
#: A context that was seen less often is left to its shorter one.
LEAST_SEEN = 4
UNDETERMINED = "und"
PIECE_BYTES = 1 << 19
CONTEXTS_AT_ONCE = 1024
PAD = 0


def held_out(id_col: str = "doc_id") -> Column:
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % 5 == 0, F.lit(False))


def _folded(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of the lower-cased texts, and where each text begins, with the end of the last."""
    low = pc.utf8_lower(texts.fill_null("").cast(pa.large_string()))
    _, offsets, data = low.buffers()
    at = np.frombuffer(offsets, np.int64)[low.offset : low.offset + len(low) + 1]
    body = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return body[at[0] : at[-1]], at - at[0]


def _padded(body: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The texts with ``ORDER`` pad bytes before each, and the places of the texts' own bytes."""
    n = len(at) - 1
    places = np.arange(len(body)) + ORDER * (np.repeat(np.arange(n), np.diff(at)) + 1)
    out = np.full(len(body) + ORDER * n, PAD, body.dtype)
    out[places] = body
    return out, places


def grams(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Distinct byte quadruples (three of context, then the byte) as integers, with their counts."""
    body, at = _folded(texts)
    seq, places = _padded(body.astype(np.int64), at)
    code = np.zeros(len(places), np.int64)
    for back in range(ORDER, -1, -1):
        code = (code << 8) | seq[places - back]
    return np.unique(code, return_counts=True)


def training_sample(docs: DataFrame, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """(lang, text) of about ``sample_rows`` documents of each language, none of them held out."""
    labelled = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out())
    sizes = labelled.groupBy("lang").agg(F.count("*").alias("rows"))
    draw = F.pmod(F.xxhash64(F.col("doc_id"), F.lit("train")), F.lit(1 << 30)).cast("double") / float(1 << 30)
    # One row a language: as many as the model has, which the driver holds.
    return labelled.join(F.broadcast(sizes), "lang").where(draw * F.col("rows") < sample_rows).select("lang", "text")


def count_grams(docs: DataFrame, sample_rows: int = SAMPLE_ROWS) -> pa.Table:
    """Rows (lang, gram, n) of the training sample; there are at most as many as the sample has distinct grams."""
    sample = training_sample(docs, sample_rows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lang in pc.unique(batch.column(0)).to_pylist():
                code, n = grams(batch.column(1).filter(pc.equal(batch.column(0), lang)))
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(code), pa.string()), pa.array(code), pa.array(n)], names=["lang", "gram", "n"])

    return sample.mapInArrow(run, "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n")).toArrow()


@dataclass
class Model:
    """Frozen statistics: code lengths in bits by (context row, symbol, language)."""

    langs: list[str]
    symbol: np.ndarray  # of each byte; the last symbol stands for all bytes that training never saw
    row: np.ndarray  # of each triple of symbols
    bits: np.ndarray


def build(langs: list[str], lang: np.ndarray, gram: np.ndarray, n: np.ndarray, least_seen: int = LEAST_SEEN) -> Model:
    """The code-length table from quadruple counts; ``lang`` indexes ``langs``."""
    parts = [(gram >> (8 * k)) & 255 for k in (3, 2, 1, 0)]
    seen = np.unique(np.concatenate([*parts, [PAD]]))
    size = len(seen) + 1
    symbol = np.full(256, size - 1, np.int64)
    symbol[seen] = np.arange(len(seen))
    members = np.ones(size)
    members[-1] = max(1, 256 - len(seen))
    a, b, c, s = (symbol[p] for p in parts)
    contexts = [np.zeros(len(gram), np.int64), c, b * size + c, (a * size + b) * size + c]
    row = np.zeros((size, size, size), np.int32)  # row 0: the empty context
    kept: list[tuple[np.ndarray, np.ndarray]] = []  # contexts and distributions of the shorter orders
    bits, base = [], 0
    for order, ctx in enumerate(contexts):
        known, which = np.unique(ctx, return_inverse=True)
        often = (np.bincount(which, n) >= least_seen) | (order == 0)
        known, place = known[often], np.cumsum(often) - 1
        use = np.flatnonzero(often[which])
        use = use[np.argsort(which[use], kind="stable")]
        at = place[which[use]]
        if order == 1:
            row[:, :, known] = base + np.arange(len(known), dtype=np.int32)
        elif order == 2:
            row[:, known // size, known % size] = base + np.arange(len(known), dtype=np.int32)
        elif order == 3:
            row.reshape(-1)[known] = base + np.arange(len(known), dtype=np.int32)
        base += len(known)
        parts = []
        for lo in range(0, len(known), CONTEXTS_AT_ONCE):  # a few contexts at a time: the counts of all would be large
            hi = min(lo + CONTEXTS_AT_ONCE, len(known))
            mine = use[np.searchsorted(at, lo) : np.searchsorted(at, hi)]
            counts = np.zeros((hi - lo, len(langs), size))
            np.add.at(counts, (place[which[mine]] - lo, lang[mine], s[mine]), n[mine])
            p = _predicted(counts, _shorter(known[lo:hi], order, size, kept) if order else np.tile(members / 256, (1, len(langs), 1)))
            bits.append((-np.log2(p / members)).transpose(0, 2, 1).reshape(-1, len(langs)).astype(np.float32))
            if order < ORDER:
                parts.append(p)
        kept.append((known, np.concatenate(parts) if parts else np.zeros((0, len(langs), size))))
    return Model(langs, symbol, row.reshape(-1), np.concatenate(bits))


def _predicted(counts: np.ndarray, lower: np.ndarray) -> np.ndarray:
    """Distributions of contexts from counts (context, language, symbol) and those of their shorter contexts."""
    got = counts > 0
    kinds, total = got.sum(2, keepdims=True), counts.sum(2, keepdims=True)
    rest = np.where(got, 0, lower)
    left = rest.sum(2, keepdims=True)
    own = np.where(left > 0, counts / np.maximum(total + kinds, 1), counts / np.maximum(total, 1))
    escape = kinds / np.maximum(total + kinds, 1)
    return np.where(total > 0, own + escape * rest / np.maximum(left, 1e-300), lower)


def _shorter(known: np.ndarray, order: int, size: int, kept: list) -> np.ndarray:
    """Distributions of the longest kept proper suffixes of contexts."""
    out, done = None, np.zeros(len(known), bool)
    for k in range(order - 1, -1, -1):
        ctx, p = kept[k]
        if not len(ctx):
            continue
        key = known % size**k
        i = np.minimum(np.searchsorted(ctx, key), len(ctx) - 1)
        hit = (ctx[i] == key) & ~done
        out = np.where(hit[:, None, None], p[i], 0 if out is None else out)
        done |= hit
    return out


def train(docs: DataFrame, sample_rows: int = SAMPLE_ROWS):
    """Sparse counts (langs, lang, gram, n): a few megabytes, whatever the table's size."""
    t = count_grams(docs, sample_rows)
    order = np.lexsort((t["gram"].to_numpy(), np.array(t["lang"].to_pylist(), dtype=str))) if t.num_rows else np.zeros(0, np.int64)
    names = np.array(t["lang"].to_pylist(), dtype=str)[order] if t.num_rows else np.zeros(0, str)
    langs, lang = np.unique(names, return_inverse=True)
    return langs.tolist(), lang, t["gram"].to_numpy()[order].astype(np.int64), t["n"].to_numpy()[order].astype(np.float64)


def code_lengths(texts: pa.Array, model: Model, piece: int = PIECE_BYTES) -> np.ndarray:
    """Bits of each text in each language."""
    body, at = _folded(texts)
    out = np.zeros((len(at) - 1, len(model.langs)))
    size = int(round(len(model.row) ** (1 / 3)))
    lengths = np.diff(at)
    lo = 0
    while lo < len(lengths):
        hi = int(np.searchsorted(at, at[lo] + piece, "right")) - 1
        hi = max(hi, lo + 1)
        seq, places = _padded(model.symbol[body[at[lo] : at[hi]]], at[lo : hi + 1] - at[lo])
        owner = np.repeat(np.arange(lo, hi), lengths[lo:hi])
        for i in range(0, len(places), piece):  # a text longer than a piece is summed in several
            p = places[i : i + piece]
            ctx = (seq[p - 3] * size + seq[p - 2]) * size + seq[p - 1]
            cost = model.bits[model.row[ctx].astype(np.int64) * size + seq[p]]
            own = owner[i : i + piece]
            first = np.flatnonzero(np.diff(own, prepend=-1))
            out[own[first]] += np.add.reduceat(cost, first, axis=0, dtype=np.float64)
        lo = hi
    return out


def _scored(docs: DataFrame, counts, text_col: str) -> DataFrame:
    """(row, lang_pred, score, bits_per_byte); ``row`` holds the columns of ``docs``."""
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")
    base = docs.select(row, F.coalesce(F.col(f"`{text_col}`").rlike(r"\p{L}"), F.lit(False)).alias("letters"))
    if not counts[0]:
        return base.select("row", F.lit(UNDETERMINED).alias("lang_pred"), F.lit(0.0).alias("score"), F.lit(None).cast("double").alias("bits_per_byte"))
    shared, name, at = docs.sparkSession.sparkContext.broadcast(counts), uuid.uuid4().hex, docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = held(f"language {name}", lambda: build(*shared.value))
        release_memory()
        names = np.array([*model.langs, UNDETERMINED], dtype=object)
        for batch in batches:
            texts = batch.column(0).field(at).fill_null("")
            bits = code_lengths(texts, model)
            best = bits.argmin(axis=1)
            low = bits[np.arange(len(best)), best]
            score = 1 / np.exp2(np.maximum(low[:, None] - bits, -1000)).sum(axis=1)
            ok = batch.column(1).to_numpy(zero_copy_only=False).astype(bool)
            size = pc.binary_length(texts).to_numpy(zero_copy_only=False)
            made = [pa.array(names[np.where(ok, best, len(model.langs))], pa.string()), pa.array(np.where(ok, score, 0.0)), pa.array(low / np.maximum(size, 1))]
            yield pa.RecordBatch.from_arrays([batch.column(0), *made], names=["row", "lang_pred", "score", "bits_per_byte"])
            release_memory()

    more = [T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType()), T.StructField("bits_per_byte", T.DoubleType())]
    return base.mapInArrow(run, T.StructType([base.schema["row"], *more]))


def predict(docs: DataFrame, counts, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, held_out, lang_pred, score, bits_per_byte) of every row. The score is the probability of the language, all
    learned languages being equally likely beforehand, and the texts' bytes coming from one of them."""
    found = _scored(docs.select(F.col(f"`{id_col}`").alias("doc_id"), held_out(id_col).alias("held_out"), F.col(f"`{text_col}`").alias("text")), counts, "text")
    return found.select("row.doc_id", "row.held_out", "lang_pred", "score", "bits_per_byte")


def _surprise(size: Column) -> Column:
    """Bits a byte, ``SPARE`` bytes being added that cost nothing."""
    return F.col("bits_per_byte") * size / (size + SPARE)


def dearest(docs: DataFrame, counts, sample_rows: int = SAMPLE_ROWS) -> float:
    """What the bytes of the dearest training document cost."""
    found = _scored(training_sample(docs, sample_rows).select("text"), counts, "text")
    return found.agg(F.max(_surprise(F.octet_length("row.text")))).first()[0] or 0.0


def accepted(docs: DataFrame, counts=None, least_score: float = 0.5) -> DataFrame:
    """The rows of ``docs`` whose language could be told, with their own columns; the others are rejected: texts without a letter,
    those that two languages explain alike, and those that no learned language explains about as well as its training documents."""
    counts = counts or train(docs)
    found = _scored(docs, counts, "text")
    told = (F.col("lang_pred") != UNDETERMINED) & (F.col("score") >= least_score)
    if counts[0]:
        told &= _surprise(F.octet_length("row.text")) <= DEAREST * dearest(docs, counts)
    return found.where(told).select(*[F.col("row").getField(c).alias(c) for c in docs.columns])


def query(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    return predict(docs.select("doc_id", "text"), train(docs)).select("doc_id", "held_out", "lang_pred", "score")
