"""Byte-pair encoding and decoding with a given public vocabulary.

A text is cut into pre-tokens; the symbols of each pre-token form a doubly linked list, and a heap of merge ranks says which
neighbours to join next. A heap entry whose symbols have changed since it was pushed is stale and skipped. Decoding
concatenates the byte strings of the vocabulary. Frequent pre-tokens repeat, so a worker keeps the ids of those it has met
lately, up to a fixed number; nothing depends on that memory.

Defined results: a null text is encoded as an empty one, which has no ids; whole texts are encoded, their memory is in
proportion to the longest text of a batch; each row stands alone, so repeated rows get equal ids; an empty table gives an empty
result; further columns pass through ``encode``.
"""

from __future__ import annotations

import hashlib
import json
from array import array
from collections.abc import Iterator
from heapq import heapify, heappop, heappush

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from adaptivejoin.llm.common import held, release_memory, table

#: Fixed value: how the byte-level vocabulary cuts a text into pre-tokens.
PRE_TOKENS = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Pre-tokens of a generation; the last two are remembered.
REMEMBERED = 120_000
#: Longer ones are not remembered.
LONGEST = 64
ROWS_A_BATCH = 256


def byte_alphabet() -> dict[str, int]:
    """The printable stand-in of every byte in vocabulary files: printable Latin-1 stands for itself, the rest follows at 256."""
    own = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(own)]
    return {chr(b): b for b in own} | {chr(256 + i): b for i, b in enumerate(rest)}


class Memory(dict):
    """What ``make`` gives for a string, remembered for the last two generations of strings."""

    def __init__(self, make, size: int):
        self.make, self.size = make, size
        self.before: dict[str, bytes] = {}

    def __missing__(self, key: str) -> bytes:
        got = self.before.get(key)
        if got is None:
            got = self.make(key)
        if len(key) <= LONGEST:
            if len(self) >= self.size:
                self.before = self.copy()
                self.clear()
            self[key] = got
        return got


class Codec:
    """Encoder and decoder of one vocabulary file."""

    def __init__(self, path: str, remembered: int | None = None):
        self.remembered = remembered or REMEMBERED
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        letters = byte_alphabet()
        raw = lambda s: bytes(letters[c] for c in s)
        added = {a["content"]: a["id"] for a in spec.get("added_tokens", ())}
        vocab = {raw(k): v for k, v in spec["model"]["vocab"].items() if k not in added}
        self.text_of = {v: k for k, v in vocab.items()} | {v: k.encode() for k, v in added.items()}
        self.byte_id = [vocab[bytes([b])] for b in range(256)]
        self.ranks: list[dict[int, int]] = [{} for _ in range(max(vocab.values()) + 1)]  # by left id, then right id
        self.joined: list[int] = []  # the id of each rank
        for rank, m in enumerate(spec["model"]["merges"]):
            a, b = map(raw, m.split(" ") if isinstance(m, str) else m)
            self.ranks[vocab[a]].setdefault(vocab[b], rank)
            self.joined.append(vocab[a + b])
        self.added = added
        self.cut = regex.compile("(" + "|".join(regex.escape(a) for a in sorted(added, key=len, reverse=True)) + ")") if added else None
        self.find = regex.compile(PRE_TOKENS).findall
        self.known = Memory(lambda piece: array("I", self.merge(piece.encode())).tobytes(), self.remembered)

    @property
    def before(self) -> dict[str, bytes]:
        return self.known.before

    def merge(self, piece: bytes) -> tuple[int, ...]:
        """Ids of one pre-token."""
        symbols: list[int] = [self.byte_id[b] for b in piece]
        n = len(symbols)
        if n == 1:
            return tuple(symbols)
        by_left, joined, bits = self.ranks, self.joined, n.bit_length()
        place = (1 << bits) - 1
        # Rank of each symbol with the next one; -1: none.
        ranks = [by_left[a].get(b, -1) for a, b in zip(symbols, symbols[1:], strict=False)]
        ranks.append(-1)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [rank << bits | i for i, rank in enumerate(ranks) if rank >= 0]
        heapify(heap)
        while heap:
            least = heappop(heap)
            i, rank = least & place, least >> bits
            if ranks[i] != rank:
                continue  # stale
            symbols[i] = new = joined[rank]
            j = after[i]
            symbols[j] = ranks[j] = -1
            after[i] = k = after[j]
            if k < n:
                before[k] = i
                ranks[i] = rank = by_left[new].get(symbols[k], -1)
                if rank >= 0:
                    heappush(heap, rank << bits | i)
            else:
                ranks[i] = -1
            h = before[i]
            if h >= 0:
                ranks[h] = rank = by_left[symbols[h]].get(new, -1)
                if rank >= 0:
                    heappush(heap, rank << bits | h)
        return tuple([s for s in symbols if s >= 0])

    def encode(self, text: str) -> array:
        ids = array("I")
        known = self.known.__getitem__
        for part in self.cut.split(text) if self.cut else (text,):
            if part in self.added:
                ids.append(self.added[part])
            else:
                ids.frombytes(b"".join(map(known, self.find(part))))
        return ids

    def decode(self, ids) -> str:
        return b"".join(map(self.text_of.__getitem__, ids)).decode("utf-8", errors="replace")


def codec(path: str, remembered: int | None = None) -> Codec:
    """One codec a worker; it lives until another step needs its place."""
    return held(f"codec {path} {remembered}", lambda: Codec(path, remembered))


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def _mapped(df: DataFrame, text_col: str, vocabulary: str, fields: list[T.StructField], make, remembered: int | None = None) -> DataFrame:
    """``df`` with more columns that ``make(ids, codec)`` gives for each text; an input column of the same name is replaced."""
    new = [f.name for f in fields]
    keep = [c for c in df.columns if c not in new]
    schema = T.StructType([df.schema[c] for c in keep] + fields)
    inputs = df.select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{text_col}`").alias("\x00text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark.sql.pandas.types import to_arrow_schema

        release_memory()
        own = codec(vocabulary, remembered)
        arrow = to_arrow_schema(schema)
        for whole in batches:
            for at in range(0, whole.num_rows, ROWS_A_BATCH):
                batch = whole.slice(at, ROWS_A_BATCH)
                rows = [make(own.encode(t.as_py() or ""), own) for t in batch.column(len(keep))]
                cols = [batch.column(i).cast(arrow.field(i).type) for i in range(len(keep))]
                made = [pa.array([r[i] for r in rows], arrow.field(len(keep) + i).type) for i in range(len(fields))]
                yield pa.RecordBatch.from_arrays(cols + made, schema=arrow)

    return inputs.mapInArrow(run, schema)


def encode(df: DataFrame, vocabulary: str | None = None, text_col: str = "text") -> DataFrame:
    """``df`` with ``ids`` (array<int>) and ``n_tokens``."""
    fields = [T.StructField("ids", T.ArrayType(T.IntegerType())), T.StructField("n_tokens", T.LongType())]
    return _mapped(df, text_col, vocabulary or default_vocabulary(), fields, lambda ids, _: (ids, len(ids)))


def decode(df: DataFrame, vocabulary: str | None = None, ids_col: str = "ids") -> DataFrame:
    """``df`` with ``decoded``, the text of its ids; null ids give an empty text."""
    path = vocabulary or default_vocabulary()

    @F.pandas_udf("string")
    def text(ids):
        own = codec(path)
        return ids.map(lambda x: own.decode(x) if x is not None else "")

    return df.withColumn("decoded", text(F.col(f"`{ids_col}`")))


def digests(df: DataFrame, vocabulary: str | None = None, text_col: str = "text", with_ids: bool = False, remembered: int | None = None) -> DataFrame:
    """``df`` with n_tokens and digests of the ids (little-endian unsigned 32-bit) and of the decoded text; with the ids, if asked.
    ``remembered``: pre-tokens of a generation, where workers have less room."""
    fields = [T.StructField("n_tokens", T.LongType()), T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType())]
    if with_ids:
        fields.append(T.StructField("ids", T.ArrayType(T.IntegerType())))

    def make(ids: array, own: Codec) -> tuple:
        import sys

        decoded, n, out = own.decode(ids), len(ids), array("I", ids)
        if sys.byteorder == "big":
            out.byteswap()
        found = n, hashlib.sha256(out.tobytes()).hexdigest(), hashlib.sha256(decoded.encode()).hexdigest()
        return (*found, np.frombuffer(ids, np.uint32).astype(np.int32)) if with_ids else found

    return _mapped(df, text_col, vocabulary or default_vocabulary(), fields, make, remembered)


def query(spark, sf_dir: str) -> DataFrame:
    return digests(table(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256")
