"""Lines and word hashes of many texts at once, as arrays over the bytes of a column."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

PIECE_BYTES = 1 << 19
_BLOCK_MASK = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)
_LENGTH = np.uint64(0x9E3779B97F4A7C15)
#: Words of more bytes are hashed one by one.
LONG_WORD = 256


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection that spreads 64 bits."""
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


def word_hashes(data: np.ndarray, begin: np.ndarray, length: np.ndarray) -> np.ndarray:
    """64-bit hashes of the words at ``begin``, eight bytes a step; ``data`` ends with eight spare bytes. Every step mixes all
    64 bits, so neither the order of bytes nor their place in a word can be exchanged."""
    from xxhash import xxh64_intdigest

    eight = np.ndarray((max(len(data) - 7, 0),), "<u8", data, strides=(1,))  # those that begin at each byte
    block = lambda at, size: eight[at] & _BLOCK_MASK.take(size, mode="clip")
    out = mix(block(begin, length) ^ (length.astype(np.uint64) * _LENGTH))
    at, left = np.flatnonzero((length > 8) & (length <= LONG_WORD)), 8
    while len(at):
        out[at] = mix(out[at] ^ block(begin[at] + left, length[at] - left))
        left += 8
        at = at[length[at] > left]
    for i in np.flatnonzero(length > LONG_WORD).tolist():
        out[i] = xxh64_intdigest(data[begin[i] : begin[i] + length[i]].tobytes(), 11)
    return out


@dataclass
class Lines:
    """``word``: hash of each word; ``line``: index of its line; ``row``, ``number``: of each line, its row and place in it."""

    word: np.ndarray
    line: np.ndarray
    row: np.ndarray
    number: np.ndarray


def buffers(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all texts (null: none), and where each begins, with the end of the last."""
    arr = texts.fill_null("")
    wide = pa.types.is_large_string(arr.type)
    _, offsets, data = arr.buffers()
    at = np.frombuffer(offsets, np.int64 if wide else np.int32)[arr.offset : arr.offset + len(arr) + 1].astype(np.int64)
    body = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return body, at


def pieces(texts: pa.Array, size: int = PIECE_BYTES) -> Iterator[tuple[int, Lines]]:
    """(index of the first row, lines) of runs of rows of about ``size`` bytes; a text is never divided."""
    body, at = buffers(texts)
    lo, n = 0, len(at) - 1
    while lo < n:
        hi = max(int(np.searchsorted(at, at[lo] + size, "right")) - 1, lo + 1)
        yield lo, split(body[at[lo] : at[hi]], at[lo : hi + 1] - at[lo])
        lo = hi


def split(data: np.ndarray, at: np.ndarray) -> Lines:
    n, rows = len(data), len(at) - 1
    solid = (data - np.uint8(9) > 4) & (data != 32)
    edges = np.flatnonzero(solid[1:] != solid[:-1]) + 1
    inner = at[1:-1][(at[1:-1] > 0) & (at[1:-1] < n)]
    cut = np.unique(inner[solid[inner] & solid[inner - 1]])  # one word ends and the next begins where rows meet
    ends = [x for x, word in ((0, solid[:1]), (n, solid[-1:])) if word.any()]
    if len(cut) or ends:
        edges = np.sort(np.concatenate((edges, cut, cut, np.array(ends, np.int64))), kind="stable")
    begin = edges[0::2]
    length = edges[1::2] - begin
    folded = np.zeros(n + 8, np.uint8)
    np.bitwise_or(data, (data - np.uint8(65) < 26).view(np.uint8) << np.uint8(5), out=folded[:n])
    word = word_hashes(folded, begin, length) if len(begin) else np.zeros(0, np.uint64)
    breaks = np.flatnonzero(data == 10)
    of_break = np.searchsorted(at, breaks, "right") - 1
    count = np.bincount(of_break, minlength=rows) + 1
    start_line = np.cumsum(count) - count
    row = np.repeat(np.arange(rows), count)
    begins = np.empty(len(row), np.int64)
    begins[start_line] = at[:-1]
    begins[np.arange(len(breaks)) + of_break + 1] = breaks + 1
    in_line = np.diff(np.searchsorted(begin, np.append(begins, n)))
    return Lines(word, np.repeat(np.arange(len(row)), in_line), row, np.arange(len(row)) - start_line[row])
