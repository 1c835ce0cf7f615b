"""Line deduplication by an exact set-similarity join of all lines of a corpus.

A line is the set of its words, ASCII letters folded. It is removed if an earlier line (by document id, then place) has a Jaccard
similarity of ``SIMILARITY`` or more with it, whether or not that one is removed itself. Every
line with a word takes part; lines of fewer than ``LEAST_NEAR`` distinct words match only if their sets are equal.

Words are ordered by rarity: by the logarithm of their count over the whole corpus, kept in a table of fixed size (words that
share a cell share a count; any order that is the same everywhere gives exact results), then by hash. Two similar lines share a
word among the first ``n - ceil(t n) + 1`` of each (prefix filter), so lines meet at these words. Words of count one meet
nothing and are left out. At a shared word the lengths (length filter), the words left after it (positional filter) and parity
sketches, whose distance never exceeds that of the sets, discard almost all pairs that are not similar.

Lines with equal sets are one node. At each word a later line keeps its ``FIRST`` candidates of the least estimated distance, and
up to ``RESERVE`` where that estimate is no clear sign; they are verified with all their words. A line that none of them settles and
that has more is looked up again: it is held, with its words, while all lines that share one of its first words stream past and are
compared in full. So nothing is lost, and a group of near copies yields a few pairs a line. Lists of more than a block of lines are dealt out by pairs of
blocks. The lines themselves travel in the same shuffle, under keys of their sets; of equal lines that a worker holds all but the
first are known to go and are dealt by row, so that a line with a third of all places is spread; what remains of them is which places
are first. Rows of the shuffle are a key and one packed value. They are bundled by bucket, the leading bits of their keys, so that the
JVM deals and sorts a few bundles; a worker opens and sorts a bucket at a time. Removed lines go back by a key of the row.

Words are compared by 64-bit hashes of all their bytes (``tokens.word_hashes``).

Defined results: a null text stays null; blank lines stay; rows without an id come last; rows that share an id, or have
none, are documents of their own, in order by line number first; a document whose lines all go keeps an empty text; whole texts are read in
pieces of about ``tokens.PIECE_BYTES`` or one text; an empty table gives an empty result; further columns pass through.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from adaptivejoin.llm import tokens
from adaptivejoin.llm.common import Workspace, release_memory, release_shuffles, row_keyed, small_batches, table

#: The similarity as a fraction, so that thresholds are integers.
NUM, DEN = 4, 5
LEAST_WORDS = 1
#: The least size of a set that can match another one: four words match the same four and a fifth.
LEAST_NEAR = 4
FIRST = 2
RESERVE = 64
BLOCK = 2048
TABLE_BITS = 23
CHUNK = 1 << 16
SALTS = 64
REMEMBERED = 50_000
#: Lines looked up again that are held at a time, and how many ways the lines that stream past them are dealt.
HELD, WAYS = 4096, 16
ROWS_A_BATCH = 2500
#: Turns in which the rows are dealt, each with its share of the keys: the texts are cut in every turn, but only one share lies on disk.
TURNS = 1
#: Rows that a worker holds to bundle them, and the most in a bundle.
BUNDLED, BUNDLE = 1 << 18, 256
#: Rows of a bucket of keys, about.
A_BUCKET = 1 << 18
#: Rows that are compared at a time, or held of a bucket before long lists are passed on.
GATHERED = 1 << 17
#: Lists up to this size are compared together, and so many pairs of rows at a time.
SHORT = 48
PAIRS = 1 << 18
#: Sets of more words have wider sketches: a narrow one would be full of differences.
NARROW = 60
#: Sets of at most so many words have three sketches instead: in a large group of near copies a chance collision in one is common.
SMALL = 40
LAST_ID = (1 << 63) - 1


def needed(n: np.ndarray) -> np.ndarray:
    """The least overlap of two sets with ``n`` words together."""
    return -(-NUM * n // (NUM + DEN))


def count_table(df: DataFrame, hashes: Callable[[pa.RecordBatch], Iterator[np.ndarray]], least: int = 1, bits: int = TABLE_BITS) -> np.ndarray:
    """A table of 2^bits cells with 1 + log2 of how many of the hashes fall into each (0: under ``least``).

    Each task sends its filled cells, in chunks, which are fewer than its hashes; chunks stream past and are summed in two steps,
    and the driver gets three bytes a cell. The table has one size for any corpus.
    """
    size = 1 << bits
    chunk = min(CHUNK, size)
    packed = lambda c, i, n: pa.RecordBatch.from_arrays([pa.array([c], pa.int32()), pa.array([_task() % SALTS], pa.int32()), pa.array([i.astype("<u2").tobytes()], pa.binary()), pa.array([n.tobytes()], pa.binary())], names=["chunk", "salt", "i", "n"])

    def fill(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release_memory()
        cells = np.zeros(size, np.uint32)
        for batch in batches:
            for h in hashes(batch):
                np.add.at(cells, (h & np.uint64(size - 1)).astype(np.int64), np.uint32(1))
        for c in range(size // chunk):
            i = np.flatnonzero(cells[c * chunk : (c + 1) * chunk])
            if len(i):
                yield packed(c, i, cells[c * chunk + i])

    def total(last: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums: dict[int, np.ndarray] = {}
            for batch in batches:
                for c, i, n in zip(batch.column(0).to_pylist(), batch.column(2), batch.column(3), strict=True):
                    cells = sums.setdefault(c, np.zeros(chunk, np.uint32))
                    at, more = np.frombuffer(i.as_py(), "<u2"), np.frombuffer(n.as_py(), "<u4")
                    cells[at] += np.minimum(more, np.iinfo(np.uint32).max - cells[at])
            for c, cells in sums.items():
                i = np.flatnonzero(cells >= (least if last else 1))
                yield packed(c, i, (1 + np.floor(np.log2(cells[i]))).astype(np.uint8) if last else cells[i])

        return run

    kind = "chunk int, salt int, i binary, n binary"
    halfway = df.mapInArrow(fill, kind).repartition("chunk", "salt").mapInArrow(total(False), kind)
    out = np.zeros(size, np.uint8)
    for r in halfway.repartition("chunk").mapInArrow(total(True), kind).collect():
        out[np.frombuffer(r.i, "<u2").astype(np.int64) + r.chunk * chunk] = np.frombuffer(r.n, np.uint8)
    return out


def _task() -> int:
    from pyspark import TaskContext

    return TaskContext.get().partitionId()


def ordered_sets(lines: tokens.Lines, rarity: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct words of each line, rarest first: (word, line, class) in order."""
    cls = rarity[(lines.word & np.uint64(len(rarity) - 1)).astype(np.int64)]
    n_lines = len(lines.row)
    exact = n_lines < 1 << 14
    if exact:
        key = (lines.line.astype(np.uint64) << np.uint64(50)) | (cls.astype(np.uint64) << np.uint64(44)) | (lines.word >> np.uint64(20))
        order = np.argsort(key)
        k, w = key[order], lines.word[order]
        same = k[1:] == k[:-1]
        exact = not (same & (w[1:] != w[:-1])).any()
    if not exact:  # words that the packed key can't tell apart, or too many lines for it
        order = np.lexsort((lines.word, cls, lines.line))
        w, li = lines.word[order], lines.line[order]
        same = (w[1:] == w[:-1]) & (li[1:] == li[:-1])
    keep = order[np.concatenate(([True], ~same))] if len(order) else order
    return lines.word[keep], lines.line[keep], cls[keep]


def describe(word: np.ndarray, line: np.ndarray, n_lines: int, sketched: bool = True) -> tuple[np.ndarray, ...]:
    """Of each line: first word, size, set hash, and parity sketches: one of 64 bits, and in the other places one of 192 for a set of
    over ``NARROW`` words, two more of 64 for a set of up to ``SMALL``. Where all similar sets have the wide one, the first is 0.
    Not ``sketched``: the sketches stay 0."""
    size = np.bincount(line, minlength=n_lines)
    begin = np.cumsum(size) - size
    some = size > 0
    out = np.zeros((1, n_lines), np.uint64)
    sketch = np.zeros((n_lines, 4), np.uint64)
    if some.any():
        at = begin[some]
        spread = tokens.mix(word + np.uint64(0x5851F42D4C957F2D))
        out[0, some] = tokens.mix(np.add.reduceat(spread, at) + size[some].astype(np.uint64))
    if some.any() and sketched:
        bit = np.uint64(1) << (spread & np.uint64(63))
        sketch[some, 0] = np.bitwise_xor.reduceat(bit, at)
        few = some & (size <= SMALL)
        if few.any():
            small = few[line]
            starts = np.flatnonzero(np.diff(line[small], prepend=-1))
            for k in (1, 2):
                sketch[few, k] = np.bitwise_xor.reduceat(np.uint64(1) << ((spread[small] >> np.uint64(8 * k)) & np.uint64(63)), starts)
        wide = size > NARROW
        if wide.any():
            long = wide[line]
            starts, part = np.flatnonzero(np.diff(line[long], prepend=-1)), (spread[long] >> np.uint64(6)) % np.uint64(3) + np.uint64(1)
            for k in (1, 2, 3):
                sketch[wide, k] = np.bitwise_xor.reduceat(np.where(part == k, bit[long], 0), starts)
            sketch[size * NUM > NARROW * DEN, 0] = 0
    return begin, size, out[0], sketch


#: Packed values of eight bytes each. A set: its hash, document, place and row. A word's line: these but the row, its size (above it
#: the word, where the key is salted), and sketches.
OF_SET, OF_LINE = 4, 8
SET, DOC, AT, SIZE, SKETCH = 0, 1, 2, 3, 4
ROW = "key long, packed binary"
#: Keys from here on are salted ones of frequent words.
HOT = 1 << 62


def _first_column(batch: pa.RecordBatch) -> Iterator[np.ndarray]:
    yield tokens.mix(batch.column(0).to_numpy().view(np.uint64))


def _in_table(cells: np.ndarray, x: np.ndarray) -> np.ndarray:
    return cells[(tokens.mix(x) & np.uint64(len(cells) - 1)).astype(np.int64)] > 0


def _binary(rows: np.ndarray) -> pa.Array:
    """Rows of a matrix as binary values."""
    rows = np.ascontiguousarray(rows)
    at = np.arange(len(rows) + 1, dtype=np.int32) * np.int32(rows.shape[1] * 8)
    return pa.Array.from_buffers(pa.binary(), len(rows), [None, pa.py_buffer(at), pa.py_buffer(rows)])


def _matrix(values: pa.Array, width: int) -> np.ndarray:
    """The inverse of ``_binary``."""
    _, offsets, data = values.buffers()
    if not len(values):
        return np.zeros((0, width), np.uint64)
    at = np.frombuffer(offsets, np.int32)[values.offset : values.offset + len(values) + 1]
    return np.frombuffer(data, np.uint64, (int(at[-1]) - int(at[0])) // 8, int(at[0])).reshape(-1, width)


def _bits(x: np.ndarray) -> np.ndarray:
    return x if x.dtype == np.uint64 else x.astype(np.int64).view(np.uint64)


def _holding(lines: tokens.Lines, cells: np.ndarray) -> tokens.Lines:
    """The lines that hold a word whose key is in the table."""
    hit = np.zeros(len(lines.row), bool)
    hit[lines.line[_in_table(cells, lines.word >> np.uint64(32))]] = True
    keep = hit[lines.line]
    return tokens.Lines(lines.word[keep], (np.cumsum(hit) - 1)[lines.line[keep]], lines.row[hit], lines.number[hit])


def _nodes(shared, sets=None, keys=None, hot: int = 255, parts: int = 1, blocks: int = 0, turn: int = 0, turns: int = 1):
    """Words of class ``hot`` or more are salted over ``parts`` keys; their lists are put together later. With ``blocks`` rows are
    those of ``_asked``: only words in ``keys``; lines of ``sets`` are asked for, in so many blocks, and meet all lines of their words. Of
    ``turns`` only the rows whose key falls to this ``turn``; those of one key fall to the same."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows with a negative key are the lines that take part (the place is a line's number); the others are words that a line
        meets others at (the place is the number and the word's position in the line's order)."""
        release_memory()
        rarity = shared.value
        first_at: dict[int, tuple[int, int]] = {}
        for batch in batches:
            ids, row_keys = batch.column(0).to_numpy(), batch.column(2).to_numpy()
            for lo, lines in tokens.pieces(batch.column(1)):
                if blocks:
                    lines = _holding(lines, keys.value)
                word, line, cls = ordered_sets(lines, rarity)
                begin, size, h, sketch = describe(word, line, len(lines.row))
                of = np.flatnonzero(size >= LEAST_WORDS)
                doc = _bits(ids[lo + lines.row])
                number = _bits(lines.number) << np.uint64(32)
                if not blocks:
                    own = _bits(row_keys[lo + lines.row[of]])
                    key = h[of] | np.uint64(1 << 63)
                    now = np.flatnonzero(key % np.uint64(turns) == turn)
                    part = of[now]
                    yield pa.RecordBatch.from_arrays([pa.array(key[now].view(np.int64)), _binary(np.stack([h[part], doc[part], number[part], own[now]], 1))], names=["key", "packed"])
                # Of equal lines only those before the earliest met so far go on: the rest are the same node.
                meets = np.zeros(len(size), bool)
                of = of[size[of] >= LEAST_NEAR]
                for i, x, d, k in zip(of.tolist(), h[of].tolist(), doc[of].view(np.int64).tolist(), lines.number[of].tolist(), strict=True):
                    got = first_at.get(x)
                    if got is None or (d, k) < got:
                        if len(first_at) >= REMEMBERED:
                            first_at.clear()
                        first_at[x] = (d, k)
                        meets[i] = True
                prefix = size - (-(-NUM * size // DEN)) + 1
                meeting = np.flatnonzero(meets)
                li = np.repeat(meeting, prefix[meeting])
                use = np.arange(len(li)) + np.repeat(begin[meeting] + prefix[meeting] - np.cumsum(prefix[meeting]), prefix[meeting])
                rare = cls[use] > 1
                li, use = li[rare], use[rare]
                # 32 bits of the word: words that share them only cost filters.
                key = word[use] >> np.uint64(32)
                if blocks or turns > 1:
                    hit = _in_table(keys.value, key) if blocks else key % np.uint64(turns) == turn
                    li, use, key = li[hit], use[hit], key[hit]
                common = np.flatnonzero(cls[use] >= hot)
                packed = np.empty((len(use), OF_LINE), np.uint64)
                packed[:, SET], packed[:, DOC], packed[:, AT], packed[:, SIZE], packed[:, SKETCH:] = h[li], doc[li], number[li] | _bits(use - begin[li]), _bits(size[li]), sketch[li]
                if blocks:
                    yield from _asked(key, packed, word, begin[li], _in_table(sets.value, h[li]), blocks)
                    continue
                packed[common, SIZE] |= key[common] << np.uint64(32)
                key[common] = np.uint64(HOT) | (tokens.mix(key[common] + (h[li[common]] % np.uint64(parts) << np.uint64(32))) >> np.uint64(2))
                yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), _binary(packed)], names=["key", "packed"])

    return run


ASKED = "key long, asked int, packed binary"


def _asked(key, packed, word, begin, asked, blocks: int) -> Iterator[pa.RecordBatch]:
    """Rows (key, 0 for a line asked for, packed with its words): each in every way of its word and in its block, and all lines in one
    way and in every block."""
    out_key, out_asked, out = [], [], []
    for i in range(len(key)):
        own = int(packed[i, SET])
        value = packed[i].tobytes() + word[begin[i] : begin[i] + int(packed[i, SIZE])].tobytes()
        places = [(own // WAYS % blocks, way, 0) for way in range(WAYS)] if asked[i] else []
        for block, way, kind in [*places, *((block, own % WAYS, 1) for block in range(blocks))]:
            out_key.append((int(key[i]) * WAYS + way) * blocks + block), out_asked.append(kind), out.append(value)
    yield pa.RecordBatch.from_arrays([pa.array(out_key, pa.int64()), pa.array(out_asked, pa.int32()), pa.array(out, pa.binary())], names=["key", "asked", "packed"])


def _settled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The sets asked for that an earlier line matches; rows come by key, those asked for first."""
    release_memory()
    key, held = None, []
    for batch in batches:
        keys, kinds, values = batch.column(0).to_numpy(), batch.column(1).to_numpy(), batch.column(2)
        cuts = np.concatenate(([0], np.flatnonzero(np.diff(keys) | np.diff(kinds)) + 1, [len(keys)]))
        found = []
        for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            if lo == hi:
                continue
            if keys[lo] != key:
                key, held = keys[lo], []
            lines = [np.frombuffer(v.as_buffer(), np.uint64) for v in values[lo:hi]]
            if kinds[lo] == 0:
                held += [x.copy() for x in lines]
            elif held:
                hit = [_matches(x, lines) for x in held]
                found += [int(x[SET]) for x, ok in zip(held, hit, strict=True) if ok]
                held = [x for x, ok in zip(held, hit, strict=True) if not ok]
        yield pa.RecordBatch.from_arrays([pa.array(np.array(found, np.uint64).view(np.int64))], names=["b"])


def _matches(asked: np.ndarray, lines: list[np.ndarray]) -> bool:
    """Whether one of the lines comes before the one asked for and is similar to it, word by word."""
    rows = np.stack([asked[:OF_LINE], *(x[:OF_LINE] for x in lines)])
    i, j, _, _ = near(rows, np.zeros(len(lines), np.int64), np.arange(1, len(rows)))
    j = j[_earlier(rows, j, i)]
    if not len(j):
        return False
    own = np.sort(asked[OF_LINE:])
    words = [lines[x - 1][OF_LINE:] for x in j.tolist()]
    flat = np.concatenate(words)
    same = own[np.minimum(np.searchsorted(own, flat), len(own) - 1)] == flat
    size = np.array([len(w) for w in words])
    both = np.add.reduceat(same.astype(np.int64), np.cumsum(size) - size)
    return bool((both * (NUM + DEN) >= NUM * (size + len(own))).any())


def near(rows: np.ndarray, i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of pairs (i, j) of rows that meet at a word those that pass the filters, with their estimated distance and its limit: lengths,
    words left after it, sketches. The cheap filters go first; each leaves fewer pairs to the next."""
    size, reach = _reach(rows)
    ok = (reach[i] >= size[j]) & (reach[j] >= size[i])
    return _alike(rows, size, np.ascontiguousarray(rows[:, SKETCH]), i[ok], j[ok])


def _reach(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The size of each row's set, and that of the largest set for which the words left after the meeting word can be enough overlap.
    A set that starts at the word reaches as far as lengths allow at all."""
    size = (rows[:, SIZE] & np.uint64(0xFFFFFFFF)).astype(np.int64)
    left = size - (rows[:, AT] & np.uint64(0xFFFFFFFF)).astype(np.int64)
    return size, (NUM + DEN) * left // NUM - size


def _alike(rows: np.ndarray, size: np.ndarray, sketch: np.ndarray, i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The sketches' part of ``near``; ``sketch``: the first of each row."""
    total = size[i] + size[j]
    most = total - 2 * needed(total)
    apart = np.bitwise_count(sketch[i] ^ sketch[j])
    ok = apart <= most
    i, j, most, apart = i[ok], j[ok], most[ok].astype(np.int32), apart[ok].astype(np.int32)
    further = np.bitwise_count(rows[i, SKETCH + 1 :] ^ rows[j, SKETCH + 1 :]).astype(np.int32)
    small, wide = (size[i] <= SMALL) & (size[j] <= SMALL), (size[i] > NARROW) & (size[j] > NARROW)
    apart = np.maximum(apart, np.where(small, further.max(axis=1, initial=0), np.where(wide, further.sum(axis=1), 0)))
    ok = apart <= most
    return i[ok], j[ok], apart[ok], most[ok]


def _earlier(rows: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Whether row i comes before row j: by document, line, then set, the same in every list."""
    doc, line, own = rows[:, DOC].view(np.int64), rows[:, AT] >> np.uint64(32), rows[:, SET]
    same = doc[i] == doc[j]
    return (doc[i] < doc[j]) | (same & ((line[i] < line[j]) | ((line[i] == line[j]) & (own[i] < own[j]))))


def fitting_pairs(size: np.ndarray, reach: np.ndarray, group: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All pairs of rows in the lists of a ``group`` that are within each other's reach, a stretch of pairs at a time. Rows are in order
    of group and size, so those within a row's reach follow it without a gap."""
    n, key = len(size), group << 32
    end = np.searchsorted(key + size, key + reach, "right")
    count = np.maximum(end - np.arange(1, n + 1), 0)
    upto = np.cumsum(count)
    lo = 0
    while lo < n:
        hi = max(int(np.searchsorted(upto, upto[lo] - count[lo] + PAIRS, "right")), lo + 1)
        part = count[lo:hi]
        i = np.repeat(np.arange(lo, hi), part)
        j = np.arange(len(i)) + np.repeat(np.arange(lo + 1, hi + 1) + part - np.cumsum(part), part)
        ok = reach[j] >= size[i]
        yield i[ok], j[ok]
        lo = hi


#: kind 0: a pair of sets (a, b), n twice its rank for b and odd if b has more; 1: the first place (at) of a set a, in row b; 2: a later place; 3: a packed row of too long a list.
FOUND = "kind int, a long, b long, doc long, at long, n int, key long, packed binary"
FOUND_NAMES = [x.split()[0] for x in FOUND.split(", ")]


def _found(kind: int, a, b=None, doc=None, at=None, n=None, key=None, packed=None) -> pa.RecordBatch:
    size = len(a)
    long = lambda x: pa.nulls(size, pa.int64()) if x is None else pa.array(np.ascontiguousarray(x).view(np.int64))
    return pa.RecordBatch.from_arrays([pa.array(np.full(size, kind, np.int32)), long(a), long(b), long(doc), long(at), pa.nulls(size, pa.int32()) if n is None else pa.array(n.astype(np.int32)), long(key), pa.nulls(size, pa.binary()) if packed is None else _binary(packed)], names=FOUND_NAMES)


def _firsts(keys: np.ndarray, rows: np.ndarray, *more: int) -> tuple[np.ndarray, np.ndarray]:
    """(order, head): an order by key and set, of equal ones by place, and which of it are the first of their key and set. The keys are
    in order."""
    full = lambda at: at[np.lexsort((*(rows[at, c] for c in more), rows[at, AT], rows[at, DOC].view(np.int64), rows[at, SET], keys[at]))]
    group = np.cumsum(np.concatenate(([False], keys[1:] != keys[:-1]))[: len(keys)])
    if len(keys) and group[-1] < 1 << 20:
        packed = (_bits(group) << np.uint64(44)) | (rows[:, SET] >> np.uint64(20))
        order = np.argsort(packed)
        same = packed[order[1:]] == packed[order[:-1]]
        tied = np.flatnonzero(np.concatenate((same, [False])) | np.concatenate(([False], same)))
        order[tied] = full(order[tied])
    else:
        order = full(np.arange(len(keys)))
    k, x = keys[order], rows[order, SET]
    return order, np.concatenate(([True], (k[1:] != k[:-1]) | (x[1:] != x[:-1])))[: len(order)]


#: Marks the place of a set that is known to be a later one.
LATE = np.uint64(1)


def _late_apart(keys: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of equal sets that a worker holds only the first keeps its key; the others are marked and dealt by their documents' rows, so that
    a line with a third of all places is spread."""
    order = np.argsort(keys)
    keys, rows = keys[order], rows[order]
    order, head = _firsts(keys, rows, 3)
    late = order[~head]
    rows[late, AT] |= LATE
    keys[late] = (tokens.mix(rows[late, 3]) | np.uint64(1 << 63)).view(np.int64)
    return keys, rows


def _parted(keys: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(which rows of sets have the first place of their set, all others); keys are in order."""
    fresh = np.flatnonzero((rows[:, AT] & LATE) == 0)
    order, head = _firsts(keys[fresh], rows[fresh], 3)
    first = np.zeros(len(keys), bool)
    first[fresh[order[head]]] = True
    return np.flatnonzero(first), np.flatnonzero(~first)


def _places(kind: int, rows: np.ndarray) -> Iterator[pa.RecordBatch]:
    if len(rows):
        yield _found(kind, rows[:, SET], rows[:, 3], at=rows[:, AT])


def _limited(rows: np.ndarray, group: np.ndarray, first: int) -> pa.RecordBatch | None:
    """The pairs of lists that pass, with the earlier set first: of each later row the ``first`` nearest. Rows are in order of group
    and size."""
    got = []
    size, reach = _reach(rows)
    sketch = np.ascontiguousarray(rows[:, SKETCH])
    for i, j in fitting_pairs(size, reach, group):
        i, j, apart, most = _alike(rows, size, sketch, i, j)
        if len(i):
            ok = _earlier(rows, i, j)
            got.append((np.where(ok, i, j), np.where(ok, j, i), apart, most))
    if not got:
        return None
    i, j, apart, most = (np.concatenate(x) for x in zip(*got, strict=True))
    order = np.lexsort((rows[i, SET], rows[i, AT], rows[i, DOC].view(np.int64), apart, j))
    i, j, apart, most = i[order], j[order], apart[order], most[order]
    begin = np.flatnonzero(np.diff(j, prepend=-1))
    count = np.diff(np.append(begin, len(j)))
    rank = np.arange(len(j)) - np.repeat(begin, count)
    # Half of the limit or less: the nearest is almost certainly similar, so a few will do.
    kept = np.where(2 * apart[begin] <= most[begin], first, max(first, RESERVE))
    more = np.repeat(count > kept, count)
    keep = rank < np.repeat(kept, count)
    i, j = i[keep], j[keep]
    return _found(0, rows[i, SET], rows[j, SET], rows[i, DOC], rows[j, DOC], n=2 * rank[keep] + more[keep])


def _lists(keys: np.ndarray, rows: np.ndarray, first: int, block: int) -> Iterator[pa.RecordBatch]:
    """Whole lists of words met again, in order of key; a set stays once in each, at its first place."""
    order, head = _firsts(keys, rows)
    once = order[head]
    keys = keys[once]
    group = np.cumsum(np.concatenate(([False], keys[1:] != keys[:-1]))[: len(keys)])
    count = np.bincount(group)
    order = np.flatnonzero(count[group] > 1)
    size = (rows[once[order], SIZE] & np.uint64(0xFFFFFFFF)).astype(np.int64)
    order = order[np.argsort(group[order] << 32 | size)]
    keys, rows, group = keys[order], rows[once[order]], group[order]
    few = count[group] <= SHORT
    if (got := _limited(rows[few], group[few], first)) is not None:
        yield got
    begin = np.flatnonzero(~few & np.concatenate(([True], group[1:] != group[:-1]))[: len(group)])
    for lo in begin.tolist():
        hi = lo + int(count[group[lo]])
        if hi - lo > block:
            yield _passed(rows[lo:hi], keys[lo])
        elif (got := _limited(rows[lo:hi], group[lo:hi], first)) is not None:
            yield got


def _passed(rows: np.ndarray, key=None) -> pa.RecordBatch:
    """Rows of too long a list, for another stage; without ``key`` the word above their size is their key."""
    return _found(3, rows[:, SET], None, rows[:, DOC], rows[:, AT], key=rows[:, SIZE] >> np.uint64(32) if key is None else np.broadcast_to(key, len(rows)), packed=rows)


def _repeated(keys: np.ndarray) -> np.ndarray:
    """Which keys occur more than once; they are in order."""
    again = np.zeros(len(keys), bool)
    again[1:] = keys[1:] == keys[:-1]
    again[:-1] |= again[1:]
    return again


def _bucket(keys: np.ndarray, bits: int) -> np.ndarray:
    """The leading bits of keys, in their order: negative for sets, 2^bits and more for salted words."""
    return np.where(keys < 0, keys >> (63 - bits), np.where(keys < HOT, keys >> (32 - bits), ((keys - HOT) >> (62 - bits)) + (1 << bits)))


BUNDLES = "bucket int, packed binary"


def _bundled(nodes, bits: int):
    """The rows of ``nodes`` as bundles, each of one bucket of 2^``bits``: far fewer rows for the shuffle to deal and to sort."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[tuple[np.ndarray, np.ndarray]]] = {OF_SET: [], OF_LINE: []}
        for batch in nodes(batches):
            keys = batch.column(0).to_numpy()
            if len(keys):
                width = OF_SET if keys[0] < 0 else OF_LINE
                held[width].append((keys, _matrix(batch.column(1), width)))
                if sum(len(k) for k, _ in held[width]) >= BUNDLED:
                    yield from _bundles(held[width], bits)
        for own in held.values():
            if own:
                yield from _bundles(own, bits)

    return run


def _bundles(held: list[tuple[np.ndarray, np.ndarray]], bits: int) -> Iterator[pa.RecordBatch]:
    """Bundles of ``held``, which is emptied. A bundle has the bytes of keys and rows by their place in a row: most places hold a few
    values only, so that they take little room when compressed."""
    keys, rows = (np.concatenate(x) for x in zip(*held, strict=True))
    held.clear()
    if keys[0] < 0:
        keys, rows = _late_apart(keys, rows)
    bucket = _bucket(keys, bits)
    least = bucket.min()
    order = np.argsort((bucket - least).astype(np.min_scalar_type(int(bucket.max() - least))), kind="stable")
    bucket = bucket[order]
    whole = np.empty((len(keys), 1 + rows.shape[1]), np.uint64)
    whole[:, 0], whole[:, 1:] = keys[order].view(np.uint64), rows[order]
    size = 8 * whole.shape[1]
    own, out = whole.view(np.uint8), np.empty(whole.nbytes, np.uint8)
    begin = np.flatnonzero(np.diff(bucket, prepend=bucket[0] - 1))
    place = np.arange(len(bucket)) - np.repeat(begin, np.diff(np.append(begin, len(bucket))))
    cut = np.append(np.flatnonzero(place % BUNDLE == 0), len(bucket))
    for lo, hi in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
        out[lo * size : hi * size].reshape(size, hi - lo)[:] = own[lo:hi].T
    values = pa.Array.from_buffers(pa.binary(), len(cut) - 1, [None, pa.py_buffer((cut * size).astype(np.int32)), pa.py_buffer(out)])
    batch = pa.RecordBatch.from_arrays([pa.array(bucket[cut[:-1]].astype(np.int32)), values], names=["bucket", "packed"])
    for lo in range(0, batch.num_rows, BUNDLE):
        yield batch.slice(lo, BUNDLE)


def _unbundled(values: pa.Array, width: int) -> np.ndarray:
    """Rows of bundles: a key and ``width`` values."""
    _, offsets, data = values.buffers()
    at = np.frombuffer(offsets, np.int32)[values.offset : values.offset + len(values) + 1].tolist()
    body, size = np.frombuffer(data, np.uint8), 8 * (1 + width)
    out = np.empty((at[-1] - at[0], 1), np.uint8).reshape(-1, size)
    done = 0
    for lo, hi in zip(at[:-1], at[1:], strict=True):
        n = (hi - lo) // size
        out[done : done + n] = body[lo:hi].reshape(size, n).T
        done += n
    return out.view(np.uint64)


def _by_bucket(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, bool, pa.Array]]:
    """(bucket, whether it is another than before, bundles) of a stream sorted by bucket."""
    last = None
    for batch in batches:
        bucket, values = batch.column(0).to_numpy(), batch.column(1)
        cuts = np.concatenate(([0], np.flatnonzero(np.diff(bucket)) + 1, [len(bucket)])).tolist()
        for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
            if lo < hi:
                yield int(bucket[lo]), last != bucket[lo], values[lo:hi]
                last = bucket[lo]


class _Bucket:
    """Rows of one bucket. Past a limit, sets keep their first places only and lists of over four blocks are passed on."""

    def __init__(self, of_sets: bool, first: int, block: int):
        self.of_sets, self.first, self.block = of_sets, first, block
        self.parts: list[np.ndarray] = []
        self.limit = GATHERED
        self.over = np.zeros(0, np.int64)

    def add(self, values: pa.Array) -> Iterator[pa.RecordBatch]:
        self.parts.append(_unbundled(values, OF_SET if self.of_sets else OF_LINE))
        if sum(map(len, self.parts)) >= self.limit:
            keys, rows = self._sorted()
            if self.of_sets:
                stay, late = _parted(keys, rows)
                yield from _places(2, rows[late])
            else:
                own, count = np.unique(keys, return_counts=True)
                self.over = np.union1d(self.over, own[count > 4 * self.block])
                far = np.isin(keys, self.over)
                if far.any():
                    yield _passed(rows[far], keys[far])
                stay = np.flatnonzero(~far)
            self.parts = [np.column_stack((keys[stay].view(np.uint64), rows[stay]))]
            self.limit = max(GATHERED, 2 * len(stay))

    def _sorted(self) -> tuple[np.ndarray, np.ndarray]:
        whole = np.concatenate(self.parts)
        self.parts = []
        keys = np.ascontiguousarray(whole[:, 0]).view(np.int64)
        order = np.argsort(keys)
        return keys[order], whole[order, 1:]

    def close(self) -> Iterator[pa.RecordBatch]:
        keys, rows = self._sorted()
        if self.of_sets:
            begin, late = _parted(keys, rows)
            yield from _places(1, rows[begin])
            yield from _places(2, rows[late])
            return
        if len(self.over):
            far = np.isin(keys, self.over)
            if far.any():
                yield _passed(rows[far], keys[far])
            keys, rows = keys[~far], rows[~far]
        again = _repeated(keys)
        yield from _lists(keys[again], rows[again], self.first, self.block)


def _meet_bundles(first: int, block: int, bits: int):
    """Pairs of the lists of a stream of bundles sorted by bucket, and the places of sets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release_memory()
        held: _Bucket | None = None
        for bucket, new, values in _by_bucket(batches):
            if new and held is not None:
                yield from held.close()
                held = None
            if bucket >= 1 << bits:
                yield _passed(_unbundled(values, OF_LINE)[:, 1:])
                continue
            held = held or _Bucket(bucket < 0, first, block)
            yield from held.add(values)
        if held is not None:
            yield from held.close()

    return run


def _gathered(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(keys, rows) of words in a stream sorted by key, about ``GATHERED`` rows at a time."""
    held: list[tuple[np.ndarray, np.ndarray]] = []
    for batch in batches:
        if batch.num_rows:
            held.append((batch.column(0).to_numpy(), _matrix(batch.column(1), OF_LINE)))
        if sum(len(k) for k, _ in held) >= GATHERED:
            yield tuple(np.concatenate(x) for x in zip(*held, strict=True))
            held.clear()
    if held:
        yield tuple(np.concatenate(x) for x in zip(*held, strict=True))


def _meet(first: int, block: int):
    """Pairs of the lists of a stream sorted by key."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release_memory()
        keys, rows = np.zeros(0, np.int64), np.zeros((0, OF_LINE), np.uint64)
        for more, further in _gathered(batches):
            keys, rows = np.concatenate([keys, more]), np.concatenate([rows, further])
            tail = int(np.searchsorted(keys, keys[-1]))
            again = np.flatnonzero(_repeated(keys[:tail]))
            yield from _lists(keys[again], rows[again], first, block)
            keys, rows = keys[tail:], rows[tail:]
        again = _repeated(keys)
        yield from _lists(keys[again], rows[again], first, block)

    return run


def _dealt(rows: DataFrame, by: str) -> DataFrame:
    return rows.repartition(by).sortWithinPartitions(by)


def _pairs(found: DataFrame, first: int, block: int) -> DataFrame:
    """(a, b, doc_a, doc_b, more) of distinct pairs, those of overlong lists included."""
    few = found.where("kind = 0").select("a", "b", "doc", "at", "n")
    every = few.unionAll(_overfull(found.where("kind = 3"), first, block))
    # A set's rows all name its first place, so any of them does.
    return every.groupBy("a", "b").agg(F.min("doc").alias("doc_a"), F.min("at").alias("doc_b"), (F.max(F.col("n") % 2) > 0).alias("more"))


def _overfull(rows: DataFrame, first: int, block: int) -> DataFrame:
    """Pairs of the lists over a block: sets are dealt into blocks by hash, each pair of blocks is a list of its own."""
    once = rows.groupBy("key", "a").agg(F.min(F.struct("doc", "at", "packed")).alias("first"))
    sizes = once.groupBy("key").agg(F.count("*").alias("size")).select(F.col("key").bitwiseXOR(F.lit(1)).alias("k"), F.ceil(F.col("size") / block).cast("int").alias("of"))
    # The key is computed anew, so that the join can split a list that is too long for a task.
    own = once.join(sizes, F.col("key").bitwiseXOR(F.lit(1)) == F.col("k")).withColumn("own", F.pmod(F.xxhash64("a"), F.col("of")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("of") - 1))
    # Like keys of words: neither negative nor salted.
    key = F.xxhash64("key", F.least("own", "other"), F.greatest("own", "other")).bitwiseAND(F.lit(HOT - 1))
    paired = own.withColumn("other", other).select(key.alias("key"), F.col("first.packed").alias("packed"))
    return _dealt(paired, "key").mapInArrow(_meet(first, 1 << 60), FOUND).where("kind = 0").select("a", "b", "doc", "at", "n")


def _doc_key(c: str) -> Column:
    return F.col(c).bitwiseXOR(F.lit(-1))


def _verified(pairs: DataFrame, docs: DataFrame, work: Workspace, rarity) -> tuple[DataFrame, DataFrame]:
    """``pairs`` (a, b, doc_a, doc_b, ...) with ``same``, compared word by word, and the words of their sets. Only documents in pairs are cut into words again,
    and only lines in pairs are shuffled; both are found in one table of fixed size, whose chance hits cost time only."""
    wanted_of = pairs.select(F.explode(F.array("a", "b", _doc_key("doc_a"), _doc_key("doc_b"))).alias("h")).distinct()
    wanted = docs.sparkSession.sparkContext.broadcast(count_table(wanted_of, _first_column))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release_memory()
        asked, own = wanted.value, rarity.value
        hit = lambda h: _in_table(asked, h)
        for batch in batches:
            texts = batch.column(1).filter(pa.array(hit((batch.column(0).to_numpy() ^ -1).view(np.uint64))))
            for _, lines in tokens.pieces(texts):
                word, line, _ = ordered_sets(lines, own)
                begin, size, h, _ = describe(word, line, len(lines.row), sketched=False)
                of = np.flatnonzero((size >= LEAST_NEAR) & hit(h))
                _, once = np.unique(h[of], return_index=True)
                of = of[once]
                if len(of):
                    at = np.concatenate([np.arange(b, b + s) for b, s in zip(begin[of], size[of], strict=True)])
                    lists = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(size[of]))).astype(np.int32)), pa.array(word[at].view(np.int64)))
                    yield pa.RecordBatch.from_arrays([pa.array(h[of].view(np.int64)), lists], names=["set", "words"])

    sets = pairs.select(F.explode(F.array("a", "b")).alias("set")).distinct()
    words = docs.mapInArrow(run, "set long, words array<long>").join(sets, "set", "left_semi").dropDuplicates(["set"])
    words = work.save(words, "words")
    left, right = (words.select(F.col("set").alias(c), F.col("words").alias(f"words_{c}")) for c in ("a", "b"))
    both = F.size(F.array_intersect("words_a", "words_b"))
    total = F.size("words_a") + F.size("words_b")
    return pairs.join(left, "a").join(right, "b").select("a", "b", (both * (NUM + DEN) >= NUM * total).alias("same")), words


def _keys_of(rarity):
    """The keys at which sets meet others, from their words in order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release_memory()
        own = rarity.value
        for batch in batches:
            lists = batch.column(0)
            word = lists.flatten().to_numpy().view(np.uint64)
            size = lists.value_lengths().to_numpy().astype(np.int64)
            place = np.arange(len(word)) - np.repeat(np.cumsum(size) - size, size)
            rare = own[(word & np.uint64(len(own) - 1)).astype(np.int64)] > 1
            use = rare & (place < np.repeat(size - (-(-NUM * size // DEN)) + 1, size))
            yield pa.RecordBatch.from_arrays([pa.array((word[use] >> np.uint64(32)).view(np.int64))], names=["key"])

    return run


def _decided(docs: DataFrame, work: Workspace, id_col: str, text_col: str, first: int, block: int) -> tuple[DataFrame, ...]:
    """First places of sets, later places, and the sets that match an earlier one; all of them saved."""
    spark = docs.sparkSession
    text = F.col("row").getField(text_col)
    texts = docs.where(text.isNotNull()).select(F.coalesce(F.col("row").getField(id_col).cast("long"), F.lit(LAST_ID)).alias("doc"), text.alias("text"), "row_key")
    shared = spark.sparkContext.broadcast
    # A word of count one meets nothing, so that its cell may as well be empty.
    rarity = shared(count_table(texts.select("text"), lambda b: (p.word for _, p in tokens.pieces(b.column(0))), least=2))
    # A word is frequent if it may make a task's rows several times as many as others'; there are few such words.
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    total = (np.bincount(rarity.value, minlength=64) * 2.0 ** (np.arange(64) - 0.5))[1:].sum()
    hot = max(int(np.log2(2 * block)) + 1, int(np.log2(max(total / (8 * parts), 1))) + 2)
    salted = {"hot": hot, "parts": parts}
    # Fewer than a fourth of all words are rows; a bucket is a small share of a task.
    bits = min(int(max(total / (4 * A_BUCKET), 16 * parts)).bit_length(), 24)
    found = None
    for turn in range(TURNS):
        rows = _dealt(texts.mapInArrow(_bundled(_nodes(rarity, turn=turn, turns=TURNS, **salted), bits), BUNDLES), "bucket")
        more = work.save(rows.mapInArrow(_meet_bundles(first, block, bits), FOUND), "found")
        found = more if found is None else found.unionAll(more)
        del rows
        release_shuffles(spark)
    place = F.shiftright("at", 32).cast("int").alias("line")
    begins = found.where("kind = 1").select(F.col("a").alias("set"), F.col("b").alias("row_key"), place)
    again = found.where("kind = 2").select(F.col("b").alias("row_key"), place)
    pairs = work.save(_pairs(found, first, block), "candidates")
    compared, words = _verified(pairs, texts, work, rarity)
    checked = work.save(compared, "checked")
    matched = checked.where("same").select("b").distinct()
    left = pairs.where("more").join(matched, "b", "left_anti").select("b").distinct()
    left = work.save(left, "left")
    if not left.isEmpty():
        # The lines are cut again, all that meet those asked for. Tables of fixed size hold sets and words, whose chance hits are
        # compared in vain, so only these rows are shuffled.
        asked_sets = shared(count_table(left, _first_column))
        asked_words = words.join(left, F.col("set") == F.col("b"), "left_semi").select("words")
        asked_keys = shared(count_table(asked_words.mapInArrow(_keys_of(rarity), "key long"), _first_column))
        blocks = -(-left.count() // HELD)
        rows = texts.mapInArrow(_nodes(rarity, sets=asked_sets, keys=asked_keys, blocks=blocks), ASKED)
        rest = rows.repartition("key").sortWithinPartitions("key", "asked").mapInArrow(_settled, "b long")
        matched = matched.unionAll(rest).distinct()
    matched = work.save(matched, "matched")
    for done in (pairs, checked, left, words):
        work.drop(done)
    release_shuffles(spark)
    return begins, again, matched


def _removals(rows: DataFrame, work: Workspace, id_col: str, text_col: str, first: int, block: int) -> DataFrame:
    """(gone_from, gone): of each row that loses lines, by its key, their numbers from 0."""
    with small_batches(rows.sparkSession, ROWS_A_BATCH):
        begins, again, matched = _decided(rows, work, id_col, text_col, first, block)
    gone = again.unionAll(begins.join(matched, F.col("set") == F.col("b"), "left_semi").select("row_key", "line"))
    return gone.groupBy(F.col("row_key").alias("gone_from")).agg(F.collect_set("line").alias("gone"))


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", first: int = FIRST, block: int = BLOCK) -> DataFrame:
    """(row, text, n_lines, n_removed): ``row`` holds the columns of ``docs``, ``text`` what is left of its text."""
    work = Workspace(docs.sparkSession, "lines")
    rows = row_keyed(docs, work)
    gone = _removals(rows, work, id_col, text_col, first, block)
    own = rows.select("row", F.col("row").getField(text_col).alias("t"), "row_key")
    joined = own.join(gone.hint("shuffle_hash"), F.col("row_key") == F.col("gone_from"), "left")
    n_lines = F.octet_length("t") - F.octet_length(F.replace("t", F.lit("\n"), F.lit(""))) + 1
    # The numbers that stay, as a set difference: a test of each line against a list would take lines times removals.
    stay = F.array_except(F.sequence(F.lit(0), (n_lines - 1).cast("int")), "gone")
    # The lines are bound once, by a lambda over the one array of them.
    kept = F.get(F.transform(F.array(F.split("t", "\n", -1)), lambda lines: F.array_join(F.transform(stay, lambda i: F.get(lines, i)), "\n")), 0)
    return joined.select("row", F.when(F.col("gone").isNull(), F.col("t")).otherwise(kept).alias("text"), n_lines.cast("long").alias("n_lines"), F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("n_removed"))


def query(spark, sf_dir: str) -> DataFrame:
    out = deduplicate(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("row.doc_id", "text", "n_lines", "n_removed")
