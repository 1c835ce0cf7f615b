"""Transcript parsing by a hidden Markov model, and canonical rendering of turns.

``parse_transcripts`` takes whole transcripts as texts: each line is in the beginning or in the rest of a role's turn, which is
the hidden state; it is observed through its marker, length and end. Viterbi over the lines cuts a text into turns.

``parse`` takes transcripts that are cut already, as rows. A transcript is a sequence of blocks of lines. Hidden states are the roles; a block is observed through features: the marker that
its first line may begin with, how many lines and words it has, how it ends, and whether it opens the transcript. Probabilities
are smoothed counts of a labelled sample. Viterbi gives the roles; markers are stripped and turns rendered in one form.

Transcripts are not gathered: blocks are range-partitioned by (transcript, position), so one with a third of all rows is spread
over many tasks. A task condenses the transcript pieces that cross its borders into transfer matrices (best score from any state
before to any state after); these few rows, two a partition, are chained on the driver, and the second pass decodes every piece
with its fixed border states. The result is that of one sequential Viterbi.

Defined results: a null text is an empty block; equal scores go to the role that sorts first, from the end backwards; blocks
with equal position are ordered by text; a null transcript id is a transcript of its own, a null position sorts first; an empty
table gives an empty result; without labelled rows every role is ``user``; further columns do not matter. A transcript that is null
or has nothing but blank lines has no turns; lines before the first marker are a turn like any others; a text is read whole.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from adaptivejoin.llm.common import Workspace, table

#: Markers that begin a speaker's block, by what they usually stand for.
MARKERS = {
    "user": ("user", "human", "q", "question", "me", "customer", "prompter"),
    "assistant": ("assistant", "ai", "bot", "a", "answer", "agent", "model", "gpt"),
    "system": ("system", "instructions", "instruction", "context"),
}
MARKER = re.compile(r"\s*(?:#{1,4}\s*|\[|<\|?|\*\*)?(" + "|".join(sorted((m for ms in MARKERS.values() for m in ms), key=len, reverse=True)) + r")(?:\]|\|?>|\*\*)?\s*[:\n>-]\s*", re.I)
OF_MARKER = {m: role for role, ms in MARKERS.items() for m in ms}
SAMPLE_ROWS = 20_000
SMOOTHING = 1.0
#: Begins the names of features of lines; those of blocks have no such name.
LINE = "line "
#: Assumed before any is seen, as so many lines: how often a turn's first line has a marker, in transcripts with and without them, and
#: how often a later line; how often it is that of the turn's own role.
ASSUMED, FIRST_MARKED, LATER_MARKED, OWN_MARKER = 10_000.0, (0.999, 0.02), 0.01, 0.95


def features(text: str, opens: bool) -> tuple[str, ...]:
    m = MARKER.match(text)
    body = text[m.end() :] if m else text
    words, tail = len(body.split()), body.rstrip()[-1:]
    return (
        f"marker={OF_MARKER[m[1].lower()] if m else ''}",
        f"lines={min(body.count(chr(10)), 4)}",
        f"words={min(int(np.log2(words + 1) * 2), 20)}",
        f"end={tail if tail in '?.!:' else '-'}",
        f"opens={opens}",
    )


def strip_marker(text: str) -> str:
    m = MARKER.match(text)
    return (text[m.end() :] if m else text).strip()


def render(role: str, body: str) -> str:
    return f"<|{role}|>\n{body}\n<|end|>\n"


def line_features(line: str) -> tuple[str, ...]:
    m = MARKER.match(line)
    body = line[m.end() :] if m else line
    words, tail = len(body.split()), body.rstrip()[-1:]
    return (f"{LINE}marker={OF_MARKER[m[1].lower()] if m else ''}", f"{LINE}words={min(int(np.log2(words + 1) * 2), 16)}", f"{LINE}end={tail if tail in '?.!:' else '-'}")


def line_keys(text: str, role: str) -> list[tuple[str, str, str]]:
    """What a training turn says about lines: the features of its first and of later ones, and how many there are of these."""
    out = []
    for i, line in enumerate(text.split("\n")):
        part = "later" if i else "first"
        out += [(f"{LINE}n", role, part), *((f, role, part) for f in line_features(line))]
    return out


class Model:
    """Log probabilities; states in sorted order."""

    def __init__(self, counts: dict):
        self.roles = sorted({y for f, y, _ in counts if f == "role"}) or ["user"]
        at = {y: i for i, y in enumerate(self.roles)}
        k = len(self.roles)
        total, step = np.zeros(k), np.full((k, k), SMOOTHING)
        seen: dict[str, np.ndarray] = {}
        for (f, y, v), n in counts.items():
            if f.startswith(LINE):
                continue
            if f == "role":
                total[at[y]] += n
            elif f == "step":
                if v in at:
                    step[at[v], at[y]] += n
            else:
                seen.setdefault(f, np.zeros(k))[at[y]] += n
        self.step = np.log(step / step.sum(1, keepdims=True))
        kinds = {f.split("=")[0]: 1 for f in seen}
        values = {kind: sum(f.startswith(kind + "=") for f in seen) + 1 for kind in kinds}
        self.seen = {f: np.log((n + SMOOTHING) / (total + SMOOTHING * values[f.split("=")[0]])) for f, n in seen.items()}
        self.none = np.zeros(k)
        self.start = np.log((total + SMOOTHING) / (total + SMOOTHING).sum())
        self.lines = tuple(LineModel(counts, self, marked) for marked in FIRST_MARKED)

    def emit(self, text: str, opens: bool) -> np.ndarray:
        out = self.start.copy() if opens else self.none.copy()
        for f in features(text, opens):
            out += self.seen.get(f, self.none)
        return out


class LineModel:
    """Log probabilities of lines; states are the first lines of each role, then the later ones."""

    def __init__(self, counts: dict, blocks: Model, first_marked: float):
        self.roles = blocks.roles
        k = len(self.roles)
        at = {y: i for i, y in enumerate(self.roles)}
        place = lambda y, part: at[y] + (k if part == "later" else 0)
        total = np.zeros(2 * k)
        seen: dict[str, np.ndarray] = {}
        for (f, y, v), n in counts.items():
            if f == f"{LINE}n":
                total[place(y, v)] += n
            elif f.startswith(LINE):
                seen.setdefault(f, np.zeros(2 * k))[place(y, v)] += n
        for role in ["", *MARKERS]:
            own = np.array([OWN_MARKER if r == role else (1 - OWN_MARKER) / max(len(MARKERS) - 1, 1) for r in self.roles])
            marked = np.concatenate([first_marked * own, np.full(k, LATER_MARKED / len(MARKERS))])
            plain = np.repeat([1 - first_marked, 1 - LATER_MARKED], k)
            seen[f"{LINE}marker={role}"] = seen.get(f"{LINE}marker={role}", np.zeros(2 * k)) + ASSUMED * (marked if role else plain)
        values = {kind: sum(f.split("=")[0] == kind for f in seen) + 1 for kind in {f.split("=")[0] for f in seen}}
        extra = {kind: ASSUMED if kind == f"{LINE}marker" else 0.0 for kind in values}
        self.seen = {f: np.log((n + SMOOTHING) / (total + extra[f.split("=")[0]] + SMOOTHING * values[f.split("=")[0]])) for f, n in seen.items()}
        self.none = np.zeros(2 * k)
        stay = (total[k:] + SMOOTHING) / (total[:k] + total[k:] + 2 * SMOOTHING)
        with np.errstate(divide="ignore"):
            goes_on = np.log(np.diag(stay))
        begins = blocks.step + np.log(1 - stay)[:, None]
        # From a role's first or later line to the first line of any role, or to a later one of its own.
        self.step = np.tile(np.concatenate([begins, goes_on], axis=1), (2, 1))
        self.start = np.concatenate([blocks.start, np.full(k, -np.inf)])

    def emit(self, line: str) -> np.ndarray:
        out = self.none.copy()
        for f in line_features(line):
            out += self.seen.get(f, self.none)
        return out


def turns_of(text: str, models: tuple[LineModel, ...]) -> list[tuple[str, str]]:
    """(role, body) of the turns of a transcript, under the model that explains it best."""
    if not text.strip():
        return []
    lines: list[str] = []
    for line in text.split("\n"):
        if lines and (m := MARKER.match(lines[-1] + "\n")) and m.end() > len(lines[-1]):
            lines[-1] += "\n" + line  # a marker that stands alone belongs to what follows
        else:
            lines.append(line)
    best: tuple[float, list[int]] | None = None
    for model in models:
        emits = np.array([model.emit(line) for line in lines])
        emits[0] += model.start
        states = decode(emits, model.step)
        score = emits[np.arange(len(lines)), states].sum() + model.step[states[:-1], states[1:]].sum()
        if best is None or score > best[0]:
            best = score, states
    k, out = len(models[0].roles), []
    for line, state in zip(lines, best[1], strict=True):
        if state < k:
            out.append((models[0].roles[state], [line]))
        else:
            out[-1][1].append(line)
    return [(role, strip_marker("\n".join(body))) for role, body in out]


def parse_transcripts(docs: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """(row, turns, rendered) of every transcript: ``row`` holds the columns of ``docs``, ``turns`` are (role, text) in order."""
    shared = docs.sparkSession.sparkContext.broadcast(model.lines)
    base = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col(f"`{text_col}`").alias("text"))
    typ = pa.list_(pa.struct([("role", pa.string()), ("text", pa.string())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in batches:
            found = [turns_of(t.as_py() or "", own) for t in batch.column(1)]
            made = pa.array([[{"role": r, "text": b} for r, b in ts] for ts in found], typ)
            yield pa.RecordBatch.from_arrays([batch.column(0), made, pa.array(["".join(render(r, b) for r, b in ts) for ts in found], pa.string())], names=["row", "turns", "rendered"])

    kinds = T.StructType([base.schema["row"], T.StructField("turns", T.ArrayType(T.StructType([T.StructField("role", T.StringType()), T.StructField("text", T.StringType())]))), T.StructField("rendered", T.StringType())])
    return base.mapInArrow(run, kinds)


def decode(emits: np.ndarray, step: np.ndarray, before: np.ndarray | None = None, last: int | None = None) -> list[int]:
    """Viterbi over one piece: ``before`` are the best scores before it (None: it opens the transcript), ``last`` its final state."""
    n, k = emits.shape
    score = emits[0] if before is None else (before[:, None] + step).max(0) + emits[0]
    back = np.zeros((n, k), np.int16)
    for i in range(1, n):
        cand = score[:, None] + step
        back[i] = cand.argmax(0)
        score = cand.max(0) + emits[i]
    states = [int(score.argmax()) if last is None else last]
    for i in range(n - 1, 0, -1):
        states.append(int(back[i, states[-1]]))
    return states[::-1]


def transfer(emits: np.ndarray, step: np.ndarray, opens: bool) -> np.ndarray:
    """Best score of a piece from each state before it (rows; equal rows if it opens the transcript) to each last state."""
    k = step.shape[0]
    m = np.tile(emits[0], (k, 1)) if opens else step + emits[0]
    for e in emits[1:]:
        m = (m[:, :, None] + step[None]).max(1) + e
    return m


def train(turns: DataFrame, sample_rows: int = SAMPLE_ROWS) -> Model:
    """Counts of a bounded sample of labelled transcripts: those whose hash falls under ``sample_rows / rows``."""
    labelled = turns.where(F.col("role").isNotNull() & (F.coalesce(F.crc32(F.col("conv_id").cast("string")), F.lit(0)) % 5 != 0))
    rows = labelled.agg(F.count("*").alias("n")).first()["n"]
    draw = F.pmod(F.xxhash64("conv_id", F.lit("chat"), F.floor(F.col("turn") / 16)), F.lit(1 << 30)).cast("double") / float(1 << 30)
    # Long transcripts are sampled in stretches of 16 turns, so that one of them cannot fill the sample.
    sample = labelled.where(draw * rows < sample_rows).select("conv_id", "turn", "role", "text")
    # A transcript opens with its first block, whatever number that has.
    opening = labelled.groupBy(F.col("conv_id").alias("of")).agg(F.min("turn").alias("opening"))
    sample = sample.join(opening, F.col("conv_id") == F.col("of"), "left").withColumn("opens", F.col("turn").eqNullSafe(F.col("opening"))).drop("of", "opening")
    first = sample.alias("a").join(sample.select(F.col("conv_id").alias("c"), (F.col("turn") + 1).alias("t"), F.col("role").alias("previous")).distinct(), (F.col("conv_id") == F.col("c")) & (F.col("turn") == F.col("t")), "left")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: dict = {}
        for batch in batches:
            for opens, role, text, previous in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                keys = [("role", role, ""), *((f, role, "") for f in features(text or "", opens)), *line_keys(text or "", role)]
                if previous is not None:
                    keys.append(("step", role, previous))
                for key in keys:
                    counts[key] = counts.get(key, 0) + 1
        yield pa.RecordBatch.from_arrays([*(pa.array([k[i] for k in counts], pa.string()) for i in range(3)), pa.array(list(counts.values()), pa.int64())], names=["f", "y", "v", "n"])

    got = first.select("opens", "role", "text", "previous").mapInArrow(run, "f string, y string, v string, n long").groupBy("f", "y", "v").agg(F.sum("n").alias("n")).collect()
    return Model({(r.f, r.y, r.v): r.n for r in sorted(got, key=lambda r: (r.f, r.y, r.v))})


def _pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
    """(part, transcript, rows) of a stream sorted by transcript and position."""
    key, rows = None, []
    for batch in batches:
        cols = [batch.column(i).to_pylist() for i in range(batch.num_columns)]
        for row in zip(*cols, strict=True):
            if key is not None and row[:2] != key:
                yield (*key, rows)
                rows = []
            key = row[:2]
            rows.append(row[2:])
    if rows:
        yield (*key, rows)


def parse(blocks: DataFrame, model: Model, id_col: str = "conv_id", at_col: str = "turn", text_col: str = "text") -> DataFrame:
    """(conv_id, turn, role, rendered) of every block."""
    spark = blocks.sparkSession
    work = Workspace(spark, "chat")
    rows = blocks.select(F.col(id_col).alias("conv_id"), F.col(at_col).alias("turn"), F.col(text_col).alias("text"))
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ranged = rows.repartitionByRange(n, "conv_id", "turn", "text").sortWithinPartitions("conv_id", "turn", "text").withColumn("part", F.spark_partition_id())
    saved = work.save(ranged.select("part", "conv_id", "turn", "text"), "blocks")
    dealt = saved.repartition(n, "part").sortWithinPartitions("part", "conv_id", "turn", "text")
    shared = spark.sparkContext.broadcast(model)
    # Transcripts that two parts share; there are fewer of them than parts.
    crossing = saved.select("part", "conv_id").groupBy("part").agg(F.min(F.struct(F.col("conv_id").isNotNull().alias("k"), "conv_id")).alias("lo"), F.max(F.struct(F.col("conv_id").isNotNull().alias("k"), "conv_id")).alias("hi")).orderBy("part").collect()
    ends = [(r.part, r.lo.conv_id, r.hi.conv_id) for r in crossing]
    joined = {(p, c) for (p, _, hi), (q, lo, _) in zip(ends, ends[1:], strict=False) if hi == lo for p, c in ((p, hi), (q, hi))}
    follows = {(q, lo) for (_, _, hi), (q, lo, _) in zip(ends, ends[1:], strict=False) if hi == lo}

    def matrices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for part, conv, texts in _pieces(batches):
            if (part, conv) in joined:
                opens = (part, conv) not in follows
                emits = np.array([own.emit(t or "", opens and i == 0) for i, (_, t) in enumerate(texts)])
                m = transfer(emits, own.step, opens).ravel().tolist()
                yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([not opens]), pa.array([m], pa.list_(pa.float64()))], names=["part", "follows", "m"])

    borders: dict = {}
    if joined:
        k = len(model.roles)
        got = dealt.mapInArrow(matrices, "part int, follows boolean, m array<double>").collect()
        borders = _chain(ends, {(r.part, r.follows): np.array(r.m).reshape(k, k) for r in got}, k)

    def roles(batches):
        own = shared.value
        for part, conv, texts in _pieces(batches):
            before, last = borders.get((part, (part, conv) in follows), (None, None)) if (part, conv) in joined else (None, None)
            opens = before is None
            emits = np.array([own.emit(t or "", opens and i == 0) for i, (_, t) in enumerate(texts)])
            states = decode(emits, own.step, before, last)
            names = [own.roles[s] for s in states]
            yield pa.RecordBatch.from_arrays(
                [pa.array([conv] * len(texts), id_type), pa.array([t for t, _ in texts], at_type), pa.array(names, pa.string()), pa.array([render(r, strip_marker(t or "")) for r, (_, t) in zip(names, texts, strict=True)], pa.string())],
                names=["conv_id", "turn", "role", "rendered"],
            )

    from pyspark.sql.pandas.types import to_arrow_type

    id_type, at_type = (to_arrow_type(saved.schema[c].dataType) for c in ("conv_id", "turn"))
    kinds = {c: saved.schema[c].dataType.simpleString() for c in ("conv_id", "turn")}
    return dealt.mapInArrow(roles, f"conv_id {kinds['conv_id']}, turn {kinds['turn']}, role string, rendered string")


def _chain(ends: list[tuple], matrix: dict, k: int) -> dict:
    """(scores before, last state) of each border piece, by (part, whether it continues)."""
    out: dict = {}
    chain: list[tuple] = []

    def close():
        """One transcript over the pieces of ``chain``: forward scores, then the last states backwards."""
        if len(chain) < 2:
            chain.clear()
            return
        scores = [matrix[chain[0]][0]]
        for key in chain[1:]:
            scores.append((scores[-1][:, None] + matrix[key]).max(0))
        last = int(scores[-1].argmax())
        for i in range(len(chain) - 1, -1, -1):
            out[chain[i]] = (scores[i - 1] if i else None, last)
            if i:
                last = int((scores[i - 1] + matrix[chain[i]][:, last]).argmax())
        chain.clear()

    for i, (p, lo, hi) in enumerate(ends):
        goes_on = i > 0 and ends[i - 1][2] == lo
        if goes_on:
            chain.append((p, True))
            if lo != hi:
                close()
        shared_next = i + 1 < len(ends) and ends[i + 1][1] == hi
        if shared_next and not (goes_on and lo == hi):
            chain.append((p, False))
        elif not shared_next:
            close()
    close()
    return out


def query(spark, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations")
    return parse(turns.select("conv_id", "turn", "text"), train(turns))
