"""Personal data by a skip-chain conditional random field on top of fixed patterns.

Four kinds (email, ip, card, phone) have fixed patterns; their matches are always found. The field adds what patterns miss: a
mention that is weak by itself (a number without its plus sign, an address written with "(at)", a key without its label) is found
where its context or a repetition elsewhere in the document supports it. Nodes are the mentions: pattern matches, whose label is
given, groups of digits, written-out addresses, and tokens that hold a digit or an ``@``. Neighbours in the text share chain
potentials, and mentions with equal or similar content share skip potentials, however far apart. All mentions of one content are
joined through one factor (a star), not pairwise, so a token that repeats a thousand times costs a thousand messages. Beliefs are
computed by loopy sum-product message passing in arrays.

Weights are trained here, piecewise, on a sample of documents whose labels come from the patterns and from labelled keys (``token =
"..."``): unary weights by regularised logistic regression on features, chain weights from label agreement, skip weights from the
same and a prior for equal labels. Every mention is also shown without its context and signs, as one that is something else as
likely as not (``WEAK``): the sample says nothing about such mentions, so alone they stay under the threshold and a repetition decides.
The sample is bounded: documents whose hash falls under ``SAMPLE_DOCS / documents``.

Defined results: a null text counts as empty and has no spans; offsets are code points, ends exclusive; of overlapping spans of
one kind the first stays; added spans never overlap pattern spans; whole texts are read, memory is in proportion to the longest;
rows are independent, so repeated rows agree; an empty table gives an empty result; further columns do not matter.
"""

from __future__ import annotations

import bisect
import hashlib
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adaptivejoin.llm.common import release_memory, table

#: The kinds in order, and the patterns of the first four.
KINDS = ("email", "ip", "card", "phone", "secret")
LABELS = ("other", *KINDS)
EMAIL = re.compile(r"[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++")
EMAIL_BEGIN = re.compile(r"(?<![A-Za-z0-9._%+-])" + EMAIL.pattern)
IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
DIGITS = re.compile("[^0-9]+")

SAMPLE_DOCS = 3000
ROUNDS = 4
#: A token is added if the belief in a kind exceeds this.
LEAST_BELIEF = 0.9

#: A run without white space that holds a digit or an at sign; matched from its beginning only, without going back.
TOKEN = re.compile(r"(?<!\S)[^\s0-9@]*+[0-9@]\S*")
#: Groups of digits with single separators, and addresses written out.
GROUPS = re.compile(r"(?<![0-9A-Za-z])\(?[0-9]++\)?(?:[ ().-]{1,2}[0-9]++)++")
WRITTEN = re.compile(r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++ ?[(\[]at[)\]] ?[A-Za-z0-9-]++(?: ?(?:[(\[]dot[)\]]|\.) ?[A-Za-z0-9-]++)++", re.I)
CODE = re.compile(r"\A\+[0-9]{1,3}[ .-]+")
SIGNS = re.compile(r" ?[(\[](at|dot)[)\]] ?", re.I)
EDGE = "\"'()[]{}<>,;:.!?#*$%&|"
HEX = re.compile(r"[0-9a-fA-F]{16,}\Z")
KEYWORD = re.compile(r"(token|secret|key|password|passwd|pwd|mail|email|ip|host|addr|address|card|visa|phone|tel|mobile|call)\W*\Z", re.I)
#: Numbers of so many digits or more are alike if their last digits are: a country's code may be left out.
SAME_DIGITS = 9
#: How much a mention without context and signs counts as its label; the rest counts as something else.
WEAK = 0.5
#: Agreeing pairs of equal mentions of each label that are assumed before any is seen.
AGREEMENT = 100.0


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        x = ord(d) - 48
        total += x if i % 2 == 0 else (2 * x - 9 if x > 4 else 2 * x)
    return total % 10 == 0


def emails(text: str) -> Iterator[tuple[int, int]]:
    """A match begins where a run of its first class begins, or where the previous match ended: elsewhere in a run it would end alike."""
    if "@" not in text:
        return
    at = 0
    while True:
        m = (EMAIL.match(text, at) if at else None) or EMAIL_BEGIN.search(text, at)
        if not m:
            return
        yield m.span()
        at = m.end()


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of all pattern matches, in order."""
    out = [(a, 0, b) for a, b in emails(text)]
    for m in IP.finditer(text):
        if all(len(p) <= 3 and int(p or "0") <= 255 for p in (q.lstrip("0") for q in m[0].split("."))):
            out.append((m.start(), 1, m.end()))
    for m in CARD.finditer(text):
        if m.end() - m.start() >= 12:
            digits = DIGITS.sub("", m[0])
            if 12 <= len(digits) <= 19 and luhn(digits):
                out.append((m.start(), 2, m.end()))
    if "+" in text:
        for m in PHONE.finditer(text):
            if 9 <= len(DIGITS.sub("", m[0])) <= 15:
                out.append((m.start(), 3, m.end()))
    return sorted(out)


def content(t: str) -> str:
    """A key that similar mentions share: the last digits of a number, else the letters and dots, case and signs apart."""
    digits = DIGITS.sub("", t)
    if len(digits) >= 7 and len(digits) >= 0.6 * len(t):
        return digits[-SAME_DIGITS:]
    plain = SIGNS.sub(lambda m: "@" if m[1].lower() == "at" else ".", t) if "(" in t or "[" in t else t
    return re.sub(r"[^\w.@]+", "", plain).strip(".").lower()


def described(text: str, a: int, b: int, weakly: bool = False) -> tuple[str, ...]:
    """Features of a mention; ``weakly``: without what stands before it, a plus sign and the country's code after that."""
    t = text[a:b]
    if weakly:
        t = CODE.sub("", t) or t
    digits = DIGITS.sub("", t)
    n = len(digits)
    before = None if weakly else KEYWORD.search(text[max(0, a - 24) : a])
    plus = not weakly and (text[a - 1 : a] == "+" or t[:1] == "+")
    shape = re.sub("[a-z]+", "x", re.sub("[A-Z]+", "X", re.sub("[0-9]+", "9", t[:64].lstrip("+"))))
    if t.count(".") < 3 and n >= 0.6 * len(t):  # a number, whatever separates its groups
        shape = re.sub("[ ().-]+", "-", shape).strip("-")
    return (
        f"shape={shape[:12]}", f"digits={min(n, 20)}", f"part={round(4 * n / len(t))}", f"dots={min(t.count('.'), 4)}", f"at={'@' in t or bool(SIGNS.search(t))}", f"hex={bool(HEX.match(t))}",
        f"plus={plus}", f"long={min(len(t) // 8, 6)}", f"before={before[1].lower() if before else ''}", f"luhn={12 <= n <= 19 and luhn(digits)}",
    )


def candidates(text: str) -> Iterator[tuple[int, int]]:
    """Spans that may be personal data, in no order; they may overlap."""
    if any(x in text for x in ("at)", "at]", "AT)", "AT]")):
        yield from (m.span() for m in WRITTEN.finditer(text))
    for m in GROUPS.finditer(text):
        if 7 <= len(DIGITS.sub("", m[0])) <= 19:
            yield m.span()
    for m in TOKEN.finditer(text):
        a, b = m.span()
        while a < b and text[a] in EDGE:
            a += 1
        while b > a and text[b - 1] in EDGE:
            b -= 1
        if b - a >= 6 and any(c in "0123456789@" for c in text[a:b]):
            yield a, b


def nodes(text: str, base: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """(start, end, given label or 0) of the mentions in order: pattern matches, then the candidates that overlap none before."""
    given: list[tuple[int, int, int]] = []
    for a, k, b in base:
        if not given or given[-1][1] <= a:
            given.append((a, b, k + 1))
    free: list[tuple[int, int, int]] = []
    end = 0
    for a, b in sorted(candidates(text), key=lambda s: (s[0], -s[1])):  # of overlapping ones the longest that begins first
        i = bisect.bisect_right(given, (a, 1 << 62, 0))
        if a >= end and (i == 0 or given[i - 1][1] <= a) and (i == len(given) or given[i][0] >= b):
            free.append((a, b, 0))
            end = b
    return sorted(given + free)


def silver(text: str, spans: list[tuple[int, int, int]]) -> list[int]:
    """Training labels of nodes: the given ones, and hexadecimal keys that their text calls so."""
    secret = LABELS.index("secret")
    named = lambda a, b: HEX.match(text[a:b]) and re.search(r"(token|secret|key|password)\W*\Z", text[max(0, a - 24) : a], re.I)
    return [y or (secret if named(a, b) else 0) for a, b, y in spans]


def learn(docs: DataFrame, sample_docs: int = SAMPLE_DOCS) -> dict[str, np.ndarray]:
    """Weights of the field from the training sample: unary by feature, "chain" and "skip" by label pair."""
    with_text = docs.where(F.col("text").isNotNull())
    total = with_text.agg(F.count("*").alias("n")).first()["n"]
    draw = F.pmod(F.xxhash64(F.col("doc_id"), F.lit("field")), F.lit(1 << 30)).cast("double") / float(1 << 30)
    sample = with_text.where(draw * total < sample_docs).select("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: Counter = Counter()
        for batch in batches:
            for t in batch.column(0):
                counts.update(evidence(t.as_py()))
        rows = list(counts.items())
        yield pa.RecordBatch.from_arrays([pa.array([k[0] for k, _ in rows], pa.string()), *(pa.array([k[i] for k, _ in rows], pa.int32()) for i in (1, 2)), pa.array([n for _, n in rows], pa.int64())], names=["f", "y", "z", "n"])

    rows = sample.mapInArrow(run, "f string, y int, z int, n long").groupBy("f", "y", "z").agg(F.sum("n").alias("n")).orderBy("f", "y", "z").toArrow().to_pylist()
    return weights_of({(r["f"], r["y"], r["z"]): r["n"] for r in rows})


def evidence(text: str) -> Counter:
    """Counts of one training document: (features, label, seen weakly), and of label pairs ("chain" or "skip", label, label)."""
    counts: Counter = Counter()
    spans = nodes(text, base_spans(text))
    labels = silver(text, spans)
    first: dict[str, int] = {}
    for i, (y, (a, b, _)) in enumerate(zip(labels, spans, strict=True)):
        for weakly in (0, 1):
            counts["\t".join(described(text, a, b, bool(weakly))), y, weakly] += 1
        if i:
            counts["chain", labels[i - 1], y] += 1
        key = content(text[a:b])
        if key in first:
            counts["skip", first[key], y] += 1
        first[key] = y
    return counts


def weights_of(counts: dict, rounds: int = 300, decay: float = 1e-3) -> dict[str, np.ndarray]:
    k = len(LABELS)
    rows: dict[str, np.ndarray] = {}
    for (f, y, weakly), n in counts.items():
        if f not in ("chain", "skip"):
            at = rows.setdefault(f, np.zeros(k))
            at[y] += n * (WEAK if weakly and y else 1)
            at[0] += n * (1 - WEAK) if weakly and y else 0
    out = _logistic(sorted(rows), rows, rounds, decay)
    for kind, most, own in (("chain", 1.0, 0.0), ("skip", 3.0, AGREEMENT)):
        n = np.array([[counts.get((kind, y, z), 0) + counts.get((kind, z, y), 0) for z in range(k)] for y in range(k)], float) + 1 + own * np.eye(k)
        pair = np.log(n / n.sum()) - np.log(n.sum(1, keepdims=True) / n.sum()) - np.log(n.sum(0, keepdims=True) / n.sum())
        out[kind] = np.clip(pair, -most, most)
    return out


def _logistic(tuples: list[str], rows: dict[str, np.ndarray], rounds: int, decay: float) -> dict[str, np.ndarray]:
    """Multinomial logistic regression of labels on features, by accelerated gradient steps from zero."""
    if not tuples:
        return {"labels": np.zeros(len(LABELS))}
    split = [t.split("\t") for t in tuples]
    names = sorted({f for fs in split for f in fs})
    at = {f: i for i, f in enumerate(names)}
    index = np.array([[at[f] for f in fs] for fs in split], np.int64).reshape(len(tuples), -1)
    target = np.array([rows[t] for t in tuples]).reshape(len(tuples), len(LABELS))
    total = target.sum(1, keepdims=True)
    weights, bias = np.zeros((len(names), len(LABELS))), np.zeros(len(LABELS))
    ahead, ahead_bias = weights.copy(), bias.copy()
    step = 1 / (0.5 * (index.shape[1] + 1) + decay)
    for i in range(rounds):
        score = ahead[index].sum(1) + ahead_bias
        p = np.exp(score - score.max(1, keepdims=True))
        gap = (target - total * p / p.sum(1, keepdims=True)) / total.sum()
        grad = np.zeros_like(weights)
        np.add.at(grad, index.ravel(), np.repeat(gap, index.shape[1], axis=0))
        new, new_bias = ahead + step * (grad - decay / 10 * ahead), ahead_bias + step * gap.sum(0)
        pull = i / (i + 3)
        ahead, ahead_bias = new + pull * (new - weights), new_bias + pull * (new_bias - bias)
        weights, bias = new, new_bias
    return {"labels": bias} | {f: weights[i] for f, i in at.items()}


def beliefs(unary: np.ndarray, keys: list[str], weights: dict[str, np.ndarray], rounds: int = ROUNDS) -> np.ndarray:
    """Marginals of the nodes by loopy message passing over the chain and over one star for each content."""
    n, k = unary.shape
    norm = lambda m: m - np.logaddexp.reduce(m, axis=-1, keepdims=True)
    send = lambda m, w: norm(np.logaddexp.reduce(m[:, :, None] + w[None], axis=1))
    chain, skip = weights["chain"], weights["skip"]
    _, group = np.unique(np.array(keys, dtype=object).astype(str), return_inverse=True)
    size = np.bincount(group)
    shared = size[group] > 1
    right, left = np.zeros((n, k)), np.zeros((n, k))  # messages that arrive from the left and from the right neighbour
    up, down = np.zeros((n, k)), np.zeros((n, k))  # to a content's hub and back
    for _ in range(rounds):
        local = unary + down
        right[1:], left[:-1] = send((local + right)[:-1], chain), send((local + left)[1:], chain.T)
        if shared.any():
            up[shared] = send((unary + right + left)[shared], skip)
            total = np.zeros((len(size), k))
            np.add.at(total, group[shared], up[shared])
            down[shared] = send(norm(total[group[shared]] - up[shared]), skip)
    return np.exp(norm(unary + right + left + down))


#: Log weight against every other label of a mention whose label is given.
GIVEN = -30.0


def unary_of(text: str, spans: list[tuple[int, int, int]], weights: dict[str, np.ndarray]) -> np.ndarray:
    zero = np.zeros(len(LABELS))
    out = np.full((len(spans), len(LABELS)), GIVEN)
    for i, (a, b, y) in enumerate(spans):
        if y:
            out[i, y] = 0
        else:
            out[i] = weights["labels"] + sum((weights.get(f, zero) for f in described(text, a, b)), zero)
    return out


def find(text: str, weights: dict[str, np.ndarray]) -> tuple[list, list]:
    """Pattern spans and all spans, each as (start, kind, end) in order."""
    base = base_spans(text)
    spans = nodes(text, base)
    if not any(not y for _, _, y in spans):
        return base, base
    p = beliefs(unary_of(text, spans, weights), [content(text[a:b]) for a, b, _ in spans], weights)
    best = p.argmax(axis=1)
    added = [(a, int(y) - 1, b) for (a, b, given), y, own in zip(spans, best.tolist(), p.max(axis=1).tolist(), strict=True) if y and not given and own >= LEAST_BELIEF]
    return base, sorted(base + added)


def written(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


def detect(docs: DataFrame, weights: dict[str, np.ndarray], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, spans, base): arrays of (start, kind, end); ``base`` holds the pattern matches among them."""
    kind = "array<struct<start:int,kind:string,end:int>>"
    id_type = docs.schema[id_col].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast(weights)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release_memory()
        own = shared.value
        typ = pa.list_(pa.struct([("start", pa.int32()), ("kind", pa.string()), ("end", pa.int32())]))
        for batch in batches:
            found = [find(t.as_py() or "", own) for t in batch.column(1)]
            cols = [pa.array([[{"start": a, "kind": KINDS[k], "end": b} for a, k, b in f[i]] for f in found], typ) for i in (1, 0)]
            yield pa.RecordBatch.from_arrays([batch.column(0), *cols], names=["doc_id", "spans", "base"])

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, f"doc_id {id_type}, spans {kind}, base {kind}")


def digests(found: DataFrame) -> DataFrame:
    """The result of ``detect`` as counts of pattern matches, their digest and all spans as text."""
    count = lambda k: F.size(F.filter("base", lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    text = lambda c: F.array_join(F.transform(c, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    return found.select("doc_id", *[count(k) for k in KINDS[:4]], F.sha2(text("base"), 256).alias("base_sha256"), text("spans").alias("spans"))


def redact(text: str, spans: list[tuple[int, int, int]]) -> str:
    """The text with every span replaced by its kind; of overlapping spans the first stays."""
    out, at = [], 0
    for a, k, b in spans:
        if a >= at:
            out += [text[at:a], f"[{KINDS[k]}]"]
            at = b
    return "".join([*out, text[at:]])


def sha_of(spans) -> str:
    return hashlib.sha256(written(spans).encode()).hexdigest()


def query(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return digests(detect(docs, learn(docs)))
