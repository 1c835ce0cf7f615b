"""Quality rules: one table of thresholds, compiled into one projection.

Each rule names a ratio or a count, a lower and an upper bound. ``compile_rules`` turns the table into a boolean column; all
statistics are built-in expressions over the text, so a scan, a projection and nothing else run: no shuffle, no user function.

Defined results: a null text counts as an empty one, which has no words and fails; very long texts need memory in proportion
to their words and time in proportion to words times their logarithm; every row is judged alone, so ties and repeated rows
get equal verdicts; an empty table gives an empty result; further columns pass through ``apply_rules``.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from adaptivejoin.llm.common import SPACES, table, words

#: The characters that count as symbols, and frequent words of the four languages.
SYMBOLS = "#*$%&|<>"
STOP_WORDS = ("the", "of", "and", "to", "in", "a", "is", "that", "de", "la", "le", "et", "les", "des", "en", "un", "el", "que", "y", "los", "der", "die", "und", "das", "ist", "von", "den", "zu")
WINDOW = 5


@dataclass(frozen=True)
class Rule:
    """``100 * top`` must lie between ``low * bottom`` and ``high * bottom``: percentages, in integers.

    Texts of fewer than ``least_words`` words are not asked: in a few words a ratio says little.
    """

    name: str
    top: str
    bottom: str
    low: int | None = None
    high: int | None = None
    least_words: int = 0


#: The rules every text must pass before the others are asked.
BASE_RULES = (Rule("enough_words", "n_words", "one", low=1000), Rule("few_repeats", "n_repeat_words", "n_words", high=20))
#: Thresholds in per cent of the bottom.
RULES = (
    Rule("word_length", "word_chars", "n_words", low=200, high=1500),
    Rule("symbols", "n_symbols", "n_words", high=30),
    Rule("duplicate_lines", "n_dup_lines", "n_lines", high=40),
    Rule("stop_words", "n_stop_words", "n_words", low=1, least_words=50),
)


def compile_rules(rules: tuple[Rule, ...]) -> Column:
    """True where every rule holds."""
    verdict = F.lit(True)
    for r in rules:
        held = F.lit(True)
        if r.low is not None:
            held = held & (100 * F.col(r.top) >= r.low * F.col(r.bottom))
        if r.high is not None:
            held = held & (100 * F.col(r.top) <= r.high * F.col(r.bottom))
        verdict = verdict & (held | (F.col("n_words") < r.least_words) if r.least_words else held)
    return verdict


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body(value)`` with the value computed once. A lambda's variable is bound to it, so that lambdas within the body read it
    instead of building it anew for each element, wherever the optimizer moves the expression."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def repeated_words(ws: Column, width: int = WINDOW) -> Column:
    """How many words lie in a window of ``width`` words that occurs at least twice.

    Hashes of the windows are sorted with their positions and equal neighbours mark repeats; the marked positions, sorted again,
    each add the words that the next one does not cover. Most texts repeat no window and are not sorted.
    """
    n = F.size(ws)
    starts = F.when(n >= width, F.sequence(F.lit(0), n - width)).otherwise(F.array().cast("array<int>"))
    hashes = F.transform(starts, lambda i: F.xxhash64(*[F.get(ws, i + k) for k in range(width)]))

    def marked(pairs: Column) -> Column:
        same = F.filter(pairs, lambda p, i: (p["h"] == F.get(pairs, i - 1)["h"]) | (p["h"] == F.get(pairs, i + 1)["h"]))
        return F.sort_array(F.transform(same, lambda p: p["i"]))

    def covered(at: Column) -> Column:
        gaps = F.transform(at, lambda p, i: F.least(F.lit(width), F.coalesce(F.get(at, i + 1) - p, F.lit(width))))
        return F.aggregate(gaps, F.lit(0), lambda a, g: a + g)

    def count(hs: Column) -> Column:
        pairs = F.sort_array(F.transform(hs, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        return F.when(F.size(F.array_distinct(hs)) < F.size(hs), let(let(pairs, marked), covered)).otherwise(F.lit(0)).cast("long")

    return let(hashes, count)


def statistics(text: Column, width: int = WINDOW) -> Column:
    """All statistics of a text as one struct."""
    t = F.coalesce(text, F.lit(""))
    length = lambda x: F.length(x).cast("long")
    lines = F.filter(F.split(t, "\n", -1), lambda x: F.length(F.translate(x, SPACES, "")) > 0)

    def of_words(ws: Column) -> Column:
        return F.struct(
            F.size(ws).cast("long").alias("n_words"),
            repeated_words(ws, width).alias("n_repeat_words"),
            F.size(F.filter(ws, lambda w: F.lower(w).isin(*STOP_WORDS))).cast("long").alias("n_stop_words"),
        )

    def of_lines(ls: Column) -> Column:
        return F.struct(F.size(ls).cast("long").alias("n_lines"), (F.size(ls) - F.size(F.array_distinct(ls))).cast("long").alias("n_dup_lines"))

    return F.struct(
        F.lit(1).cast("long").alias("one"),
        let(words(text), of_words).alias("w"),
        let(lines, of_lines).alias("l"),
        length(F.translate(t, SPACES, "")).alias("word_chars"),
        (length(t) - length(F.translate(t, SYMBOLS, ""))).alias("n_symbols"),
    )


def with_statistics(df: DataFrame, text_col: str = "text", width: int = WINDOW) -> DataFrame:
    """(row, stats): ``row`` holds the columns of ``df``, ``stats`` the statistics of its text."""
    own = F.struct(*[F.col(f"`{c}`") for c in df.columns])
    out = df.select(own.alias("row"), statistics(F.col(f"`{text_col}`"), width).alias("s"))
    return out.select("row", F.struct("s.one", "s.w.*", "s.l.*", "s.word_chars", "s.n_symbols").alias("stats"))


def apply_rules(df: DataFrame, rules: tuple[Rule, ...] = RULES, text_col: str = "text") -> DataFrame:
    """``df`` with (row, stats, base_failed, kept); ``row`` holds the input's own columns."""
    judged = with_statistics(df, text_col)
    flat = judged.select("row", "stats", "stats.*")
    return flat.select("row", "stats", (~compile_rules(BASE_RULES)).alias("base_failed"), (compile_rules(BASE_RULES) & compile_rules(rules)).alias("kept"))


def query(spark, sf_dir: str) -> DataFrame:
    judged = apply_rules(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return judged.select("row.doc_id", *[f"stats.{c}" for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")], "base_failed", "kept")


ORACLE = r"""
WITH base AS (
  SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents
), measured AS (
  SELECT doc_id, t, ws, CAST(len(ws) AS BIGINT) AS n_words,
    CAST(length(regexp_replace(t, '[\x20\x09-\x0D]+', '', 'g')) AS BIGINT) AS word_chars,
    CAST(length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
    list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines
  FROM base
), windows AS (
  SELECT doc_id, i, ws[i : i + 4] AS w FROM (SELECT doc_id, ws, unnest(range(1, CAST(n_words - 3 AS BIGINT))) AS i FROM measured)
), repeated AS (
  SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, w) AS c FROM windows) WHERE c > 1
), covered AS (
  SELECT doc_id, CAST(sum(least(5, coalesce(following - i, 5))) AS BIGINT) AS n_repeat_words
  FROM (SELECT doc_id, i, lead(i) OVER (PARTITION BY doc_id ORDER BY i) AS following FROM repeated) GROUP BY doc_id
), stats AS (
  SELECT m.doc_id, n_words, word_chars, n_symbols, CAST(len(lines) AS BIGINT) AS n_lines,
    CAST(len(lines) - len(list_distinct(lines)) AS BIGINT) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words,
    CAST(len(list_filter(ws, lambda x: lower(x) IN (STOPS))) AS BIGINT) AS n_stop_words
  FROM measured m LEFT JOIN covered c ON m.doc_id = c.doc_id
), judged AS (
  SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM stats
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  NOT base_failed AND 100 * word_chars >= 200 * n_words AND 100 * word_chars <= 1500 * n_words AND 100 * n_symbols <= 30 * n_words
    AND 100 * n_dup_lines <= 40 * n_lines AND (100 * n_stop_words >= n_words OR n_words < 50) AS kept
FROM judged
""".replace("STOPS", ", ".join(f"'{w}'" for w in STOP_WORDS))
