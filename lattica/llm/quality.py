"""Quality rules: a threshold table compiled into one Spark projection, without user functions.

Every measure is a built-in expression over one row, so the plan is a scan and a projection: no shuffle, no Python.
Defined results: a null or empty text has no words and fails; null in other columns has no effect; repeated rows are
judged one by one; an empty table gives an empty table; other columns pass through, and a column whose name is that
of a measure is replaced.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACES, WORD_BREAK

SYMBOLS = "#*$%&|<>"
WINDOW = 5

# Frequent function words by language.
STOP_WORDS = {
    "en": ["the", "be", "to", "of", "and", "that", "have", "with", "in", "is", "was", "for", "it", "on", "as", "are"],
    "fr": ["le", "la", "les", "de", "des", "et", "en", "un", "une", "que", "est", "dans", "pour", "qui", "au", "du"],
    "de": ["der", "die", "das", "und", "in", "zu", "den", "von", "mit", "ist", "ein", "eine", "nicht", "auf", "im", "sie"],
    "es": ["el", "la", "los", "las", "de", "y", "en", "que", "un", "una", "por", "con", "para", "es", "del", "se"],
}


@dataclass(frozen=True)
class Threshold:
    """A document passes if low <= measure <= high (either may be missing); measures are columns of `measured`."""

    measure: str
    low: float | None = None
    high: float | None = None


BASE = (Threshold("n_words", low=10), Threshold("repeat_ratio", high=0.20))
#: The method's own verdict. Ratios are by word or by line.
PRODUCTION = (
    Threshold("n_words", low=10),
    Threshold("mean_word_chars", low=1.5, high=14.0),
    Threshold("symbol_ratio", high=0.25),
    Threshold("dup_line_ratio", high=0.30),
    Threshold("ellipsis_line_ratio", high=0.50),
    Threshold("bullet_line_ratio", high=0.90),
    Threshold("letter_word_ratio", low=0.60),
    Threshold("stop_word_ratio", low=0.01),
)


def _bound(value: Column, body) -> Column:
    """body(value) with the value computed once, however often the body uses it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _windows(words: Column, n: Column) -> Column:
    """A 64-bit key for each run of five words."""
    starts = F.when(n >= WINDOW, F.sequence(F.lit(0), n - WINDOW)).otherwise(F.array().cast("array<int>"))
    return F.transform(starts, lambda i: F.xxhash64(*[F.get(words, i + k) for k in range(WINDOW)]))


def _covered(keys: Column) -> Column:
    """Words inside windows that occur twice or more: sort (key, place), keep places whose neighbour has the same key, add up the union of [place, place + 5)."""

    def places(s: Column) -> Column:
        return F.array_sort(
            F.filter(
                F.transform(s, lambda x, i: F.when((F.get(s, i - 1)["k"] == x["k"]) | (F.get(s, i + 1)["k"] == x["k"]), x["p"])),
                lambda p: p.isNotNull(),
            )
        )

    def union(p: Column) -> Column:
        return F.aggregate(
            F.transform(p, lambda x, i: F.least(F.lit(WINDOW), F.coalesce(F.get(p, i + 1) - x, F.lit(WINDOW)))),
            F.lit(0).cast("bigint"),
            lambda acc, x: acc + x,
        )

    pairs = F.sort_array(F.transform(keys, lambda k, i: F.struct(k.alias("k"), i.alias("p"))))
    return _bound(pairs, lambda s: _bound(places(s), union))


def _free(docs: DataFrame, stem: str) -> str:
    """A column name that the table doesn't have."""
    while stem.lower() in {c.lower() for c in docs.columns}:
        stem += "_"
    return stem


def measured(docs: DataFrame, text: str = "text") -> DataFrame:
    """Adds the measures to every row.

    n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words (bigint); mean_word_chars, symbol_ratio,
    dup_line_ratio, repeat_ratio, ellipsis_line_ratio, bullet_line_ratio, letter_word_ratio, stop_word_ratio (double).
    A stop word is a run of letters that is one in any of the languages, whatever its case; the ratio is by word.
    Two different windows of one text count as equal if their 64-bit hashes are, which for a text of n words has a
    probability below n * n / 2**65.
    """
    whole = F.coalesce(F.col(text), F.lit(""))
    stop = sorted({w for words in STOP_WORDS.values() for w in words})
    words, kept_lines, keys = (_free(docs, stem) for stem in ("_words", "_lines", "_keys"))
    step = docs.withColumn(words, F.array_remove(F.split(whole, WORD_BREAK), ""))
    step = step.withColumn(kept_lines, F.filter(F.split(whole, "\n"), lambda x: F.length(F.translate(x, SPACES, "")) > 0))
    step = step.withColumn("n_words", F.size(words).cast("bigint"))
    step = step.withColumn(keys, _windows(F.col(words), F.col("n_words").cast("int")))
    n, lines = F.greatest(F.col("n_words"), F.lit(1)), F.greatest(F.size(kept_lines), F.lit(1))
    bare = F.translate(whole, SPACES, "")
    step = step.withColumns(
        {
            "word_chars": F.length(bare).cast("bigint"),
            "n_symbols": (F.length(whole) - F.length(F.translate(whole, SYMBOLS, ""))).cast("bigint"),
            "n_lines": F.size(kept_lines).cast("bigint"),
            "n_dup_lines": (F.size(kept_lines) - F.size(F.array_distinct(kept_lines))).cast("bigint"),
            "n_repeat_words": F.when(F.size(F.array_distinct(keys)) == F.size(keys), F.lit(0).cast("bigint")).otherwise(_covered(F.col(keys))),
            "ellipsis_line_ratio": F.size(F.filter(kept_lines, lambda x: F.rtrim(x).endswith("...") | F.rtrim(x).endswith("…"))) / lines,
            "bullet_line_ratio": F.size(F.filter(kept_lines, lambda x: F.ltrim(x).rlike("^[-*•]"))) / lines,
            "letter_word_ratio": F.regexp_count(whole, F.lit(r"(?<![^\x20\x09-\x0D])[^\x20\x09-\x0D\p{L}]*\p{L}")) / n,
            "stop_word_ratio": F.size(F.filter(F.split(F.lower(whole), r"[^\p{L}]+"), lambda x: x.isin(stop))) / n,
        }
    )
    step = step.withColumns(
        {
            "mean_word_chars": F.col("word_chars") / n,
            "symbol_ratio": F.col("n_symbols") / n,
            "dup_line_ratio": F.col("n_dup_lines") / lines,
            "repeat_ratio": F.col("n_repeat_words") / n,
        }
    )
    return step.drop(words, kept_lines, keys)


def compiled(rules: tuple[Threshold, ...]) -> Column:
    """The threshold table as one boolean expression."""
    out = F.lit(True)
    for rule in rules:
        if rule.low is not None:
            out &= F.col(rule.measure) >= F.lit(rule.low)
        if rule.high is not None:
            out &= F.col(rule.measure) <= F.lit(rule.high)
    return out


def judged(docs: DataFrame, rules: tuple[Threshold, ...] = PRODUCTION, text: str = "text") -> DataFrame:
    """Adds the measures, base_failed and kept (false where the base fails, else the table's verdict)."""
    out = measured(docs, text).withColumn("base_failed", ~compiled(BASE))
    return out.withColumn("kept", ~F.col("base_failed") & compiled(rules))


def kept(docs: DataFrame, rules: tuple[Threshold, ...] = PRODUCTION, text: str = "text") -> DataFrame:
    """The documents that stay, with their own columns only (whatever their names)."""
    whole = docs.select(F.col(text).alias("text"), F.struct(*[docs[c].alias(f"c{i}") for i, c in enumerate(docs.columns)]).alias("_row"))
    # a filter over the row's number stays above the projection, so that no measure is computed again inside it
    return judged(whole, rules).withColumn("_nth", F.monotonically_increasing_id()).where(F.col("kept") & (F.col("_nth") >= 0)).select("_row.*").toDF(*docs.columns)
