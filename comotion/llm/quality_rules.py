"""Rule filter (operator 9): one threshold table, compiled into one native projection.

Every rule is a row ``(measure, low, high)`` of ``RULES``; ``verdict`` turns the rows into a single boolean Column.
Only built-in Spark functions run.

Defined results: null text counts as a text without words, so it has zero measures, fails the base rule and goes; an
empty text likewise. Rows with equal content get equal results; other columns of the input pass through untouched.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from comotion.llm.common import WORD_GAP, doc_text

# Frequent function words of the four languages.
STOP_WORDS = (
    "the of and to in a is that it was for on are with as at be this by from or an have not he "
    "der die und das von zu mit den ist im des ein eine auf für nicht sich als auch dem "
    "le la les de des et un une est en que qui pour dans par sur du pas au ou avec "
    "el los las y del se por con una su para al es lo como más o pero sus"
).split()


@dataclass(frozen=True)
class Rule:
    """A document passes when ``low <= measure <= high``."""

    measure: str
    low: float
    high: float


#: The threshold table. Ratios are per word, per character or per line as the measure's name says.
RULES = (
    Rule("n_words", 10, float("inf")),
    Rule("mean_word_chars", 2.0, 15.0),
    Rule("symbols_per_word", 0.0, 0.3),
    Rule("capitals_per_char", 0.0, 0.5),
    Rule("stop_words_per_word", 0.01, 1.0),
    Rule("dup_lines_per_line", 0.0, 0.5),
)


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """Binds ``value`` once, so that a lambda over an array can look at its neighbours without recomputing it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _windows(words: Column, make: Callable[[Column], Column]) -> Column:
    n = F.size(words)
    return F.when(n >= 5, F.transform(F.sequence(F.lit(0), n - 5), lambda i: make(i)))


def _repeat_words(words: Column) -> Column:
    """Words covered by 5-word windows that the text holds twice or more.

    Window hashes that are all distinct prove that no window repeats; only other texts sort their real windows.
    """
    at = lambda i: [F.get(words, i + k) for k in range(5)]
    hashes = _windows(words, lambda i: F.xxhash64(*at(i)))
    real = _windows(words, lambda i: F.struct(F.concat_ws(" ", *at(i)).alias("w"), i.alias("i")))

    def covered(spots: Column) -> Column:
        gaps = F.transform(spots, lambda p, j: F.least(F.lit(5), F.coalesce(F.get(spots, j + 1), p + 5) - p))
        return F.aggregate(gaps, F.lit(0).cast("long"), lambda a, g: a + g)

    def twins(s: Column) -> Column:
        same = lambda x, k: F.coalesce(x["w"] == F.get(s, k)["w"], F.lit(False))
        marked = F.filter(s, lambda x, j: same(x, j - 1) | same(x, j + 1))
        return let(F.sort_array(F.transform(marked, lambda x: x["i"])), covered)

    slow = let(F.sort_array(real), twins)
    return let(hashes, lambda h: F.when(F.size(F.array_distinct(h)) < F.size(h), slow).otherwise(F.lit(0).cast("long")))


def measures(docs: DataFrame) -> DataFrame:
    """doc_id, the contract's base counts, and the measures that the threshold table names."""
    return _measured(doc_text(docs), "doc_id")


def _measured(docs: DataFrame, carry: str) -> DataFrame:
    gap = r"[^\x20\x09-\x0D]"
    text = F.coalesce("text", F.lit(""))
    base = docs.select(
        carry,
        text.alias("_t"),
        F.array_remove(F.split(text, WORD_GAP), "").alias("_w"),
        F.filter(F.split(text, "\n"), lambda x: x.rlike(gap)).alias("_l"),
    )
    stops = sorted({form for w in STOP_WORDS for form in (w, w.capitalize())})
    counts = F.struct(
        F.size("_w").cast("long").alias("n_words"),
        F.length(F.translate("_t", " \t\n\x0b\x0c\r", "")).cast("long").alias("word_chars"),
        (F.length("_t") - F.length(F.translate("_t", "#*$%&|<>", ""))).cast("long").alias("n_symbols"),
        (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"),
        F.coalesce(_repeat_words(F.col("_w")), F.lit(0).cast("long")).alias("n_repeat_words"),
        (F.length("_t") - F.length(F.regexp_replace("_t", r"\p{Lu}", ""))).cast("long").alias("_capitals"),
        F.size("_l").cast("long").alias("_lines"),
        F.size(F.filter("_w", lambda x: x.isin(stops))).cast("long").alias("_stops"),
    )
    # one struct a row, built once: no filter above a generator is pushed below it, which would count again for each rule
    counted = base.select(carry, F.explode(F.array(counts)).alias("_m")).select(carry, "_m.*")
    per = lambda a, b: F.coalesce(F.try_divide(F.col(a).cast("double"), F.col(b)), F.lit(0.0))
    return counted.select(
        *counted.columns[:6],
        per("word_chars", "n_words").alias("mean_word_chars"),
        per("n_symbols", "n_words").alias("symbols_per_word"),
        per("_capitals", "word_chars").alias("capitals_per_char"),
        per("_stops", "n_words").alias("stop_words_per_word"),
        per("n_dup_lines", "_lines").alias("dup_lines_per_line"),
    )


def base_failed() -> Column:
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


def verdict(rules: tuple[Rule, ...] = RULES) -> Column:
    """The whole table as one predicate."""
    passed = F.lit(True)
    for rule in rules:
        value = F.col(rule.measure).cast("double")
        if rule.low > float("-inf"):
            passed = passed & (value >= rule.low)
        if rule.high < float("inf"):
            passed = passed & (value <= rule.high)
    return passed


def judge(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """doc_id, counts, measures, base_failed and kept for every row of ``docs``."""
    return _measured(doc_text(docs), "doc_id").select("*", base_failed().alias("base_failed"), (~base_failed() & verdict(rules)).alias("kept"))


def keep(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """The rows of ``docs``, all columns, that pass; a narrow native pass."""
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_row"), F.col("text").cast("string").alias("text"))
    return _measured(rows, "_row").filter(~base_failed() & verdict(rules)).select("_row.*")
