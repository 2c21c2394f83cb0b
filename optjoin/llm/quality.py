"""Quality rules: a table of thresholds compiled into one projection of built-in functions.

Every measure is a column expression on one row, so the plan is a scan and projections: no shuffle,
no user function. `let` binds a value to a lambda variable, since a column used inside a lambda would
be evaluated again for every element.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BLANKS = r"[\x20\x09-\x0D]"
SYMBOLS = r"[#*$%&|<>]"
WINDOW = 8
#: Frequent function words of English, French, German and Spanish (fixed values).
STOP_WORDS = (
    "the of and to in is was that for it with as on be at by this are or from he she they a an "
    "le la les de des et en un une du que qui dans pour est pas sur au ne se ce il elle ou "
    "der die das und ist nicht ein eine zu den von mit für auf sich dem im es als auch "
    "el los las y que por una con para no su al lo como más pero sus o si"
).split()


@dataclass(frozen=True)
class Rule:
    """Keeps a text while low <= numerator / denominator <= high; a zero denominator passes."""

    name: str
    numerator: str
    denominator: str
    low: float
    high: float


#: Fixed values, after public heuristics for web text; any table of the same form can be given.
RULES = (
    Rule("mean_word_length", "word_chars", "n_words", 2.0, 15.0),
    Rule("symbols_per_word", "n_symbols", "n_words", 0.0, 0.10),
    Rule("duplicate_lines", "n_dup_lines", "n_lines", 0.0, 0.50),
    Rule("stop_words", "n_stop_words", "n_words", 0.02, 1.0),
    Rule("words_with_letters", "n_letter_words", "n_words", 0.70, 1.0),
    Rule("ellipsis_lines", "n_ellipsis_lines", "n_lines", 0.0, 0.50),
    Rule("bullet_lines", "n_bullet_lines", "n_lines", 0.0, 0.90),
)


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    return F.transform(F.array(value), body)[0]


def _count(array: Column, test: Callable[[Column], Column]) -> Column:
    return F.size(F.filter(array, test)).cast("long")


def repeated_window_words(words: Column, window: int = WINDOW) -> Column:
    """Words in windows of consecutive words found twice or more, the first included.

    The window is a power of two. Windows are compared by 64-bit hashes inside one text. Texts without a repeat, nearly all, end
    at a hash-set comparison; for the others the hashes are sorted with their places.
    """
    none = F.array().cast("array<bigint>")

    def joined(step: int) -> Callable[[Column], Column]:
        return lambda h: F.transform(h, lambda x, i: F.xxhash64(x, F.get(h, i + step)))

    def windows(h: Column) -> Column:
        return F.when(F.size(h) < window, none).otherwise(F.slice(h, 1, F.size(h) - (window - 1)))

    def places(s: Column) -> Column:
        near = lambda e, j: (e["h"] == F.get(s, j - 1)["h"]) | (e["h"] == F.get(s, j + 1)["h"])
        return F.sort_array(F.filter(F.transform(s, lambda e, j: F.when(near(e, j), e["i"])), lambda x: x.isNotNull()))

    def total(p: Column) -> Column:
        gaps = F.transform(p, lambda x, j: F.least(F.lit(window), F.coalesce(F.get(p, j + 1) - x, F.lit(window))))
        return F.aggregate(gaps, F.lit(0).cast("long"), lambda a, x: a + x)

    def heavy(w: Column) -> Column:
        placed = F.sort_array(F.transform(w, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        return let(let(placed, places), total)

    hashes, step = words, 1
    while step < window:  # hashes of 2, 4 and 8 words
        hashes, step = let(hashes, joined(step)), 2 * step
    return let(let(hashes, windows), lambda w: F.when(F.size(F.array_distinct(w)) == F.size(w), F.lit(0).cast("long")).otherwise(heavy(w)))


def measures(docs: DataFrame, text_col: str = "text", keep: Iterable[str] = ()) -> DataFrame:
    """One row per row: the kept columns and every measure. A null text has no words and no lines."""
    keep = list(keep)
    text = F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit(""))
    base = docs.select(*(F.col(f"`{c}`").alias(f"k{i}") for i, c in enumerate(keep)), text.alias("t"))
    words = F.filter(F.split("t", BLANKS + "+"), lambda w: w != "")
    lines = F.filter(F.split("t", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    parts = base.withColumns({"w": words, "l": lines})
    stops = sorted({*STOP_WORDS})
    w, l = F.col("w"), F.col("l")  # noqa: E741
    return parts.select(
        *(F.col(f"k{i}").alias(c) for i, c in enumerate(keep)),
        F.size(w).cast("long").alias("n_words"),
        F.length(F.array_join(w, "")).cast("long").alias("word_chars"),
        F.regexp_count("t", F.lit(SYMBOLS)).cast("long").alias("n_symbols"),
        (F.size(l) - F.size(F.array_distinct(l))).cast("long").alias("n_dup_lines"),
        repeated_window_words(w).alias("n_repeat_words"),
        F.size(l).cast("long").alias("n_lines"),
        _count(w, lambda x: x.isin(stops)).alias("n_stop_words"),
        _count(w, lambda x: x.rlike(r"\p{L}")).alias("n_letter_words"),
        _count(l, lambda x: F.endswith(x, F.lit("...")) | F.endswith(x, F.lit("…"))).alias("n_ellipsis_lines"),
        _count(l, lambda x: F.startswith(x, F.lit("- ")) | F.startswith(x, F.lit("* ")) | F.startswith(x, F.lit("• "))).alias("n_bullet_lines"),
    )


def verdict(rules: Iterable[Rule] = RULES) -> Column:
    """The table as one condition on the measures."""
    passed = F.lit(True)
    for r in rules:
        n, d = F.col(r.numerator), F.col(r.denominator)
        passed = passed & ((d == 0) | ((n >= F.lit(r.low) * d) & (n <= F.lit(r.high) * d)))
    return passed


def quality(docs: DataFrame, text_col: str = "text", keep: Iterable[str] = ("doc_id",), rules: Iterable[Rule] = RULES) -> DataFrame:
    """Measures, base_failed (under 20 words, or over 30 in 100 words in repeated windows) and kept.

    Each row is judged alone: repeated rows give repeated results, an empty table none; a null or
    blank text has no words and fails. Columns that aren't named in `keep` are ignored.
    """
    out = measures(docs, text_col, keep)
    failed = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    return out.withColumn("base_failed", failed).withColumn("kept", ~failed & verdict(rules))
