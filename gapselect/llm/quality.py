"""Quality rules: one threshold table compiled into one Spark projection.

Every measure is an expression of built-in functions over the whole text; every rule is
a row ``(measure, lowest, highest)`` of a table; the verdict is the conjunction of all
rows. No user function runs.

Defined results: a null or blank text has no words, all counts are 0 and it fails the
base rule; other columns, whatever their names, pass through untouched in
``filter_quality``; repeated rows are judged each; an empty table gives no rows; very long
texts are measured whole, in one row's memory.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gapselect.llm.common import SPACES, as_text

WINDOW = 8

#: Frequent function words of the corpus languages: fixed values.
STOP_WORDS = (
    "the a an and of to in is was for with that on as by it be are this from at or he "
    "der die das und ist nicht mit für ein eine auf von zu im den dem sich "
    "le la les de des du un une et est que pour dans qui au pas en "
    "el los las y del por para con una se no su"
).split()


@dataclass(frozen=True)
class Rule:
    """``lowest <= measure <= highest``; None leaves a side open."""

    measure: str
    lowest: float | None = None
    highest: float | None = None


#: Thresholds of the published heuristics for web text, loosened where the corpus has
#: short paragraphs: fixed values.
RULES = (
    Rule("mean_word_length", 2.0, 14.0),
    Rule("symbols_per_word", None, 0.10),
    Rule("dup_line_ratio", None, 0.35),
    Rule("stop_word_ratio", 0.02, None),
    Rule("longest_word", None, 1000),
)


def _let(value: Column, body) -> Column:
    """``body(value)`` with ``value`` evaluated once."""
    return F.get(F.transform(F.array(value), body), 0)


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(text, SPACES), "")


def repeated_words(words: Column, width: int = WINDOW) -> Column:
    """Words covered by windows of ``width`` words that occur twice or more in the text.

    Windows are compared by 64-bit hashes chained from word hashes. Only texts where some
    window repeats pay for finding the places: (hash, place) pairs are sorted, equal
    neighbours kept, and the union of their spans measured from gaps between places.
    """

    def covered(pairs: Column) -> Column:
        def same(j: Column) -> Column:
            return F.coalesce(F.get(pairs, j)["h"] == F.get(pairs, j + 1)["h"], F.lit(False))

        again = F.filter(pairs, lambda _, j: F.when(j > 0, same(j - 1)).otherwise(F.lit(False)) | same(j))
        return _let(
            F.sort_array(F.transform(again, lambda s: s["i"])),
            lambda at: F.aggregate(
                F.transform(at, lambda p, k: F.least(F.lit(width), F.coalesce(F.get(at, k + 1) - p, F.lit(width)))),
                F.lit(0),
                lambda a, b: a + b,
            ),
        )

    def hashed(h: Column) -> Column:
        windows = F.transform(F.sequence(F.lit(0), F.size(h) - width), lambda i: F.xxhash64(*[F.get(h, i + k) for k in range(width)]))
        return _let(
            windows,
            lambda w: F.when(F.size(F.array_distinct(w)) == F.size(w), F.lit(0)).otherwise(
                _let(F.sort_array(F.transform(w, lambda x, i: F.struct(x.alias("h"), i.alias("i")))), covered)
            ),
        )

    return F.when(F.size(words) < width + 1, F.lit(0)).otherwise(_let(F.transform(words, lambda w: F.xxhash64(w)), hashed)).cast("long")


def counts(words: Column, text: Column) -> dict[str, Column]:
    """What the ratios are made of, from the words of a text and the text."""
    lines = F.filter(F.split(text, "\n"), lambda x: F.length(F.translate(x, " \t\n\x0b\x0c\r", "")) > 0)
    joined = F.array_join(words, "")
    return {
        "n_words": F.size(words).cast("long"),
        "word_chars": F.length(joined).cast("long"),
        "n_symbols": (F.length(joined) - F.length(F.translate(joined, "#*$%&|<>", ""))).cast("long"),
        "lines": _let(lines, lambda x: F.struct(F.size(x).cast("long").alias("n"), F.size(F.array_distinct(x)).cast("long").alias("d"))),
        "n_repeat_words": repeated_words(words),
        "n_stop_words": F.size(F.filter(words, lambda w: F.lower(w).isin(STOP_WORDS))).cast("long"),
        "longest_word": F.coalesce(F.array_max(F.transform(words, lambda w: F.length(w))), F.lit(0)).cast("long"),
    }


def ratios(of) -> dict[str, Column]:
    """Measures of the rules; ``of(name)`` gives a count."""

    def over(a: Column, b: Column) -> Column:
        return F.when(b > 0, a / b).otherwise(F.lit(0.0))

    return {
        "mean_word_length": over(of("word_chars"), of("n_words")),
        "symbols_per_word": over(of("n_symbols"), of("n_words")),
        "dup_line_ratio": over(of("n_dup_lines"), of("n_lines")),
        "stop_word_ratio": over(of("n_stop_words"), of("n_words")),
        "longest_word": of("longest_word"),
    }


def verdict(measures: dict[str, Column], rules: tuple[Rule, ...] = RULES) -> Column:
    """All rows of the table as one boolean expression."""
    out = F.lit(True)
    for r in rules:
        if r.lowest is not None:
            out &= measures[r.measure] >= F.lit(r.lowest)
        if r.highest is not None:
            out &= measures[r.measure] <= F.lit(r.highest)
    return out


def base_failed(of) -> Column:
    return (of("n_words") < 20) | (100 * of("n_repeat_words") > 30 * of("n_words"))


def measured(text: Column) -> Column:
    """All counts of a text as one struct; words are taken once."""
    return _let(words_of(text), lambda w: F.struct(*[c.alias(k) for k, c in counts(w, text).items()]))


def _field(s: Column):
    """Counts of the struct by name; the two line counts are one field of it."""

    def of(name: str) -> Column:
        if name == "n_lines":
            return s["lines"]["n"]
        return s["lines"]["n"] - s["lines"]["d"] if name == "n_dup_lines" else s[name]

    return of


def quality_rules(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """id, all counts and measures, base_failed and kept."""
    base = docs.select(F.col(id_col).alias("__id"), measured(as_text(text_col)).alias("__m"))
    of = _field(F.col("__m"))
    names = ["n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words", "n_stop_words"]
    parts = ratios(of)
    return base.select(
        F.col("__id").alias(id_col), *[of(n).alias(n) for n in names], *[c.alias(k) for k, c in parts.items()],
        base_failed(of).alias("base_failed"), (~base_failed(of) & verdict(parts, rules)).alias("kept"),
    )


def filter_quality(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text_col: str = "text") -> DataFrame:
    """``docs`` without the rejected rows: one filter, no join, no shuffle."""

    def keep(m: Column) -> Column:
        of = _field(m)
        return ~base_failed(of) & verdict(ratios(of), rules)

    return docs.filter(_let(measured(as_text(text_col)), keep))
