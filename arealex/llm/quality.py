"""Quality rules: a threshold table compiled into one Spark projection.

Everything is a built-in expression; arrays that are used more than once are bound to a lambda variable so that they are computed once for each row.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from arealex.llm.common import SPACES, WORD, let

# Frequent function words of the corpus languages.
STOP_WORDS = (
    "the be to of and that have with for it on as is are was this by not from at in a an or "
    "le la les de des du et un une est que qui dans pour par sur pas au avec "
    "der die das und ist von den mit sich nicht für auf ein eine im zu es dem "
    "el los las del y en una por se no con su para lo como más"
).split()


@dataclass(frozen=True)
class Rule:
    """``measure`` (a key of MEASURES) has to lie between ``least`` and ``most``; None leaves a side open."""

    measure: str
    least: float | None = None
    most: float | None = None


#: The default table. Ratios are to words, lines or characters as the measure's name says.
RULES = (
    Rule("mean_word_chars", 2.0, 15.0),
    Rule("symbols_per_word", None, 0.25),
    Rule("dup_line_share", None, 0.5),
    Rule("stop_word_share", 0.02, None),
    Rule("letter_share", 0.5, None),
    Rule("bullet_line_share", None, 0.9),
    Rule("ellipsis_line_share", None, 0.5),
)


def words_of(text: Column) -> Column:
    return F.filter(F.split(text, SPACES), lambda x: x != "")


def repeat_words(words: Column) -> Column:
    """Words inside a 3-word window that occurs at least twice, the first occurrence included. Windows are compared by a 64-bit hash of their words: they are sorted with their places, and equal neighbours mark their three words."""

    def within(w: Column) -> Column:
        windows = F.transform(F.slice(w, 1, F.greatest(F.size(w) - 2, F.lit(0))), lambda x, i: F.struct(F.xxhash64(x, F.get(w, i + 1), F.get(w, i + 2)).alias("h"), i.alias("i")))
        return let(
            F.sort_array(windows),
            lambda s: F.size(
                F.array_distinct(
                    F.flatten(
                        F.filter(
                            F.zip_with(
                                F.slice(s, 1, F.greatest(F.size(s) - 1, F.lit(0))),
                                F.slice(s, 2, F.greatest(F.size(s) - 1, F.lit(0))),
                                lambda a, b: F.when(a["h"] == b["h"], F.array(a["i"], a["i"] + 1, a["i"] + 2, b["i"], b["i"] + 1, b["i"] + 2)),
                            ),
                            lambda x: x.isNotNull(),
                        )
                    )
                )
            ),
        )

    return let(words, within).cast("long")


def _ratio(a: Column, b: Column) -> Column:
    return F.when(b > 0, a.cast("double") / b).otherwise(F.lit(0.0))


def _base(docs: DataFrame, text: str, extra: list[str]) -> DataFrame:
    """Two projections: arrays once, then counts. Null counts as empty."""
    raw = F.coalesce(F.col(text).cast("string"), F.lit(""))
    words = words_of(raw)
    lines = F.filter(F.split(raw, "\n"), lambda x: x.rlike(WORD))
    measured = F.struct(
        F.length(F.regexp_replace(raw, SPACES, "")).cast("long").alias("word_chars"),
        F.length(F.regexp_replace(raw, "\\P{L}+", "")).cast("long").alias("n_letters"),
        F.length(F.regexp_replace(raw, "[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"),
        let(lines, lambda x: F.struct(F.size(x).cast("long").alias("n_lines"), (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"), F.size(F.filter(x, lambda y: F.ltrim(y).rlike("^[-*•]"))).cast("long").alias("n_bullets"), F.size(F.filter(x, lambda y: F.rtrim(y).endswith("...") | F.rtrim(y).endswith("…"))).cast("long").alias("n_ellipses"))).alias("line"),
        let(words, lambda w: F.struct(F.size(w).cast("long").alias("n_words"), repeat_words(w).alias("n_repeat_words"), F.size(F.filter(w, lambda x: F.lower(x).isin(*STOP_WORDS))).cast("long").alias("n_stop_words"))).alias("word"),
    )
    # One generator row keeps the optimiser from inlining the struct into each use of its fields.
    return docs.select(*extra, F.explode(F.array(measured)).alias("m")).select(*extra, "m.word.n_words", "m.word_chars", "m.n_symbols", "m.line.n_dup_lines", "m.word.n_repeat_words", "m.line.n_lines", "m.line.n_bullets", "m.line.n_ellipses", "m.word.n_stop_words", "m.n_letters")


MEASURES = {
    "n_words": F.col,
    "mean_word_chars": lambda _: _ratio(F.col("word_chars"), F.col("n_words")),
    "symbols_per_word": lambda _: _ratio(F.col("n_symbols"), F.col("n_words")),
    "dup_line_share": lambda _: _ratio(F.col("n_dup_lines"), F.col("n_lines")),
    "stop_word_share": lambda _: _ratio(F.col("n_stop_words"), F.col("n_words")),
    "letter_share": lambda _: _ratio(F.col("n_letters"), F.col("word_chars")),
    "bullet_line_share": lambda _: _ratio(F.col("n_bullets"), F.col("n_lines")),
    "ellipsis_line_share": lambda _: _ratio(F.col("n_ellipses"), F.col("n_lines")),
}


def compiled(rules: tuple[Rule, ...]) -> Column:
    """The names of the rules that fail, as one array expression."""
    checks = []
    for r in rules:
        value = MEASURES[r.measure](r.measure)
        bad = F.lit(False)
        if r.least is not None:
            bad = bad | (value < r.least)
        if r.most is not None:
            bad = bad | (value > r.most)
        checks.append(F.when(bad, F.lit(r.measure)))
    return F.filter(F.array(*checks), lambda x: x.isNotNull()) if checks else F.array().cast("array<string>")


def measure(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text: str = "text", keys: tuple[str, ...] = ("doc_id",), min_words: int = 50, max_repeat_percent: int = 50) -> DataFrame:
    """``keys``, the counts, base_failed, failed_rules and kept, one row for each row of ``docs``.

    A null or empty text has zero counts and fails the base (too few words). Other columns of ``docs`` are ignored, so their names can't clash.
    """
    m = _base(docs, text, list(keys))
    base = (F.col("n_words") < min_words) | (100 * F.col("n_repeat_words") > max_repeat_percent * F.col("n_words"))
    out = m.withColumn("base_failed", base).withColumn("failed_rules", compiled(rules))
    return out.withColumn("kept", ~F.col("base_failed") & (F.size("failed_rules") == 0))


def keep(docs: DataFrame, rules: tuple[Rule, ...] = RULES, **options) -> DataFrame:
    """The rows of ``docs`` that pass, with the columns they had."""
    names = docs.columns
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("row"), F.col("text").alias("text"))
    return measure(packed, rules, keys=("row",), **options).where("kept").select("row.*")
