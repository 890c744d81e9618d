"""Quality rules: a threshold table compiled into one projection.

Native: every measure and verdict is a column expression; no user function runs.

Defined cases: a null or blank text has no words and fails the base; ties and
repeated rows are judged row by row; an empty table gives no rows; other columns
of the input are ignored by the query and kept by ``apply_rules``.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BLANKS = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"

# Frequent function words of the corpus languages.
STOP_WORDS = {
    "en": "the of and to in is that for it with as on be by at are this from or an was which a",
    "fr": "de la le et les des une que en du dans pour est un sur au par il qui pas ce",
    "de": "der die und das von den des mit ist zu auf eine für nicht dem im sich als ein auch",
    "es": "de la que el y los del las un por con una su para es no al lo se en",
}


@dataclass(frozen=True)
class Rule:
    """``low <= measure <= high``; a missing bound is open."""

    measure: str
    low: float | None = None
    high: float | None = None


RULES = (
    Rule("n_words", 50, 10_000_000),
    Rule("mean_word_chars", 2.0, 14.0),
    Rule("symbols_per_word", None, 0.1),
    Rule("marks_per_word", None, 0.25),
    Rule("upper_share", None, 0.5),
    Rule("distinct_stop_words", 2, None),
    Rule("duplicate_line_share", None, 0.5),
    Rule("bullet_line_share", None, 0.9),
    Rule("ellipsis_line_share", None, 0.3),
)


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """Bind ``value`` once and use it many times inside one expression."""
    return F.element_at(F.transform(F.array(value), body), 1)


def words_of(text: Column) -> Column:
    """Array of maximal runs free of blanks; none for null."""
    bare = F.btrim(F.coalesce(text, F.lit("")), F.lit(BLANKS))
    return F.when(bare == "", F.array().cast("array<string>")).otherwise(
        F.split(bare, "[\\x20\\x09-\\x0D]+")
    )


def repeated_words(words: Column) -> Column:
    """Words inside 3-word windows that occur twice or more in the text.

    Windows are sorted as text with their position appended, so equal windows are
    neighbours; the positions of equal neighbours are then merged into covered words.
    """
    width = 10
    first = F.lit(10 ** (width - 1)).cast("long")

    def count(w: Column) -> Column:
        n = F.greatest(F.size(w) - 2, F.lit(0))
        two = F.zip_with(
            F.slice(w, F.lit(1), n),
            F.slice(w, F.lit(2), n),
            lambda a, b: F.concat(a, F.lit(" "), b, F.lit(" ")),
        )
        three = F.zip_with(
            two, F.slice(w, F.lit(3), n), lambda a, b: F.concat(a, b, F.lit(" "))
        )
        keyed = F.sort_array(
            F.transform(three, lambda x, i: F.concat(x, (i + first).cast("string")))
        )

        def pairs(s: Column) -> Column:
            def both(a: Column, b: Column) -> Column:
                window = F.substring(a, F.lit(1), F.length(a) - width)
                at = lambda x: F.right(x, F.lit(width)).cast("long") - first + 1
                return F.when(F.startswith(b, window), F.array(at(a), at(b)))

            n = F.greatest(F.size(s) - 1, F.lit(0))
            return F.filter(
                F.zip_with(F.slice(s, F.lit(1), n), F.slice(s, F.lit(2), n), both),
                lambda x: x.isNotNull(),
            )

        hit = F.sort_array(F.array_distinct(F.flatten(let(keyed, pairs))))
        fold = F.aggregate(
            hit,
            F.struct(F.lit(-2).cast("long").alias("last"), F.lit(0).cast("long").alias("n")),
            lambda acc, p: F.struct(
                p.alias("last"), (acc["n"] + F.least(F.lit(3).cast("long"), p - acc["last"])).alias("n")
            ),
            lambda acc: acc["n"],
        )
        return F.when(F.size(w) < 3, F.lit(0)).otherwise(fold)

    return let(words, count)


def measures(text: Column) -> dict[str, Column]:
    """Every measure of the table, in an order where later ones use earlier names."""
    t = F.coalesce(text, F.lit(""))
    has_word = lambda x: x.rlike("[^\\x20\\x09-\\x0D]")
    only = lambda kept: F.length(F.regexp_replace(t, f"[^{kept}]+", ""))
    lines = F.filter(F.split(t, "\n"), has_word)
    stop = sorted({w for ws in STOP_WORDS.values() for w in ws.split()})
    words = F.col("_words")
    per = lambda a, b: F.when(b > 0, a / b).otherwise(F.lit(0.0))
    share = lambda test: per(
        F.size(F.filter(F.col("_lines"), test)).cast("double"), F.col("n_lines")
    )
    return {
        "_words": words_of(text),
        "_lines": lines,
        "n_words": F.size(words).cast("long"),
        "word_chars": F.length(F.array_join(words, "")).cast("long"),
        "n_symbols": only(SYMBOLS).cast("long"),
        "n_lines": F.size("_lines").cast("long"),
        "n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"),
        "n_repeat_words": repeated_words(words).cast("long"),
        "mean_word_chars": per(F.col("word_chars").cast("double"), F.col("n_words")),
        "symbols_per_word": per(F.col("n_symbols").cast("double"), F.col("n_words")),
        "marks_per_word": per(
            only("!?").cast("double"), F.col("n_words")
        ),
        "upper_share": per(
            only("\\p{Lu}").cast("double"),
            only("\\p{L}"),
        ),
        "distinct_stop_words": F.size(
            F.array_intersect(F.array(*[F.lit(w) for w in stop]), F.transform(words, F.lower))
        ).cast("long"),
        "duplicate_line_share": per(F.col("n_dup_lines").cast("double"), F.col("n_lines")),
        "bullet_line_share": share(lambda x: F.btrim(x).rlike("^[-*•]")),
        "ellipsis_line_share": share(lambda x: F.btrim(x).rlike("(\\.\\.\\.|…)$")),
    }


def compile_rules(rules: tuple[Rule, ...]) -> Column:
    """One boolean column: every rule of the table holds."""
    verdict = F.lit(True)
    for r in rules:
        m = F.col(r.measure)
        if r.low is not None:
            verdict = verdict & (m >= r.low)
        if r.high is not None:
            verdict = verdict & (m <= r.high)
    return verdict


def judge(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text: str = "text") -> DataFrame:
    """The id, every measure, ``base_failed`` and ``kept``."""
    out = docs.select(F.col("doc_id"), F.col(text).alias("_text"))
    for name, m in measures(F.col("_text")).items():
        out = out.withColumn(name, m)
    out = out.withColumn(
        "base_failed",
        (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words")),
    ).withColumn("kept", ~F.col("base_failed") & compile_rules(rules))
    return out.drop("_text", "_words", "_lines")


def apply_rules(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """The rows that pass, with their own columns."""
    names, held = docs.columns, docs.withColumn("_text", F.col("text"))
    clash = {c: f"_in_{i}" for i, c in enumerate(names)}
    held = held.select(*[F.col(c).alias(clash[c]) for c in names], "_text")
    for name, m in measures(F.col("_text")).items():
        held = held.withColumn(name, m)
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return held.filter(~failed & compile_rules(rules)).select(
        *[F.col(clash[c]).alias(c) for c in names]
    )


def op1_quality_rules(spark, sf_dir: str) -> DataFrame:
    """Verdict on every document."""
    return judge(spark.read.parquet(f"{sf_dir}/documents.parquet"))
