"""Quality rules: a threshold table compiled into one Spark projection of built-in functions.

A rule bounds the quotient of two measures of a text, in thousandths, so that all arithmetic is on integers. The base
rules (too few words; too many words inside repeated three-word windows) are applied first and named apart.

Defined cases: null or blank text has no words and fails the base rules; texts of any length are measured whole; a quotient
with denominator 0 passes its rule, and one equal to a bound does too; null and repeated ids are rows like others; repeated rows
are judged alike; empty tables give empty results; other columns are kept by :func:`filter_quality` and ignored by
:func:`judge`.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import BLANKS, NOT_BLANK, let

#: Frequent function words of English, German, French and Spanish.
STOP_WORDS = (
    "the of and to in is that it for on with as was are be by this der die und das den von mit ist nicht ein eine zu auf "
    "le la les de et des un une que est pour dans du au en il elle par el los las y con del se no su al lo esta como"
).split()


@dataclass(frozen=True)
class Rule:
    """``low <= 1000 * part / whole <= high``; a bound of None is open."""

    name: str
    part: str
    whole: str
    low: int | None = None
    high: int | None = None


#: Production thresholds, in thousandths.
RULES = (
    Rule("symbol_ratio", "n_symbols", "n_words", high=100),
    Rule("duplicate_line_ratio", "n_dup_lines", "n_lines", high=400),
    Rule("mean_word_length", "word_chars", "n_words", low=2_000, high=12_000),
    Rule("stop_word_ratio", "n_stop_words", "n_words", low=20),
    Rule("letter_ratio", "n_letters", "word_chars", low=550),
    Rule("capital_ratio", "n_capitals", "word_chars", high=400),
    Rule("exclamation_ratio", "n_exclamations", "n_words", high=500),
)
MIN_WORDS, MAX_REPEAT_PERCENT = 50, 50


def _repeated_words(words: Column) -> Column:
    """Words inside three-word windows that occur twice or more: sort (window hash, place), keep those with an equal
    neighbour, and sum the lengths of the union of their three-word reaches."""

    def windows(w):
        at = F.when(F.size(w) >= 3, F.sequence(F.lit(0), F.size(w) - 3)).otherwise(F.array().cast("array<int>"))
        return F.transform(at, lambda i: F.struct(F.xxhash64(w[i], F.lit("\n"), w[i + 1], F.lit("\n"), w[i + 2]).alias("h"), i.alias("i")))

    def starts(s):
        same = lambda x, k: F.coalesce(F.get(s, k)["h"] == x["h"], F.lit(False))
        return F.sort_array(F.transform(F.filter(s, lambda x, k: same(x, k - 1) | same(x, k + 1)), lambda x: x["i"]))

    def reach(st):
        zero = F.struct(F.lit(0).alias("n"), F.lit(-3).alias("last"))
        step = lambda a, i: F.struct((a["n"] + F.least(F.lit(3), i - a["last"])).alias("n"), i.alias("last"))
        return F.aggregate(st, zero, step, lambda a: a["n"])

    return let(words, lambda w: let(F.sort_array(windows(w)), lambda s: let(starts(s), reach)))


def measured(text: Column) -> Column:
    """struct of the measures that rules can name; words and lines are split once, however many measures use them."""
    t = F.coalesce(text, F.lit(""))
    long = lambda c: c.cast("long")
    words = let(
        F.array_remove(F.split(t, BLANKS + "+"), ""),
        lambda w: F.struct(
            F.size(w).alias("n"),
            F.length(F.array_join(w, "")).alias("chars"),
            F.size(F.filter(w, lambda x: F.lower(x).isin(STOP_WORDS))).alias("stops"),
            F.size(F.filter(w, lambda x: x.contains("!!"))).alias("bangs"),
            _repeated_words(w).alias("again"),
        ),
    )
    lines = let(F.filter(F.split(t, "\n"), lambda x: x.rlike(NOT_BLANK)), lambda x: F.struct(F.size(x).alias("n"), (F.size(x) - F.size(F.array_distinct(x))).alias("dup")))
    count = lambda pattern: F.regexp_count(t, F.lit(pattern))
    parts = F.struct(words.alias("w"), lines.alias("l"), count("[#*$%&|<>]").alias("symbols"), count(r"\p{L}").alias("letters"), count("[A-Z]").alias("capitals"))
    return let(
        parts,
        lambda m: F.struct(
            long(m["w"]["n"]).alias("n_words"),
            long(m["w"]["chars"]).alias("word_chars"),
            long(m["symbols"]).alias("n_symbols"),
            long(m["l"]["dup"]).alias("n_dup_lines"),
            long(m["w"]["again"]).alias("n_repeat_words"),
            long(m["l"]["n"]).alias("n_lines"),
            long(m["w"]["stops"]).alias("n_stop_words"),
            long(m["w"]["bangs"]).alias("n_exclamations"),
            long(m["letters"]).alias("n_letters"),
            long(m["capitals"]).alias("n_capitals"),
        ),
    )


#: The measures, in the order in which :func:`judge` returns them.
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_stop_words", "n_exclamations", "n_letters", "n_capitals")


def base_failed(m: Column) -> Column:
    return (m["n_words"] < MIN_WORDS) | (100 * m["n_repeat_words"] > MAX_REPEAT_PERCENT * m["n_words"])


def passed(rule: Rule, m: Column) -> Column:
    part, whole = 1000 * m[rule.part], m[rule.whole]
    ok = F.lit(True)
    if rule.low is not None:
        ok = ok & (part >= rule.low * whole)
    if rule.high is not None:
        ok = ok & (part <= rule.high * whole)
    return ok | (whole == 0)


def judge(docs: DataFrame, rules: tuple[Rule, ...] = RULES, *keep: str) -> DataFrame:
    """Measures, ``base_failed``, the names of the failed rules and the verdict ``kept`` for each document."""
    m = F.col("_m")
    out = docs.select("doc_id", *keep, measured(F.col("text")).alias("_m"))
    failed = F.array_compact(F.array(*(F.when(~passed(r, m), F.lit(r.name)) for r in rules)))
    out = out.select("doc_id", *keep, *(m[c].alias(c) for c in MEASURES), base_failed(m).alias("base_failed"), failed.alias("failed_rules"))
    return out.withColumn("kept", ~F.col("base_failed") & (F.size("failed_rules") == 0))


def filter_quality(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """The documents that pass, with the columns they came with.

    The verdict is one expression over one evaluation of the measures: a filter on columns of :func:`judge` would have Catalyst
    put the measures into the condition once for every use."""

    def verdict(m: Column) -> Column:
        ok = ~base_failed(m)
        for r in rules:
            ok = ok & passed(r, m)
        return ok

    return docs.where(let(measured(F.col("text")), verdict))
