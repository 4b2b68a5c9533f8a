"""Quality rules: a table of thresholds compiled into one Spark projection, without user functions.

Each document's measures are computed inside its own row (no shuffle): word and line arrays are bound once,
repeats are found by sorting the row's own hashed word windows, and the rules are plain comparisons. A document
that fails a rule is rejected. Null texts count as empty and fail the length rule; an empty table gives an empty
result; repeated rows are each judged alike; columns that aren't named are carried or left, never looked at.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from overlapsolve.llm.common import SPACES, id_and_text

#: The symbols that the base counts.
SYMBOL_CLASS = r"[#*$%&|<>]"

#: Frequent function words of the languages that the corpus holds.
STOP_WORDS = (
    "the be to of and that have with in is it for as was on are by this he an or from "
    "le la les de des et un une que qui est en du pour dans par sur pas au il elle ou "
    "el los las y se por con no su para lo como más del al es una "
    "der die das und ist zu den von nicht mit ein eine auf für im dem sich auch als er sie"
).split()

#: Each stop word as it stands within and at the start of a sentence.
STOP_FORMS = sorted({w for x in STOP_WORDS for w in (x, x.capitalize())})


@dataclass(frozen=True)
class Rule:
    """A document passes if low <= measure <= high; a bound of None doesn't bind."""

    measure: str
    low: float | None = None
    high: float | None = None


BASE_RULES = (Rule("n_words", low=50), Rule("repeat_percent", high=50))

RULES = (
    Rule("mean_word_chars", low=2, high=14),
    Rule("symbols_per_word", high=0.25),
    Rule("stop_words", low=2),
    Rule("dup_line_ratio", high=0.5),
    Rule("upper_ratio", high=0.45),
)


def _covered(flags: Column) -> Column:
    """How many positions the windows of three that begin at the given sorted positions cover."""
    steps = F.transform(flags, lambda p, k: F.least(F.lit(3), F.coalesce(F.get(flags, k + 1) - p, F.lit(3))))
    return F.when(F.size(flags) == 0, F.lit(0).cast("long")).otherwise(F.aggregate(steps, F.lit(0).cast("long"), lambda a, x: a + x))


def _measured(source: DataFrame) -> DataFrame:
    """From (row, text): row and all measures, by narrow projections over the whole texts.

    Arrays that later steps use more than once are columns of their own, so they are computed once. Windows are sorted as
    longs that hold a hash in the high bits and the position in the low ones; neighbours that lie close are compared word
    by word.
    """
    t, words, low, ordered = F.col("text"), F.col("words"), F.col("low"), F.col("ordered")
    spaced = t
    for c in SPACES[1:]:
        spaced = F.replace(spaced, F.lit(c), F.lit(" "))
    ratio = lambda a, b: F.when(b > 0, a / b).otherwise(F.lit(0.0))

    def window(i: Column) -> Column:
        return F.xxhash64(F.get(words, i), F.get(words, i + 1), F.get(words, i + 2)).bitwiseAND(F.lit(2**63 - 1) - low).bitwiseOR(i)

    def at(k: Column, shift: int) -> Column:
        return F.get(words, F.get(ordered, k).bitwiseAND(low).cast("int") + shift)

    def same(k: Column) -> Column:
        return (at(k, 0) == at(k + 1, 0)) & (at(k, 1) == at(k + 1, 1)) & (at(k, 2) == at(k + 1, 2))

    near = F.filter(F.sequence(F.lit(0), F.size(ordered) - 2), lambda k: F.get(ordered, k + 1) - F.get(ordered, k) <= low)
    twins = F.transform(F.filter("near", same), lambda k: F.array(F.get(ordered, k).bitwiseAND(low), F.get(ordered, k + 1).bitwiseAND(low)))
    lines = F.filter(F.split(t, "\n", -1), lambda x: x.rlike(r"[^ \t\n\x0B\f\r]"))
    return (
        source.select("*", F.split(spaced, " ", -1).alias("parts"))
        .select("*", F.array_remove("parts", "").alias("words"), lines.alias("lines"))
        .select(
            "row", "text", "words",
            F.size("words").cast("long").alias("n_words"),
            (F.length(t) - F.size("parts") + 1).cast("long").alias("word_chars"),
            F.size("lines").cast("long").alias("n_lines"),
            (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
            F.expr("shiftleft(1L, cast(ceil(log2(size(words) + 1)) as int)) - 1").alias("low"),
        )
        .select("*", F.when(F.col("n_words") >= 4, F.sort_array(F.transform(F.sequence(F.lit(0), F.size(words) - 3), lambda i: window(i)))).alias("ordered"))
        .select("*", F.when(F.size(ordered) >= 2, near).alias("near"))
        .select("*", F.when(F.size("near") > 0, F.sort_array(F.array_distinct(F.flatten(twins)))).alias("flags"))
        .select(
            "row", "n_words", "word_chars", "n_lines", "n_dup_lines",
            (F.length(t) - F.length(F.regexp_replace(t, SYMBOL_CLASS + "+", ""))).cast("long").alias("n_symbols"),
            (F.length(t) - F.length(F.regexp_replace(t, "[A-Z]+", ""))).cast("long").alias("n_upper"),
            F.size(F.array_intersect(words, F.array(*[F.lit(w) for w in STOP_FORMS]))).cast("long").alias("stop_words"),
            F.coalesce(_covered(F.col("flags")), F.lit(0).cast("long")).alias("n_repeat_words"),
        )
        .select(
            "*",
            ratio(100.0 * F.col("n_repeat_words"), F.col("n_words")).alias("repeat_percent"),
            ratio(F.col("word_chars"), F.col("n_words")).alias("mean_word_chars"),
            ratio(F.col("n_symbols"), F.col("n_words")).alias("symbols_per_word"),
            ratio(F.col("n_dup_lines"), F.col("n_lines")).alias("dup_line_ratio"),
            ratio(F.col("n_upper"), F.col("word_chars")).alias("upper_ratio"),
        )
    )


def compiled(rules: tuple[Rule, ...]) -> Column:
    """True where every rule holds."""
    verdict = F.lit(True)
    for r in rules:
        if r.low is not None:
            verdict = verdict & (F.col(r.measure) >= r.low)
        if r.high is not None:
            verdict = verdict & (F.col(r.measure) <= r.high)
    return verdict


def _judged(source: DataFrame, rules: tuple[Rule, ...]) -> DataFrame:
    base = compiled(BASE_RULES)
    judged = _measured(source).withColumns({"base_failed": ~base, "kept": base & compiled(rules)})
    # Rows are counted as they pass; a filter on `kept` stays above that. Pushed down, it would put all steps into one
    # expression, and into each lambda.
    return judged.observe(f"judged-{uuid.uuid4().hex}", F.count("*").alias("rows"), F.count_if("kept").alias("kept"))


def judge(docs: DataFrame, rules: tuple[Rule, ...] = RULES, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, measures, base_failed, kept); kept is false wherever the base fails."""
    source = id_and_text(docs, key, text).select(F.struct(F.col(key)).alias("row"), F.col(text).alias("text"))
    return _judged(source, rules).select("row.*", "*").drop("row")


def kept_documents(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text: str = "text") -> DataFrame:
    """The rows of docs, with all their columns, whose text passes. Nothing is shuffled or joined."""
    whole = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")
    source = docs.select(whole, F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"))
    return _judged(source, rules).where("kept").select("row.*")
