"""Quality rules: a threshold table compiled into one projection of text measures.

No user functions: every measure is a Spark expression on the text, and the rules become one
conjunction. Nulls and texts without words have all counts 0 and fail the word minimum.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACE

#: Very frequent words of English, French, German and Spanish.
STOP_WORDS = (
    "the", "be", "to", "of", "and", "that", "have", "with", "is", "in", "was", "for", "this", "it", "on", "are", "as", "by", "an", "or",
    "le", "la", "les", "de", "des", "du", "et", "un", "une", "en", "dans", "que", "qui", "pour", "par", "sur", "avec", "est", "ou", "au",
    "der", "die", "das", "den", "dem", "und", "von", "zu", "mit", "ein", "eine", "nicht", "ist", "sich", "auf", "für",
    "el", "los", "las", "del", "y", "una", "con", "no", "su", "al", "se", "es", "lo", "como", "más", "o",
)


@dataclass(frozen=True)
class Rule:
    """Keep a document while low <= numerator * 100 / denominator <= high (percent; bounds may be None)."""

    name: str
    numerator: str
    denominator: str
    low: float | None = None
    high: float | None = None


#: The default table. Percentages are of the denominator's count (``one``: of 1).
RULES = (
    Rule("mean_word_length", "word_chars", "n_words", 200, 1500),
    Rule("symbols_per_word", "n_symbols", "n_words", None, 10),
    Rule("distinct_stop_words", "n_stop_words", "one", 200, None),
    Rule("repeated_lines", "n_dup_lines", "n_lines", None, 50),
    Rule("shouts_per_word", "n_shouts", "n_words", None, 30),
)
MIN_WORDS, MAX_REPEAT_PERCENT = 50, 50


#: Low bits of a packed window that hold its position; texts with more windows take the unpacked way.
_POSITION_BITS = 20


def _window_hash(i: Column) -> Column:
    return F.xxhash64(F.get("w", i), F.get("w", i + 1), F.get("w", i + 2))


def _with_repeat_words(df: DataFrame) -> DataFrame:
    """Add n_repeat_words: the positions covered by three-word windows (64-bit hashes) found again.

    A first sort runs on plain longs (upper hash bits, position): only neighbours that agree there can be
    equal, and only those few are compared by their whole hash. Each step is a projection of its own:
    an expression used inside a lambda would be evaluated anew for every element.
    """
    low = (1 << _POSITION_BITS) - 1
    n = F.size("w") - 2
    windows = F.when(n >= 1, F.sequence(F.lit(0), n - 1)).otherwise(F.array().cast("array<int>"))
    first = F.slice("w", F.lit(1), F.greatest(n, F.lit(0)))
    packed = F.transform(
        first, lambda x, i: F.xxhash64(x, F.get("w", i + 1), F.get("w", i + 2)).bitwiseAND(F.lit(~low)).bitwiseOR(i.cast("long"))
    )
    df = df.withColumn("s", F.when(n <= low, F.sort_array(packed)))
    after = F.slice("s", F.lit(2), F.greatest(n, F.lit(1)))
    both = lambda x, y: F.when(x.bitwiseXOR(y).between(0, low), F.array(x, y))
    near = F.flatten(F.array_compact(F.zip_with("s", after, both)))
    suspects = F.array_distinct(F.transform(near, lambda x: x.bitwiseAND(F.lit(low)).cast("int")))
    df = df.withColumn("s", F.coalesce(suspects, windows))
    df = df.withColumn("s", F.sort_array(F.transform("s", lambda i: F.struct(_window_hash(i).alias("h"), i.alias("i")))))
    again = lambda x, i: F.coalesce((x.h == F.get("s", i + 1).h) | (x.h == F.get("s", i - 1).h), F.lit(False))
    df = df.withColumn("s", F.sort_array(F.transform(F.filter("s", again), lambda x: x.i)))
    covered = F.transform("s", lambda x, i: F.coalesce(F.least(F.get("s", i + 1) - x, F.lit(3)), F.lit(3)))
    return df.withColumn("n_repeat_words", F.aggregate(covered, F.lit(0), lambda s, x: s + x).cast("long")).drop("s", "w")


def measures(docs: DataFrame) -> DataFrame:
    """doc_id and the counts that the rules use, one row per row of ``docs``."""
    lines = F.filter(F.split("text", "\n"), lambda x: x.rlike(r"[^ \t\n\x0B\f\r]"))
    trimmed = F.btrim("text", F.lit(" \t\n\x0b\f\r"))
    base = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).select(
        "doc_id",
        F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, SPACE)).alias("w"),
        lines.alias("l"),
        F.regexp_count("text", F.lit(r"[#*$%&|<>]")).cast("long").alias("n_symbols"),
        ((F.length("text") - F.length(F.replace("text", F.lit("!!"), F.lit("")))) / 2).cast("long").alias("n_shouts"),
    )
    stop = F.array(*[F.lit(x) for w in STOP_WORDS for x in (w, w.capitalize())])
    return base.select(
        "doc_id",
        F.size("w").cast("long").alias("n_words"),
        F.length(F.array_join("w", "")).cast("long").alias("word_chars"),
        "n_symbols",
        F.size("l").cast("long").alias("n_lines"),
        (F.size("l") - F.size(F.array_distinct("l"))).cast("long").alias("n_dup_lines"),
        F.size(F.array_intersect("w", stop)).cast("long").alias("n_stop_words"),
        "n_shouts",
        "w",
    ).transform(_with_repeat_words)


def verdict(rules=RULES) -> Column:
    """The rule table as one boolean expression over the measures."""
    ok = F.lit(True)
    for r in rules:
        num, den = F.col(r.numerator) * 100, F.lit(1) if r.denominator == "one" else F.col(r.denominator)
        if r.low is not None:
            ok = ok & (num >= den * F.lit(float(r.low)))
        if r.high is not None:
            ok = ok & (num <= den * F.lit(float(r.high)))
    return ok


def base_failed(min_words: int = MIN_WORDS, max_repeat: int = MAX_REPEAT_PERCENT) -> Column:
    return (F.col("n_words") < min_words) | (100 * F.col("n_repeat_words") > max_repeat * F.col("n_words"))


def judge(docs: DataFrame, rules=RULES, min_words: int = MIN_WORDS, max_repeat: int = MAX_REPEAT_PERCENT) -> DataFrame:
    """The measures with ``base_failed`` and ``kept``; an empty table gives an empty result.

    ``kept`` goes through a branch on the partition number that is never taken: the optimizer leaves a filter on such a
    column where it is. Pushed below the projections, it would evaluate their arrays anew for every element.
    """
    kept = F.when(F.spark_partition_id() < 0, F.lit(False)).otherwise(~F.col("base_failed") & verdict(rules))
    return measures(docs).withColumn("base_failed", base_failed(min_words, max_repeat)).withColumn("kept", kept)


def keep_good(docs: DataFrame, rules=RULES) -> DataFrame:
    """The rows of ``docs`` that every rule keeps, with all their columns, in one narrow pass.

    The measures are computed beside the row itself (no join), so repeated or null identifiers are
    judged row by row.
    """
    names = docs.columns
    whole = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("doc_id"), F.col("text"))
    return judge(whole, rules).where("kept").select("doc_id.*")
