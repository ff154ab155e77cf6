"""Quality rules: a threshold table compiled into one projection, without user functions.

Measures are columns over the words and lines of a whole text. A rule bounds one
measure; ``compile_rules`` turns the table into a single boolean column, so the
operator is one narrow projection: no shuffle, no join, no Python.

Defined cases: null and empty texts have no words and fail; repeated rows are
judged row by row; an empty table gives an empty table; only the id and text
columns are read, so extra columns of any name do no harm.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semrank.llm.text import BLANKS, whole, words

WINDOW = 5
SYMBOLS = "[#*$%&|<>]"
#: Frequent function words of the four languages.
STOP_WORDS = (
    "the of and to in is that it was for on as with be by this are from at or an have not he which you his had but they "
    "der die das und in den von zu mit sich des auf für ist im dem nicht ein eine als auch es an werden aus er hat dass sie nach "
    "de la le et les des en un du une que est pour qui dans par au il sur pas plus ne se ce "
    "el que y los del las por con una su para al lo como más pero sus o"
).split()


@dataclass(frozen=True)
class Rule:
    """``low`` <= measure <= ``high``; a bound that is None is open."""

    measure: str
    low: float | None = None
    high: float | None = None


#: The production table. Ratios are per word, but for dup_lines (per line with a word).
RULES = (
    Rule("n_words", low=10),
    Rule("mean_word", low=2.0, high=20.0),
    Rule("symbols_per_word", high=0.25),
    Rule("shouts_per_word", high=0.5),
    Rule("stop_share", low=0.02),
    Rule("dup_line_share", high=0.6),
    Rule("repeat_share", high=0.2),
    Rule("echo_share", high=0.25),
)


def compile_rules(rules: tuple[Rule, ...]) -> Column:
    """One boolean column: every rule holds."""
    out = F.lit(True)
    for r in rules:
        if r.low is not None:
            out = out & (F.col(r.measure) >= F.lit(r.low))
        if r.high is not None:
            out = out & (F.col(r.measure) <= F.lit(r.high))
    return out


def quality_rules(docs: DataFrame, rules: tuple[Rule, ...] = RULES, *, doc_id: str = "doc_id", text: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """Measures and verdict of each row: doc_id, n_words, word_chars, n_symbols, n_dup_lines,
    n_repeat_words, the ratios the rules bound, base_failed and kept."""
    last = WINDOW - 1
    d = docs.select(F.col(doc_id).alias("doc_id"), whole(text).alias("_t"), *keep)
    d = d.select("doc_id", *keep, "_t", words("_t").alias("_w"), F.filter(F.split("_t", "\n"), lambda x: F.length(F.translate(x, " \t\n\x0b\x0c\r", "")) > 0).alias("_l"))
    d = d.withColumn("_h", F.transform("_w", lambda w: F.xxhash64(w)))
    # the hash of the window that starts at each word; a hash names a window within one text only
    d = d.withColumn("_v", F.when(F.size("_h") > last, F.transform(F.sequence(F.lit(0), F.size("_h") - WINDOW), lambda i: F.xxhash64(*[F.get("_h", i + k) for k in range(WINDOW)]))).otherwise(F.array().cast("array<bigint>")))
    # only texts in which some window comes twice are sorted; equal windows are then neighbours
    d = d.withColumn("_s", F.when(F.size(F.array_distinct("_v")) < F.size("_v"), F.sort_array(F.transform("_v", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))))
    twice = F.transform("_s", lambda s, j: F.when((F.get("_s", j - 1)["h"] == s["h"]) | (F.get("_s", j + 1)["h"] == s["h"]), s["i"]))
    starts = F.sort_array(F.filter(twice, lambda i: i.isNotNull()))
    covered = F.aggregate(
        starts,
        F.struct(F.lit(0).alias("n"), F.lit(0).alias("to")),
        lambda a, s: F.struct((a["n"] + s + WINDOW - F.greatest(a["to"], s)).alias("n"), (s + WINDOW).alias("to")),
        lambda a: a["n"],
    )
    d = d.select(
        "doc_id",
        *keep,
        F.size("_w").cast("bigint").alias("n_words"),
        F.aggregate("_w", F.lit(0).cast("bigint"), lambda a, w: a + F.length(w)).alias("word_chars"),
        F.regexp_count("_t", F.lit(SYMBOLS)).cast("bigint").alias("n_symbols"),
        (F.size("_l") - F.size(F.array_distinct("_l"))).cast("bigint").alias("n_dup_lines"),
        F.coalesce(F.when(F.col("_s").isNotNull(), covered), F.lit(0)).cast("bigint").alias("n_repeat_words"),
        F.size("_l").cast("bigint").alias("n_lines"),
        F.regexp_count("_t", F.lit("!!")).cast("bigint").alias("_shouts"),
        F.size(F.filter("_w", lambda w: F.lower(F.trim(w, F.lit(".,;:!?"))).isin(*STOP_WORDS))).alias("_stops"),
        # words that repeat the word before them
        F.size(F.filter(F.transform("_h", lambda h, i: F.get("_h", i - 1) == h), lambda x: x)).alias("_echoes"),
    )
    per = lambda n, of: F.when(F.col(of) > 0, F.col(n) / F.col(of)).otherwise(F.lit(0.0))
    d = d.select(
        "*",
        per("word_chars", "n_words").alias("mean_word"),
        per("n_symbols", "n_words").alias("symbols_per_word"),
        per("_shouts", "n_words").alias("shouts_per_word"),
        # smoothed, so that a short text without a function word is no failure yet
        ((F.col("_stops") + 1) / (F.col("n_words") + 20)).alias("stop_share"),
        per("n_dup_lines", "n_lines").alias("dup_line_share"),
        per("n_repeat_words", "n_words").alias("repeat_share"),
        per("_echoes", "n_words").alias("echo_share"),
    ).drop("_shouts", "_stops", "_echoes")
    base = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    return d.select("*", base.alias("base_failed"), (~base & compile_rules(rules)).alias("kept"))


QUERY_COLUMNS = ("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")
__all__ = ["BLANKS", "RULES", "Rule", "compile_rules", "quality_rules", "QUERY_COLUMNS"]
