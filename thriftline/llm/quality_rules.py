"""Quality rules: one table of thresholds compiled into one Spark projection, without user functions.

Measures are expressions over the whole text; rules are ratios of two measures with bounds.  Ratios are compared as products of
whole numbers, so no rule depends on rounding.  Everything about a document is worked out inside its own row: no shuffle.
Repeated word windows are found by hashing words once, joining hashes pairwise three times to hashes of 8 words, and sorting these
with their places where a first test finds a repeat at all.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# White space, symbol characters, and frequent words of English, German, French and Spanish.
SPACES = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"
STOP_WORDS = "the of and to in is it that was for on are as with his they at be this from or by the der die das und ist nicht mit von zu den ein eine auf für im le la les de des du et en est que qui un une pour dans pas sur au par avec el los las y una por con se del al lo es su para como".split()


@dataclass(frozen=True)
class Rule:
    """``scale * measure`` must be at least ``low * base`` and at most ``high * base`` (each bound optional), for texts of ``words`` or more."""

    name: str
    measure: str
    base: str
    scale: int = 100
    low: int | None = None
    high: int | None = None
    words: int = 20


#: The threshold table of the registered query.
TABLE = (
    Rule("mean_word_length", "word_chars", "n_words", 10, 20, 150),
    Rule("symbol_ratio", "n_symbols", "n_words", 100, None, 40),
    Rule("duplicate_lines", "n_dup_lines", "n_lines", 100, None, 50),
    Rule("digit_ratio", "n_digits", "word_chars", 100, None, 50),
    Rule("stop_words", "n_stop_words", "n_words", 1000, 5, None, 60),
)


def _shifted(hashes: Column, by: int) -> Column:
    return F.slice(hashes, F.lit(by + 1), F.greatest(F.size(hashes) - by, F.lit(0)))


def _joined(hashes: Column, by: int) -> Column:
    """Hashes of twice the width: each with the one ``by`` places on; nothing past the end."""
    return F.zip_with(F.slice(hashes, F.lit(1), F.greatest(F.size(hashes) - by, F.lit(0))), _shifted(hashes, by), lambda a, b: F.xxhash64(a, b))


def measured(docs: DataFrame, width_power: int = 3) -> DataFrame:
    """The measures of each row of ``docs`` (doc_id, text): n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_digits, n_stop_words and
    n_repeat_words (words in windows of 2 ** width_power words that stand twice or more in the text).

    Null texts have no words, lines or characters.
    """
    width = 1 << width_power
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", text.alias("text"))
    rows = rows.withColumn("words", F.filter(F.split("text", "[ \\t-\\r]+"), lambda w: w != ""))
    rows = rows.withColumn("lines", F.filter(F.split("text", "\n"), lambda line: line.rlike(f"[^{SPACES}]")))
    lean = rows.select(
        "doc_id",
        "words",
        F.size("words").cast("long").alias("n_words"),
        F.length(F.regexp_replace("text", f"[{SPACES}]+", "")).cast("long").alias("word_chars"),
        F.length(F.regexp_replace("text", f"[^{SYMBOLS}]+", "")).cast("long").alias("n_symbols"),
        F.length(F.regexp_replace("text", "[^0-9]+", "")).cast("long").alias("n_digits"),
        F.size("lines").cast("long").alias("n_lines"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
    )
    h = F.transform("words", lambda w: F.xxhash64(w))
    for power in range(width_power):
        lean = lean.withColumn("h", h if power == 0 else F.col("h"))
        lean = lean.withColumn("h", _joined(F.col("h"), 1 << power))
    places = F.transform("h", lambda x, i: F.struct(x.alias("x"), i.alias("i")))
    lean = lean.withColumn("ranked", F.when(F.size(F.array_distinct("h")) < F.size("h"), F.array_sort(places)))
    # Each window with its neighbours in hash order: a repeat equals one of them.
    before = F.concat(F.array(F.lit(None).cast("bigint")), F.slice(F.col("ranked")["x"], F.lit(1), F.size("ranked") - 1))
    after = F.concat(_shifted(F.col("ranked")["x"], 1), F.array(F.lit(None).cast("bigint")))
    flagged = F.zip_with(F.zip_with("ranked", before, lambda r, b: F.struct(r["x"].alias("x"), r["i"].alias("i"), (r["x"].eqNullSafe(b)).alias("same"))), after, lambda r, a: F.when(r["same"] | r["x"].eqNullSafe(a), r["i"]))
    lean = lean.withColumn("starts", F.array_sort(F.filter(flagged, lambda i: i.isNotNull())))
    covered = F.aggregate(F.zip_with("starts", _shifted(F.col("starts"), 1), lambda a, b: F.least(F.coalesce(b - a, F.lit(width)), F.lit(width)).cast("long")), F.lit(0).cast("long"), lambda s, x: s + x)
    common = F.size(F.filter("words", lambda w: F.lower(w).isin(*sorted(set(STOP_WORDS))))).cast("long")
    return lean.select("doc_id", "n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_digits", common.alias("n_stop_words"), F.coalesce(covered, F.lit(0).cast("long")).alias("n_repeat_words"))


def verdict(rules: tuple[Rule, ...]) -> Column:
    """The names of the rules that a row of measures fails."""
    failed = []
    for rule in rules:
        bad = F.lit(False)
        if rule.low is not None:
            bad = bad | (rule.scale * F.col(rule.measure) < rule.low * F.col(rule.base))
        if rule.high is not None:
            bad = bad | (rule.scale * F.col(rule.measure) > rule.high * F.col(rule.base))
        failed.append(F.when((F.col("n_words") >= rule.words) & bad, F.lit(rule.name)))
    return F.array_compact(F.array(*failed))


def apply_rules(docs: DataFrame, rules: tuple[Rule, ...] = TABLE) -> DataFrame:
    """The measures, base_failed (under 20 words, or over 30 % in repeated windows), failed_rules and kept for each row.

    Null and empty texts have no words, so base_failed is true.  Repeated rows are judged alike; null doc_ids are rows like others;
    extra columns are left.  No rows in, no rows out.
    """
    base = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    out = measured(docs).withColumn("base_failed", base).withColumn("failed_rules", verdict(rules))
    return out.withColumn("kept", ~F.col("base_failed") & (F.size("failed_rules") == 0))
