"""Quality rules as a bitmask ledger (SQL functions only).

``ledger`` evaluates every rule once per document and keeps the measurements and one bit for each failed rule.
Policies are versioned masks over that ledger: applying one, or asking what each rule alone removes, never
touches the texts again.

Defined results: a null or empty text has no words, so all counts are 0; very long texts are handled inside one
row by array functions without exploding; repeated rows and ties are independent, row by row; an empty table
gives an empty result; input columns whose names clash with the ledger's are kept out of the result.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: White space between words: space and \x09 to \x0D.
SPACE_CHARS = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"
#: Words in a window of the repetition measure.
WINDOW = 5
MEASURES = ("n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words", "n_upper", "n_chars_text")


@dataclass(frozen=True)
class Rule:
    """A document fails the rule where ``fails`` (over the measurements) holds. ``bit`` never changes meaning."""

    bit: int
    name: str
    fails: str


#: Bits are append-only: a new version of a rule gets a new bit.
RULES = (
    Rule(0, "too_few_words", "n_words < 10"),
    Rule(1, "repeated_windows", "100 * n_repeat_words > 20 * n_words"),
    Rule(2, "many_symbols", "100 * n_symbols > 15 * word_chars"),
    Rule(3, "mostly_upper_case", "2 * n_upper > word_chars"),
    Rule(4, "repeated_lines", "n_lines > 3 and 10 * n_dup_lines > 5 * n_lines"),
    Rule(5, "long_words", "n_words > 0 and word_chars > 25 * n_words"),
    Rule(6, "short_words", "n_words > 0 and word_chars < 2 * n_words"),
    Rule(7, "some_symbols", "100 * n_symbols > 3 * word_chars"),
)
#: version -> names of the rules that the policy enforces.
POLICIES = {
    "base-1": ("too_few_words", "repeated_windows"),
    "quality-1": ("too_few_words", "repeated_windows", "many_symbols", "mostly_upper_case", "repeated_lines", "long_words", "short_words"),
    "quality-2": ("too_few_words", "repeated_windows", "many_symbols", "mostly_upper_case", "repeated_lines", "long_words", "short_words", "some_symbols"),
}


def mask(policy: str, rules: tuple[Rule, ...] = RULES) -> int:
    """The bits that a policy enforces."""
    names = POLICIES[policy]
    return sum(1 << r.bit for r in rules if r.name in names)


def repeated_words(words: Column, n: Column) -> Column:
    """A hash of each window of five successive words of an array, in order; null where it has fewer words."""
    hashes = F.when(n >= WINDOW, F.transform(F.sequence(F.lit(0), n - WINDOW), lambda i: F.xxhash64(*[words[i + k] for k in range(WINDOW)])))
    return hashes


def measurements(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id and the measurements of each whole text."""
    base = docs.select(F.col(id_col).alias("_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("_text"))
    squeezed = F.translate("_text", SPACE_CHARS, "")
    d = base.select(
        "_id",
        F.array_remove(F.split("_text", r"[\x20\x09-\x0D]+"), "").alias("_words"),
        F.filter(F.split("_text", "\n"), lambda x: F.length(F.translate(x, SPACE_CHARS, "")) > 0).alias("_lines"),
        F.length(squeezed).cast("long").alias("word_chars"),
        (F.length("_text") - F.length(F.translate("_text", SYMBOLS, ""))).cast("long").alias("n_symbols"),
        (F.length("_text") - F.length(F.regexp_replace("_text", r"\p{Lu}", ""))).cast("long").alias("n_upper"),
        F.length("_text").cast("long").alias("n_chars_text"),
    )
    d = d.select(
        "*",
        F.size("_words").alias("_n"),
        F.size("_lines").cast("long").alias("n_lines"),
        (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long").alias("n_dup_lines"),
    )
    d = d.select("*", repeated_words(F.col("_words"), F.col("_n")).alias("_hashes"))
    some = F.coalesce(F.size("_hashes") > F.size(F.array_distinct("_hashes")), F.lit(False))
    at = F.array_sort(F.transform("_hashes", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    d = d.select("*", F.when(some, at).alias("_at"))
    last = F.size("_at") - 1
    twice = F.filter(
        F.transform(
            "_at",
            lambda x, k: F.when(
                ((k > 0) & (F.col("_at")[F.greatest(k - 1, F.lit(0))]["h"] == x["h"]))
                | ((k < last) & (F.col("_at")[F.least(k + 1, last)]["h"] == x["h"])),
                x["i"],
            ),
        ),
        lambda x: x.isNotNull(),
    )
    d = d.select("*", F.array_sort(twice).alias("_twice"))
    covered = F.aggregate(
        "_twice",
        F.struct(F.lit(-WINDOW).alias("p"), F.lit(0).cast("long").alias("n")),
        lambda s, x: F.struct(x.alias("p"), (s["n"] + F.least(F.lit(WINDOW), x - s["p"])).alias("n")),
        lambda s: s["n"],
    )
    return d.select(F.col("_id").alias(id_col), F.col("_n").cast("long").alias("n_words"), F.coalesce(covered, F.lit(0)).cast("long").alias("n_repeat_words"), *[m for m in MEASURES if m not in ("n_words", "n_repeat_words")])


def ledger(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """id, the measurements and ``failed``: bit ``r.bit`` is set where rule ``r`` fails."""
    bits = F.lit(0).cast("long")
    for r in rules:
        bits = bits.bitwiseOR(F.when(F.expr(r.fails), F.lit(1 << r.bit)).otherwise(F.lit(0)).cast("long"))
    return measurements(docs, id_col, text_col).withColumn("failed", bits)


def apply_policy(led: DataFrame, policy: str = "quality-1") -> DataFrame:
    """``kept``: none of the policy's bits is set."""
    return led.withColumn("kept", F.col("failed").bitwiseAND(F.lit(mask(policy)).cast("long")) == 0)


def ablation(led: DataFrame, policy: str = "quality-1", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """For each rule of a policy: documents that fail it, that fail it alone, and that stay if it is left out.

    One bitwise aggregation: documents are first counted by their failure bits (at most 2^rules groups).
    """
    m = mask(policy, rules)
    by = led.groupBy(F.col("failed").bitwiseAND(F.lit(m).cast("long")).alias("bits")).agg(F.count("*").alias("n"))
    own = [r for r in rules if m >> r.bit & 1]
    each = F.explode(F.array(*[F.struct(F.lit(r.name).alias("rule"), F.lit(1 << r.bit).cast("long").alias("bit")) for r in own]))
    x = by.select("bits", "n", each.alias("r")).select("bits", "n", "r.rule", "r.bit")
    return x.groupBy("rule", "bit").agg(
        F.sum(F.when(F.col("bits").bitwiseAND(F.col("bit")) != 0, F.col("n")).otherwise(0)).alias("n_fail"),
        F.sum(F.when(F.col("bits") == F.col("bit"), F.col("n")).otherwise(0)).alias("n_only"),
        F.sum(F.when(F.col("bits").bitwiseAND(F.bitwise_not("bit")) == 0, F.col("n")).otherwise(0)).alias("n_kept_without"),
        F.sum("n").alias("n_docs"),
    )
