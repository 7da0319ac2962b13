"""Quality rules as a bitmask ledger.

Every rule is evaluated once a document. The ledger stores the measurements and one ``failures``
long in which bit i is set if rule i fails. Policies are versioned masks over those bits, so a new
policy, or an ablation of one, never reads a text again.

Everything is a projection inside the row: no shuffle, no Python.

Defined results: a null or empty text has no words, no lines with a word and fails ``few_words``;
null ids and repeated rows keep one ledger row each; an empty table gives an empty ledger; columns
of the input called like a ledger column are dropped before the ledger's own are added.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pantry.llm import text as tx

MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")
SYMBOLS = "#*$%&|<>"


@dataclass(frozen=True)
class Rule:
    """A rule fails where ``fails()`` is true; its bit is its place in the list."""

    name: str
    fails: Callable[[], Column]


def _c(name: str) -> Column:
    return F.col(name)


RULES: tuple[Rule, ...] = (
    Rule("few_words", lambda: _c("n_words") < 50),
    Rule("repeated_words", lambda: 100 * _c("n_repeat_words") > 50 * _c("n_words")),
    Rule("short_words", lambda: _c("word_chars") < 2 * _c("n_words")),
    Rule("long_words", lambda: _c("word_chars") > 25 * _c("n_words")),
    Rule("symbols", lambda: 10 * _c("n_symbols") > _c("n_words")),
    Rule("repeated_lines", lambda: 2 * _c("n_dup_lines") > _c("n_lines")),
)


@dataclass(frozen=True)
class Policy:
    """The rules, by name, that a version of a policy applies."""

    name: str
    version: int
    rules: tuple[str, ...]

    def mask(self) -> int:
        at = {r.name: i for i, r in enumerate(RULES)}
        return sum(1 << at[n] for n in self.rules)


BASE = Policy("base", 1, ("few_words", "repeated_words"))
STANDARD = Policy("standard", 1, tuple(r.name for r in RULES))


def _repeat_words(df: DataFrame) -> DataFrame:
    """Add n_repeat_words from ``_w``: words inside three-word windows whose words occur again in the text.

    Windows are compared by a 64-bit hash chained over their words. Sorting (hash, place) brings equal
    windows together; the union of the windows' places is then measured on the sorted places. Texts
    without a repeated window, the usual case, stop after the distinct count.
    """
    at = F.greatest(F.size("_w") - 2, F.lit(0))
    df = df.withColumn("_h", F.transform("_w", lambda w: F.xxhash64(w)))
    pair = F.zip_with(F.slice("_h", F.lit(1), at), F.slice("_h", F.lit(2), at), lambda x, y: F.xxhash64(x, y))
    df = df.withColumn("_t", F.zip_with(pair, F.slice("_h", F.lit(3), at), lambda x, y: F.xxhash64(x, y)))
    df = df.withColumn("_again", F.size(F.array_distinct("_t")) < F.size("_t"))
    placed = F.sort_array(F.transform("_t", lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
    df = df.withColumn("_s", F.when(_c("_again"), placed))
    less = F.size("_s") - 1
    both = F.zip_with(
        F.slice("_s", F.lit(1), less),
        F.slice("_s", F.lit(2), less),
        lambda x, y: F.when(x["h"] == y["h"], F.array(x["i"], y["i"])),
    )
    places = F.sort_array(F.array_distinct(F.flatten(F.filter(both, lambda x: x.isNotNull()))))
    df = df.withColumn("_p", F.when(_c("_again"), places))
    less = F.size("_p") - 1
    steps = F.zip_with(F.slice("_p", F.lit(1), less), F.slice("_p", F.lit(2), less), lambda x, y: F.least(y - x, F.lit(3)))
    covered = F.aggregate(steps, F.lit(3), lambda a, x: a + x)
    return df.withColumn("n_repeat_words", F.when(_c("_again"), covered).otherwise(0).cast("long"))


def ledger(df: DataFrame, text: str = "text") -> DataFrame:
    """The rows of ``df`` with the measurements and ``failures``."""
    keep = [c for c in df.columns if c not in (*MEASURES, "failures")]
    # the input's columns wait in one struct, so that none can be taken for a measurement or a helper
    df = df.select(F.struct(*(F.col(f"`{c}`") for c in keep)).alias("_row"), F.col(f"`{text}`").alias("_text"))
    body = tx.whole(F.col("_text"))
    df = df.select("_row", "_text", tx.words(F.col("_text")).alias("_w"))
    df = df.withColumn("n_words", F.size("_w").cast("long"))
    df = df.withColumn("word_chars", F.char_length(F.translate(body, tx.SPACE, "")).cast("long"))
    df = df.withColumn("n_symbols", (F.char_length(body) - F.char_length(F.translate(body, SYMBOLS, ""))).cast("long"))
    df = df.withColumn("_l", F.filter(F.split(body, "\n"), lambda x: F.btrim(x, F.lit(tx.SPACE)) != ""))
    df = df.withColumn("n_lines", F.size("_l").cast("long"))
    df = df.withColumn("n_dup_lines", (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long"))
    df = _repeat_words(df)
    bits = F.lit(0).cast("long")
    for i, rule in enumerate(RULES):
        bits = bits.bitwiseOR(F.when(rule.fails(), F.lit(1 << i).cast("long")).otherwise(F.lit(0).cast("long")))
    return df.select(*(F.col("_row")[c].alias(c) for c in keep), *MEASURES, bits.alias("failures"))


def passes(policy: Policy, failures: str = "failures") -> Column:
    return F.col(failures).bitwiseAND(F.lit(policy.mask()).cast("long")) == 0


def ablations(entries: DataFrame, policy: Policy = STANDARD) -> DataFrame:
    """For each rule of the policy: documents that fail it, and those that only it rejects.

    One aggregation to a row for each pattern of failures, then bit tests on that small table.
    """
    patterns = entries.groupBy(F.col("failures").bitwiseAND(F.lit(policy.mask()).cast("long")).alias("f")).agg(F.count("*").alias("n"))
    at = {r.name: i for i, r in enumerate(RULES)}
    rules = F.array(*(F.struct(F.lit(n).alias("rule"), F.lit(1 << at[n]).cast("long").alias("bit")) for n in policy.rules))
    each = patterns.select("f", "n", F.explode(rules).alias("r")).select("f", "n", "r.rule", "r.bit")
    zero = F.lit(0).cast("long")
    return each.groupBy("rule").agg(
        F.sum(F.when(F.col("f").bitwiseAND(F.col("bit")) != 0, F.col("n")).otherwise(zero)).alias("n_failed"),
        F.sum(F.when(F.col("f") == F.col("bit"), F.col("n")).otherwise(zero)).alias("n_only"),
        F.sum("n").alias("n_documents"),
    )


def accepted(df: DataFrame, policy: Policy = STANDARD, text: str = "text") -> DataFrame:
    """The rows of ``df``, with its own columns, that the policy keeps."""
    entries = ledger(df.select(F.struct(*(F.col(f"`{c}`") for c in df.columns)).alias("row"), F.col(f"`{text}`").alias("text")), "text")
    # A row number that the filter asks for keeps the optimizer from pushing the filter into the ledger's
    # projections, where each rule's whole chain of expressions would be written out again at every use.
    numbered = entries.withColumn("_n", F.monotonically_increasing_id())
    return numbered.where(passes(policy) & (F.col("_n") >= 0)).select("row.*")
