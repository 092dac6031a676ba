"""Quality rules as a bitmask ledger (DataFrame functions only).

Every rule is evaluated once per document.  The ledger keeps the measurements
and one long whose bit *k* is set when rule *k* failed; policies are versioned
masks over those bits, so a new policy or an ablation never reads a text again.

Defined cases: a null or blank text has no words and fails ``few_words``;
repeated rows and repeated doc_ids are measured row by row; extra columns of the
input pass through ``ledger`` untouched, and a clash with a ledger column is
resolved in favour of the ledger.  An empty table gives an empty ledger.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .exprs import BLANKS, let, words_of

WINDOW = 8
#: Characters that count as symbols.
SYMBOLS = "[#*$%&|<>]"

MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper", "n_marks", "n_letters", "n_same_next", "n_chars_text")


@dataclass(frozen=True)
class Rule:
    """A named test over measurements; true means the document fails it."""

    name: str
    fails: str


RULES: tuple[Rule, ...] = (
    Rule("few_words", "n_words < 20"),
    Rule("repeated_windows", "100 * n_repeat_words > 30 * n_words"),
    Rule("symbols", "100 * n_symbols > 20 * n_words"),
    Rule("duplicate_lines", "10 * n_dup_lines > 3 * n_lines AND n_dup_lines >= 3"),
    Rule("word_length", "n_words > 0 AND (word_chars < 2 * n_words OR word_chars > 15 * n_words)"),
    Rule("shouting", "10 * n_upper > 4 * n_letters AND n_letters > 0"),
    Rule("marks", "10 * n_marks > 6 * n_words"),
    Rule("letters", "10 * n_letters < 6 * word_chars"),
    Rule("stuttering", "100 * n_same_next > 30 * n_words"),
)


@dataclass(frozen=True)
class Policy:
    """A versioned choice of rules; a document is kept when none of them failed."""

    name: str
    version: int
    rules: tuple[str, ...]

    @property
    def mask(self) -> int:
        index = {r.name: k for k, r in enumerate(RULES)}
        return sum(1 << index[r] for r in self.rules)


BASE = Policy("base", 1, ("few_words", "repeated_windows"))
STANDARD = Policy("standard", 1, tuple(r.name for r in RULES))
POLICIES = (BASE, STANDARD)


def _repeat_words(words: Column) -> Column:
    """Words inside 8-word windows that occur twice or more: O(n log n) in one row."""

    def covered(hashes: Column) -> Column:
        def of(pairs: Column) -> Column:
            same = lambda p, k: F.get(pairs, k)["h"].eqNullSafe(p["h"])
            starts = F.sort_array(F.filter(F.transform(pairs, lambda p, k: F.when(same(p, k - 1) | same(p, k + 1), p["i"])), lambda i: i.isNotNull()))
            step = lambda s, i: F.struct((s["n"] + F.least(F.lit(WINDOW), i - s["last"])).alias("n"), i.alias("last"))
            return F.aggregate(starts, F.struct(F.lit(0).alias("n"), F.lit(-WINDOW).alias("last")), step, lambda s: s["n"])

        repeats = F.size(F.array_distinct(hashes)) < F.size(hashes)
        return F.when(repeats, let(F.sort_array(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i")))), of)).otherwise(0)

    windows = F.transform(F.sequence(F.lit(1), F.size(words) - (WINDOW - 1)), lambda i: F.xxhash64(F.slice(words, i, WINDOW)))
    return F.when(F.size(words) > WINDOW, let(windows, covered)).otherwise(0)


def measures(text: Column) -> Column:
    """One struct of all measurements (longs) of a text."""
    text = F.coalesce(text, F.lit(""))
    lines = F.filter(F.split(text, "\n", -1), lambda x: F.trim(x, F.lit(BLANKS)) != "")

    def of_words(words: Column) -> Column:
        return F.struct(
            F.size(words).cast("long").alias("n_words"),
            F.length(F.array_join(words, "")).cast("long").alias("word_chars"),
            _repeat_words(words).cast("long").alias("n_repeat_words"),
            F.size(F.filter(words, lambda w, i: w == F.get(words, i - 1))).cast("long").alias("n_same_next"),
        )

    def of_lines(rows: Column) -> Column:
        return F.struct(F.size(rows).cast("long").alias("n_lines"), (F.size(rows) - F.size(F.array_distinct(rows))).cast("long").alias("n_dup_lines"))

    count = lambda pattern: F.regexp_count(text, F.lit(pattern)).cast("long")
    w, n = let(words_of(text), of_words), let(lines, of_lines)
    return F.struct(w.alias("w"), n.alias("l"), count(SYMBOLS).alias("n_symbols"), count("\\p{Lu}").alias("n_upper"), count("[!?=_~^]").alias("n_marks"), count("[^\\P{L}]").alias("n_letters"), F.length(text).cast("long").alias("n_chars_text"))


def _bits() -> Column:
    return F.expr(" | ".join(f"IF({r.fails}, {1 << k}L, 0L)" for k, r in enumerate(RULES)))


def ledger(docs: DataFrame, text: str = "text") -> DataFrame:
    """Input rows with the measurements and ``failed`` (the rule bits)."""
    m = docs.withColumn("__m", measures(F.col(text)))
    flat = {n: F.col("__m.w")[n] for n in ("n_words", "word_chars", "n_repeat_words", "n_same_next")} | {n: F.col("__m.l")[n] for n in ("n_lines", "n_dup_lines")}
    flat |= {n: F.col("__m")[n] for n in ("n_symbols", "n_upper", "n_marks", "n_letters", "n_chars_text")}
    return m.withColumns(flat).drop("__m").withColumn("failed", _bits())


def apply_policy(rows: DataFrame, policy: Policy, out: str = "kept") -> DataFrame:
    """Adds the verdict of a policy over a stored ledger."""
    return rows.withColumn(out, F.col("failed").bitwiseAND(F.lit(policy.mask).cast("long")) == 0)


def ablation(rows: DataFrame, policy: Policy) -> DataFrame:
    """Per rule of the policy: documents failing it, and failing only it.

    Texts are not read: the ledger is first reduced to one row per bit pattern.
    """
    patterns = rows.groupBy(F.col("failed").bitwiseAND(F.lit(policy.mask).cast("long")).alias("bits")).agg(F.count(F.lit(1)).alias("docs"))
    index = {r.name: 1 << k for k, r in enumerate(RULES)}
    rules = F.array(*[F.struct(F.lit(n).alias("rule"), F.lit(index[n]).cast("long").alias("bit")) for n in policy.rules])
    exploded = patterns.select("bits", "docs", F.explode(rules).alias("r"))
    return exploded.groupBy(F.col("r.rule").alias("rule")).agg(
        F.sum(F.when(F.col("bits").bitwiseAND(F.col("r.bit")) != 0, F.col("docs")).otherwise(0)).alias("fails"),
        F.sum(F.when(F.col("bits") == F.col("r.bit"), F.col("docs")).otherwise(0)).alias("fails_alone"),
        F.sum("docs").alias("docs"),
    )


def reject(docs: DataFrame, policy: Policy = STANDARD, text: str = "text") -> DataFrame:
    """Input rows (same columns) that the policy keeps."""
    cols = docs.columns
    mark = docs.select(F.struct(*[F.col(f"`{c}`") for c in cols]).alias("__row"), F.col(f"`{text}`").alias("__text"))
    kept = apply_policy(ledger(mark, "__text"), policy).where("kept")
    return kept.select(*[F.col("__row")[c].alias(c) for c in cols])
