"""Quality rules as a bitmask ledger (DataFrame functions only).

Every rule is evaluated once per document; the ledger keeps one bit per failed rule beside
the measurements. Policies are versioned masks over those bits, so a new policy or an
ablation never looks at a text again: both work on the counts of distinct masks.

Defined results: a null or empty text has no words (all measures 0) and fails ``few_words``;
repeated rows are judged alike; very long texts are measured whole, in n log n time; an empty
table gives no rows. Other columns of the input pass through ``ledger`` unread, whatever
their names; one called like a measure or ``rule_bits`` gets an underscore before its name.
``keep`` gives back the columns it was given.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BLANKS, beside, named, packed, words

SYMBOLS = "#*$%&|<>"
WINDOW = 5
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


@dataclass(frozen=True)
class Rule:
    """A rule fails a document when ``fails`` (SQL over the measures) is true."""

    bit: int
    name: str
    fails: str


#: Bits are never reused: a rule that is given up keeps its bit, so old ledgers stay readable.
RULES = (
    Rule(0, "few_words", "n_words < 10"),
    Rule(1, "repeated_windows", "100 * n_repeat_words > 20 * n_words"),
    Rule(2, "symbols_per_word", "2 * n_symbols > n_words"),
    Rule(3, "long_words", "word_chars > 40 * n_words"),
    Rule(4, "short_words", "word_chars < 2 * n_words"),
    Rule(5, "repeated_lines", "n_dup_lines > 30 AND 20 * n_dup_lines > n_words"),
)
BASE = ("few_words", "repeated_windows")
POLICIES: dict[str, tuple[str, ...]] = {
    "base": BASE,
    "v1": (*BASE, "symbols_per_word"),
    "v2": (*BASE, "symbols_per_word", "short_words", "repeated_lines"),
    #: Also rejects scripts written without blanks, so it is not the default.
    "spaced_scripts_only": tuple(r.name for r in RULES),
}
DEFAULT_POLICY = "v2"


def mask_of(names: tuple[str, ...]) -> int:
    bits = {r.name: r.bit for r in RULES}
    return sum(1 << bits[n] for n in names)


def _without(text: Column, chars: str) -> Column:
    return F.length(F.translate(text, chars, ""))


def measure(docs: DataFrame, text: str = "text") -> DataFrame:
    """Adds the measures to ``docs``.

    Windows are compared by a 64-bit hash within one text: two different windows of a text of
    a million words meet with a chance of about 3e-8. Sorting makes the count n log n.
    """
    kept = docs.select(*beside(docs, *MEASURES, "rule_bits"))
    prefix = "_qr_"
    while any(c.lower().startswith(prefix) for c in kept.columns):
        prefix = "_" + prefix
    t, w, h, p, q = (f"{prefix}{x}" for x in "twhpq")
    hashed = F.expr(
        f"transform(sequence(0, size({w}) - {WINDOW}), i -> xxhash64(" + ", ".join(f"{w}[i + {k}]" for k in range(WINDOW)) + "))"
    )
    any_twice = F.expr(f"size({h}) > 1 AND size(array_distinct({h})) < size({h})")
    placed = F.expr(f"sort_array(transform({h}, (x, i) -> struct(x AS x, i AS i)))")
    twice = F.expr(f"transform(filter({p}, (e, j) -> get({p}, j - 1).x <=> e.x OR get({p}, j + 1).x <=> e.x), e -> e.i)")
    covered = F.expr(
        f"aggregate(sort_array({q}), struct({-WINDOW} AS at, 0L AS n), (a, i) -> struct(i AS at, a.n + least({WINDOW}, i - a.at) AS n), a -> a.n)"
    )
    # Zero, but not deterministic: a filter on the measures would otherwise be pushed below them, with
    # every array written out inside the lambdas that read it.
    barrier = F.least(F.spark_partition_id(), F.lit(0))
    lines = F.filter(F.split(F.col(t), "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    return (
        kept.withColumn(t, F.coalesce(named(docs, text).cast("string"), F.lit("")))
        .withColumn(w, words(F.col(t)))
        .withColumn(h, F.when(F.size(w) >= WINDOW, hashed))
        .withColumn(p, F.when(any_twice, placed))
        .withColumn(q, F.when(F.col(p).isNotNull(), twice))
        .withColumn(prefix + "l", lines)
        .select(
            *(named(kept, c) for c in kept.columns),
            F.size(w).cast("long").alias("n_words"),
            _without(F.col(t), BLANKS).cast("long").alias("word_chars"),
            (F.length(t) - _without(F.col(t), SYMBOLS)).cast("long").alias("n_symbols"),
            (F.size(prefix + "l") - F.size(F.array_distinct(prefix + "l"))).cast("long").alias("n_dup_lines"),
            (F.coalesce(covered, F.lit(0)).cast("long") + barrier).alias("n_repeat_words"),
        )
    )


def ledger(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` with the measures and ``rule_bits``: bit b is set if the rule with bit b failed."""
    bits = " + ".join(f"CASE WHEN {r.fails} THEN {1 << r.bit}L ELSE 0L END" for r in RULES)
    return measure(docs, text).withColumn("rule_bits", F.expr(bits))


def verdict(policy: str = DEFAULT_POLICY, bits: str = "rule_bits") -> Column:
    """True if no rule of the policy failed."""
    return F.col(bits).bitwiseAND(F.lit(mask_of(POLICIES[policy]))) == 0


def ablation(led: DataFrame, policy: str = DEFAULT_POLICY) -> DataFrame:
    """For each rule of a policy: documents it fails, fails alone, and kept without it.

    The ledger is reduced to counts of distinct masks first, at most two to the number of rules.
    """
    full = mask_of(POLICIES[policy])
    masks = led.groupBy(F.col("rule_bits").bitwiseAND(F.lit(full)).alias("m")).agg(F.count("*").alias("n"))
    names = F.explode(F.array(*(F.struct(F.lit(r.name).alias("rule"), F.lit(1 << r.bit).cast("long").alias("b")) for r in RULES if r.name in POLICIES[policy])))
    each = masks.withColumn("r", names).select("m", "n", "r.rule", "r.b")
    failed, alone = F.col("m").bitwiseAND(F.col("b")) != 0, F.col("m") == F.col("b")
    total = lambda when: F.coalesce(F.sum(F.when(when, F.col("n"))), F.lit(0)).cast("long")
    return each.groupBy("rule").agg(
        total(failed).alias("n_failed"), total(alone).alias("n_failed_alone"), total((F.col("m") == 0) | alone).alias("n_kept_without")
    )


def digest(docs: DataFrame) -> DataFrame:
    """The query's columns, of the default policy."""
    led = ledger(docs.select("doc_id", "text"))
    base = F.col("rule_bits").bitwiseAND(F.lit(mask_of(BASE))) != 0
    return led.select("doc_id", *MEASURES, base.alias("base_failed"), (~base & verdict()).alias("kept"), "rule_bits")


def keep(docs: DataFrame, policy: str = DEFAULT_POLICY) -> DataFrame:
    """The documents that a policy keeps, with the columns they came with."""
    led = ledger(docs.select(F.col("text").alias("_text"), packed(docs).alias("_doc")), "_text")
    return led.where(verdict(policy)).select("_doc.*")


def ablation_report(docs: DataFrame) -> DataFrame:
    """Ablations of the default policy over all documents: policy, rule, n_failed, n_failed_alone, n_kept_without."""
    return ablation(ledger(docs.select("doc_id", "text"))).select(F.lit(DEFAULT_POLICY).alias("policy"), "*")


ORACLE = r"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT doc_id, t, list_filter(regexp_split_to_array(t, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM d),
pos AS (SELECT doc_id, unnest(range(1, len(ws) - 3)) AS i, ws FROM w WHERE len(ws) >= 5),
win AS (SELECT doc_id, i, array_to_string(ws[i:i + 4], ' ') AS g FROM pos),
dup AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM win) WHERE c > 1),
cov AS (SELECT doc_id, count(DISTINCT j) AS n FROM (SELECT doc_id, unnest(range(i, i + 5)) AS j FROM dup) GROUP BY doc_id),
m AS (
  SELECT w.doc_id, len(ws)::BIGINT AS n_words,
    length(regexp_replace(t, '[\x20\x09-\x0D]', '', 'g'))::BIGINT AS word_chars,
    (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
    (len(list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')))
      - len(list_distinct(list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')))))::BIGINT AS n_dup_lines,
    coalesce(cov.n, 0)::BIGINT AS n_repeat_words
  FROM w LEFT JOIN cov ON w.doc_id = cov.doc_id),
b AS (SELECT *, (CASE WHEN n_words < 10 THEN 1 ELSE 0 END + CASE WHEN 100 * n_repeat_words > 20 * n_words THEN 2 ELSE 0 END
  + CASE WHEN 2 * n_symbols > n_words THEN 4 ELSE 0 END + CASE WHEN word_chars > 40 * n_words THEN 8 ELSE 0 END
  + CASE WHEN word_chars < 2 * n_words THEN 16 ELSE 0 END
  + CASE WHEN n_dup_lines > 30 AND 20 * n_dup_lines > n_words THEN 32 ELSE 0 END)::BIGINT AS rule_bits FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, rule_bits & 3 <> 0 AS base_failed, rule_bits & 55 = 0 AS kept, rule_bits FROM b
"""

#: Ablations by judging every document anew without each rule.
ABLATION_ORACLE = (
    f"WITH l AS ({ORACLE}), p(rule, bit) AS (VALUES "
    + ", ".join(f"('{r.name}', {1 << r.bit})" for r in RULES if r.name in POLICIES[DEFAULT_POLICY])
    + f") SELECT '{DEFAULT_POLICY}' AS policy, rule, count(*) FILTER (rule_bits & bit <> 0)::BIGINT AS n_failed, "
    f"count(*) FILTER (rule_bits & bit <> 0 AND rule_bits & ({mask_of(POLICIES[DEFAULT_POLICY])} - bit) = 0)::BIGINT AS n_failed_alone, "
    f"count(*) FILTER (rule_bits & ({mask_of(POLICIES[DEFAULT_POLICY])} - bit) = 0)::BIGINT AS n_kept_without FROM l, p GROUP BY rule"
)
