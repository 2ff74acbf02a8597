"""Quality rules kept as a bitmask ledger, in built-in functions only.

Every rule is evaluated once per document.  The ledger row holds the measurements and one
failure bit per rule; a policy is a named, versioned mask over those bits, so applying another
policy or asking what a rule costs never reads the texts again.

Defined results: a null, empty or blank text has no words and fails ``few_words``.  Rows that
repeat stay as they are, one ledger row each.  An empty table gives an empty ledger.  Only
``doc_id`` and ``text`` are read (and only ``keep`` columns are carried), so extra columns with
clashing names do no harm.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from narrative_engine.llm.common import let, split_words, table

WINDOW = 5

#: Bit -> rule, over the measurements of :func:`measured`.  The first two are the base rules.
RULES: tuple[tuple[str, str], ...] = (
    ("few_words", "n_words < 10"),
    ("repeated_windows", "100 * n_repeat_words > 20 * n_words"),
    ("symbols", "10 * n_symbols > n_words"),
    ("shouting", "2 * n_upper > word_chars"),
    ("repeated_lines", "10 * n_dup_lines > 3 * n_lines"),
    ("long_words", "word_chars > 20 * n_words"),
    ("exclaiming", "3 * n_exclaim > n_words"),
)
BIT = {name: 1 << i for i, (name, _) in enumerate(RULES)}


@dataclass(frozen=True)
class Policy:
    name: str
    version: int
    rules: tuple[str, ...]

    @property
    def mask(self) -> int:
        return sum(BIT[r] for r in self.rules)


BASE = ("few_words", "repeated_windows")
POLICIES = (
    Policy("base", 1, BASE),
    Policy("prose", 1, (*BASE, "symbols", "repeated_lines")),
    Policy("prose", 2, tuple(BIT)),
)
PRODUCTION = POLICIES[-1]


def repeated_words(words: Column) -> Column:
    """How many words lie in a ``WINDOW``-word window that occurs twice or more in ``words``.

    Windows are compared by 64-bit hashes.  Most texts repeat none, which a distinct count
    shows; the others are sorted by (hash, place), and the covered places summed up.
    """

    def hashes(w: Column) -> Column:
        return F.transform(
            F.sequence(F.lit(0), F.size(w) - WINDOW),
            lambda i: F.xxhash64(*[F.get(w, i + k) for k in range(WINDOW)]),
        )

    def covered(places: Column) -> Column:
        steps = F.transform(places, lambda p, i: F.least(F.lit(WINDOW), F.coalesce(F.get(places, i + 1) - p, F.lit(WINDOW))))
        return F.aggregate(steps, F.lit(0), lambda acc, x: acc + x)

    def twice(ordered: Column) -> Column:
        same = F.filter(
            ordered,
            lambda x, i: (F.coalesce(F.get(ordered, i + 1)["h"] == x["h"], F.lit(False)))
            | (F.when(i > 0, F.get(ordered, i - 1)["h"] == x["h"]).otherwise(F.lit(False))),
        )
        return let(F.sort_array(F.transform(same, lambda x: x["at"])), covered)

    def count(h: Column) -> Column:
        pairs = F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("at")))
        return F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(let(F.sort_array(pairs), twice))

    return let(words, lambda w: F.when(F.size(w) < WINDOW, F.lit(0)).otherwise(let(hashes(w), count))).cast("long")


def measured(docs: DataFrame, *keep: str) -> DataFrame:
    """``doc_id``, the ``keep`` columns and the measurements of every document."""
    text = F.coalesce(F.col("text"), F.lit(""))
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike("[^ \\t-\\r]"))
    without = lambda chars: F.length(text) - F.length(F.regexp_replace(text, chars, ""))
    rows = docs.select(
        "doc_id",
        *keep,
        split_words(F.col("text")).alias("_words"),
        without("[#*$%&|<>]").cast("long").alias("n_symbols"),
        without("[A-Z]").cast("long").alias("n_upper"),
        without("!").cast("long").alias("n_exclaim"),
        let(lines, lambda x: F.struct(F.size(x).alias("all"), F.size(F.array_distinct(x)).alias("own"))).alias("_lines"),
    )
    return rows.select(
        "doc_id",
        *keep,
        F.size("_words").cast("long").alias("n_words"),
        F.length(F.array_join("_words", "")).cast("long").alias("word_chars"),
        "n_symbols",
        (F.col("_lines.all") - F.col("_lines.own")).cast("long").alias("n_dup_lines"),
        repeated_words(F.col("_words")).alias("n_repeat_words"),
        F.col("_lines.all").cast("long").alias("n_lines"),
        "n_upper",
        "n_exclaim",
        F.monotonically_increasing_id().alias("_row"),  # see passing()
    )


def ledger(docs: DataFrame, *keep: str) -> DataFrame:
    """Measurements plus ``fail_bits``: bit ``i`` is set when rule ``i`` fails."""
    bits = sum((F.when(F.expr(rule), F.lit(1 << i)).otherwise(F.lit(0)) for i, (_, rule) in enumerate(RULES)), F.lit(0))
    return measured(docs, *keep).withColumn("fail_bits", bits.cast("long"))


def verdict(policy: Policy = PRODUCTION) -> Column:
    return F.col("fail_bits").bitwiseAND(F.lit(policy.mask)) == 0


def passing(rows: DataFrame, policy: Policy = PRODUCTION) -> DataFrame:
    """Ledger rows that the policy keeps.

    The condition names the ledger's row number, which isn't deterministic, so the optimizer can't
    move the filter below the measurements and evaluate them once more for every rule.
    """
    return rows.where(verdict(policy) & (F.col("_row") >= 0))


def policy_report(rows: DataFrame, policies: tuple[Policy, ...] = POLICIES) -> DataFrame:
    """Documents seen, rejected and rejected by one rule alone, for each policy and rule.

    The ledger is first reduced to one count per bit pattern, at most 2^rules rows.
    """
    patterns = rows.groupBy("fail_bits").agg(F.count("*").alias("n"))
    known = [(p.name, p.version, p.mask, r, BIT[r]) for p in policies for r in p.rules]
    cases = F.explode(F.array(*[F.struct(*[F.lit(v).alias(k) for k, v in zip(("policy", "version", "mask", "rule", "bit"), c)]) for c in known]))
    failed = F.col("fail_bits").bitwiseAND(F.col("c.mask"))
    total = lambda cond: F.coalesce(F.sum(F.when(cond, F.col("n"))), F.lit(0)).cast("long")
    return (
        patterns.withColumn("c", cases)
        .groupBy(F.col("c.policy"), F.col("c.version"), F.col("c.rule"))
        .agg(
            F.sum("n").cast("long").alias("n_docs"),
            total(failed != 0).alias("n_rejected"),
            total(failed.bitwiseAND(F.col("c.bit")) != 0).alias("n_failing_rule"),
            total(failed == F.col("c.bit")).alias("n_only_by_rule"),
        )
    )


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = ledger(table(spark, sf_dir, "documents"))
    base = F.col("fail_bits").bitwiseAND(F.lit(BIT["few_words"] | BIT["repeated_windows"])) != 0
    return rows.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        base.alias("base_failed"), (~base & verdict()).alias("kept"), "n_lines", "n_upper", "n_exclaim", "fail_bits",
    )


ORACLE = r"""
WITH d AS (
  SELECT doc_id, coalesce(text, '') AS text, row_number() OVER () AS k,
         regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w,
         list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ln
  FROM documents),
p AS (SELECT k, unnest(range(1, len(w) - 3)) AS i, w FROM d WHERE len(w) >= 5),
g AS (SELECT k, i, count(*) OVER (PARTITION BY k, array_to_string(w[i:i+4], ' ')) AS c FROM p),
r AS (SELECT k, count(DISTINCT i + o) AS n FROM g, range(5) AS t(o) WHERE c > 1 GROUP BY k),
m AS (
  SELECT doc_id, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars,
         length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
         (len(ln) - len(list_distinct(ln)))::BIGINT AS n_dup_lines,
         coalesce(r.n, 0)::BIGINT AS n_repeat_words, len(ln)::BIGINT AS n_lines,
         length(regexp_replace(text, '[^A-Z]', '', 'g'))::BIGINT AS n_upper,
         length(regexp_replace(text, '[^!]', '', 'g'))::BIGINT AS n_exclaim
  FROM d LEFT JOIN r USING (k)),
b AS (
  SELECT *, ((n_words < 10)::BIGINT + 2 * (100 * n_repeat_words > 20 * n_words)::BIGINT + 4 * (10 * n_symbols > n_words)::BIGINT
    + 8 * (2 * n_upper > word_chars)::BIGINT + 16 * (10 * n_dup_lines > 3 * n_lines)::BIGINT
    + 32 * (word_chars > 20 * n_words)::BIGINT + 64 * (3 * n_exclaim > n_words)::BIGINT)::BIGINT AS fail_bits
  FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (fail_bits & 3) <> 0 AS base_failed,
       fail_bits = 0 AS kept, n_lines, n_upper, n_exclaim, fail_bits
FROM b
"""
