"""Quality rules as a ledger of bits: every rule is evaluated once, policies and ablations only read bits.

``ledger`` measures each text once and stores the measurements beside one integer in which bit i says that
rule i failed.  A policy is a named, versioned mask: a document is kept where no bit of the mask is set.
``ablation`` tells for each policy and each of its rules how many documents that rule alone removes, by
bitwise aggregation over (mask value, count), so that no text is read again.

All of it is DataFrame functions: no Python runs on the executors and nothing is shuffled for the ledger.

Defined cases: a null or empty text has zero words and fails the rules on too little text; repeated rows
are judged one by one; other columns pass through ``ledger`` untouched unless they bear the name of one of
its measurements, in which case the measurement takes their place; an empty table gives an empty ledger.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents

# White space of the contract, and its symbols.
WS_CLASS = "[ \\t\\n\\x0B\\f\\r]+"
WS_CHARS = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(text, WS_CLASS), "")


def _pick(words: Column, i: Column, k: int) -> Column:
    return F.concat_ws(" ", *[F.element_at(words, i + j) for j in range(1, k + 1)])


@dataclass(frozen=True)
class Rule:
    """``fails`` is a Spark SQL condition over the measurements."""

    name: str
    fails: str


#: The order fixes the bits; rules are only ever added at the end.
RULES = (
    Rule("few_words", "n_words < 50"),
    Rule("repeated_words", "100 * n_repeat_words > 50 * n_words"),
    Rule("many_symbols", "100 * n_symbols > 40 * n_words"),
    Rule("repeated_lines", "100 * n_dup_lines > 60 * n_lines AND n_lines >= 4"),
    Rule("word_length", "n_words > 0 AND (word_chars < 2 * n_words OR word_chars > 25 * n_words)"),
    Rule("shouting", "100 * n_upper > 70 * word_chars AND n_words > 0"),
    Rule("no_text", "n_words = 0"),
)
BIT = {r.name: 1 << i for i, r in enumerate(RULES)}

#: Name and version to the rules that count.
POLICIES = {
    "base@1": ("few_words", "repeated_words"),
    "default@1": ("few_words", "repeated_words", "many_symbols", "word_length", "shouting", "no_text"),
    "strict@1": tuple(BIT),
}
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper")


def mask_of(policy: str) -> int:
    return sum(BIT[name] for name in POLICIES[policy])


def ledger(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` without the text, with the measurements and ``failures``."""
    t = F.coalesce(F.col(text), F.lit(""))
    keep = [c for c in docs.columns if c not in (*MEASURES, "failures", text)]
    row = [F.struct(*keep).alias("_row")] if keep else []  # other columns can't clash
    cut = docs.select(*row, t.alias("_t")).withColumn("_w", words_of(F.col("_t")))
    lines = F.filter(F.split(F.col("_t"), "\n"), lambda x: x.rlike("[^ \\t\\x0B\\f\\r]"))
    k = 3
    n_windows = F.size("_w") - (k - 1)
    windows = F.when(n_windows > 1, F.transform(F.sequence(F.lit(0), n_windows - 1), lambda i: _pick(F.col("_w"), i, k)))
    cut = cut.withColumns({"_l": lines, "_g": windows})
    # Only texts with a repeated window have their windows sorted.
    again = F.size(F.array_distinct("_g")) < F.size("_g")
    cut = cut.withColumn("_s", F.when(again, F.sort_array(F.transform("_g", lambda x, i: F.struct(x.alias("w"), i.alias("at"))))))
    marked = F.filter("_s", lambda x, i: F.get(F.col("_s"), i - 1)["w"].eqNullSafe(x["w"]) | F.get(F.col("_s"), i + 1)["w"].eqNullSafe(x["w"]))
    cut = cut.withColumn("_p", F.sort_array(F.transform(marked, lambda x: x["at"])))
    gaps = F.transform("_p", lambda p, i: F.least(F.lit(k), F.coalesce(F.get(F.col("_p"), i + 1) - p, F.lit(k))))
    plain = F.translate("_t", WS_CHARS, "")
    measured = cut.select(
        *(["_row.*"] if keep else []),
        F.size("_w").cast("long").alias("n_words"),
        F.length(plain).cast("long").alias("word_chars"),
        (F.length(plain) - F.length(F.translate(plain, SYMBOLS, ""))).cast("long").alias("n_symbols"),
        (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"),
        F.coalesce(F.aggregate(gaps, F.lit(0), lambda a, x: a + x), F.lit(0)).cast("long").alias("n_repeat_words"),
        F.size("_l").cast("long").alias("n_lines"),
        (F.length(plain) - F.length(F.translate(plain, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", ""))).cast("long").alias("n_upper"),
    )
    bits = " | ".join(f"IF({r.fails}, {BIT[r.name]}L, 0L)" for r in RULES)
    # Nought, but not a constant to the optimiser: filters above stay above, where they read the measured columns
    # and don't repeat the array work.
    return measured.withColumn("failures", F.expr(bits).bitwiseOR(F.monotonically_increasing_id() * F.lit(0)))


def apply_policy(found: DataFrame, policy: str, name: str = "kept") -> DataFrame:
    return found.withColumn(name, F.col("failures").bitwiseAND(F.lit(mask_of(policy))) == 0)


def ablation(found: DataFrame, policies: tuple[str, ...] = tuple(POLICIES)) -> DataFrame:
    """Per policy and rule: documents that fail it, that only it removes, and that the policy keeps without it.

    Rows are first counted per value of ``failures`` (2^rules values at most); all else reads those counts.
    """
    spark = found.sparkSession
    counts = found.groupBy("failures").agg(F.count(F.lit(1)).alias("n"))
    asked = spark.createDataFrame([(p, mask_of(p), r, BIT[r]) for p in policies for r in POLICIES[p]], "policy string, mask long, rule string, bit long")
    on = lambda x: F.col("failures").bitwiseAND(x)
    return (
        counts.join(F.broadcast(asked))  # masks of a fixed, small number
        .groupBy("policy", "rule")
        .agg(
            F.sum(F.when(on(F.col("bit")) != 0, F.col("n")).otherwise(0)).alias("n_failed"),
            F.sum(F.when(on(F.col("mask")) == F.col("bit"), F.col("n")).otherwise(0)).alias("n_only_this"),
            F.sum(F.when(on(F.col("mask").bitwiseXOR(F.col("bit"))) == 0, F.col("n")).otherwise(0)).alias("n_kept_without"),
            F.sum(F.when(on(F.col("mask")) == 0, F.col("n")).otherwise(0)).alias("n_kept"),
        )
    )


def op7_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = apply_policy(ledger(documents(spark, sf_dir).select(F.col("doc_id").cast("long").alias("doc_id"), "text")), "default@1", "_kept")
    failed = F.col("failures").bitwiseAND(F.lit(mask_of("base@1"))) != 0
    return found.select("doc_id", *MEASURES[:5], failed.alias("base_failed"), (~failed & F.col("_kept")).alias("kept"), "failures")


_CUT = r"[\x20\x09-\x0D]+"
ORACLES = {
    "op7_rules": rf"""
WITH base AS (
  SELECT CAST(doc_id AS BIGINT) AS doc_id, coalesce(text, '') AS t,
         list_filter(regexp_split_to_array(coalesce(text, ''), '{_CUT}'), lambda x: x <> '') AS w,
         list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l
  FROM documents),
windows AS (
  SELECT doc_id, unnest(range(1, len(w) - 1)) AS pos, w FROM base WHERE len(w) >= 3),
grams AS (SELECT doc_id, pos, w[pos] || ' ' || w[pos + 1] || ' ' || w[pos + 2] AS g FROM windows),
repeated AS (SELECT doc_id, pos FROM (SELECT doc_id, pos, count(*) OVER (PARTITION BY doc_id, g) AS n FROM grams) WHERE n > 1),
covered AS (SELECT doc_id, count(DISTINCT pos + k) AS n FROM repeated, (SELECT unnest([0, 1, 2]) AS k) GROUP BY doc_id),
measured AS (
  SELECT b.doc_id, CAST(len(w) AS BIGINT) AS n_words,
         CAST(length(regexp_replace(t, '{_CUT}', '', 'g')) AS BIGINT) AS word_chars,
         CAST(length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
         CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines,
         CAST(coalesce(c.n, 0) AS BIGINT) AS n_repeat_words,
         CAST(len(l) AS BIGINT) AS n_lines,
         CAST(length(t) - length(regexp_replace(t, '[A-Z]', '', 'g')) AS BIGINT) AS n_upper
  FROM base b LEFT JOIN covered c ON c.doc_id = b.doc_id),
judged AS (
  SELECT *, {" + ".join(f"CASE WHEN {r.fails} THEN {BIT[r.name]} ELSE 0 END" for r in RULES)} AS failures FROM measured)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
       (failures & {mask_of("base@1")}) <> 0 AS base_failed,
       (failures & {mask_of("base@1") | mask_of("default@1")}) = 0 AS kept,
       CAST(failures AS BIGINT) AS failures
FROM judged"""
}
QUERIES: dict[str, Callable] = {"op7_rules": op7_rules}
