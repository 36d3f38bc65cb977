"""Mixing sources to target weights: raked cell weights, then a calibrated sample of documents.

Documents fall into cells by source, language and topic.  Iterative proportional fitting scales the cells'
tokens until the marginals of all three meet their targets.  A cell's rate is its raked weight by its
tokens; a document's probability is that rate by one factor, 1 at most, and the factor is solved from the
sorted rates so that the expected tokens equal the budget.  Rounds go on until every marginal meets its target to
``tolerance``; where they never do, since the targets contradict each other, a warning names what is missed.  A document is drawn where a hash of its id,
read as a number in [0, 1), is less than its probability: the draw needs no state and repeats exactly.

Targets without a given share follow ``tokens ^ temper`` of the input's own marginal.  Cells are few (their
number is that of value combinations, not of documents), so that raking runs in one task over them; they are
broadcast where their number is checked to be small and joined by shuffle beyond that.

DataFrame functions only.  Defined cases: a null source, language or topic is a value of its own; a null or
empty text has no tokens and the probability of its cell; repeated rows share their draw; a budget of the
input's tokens or more keeps all; other columns pass through untouched; an empty table gives an empty result.
"""

from __future__ import annotations

import warnings
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import documents, saved
from .rules import WS_CLASS

MARGINS = ("source", "lang", "topic")
FEW_CELLS = 20_000


@dataclass(frozen=True)
class Mixture:
    """Share of the tokens to keep, tempering of targets that aren't given, given shares, least and most rounds, seed, and
    the share of all tokens by which a marginal may miss its target."""

    fraction: float = 0.7
    temper: float = 0.5
    given: dict[str, dict[str, float]] = field(default_factory=dict)
    rounds: int = 30
    seed: int = 17
    most: int = 300
    tolerance: float = 1e-6


def topic_of(text: Column, words: Column) -> Column:
    """A coarse kind of content from its form, for inputs without a topic column."""
    less = lambda chars: F.length(text) - F.length(F.translate(text, chars, ""))
    return F.when(words < 50, "short").when(20 * less("|") > words, "table").when(5 * less("#*$%&<>!") > words, "signs").when(words >= 1000, "long").otherwise("prose")


def measured(docs: DataFrame) -> DataFrame:
    """``docs`` with ``_tokens`` and the three cell columns ``_source``, ``_lang``, ``_topic``."""
    text = F.coalesce("text", F.lit(""))
    out = docs.withColumn("_tokens", F.size(F.array_remove(F.split(text, WS_CLASS), "")).cast("long"))
    topic = F.col("topic").cast("string") if "topic" in docs.columns else topic_of(text, F.col("_tokens"))
    return out.withColumns({"_source": F.coalesce(F.col("source").cast("string"), F.lit("")), "_lang": F.coalesce(F.col("lang").cast("string"), F.lit("")), "_topic": F.coalesce(topic, F.lit(""))})


def raked(cells: DataFrame, how: Mixture) -> DataFrame:
    """Cells with ``weight``: tokens scaled to the target marginals, summing to the input's tokens."""
    one = cells.where("tokens > 0").coalesce(1)  # cells, not documents
    over = {m: Window.partitionBy(f"_{m}") for m in MARGINS}
    for m in MARGINS:
        own = F.sum("tokens").over(over[m])
        ask = F.pow(own, F.lit(how.temper))
        if how.given.get(m):
            shares = F.create_map(*[F.lit(x) for kv in how.given[m].items() for x in kv])
            ask = F.coalesce(shares[F.col(f"_{m}")], F.lit(0.0)).cast("double")
        # Each value's target stands once in the total, however many cells it has.
        one = one.withColumn("_ask", ask).withColumn("_n", F.count(F.lit(1)).over(over[m]))
        one = one.withColumn(f"want_{m}", F.col("_ask") / F.sum(F.col("_ask") / F.col("_n")).over(Window.partitionBy(F.lit(0)))).drop("_ask", "_n")
    one = one.withColumn("_all", F.sum("tokens").over(Window.partitionBy(F.lit(0))).cast("double")).withColumn("weight", F.col("tokens").cast("double"))
    done, missed = 0, 1.0
    while done < how.rounds or (missed > how.tolerance and done < how.most):
        for _ in range(min(10, how.rounds - done) if done < how.rounds else 10):
            done += 1
            for m in MARGINS:
                one = one.withColumn("weight", F.when(F.col("weight") > 0, F.col("weight") * F.col(f"want_{m}") * F.col("_all") / F.sum("weight").over(over[m])).otherwise(0.0))
        one = saved(one, "raked").coalesce(1)
        if done >= how.rounds:
            missed = residual(one)
    if missed > how.tolerance:
        warnings.warn(f"after {done} rounds a marginal misses its target by {missed:.2g} of all tokens: the targets may contradict each other", stacklevel=2)
    return one.drop("_all")


def residual(cells: DataFrame) -> float:
    """The most by which a value's weight misses its target, as a share of all tokens."""
    worst = [cells.groupBy(f"_{m}").agg(F.abs(F.sum("weight") / F.first("_all") - F.first(f"want_{m}")).alias("miss")) for m in MARGINS]
    return max((df.agg(F.max("miss")).first()[0] or 0.0) for df in worst)


def calibrated(cells: DataFrame, fraction: float) -> DataFrame:
    """Cells with ``probability``: min(1, factor * weight / tokens), expected tokens equal to the budget."""
    whole = Window.partitionBy(F.lit(0))
    down = whole.orderBy(F.col("rate").desc(), *[f"_{m}" for m in MARGINS])
    ranked = cells.withColumn("rate", F.col("weight") / F.col("tokens"))
    before = down.rowsBetween(Window.unboundedPreceding, -1)
    ranked = ranked.withColumns({"_budget": F.sum("tokens").over(whole) * F.lit(float(fraction)), "_full": F.coalesce(F.sum("tokens").over(before), F.lit(0)), "_rest": F.sum("weight").over(down.rowsBetween(Window.currentRow, Window.unboundedFollowing))})
    # With the cells before this one at 1, the factor that spends what is left of the budget.
    ranked = ranked.withColumn("_factor", F.when(F.col("_rest") > 0, (F.col("_budget") - F.col("_full")) / F.col("_rest")))
    # The first cell whose factor doesn't lift its own rate above 1 ends the cells at 1.
    factor = F.min(F.when(F.col("_factor") * F.col("rate") <= 1, F.struct(F.col("_full").alias("full"), F.col("_factor").alias("factor")))).over(whole)
    ranked = ranked.withColumn("_cut", factor)
    p = F.when(F.col("_cut").isNull() | (F.col("_full") < F.col("_cut.full")), 1.0).otherwise(F.least(F.lit(1.0), F.greatest(F.lit(0.0), F.col("_cut.factor") * F.col("rate"))))
    return ranked.withColumn("probability", p).drop("_budget", "_full", "_rest", "_factor", "_cut")


def drawn(doc_id: Column, seed: int) -> Column:
    """A number in [0, 1) from the id: 48 bits of an MD5."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.lit("mix"), F.lit(str(seed)), F.coalesce(doc_id.cast("string"), F.lit("")))), 1, 12), 16, 10).cast("double") / float(1 << 48)


def mixed(docs: DataFrame, how: Mixture = Mixture()) -> DataFrame:
    """``docs`` with _tokens, the cell columns, ``_weight`` by token, ``_probability`` and ``_sampled``."""
    rows = measured(docs)
    cells = saved(rows.groupBy(*[f"_{m}" for m in MARGINS]).agg(F.sum("_tokens").alias("tokens")), "cells")
    fitted = saved(calibrated(raked(cells, how), how.fraction), "fitted")
    # Cells without tokens weigh nothing and cost nothing.
    full = cells.select(*[f"_{m}" for m in MARGINS]).join(fitted, [f"_{m}" for m in MARGINS], "left").select(*[f"_{m}" for m in MARGINS], F.coalesce("rate", F.lit(0.0)).alias("_weight"), F.coalesce("probability", F.lit(float(min(1.0, how.fraction)))).alias("_probability"))
    if cells.count() <= FEW_CELLS:
        full = F.broadcast(full)
    return rows.join(full, [f"_{m}" for m in MARGINS]).withColumn("_sampled", drawn(F.col("doc_id"), how.seed) < F.col("_probability"))


def sampled(docs: DataFrame, how: Mixture = Mixture()) -> DataFrame:
    """The drawn documents with the columns of ``docs``."""
    own = ["doc_id", "text", "source", "lang", *[c for c in docs.columns if c == "topic"]]
    packed = docs.select(*own, F.struct("*").alias("_row"))  # other columns can't clash
    return mixed(packed, how).where("_sampled").select("_row.*")


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixed(documents(spark, sf_dir)).select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.col("_source").alias("source"),
        F.col("_lang").alias("lang"),
        F.col("_topic").alias("topic"),
        F.col("_tokens").alias("n_tokens"),
        F.round("_weight", 6).alias("weight"),
        F.round("_probability", 6).alias("probability"),
        F.col("_sampled").alias("sampled"),
    )


def _oracle(how: Mixture = Mixture()) -> str:
    cut = r"[\x20\x09-\x0D]+"
    less = lambda chars: f"(length(t) - length(regexp_replace(t, '[{chars}]', '', 'g')))"
    steps, last = [], "w0"
    for i in range(how.rounds):
        for m in MARGINS:
            name = f"w{i + 1}_{m}"
            steps.append(f"{name} AS MATERIALIZED (SELECT * REPLACE (weight * want_{m} * total / sum(weight) OVER (PARTITION BY {m}) AS weight) FROM {last})")
            last = name
    wants = ", ".join(f"(SELECT pow(sum(tokens), {how.temper}) FROM cells c WHERE c.{m} = cells.{m}) / (SELECT sum(s) FROM (SELECT pow(sum(tokens), {how.temper}) AS s FROM cells GROUP BY {m})) AS want_{m}" for m in MARGINS)
    return rf"""
WITH base AS (
  SELECT CAST(doc_id AS BIGINT) AS doc_id, coalesce(source, '') AS source, coalesce(lang, '') AS lang, coalesce(text, '') AS t,
         len(list_filter(regexp_split_to_array(coalesce(text, ''), '{cut}'), lambda x: x <> '')) AS n_tokens FROM documents),
rows_ AS (
  SELECT doc_id, source, lang, n_tokens,
         CASE WHEN n_tokens < 50 THEN 'short' WHEN 20 * {less("|")} > n_tokens THEN 'table'
              WHEN 5 * {less("#*$%&<>!")} > n_tokens THEN 'signs' WHEN n_tokens >= 1000 THEN 'long' ELSE 'prose' END AS topic FROM base),
all_cells AS (SELECT source, lang, topic, sum(n_tokens) AS tokens FROM rows_ GROUP BY ALL),
cells AS MATERIALIZED (SELECT * FROM all_cells WHERE tokens > 0),
w0 AS MATERIALIZED (SELECT *, CAST(tokens AS DOUBLE) AS weight, CAST((SELECT sum(tokens) FROM cells) AS DOUBLE) AS total, {wants} FROM cells),
{", ".join(steps)},
ranked AS (SELECT *, weight / tokens AS rate FROM {last}),
summed AS (
  SELECT *, {how.fraction} * total AS budget,
         coalesce(sum(tokens) OVER (ORDER BY rate DESC, source, lang, topic ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS filled,
         sum(weight) OVER (ORDER BY rate DESC, source, lang, topic ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS rest FROM ranked),
factors AS (SELECT *, (budget - filled) / rest AS factor FROM summed),
cut AS (SELECT min(filled) AS filled, arg_min(factor, filled) AS factor FROM factors WHERE factor * rate <= 1),
fitted AS (
  SELECT f.source, f.lang, f.topic, f.rate,
         CASE WHEN c.filled IS NULL OR f.filled < c.filled THEN 1.0 ELSE least(1.0, greatest(0.0, c.factor * f.rate)) END AS probability
  FROM factors f, cut c)
SELECT r.doc_id, r.source, r.lang, r.topic, CAST(r.n_tokens AS BIGINT) AS n_tokens, round(coalesce(f.rate, 0.0), 6) AS weight,
       round(coalesce(f.probability, {min(1.0, how.fraction)}), 6) AS probability,
       CAST(CAST('0x' || substr(md5('mix:{how.seed}:' || r.doc_id), 1, 12) AS BIGINT) AS DOUBLE) / {1 << 48} < coalesce(f.probability, {min(1.0, how.fraction)}) AS sampled
FROM rows_ r LEFT JOIN fitted f ON f.source = r.source AND f.lang = r.lang AND f.topic = r.topic"""


ORACLES = {"op9_mixing": _oracle()}
QUERIES: dict[str, Callable] = {"op9_mixing": op9_mixing}
