"""Signals of a pair, over the canonical columns in micro-nats.

``*_w`` belongs to the chosen response, ``*_l`` to the rejected one; ``ref``, ``pos`` and ``inv`` are sums of
token log-probabilities under the reference, the positive and the inverse policy; ``n`` counts tokens, ``len``
characters, ``ext`` is an external reward.  Columns named here are of double type and in nats unless said
otherwise; a null input gives a null signal.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .columns import MICRO, nats

SIDED = ("pos", "inv", "ref", "n", "len", "ext")
SIGNALS = "pair_id long, grp string, pos_w long, pos_l long, inv_w long, inv_l long, ref_w long, ref_l long, n_w int, n_l int, len_w int, len_l int, ext_w double, ext_l double"


def implicit_reward(policy: str, side: str) -> Column:
    return nats(F.col(f"{policy}_{side}") - F.col(f"ref_{side}"))


def implicit_margin(policy: str) -> Column:
    return nats((F.col(f"{policy}_w") - F.col("ref_w")) - (F.col(f"{policy}_l") - F.col("ref_l")))


def softplus(x: Column) -> Column:
    return F.greatest(x, F.lit(0.0)) + F.log1p(F.exp(-F.abs(x)))


def sigmoid(x: Column) -> Column:
    e = F.exp(-F.abs(x))
    return F.when(x >= 0, 1 / (1 + e)).otherwise(e / (1 + e))


def preference_probability(margin: Column, beta: float) -> Column:
    return sigmoid(margin * beta)


def pair_loss(margin: Column, beta: float, direction: str = "forward") -> Column:
    """Negative log of the preference probability; ``inverse`` exchanges the two responses."""
    sign = {"forward": -1.0, "inverse": 1.0}[direction]
    return softplus(margin * (sign * beta))


def preference_loss(df: DataFrame, policy: str, beta: float = 0.1, direction: str = "forward") -> DataFrame:
    return df.agg(F.avg(pair_loss(implicit_margin(policy), beta, direction)).alias("loss"), F.count(F.lit(1)).alias("n_pairs"))


def polarity_gap_micro() -> Column:
    """Margin of the positive policy less that of the inverse one, in micro-nats; the reference cancels, so none is read."""
    return (F.col("pos_w") - F.col("pos_l")) - (F.col("inv_w") - F.col("inv_l"))


def polarity_gap(form: str = "direct") -> Column:
    if form == "margins":
        return implicit_margin("pos") - implicit_margin("inv")
    return nats(polarity_gap_micro())


def avg_nll(side: str, model: str = "ref") -> Column:
    return F.try_divide(-nats(F.col(f"{model}_{side}")), F.col(f"n_{side}").cast("double"))


def nll_gap(model: str = "ref") -> Column:
    return avg_nll("w", model) - avg_nll("l", model)


def nll_gap_micro(model: str = "ref") -> Column:
    """The gap in whole micro-nats per token: an exact order for any engine."""
    return F.floor(nll_gap(model) * MICRO + 0.5).cast("long")


def perplexity(side: str, model: str = "ref") -> Column:
    return F.exp(avg_nll(side, model))


def ppl_gap(model: str = "ref") -> Column:
    return perplexity("w", model) - perplexity("l", model)


def external_margin() -> Column:
    return F.col("ext_w") - F.col("ext_l")


def external_reward(scores: DataFrame, dims: list[str] | None = None) -> DataFrame:
    """(pair_id, ext_w, ext_l): means over the judged dimensions of a long table (pair_id, side, dim, score)."""
    kept = scores.where(F.col("dim").isin(*dims)) if dims else scores
    side = lambda s: F.avg(F.when(F.col("side") == s, F.col("score"))).alias(f"ext_{s}")
    return kept.groupBy("pair_id").agg(side("w"), side("l"))


def sequence_scores(token_scores: DataFrame) -> DataFrame:
    """(pair_id, side, model, lp, n) from token log-probabilities in micro-nats."""
    return token_scores.groupBy("pair_id", "side", "model").agg(F.sum("lp").alias("lp"), F.count("lp").cast("int").alias("n"))


def kl_regularised_reward(df: DataFrame, policy: str, penalty: float) -> DataFrame:
    """Sample estimate of mean reward less the penalised divergence from the reference, over chosen responses."""
    return df.agg((F.avg("ext_w") - penalty * F.avg(implicit_reward(policy, "w"))).alias("objective"))


def usable(df: DataFrame) -> DataFrame:
    """Rows that selection can judge."""
    return df.where(quarantine_reason().isNull())


def quarantine_reason() -> Column:
    scores = [f"{m}_{s}" for m in ("pos", "inv", "ref") for s in "wl"]
    missing = F.lit(False)
    for c in scores:
        missing = missing | F.col(c).isNull()
    return F.when(F.col("pair_id").isNull(), "no id").when(missing, "log-probability missing").when((F.coalesce("n_w", F.lit(0)) <= 0) | (F.coalesce("n_l", F.lit(0)) <= 0), "empty response")


def quarantine(df: DataFrame) -> DataFrame:
    """Rows that selection can't judge, with the reason."""
    return df.withColumn("reason", quarantine_reason()).where("reason IS NOT NULL")
