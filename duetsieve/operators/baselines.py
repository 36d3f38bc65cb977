"""The selectors that the two-stage method is compared with.  All keep n pairs, ties by pair_id; none turns pairs round."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import signals as S
from ..functions.columns import MICRO, portable_hash
from .cutoff import distributed_rank, top_n


def _whole(x: Column) -> Column:
    return F.floor(x * MICRO + 0.5).cast("long")


def baseline_full(df: DataFrame) -> DataFrame:
    return df


def baseline_init(df: DataFrame, measures: dict[str, str]) -> DataFrame:
    """Nothing is trained on: the reference stays as it is, and what it prefers is measured by group."""
    return df.groupBy("grp").agg(*[F.expr(x).alias(k) for k, x in measures.items()])


def by_external_margin(df: DataFrame, n: int) -> DataFrame:
    return top_n(df, _whole(S.external_margin()), n)


def by_implicit_margin(df: DataFrame, n: int, policy: str = "pos") -> DataFrame:
    return top_n(df, _whole(S.implicit_margin(policy)), n)


def by_ppl_gap(df: DataFrame, n: int) -> DataFrame:
    return top_n(df, F.round(S.ppl_gap(), 4), n)


def by_chosen_length(df: DataFrame, n: int) -> DataFrame:
    return top_n(df, F.col("len_w"), n)


def by_alignment_potential(df: DataFrame, n: int, mode: str = "abs_abs") -> DataFrame:
    """Size of the external margin less the implicit one's size (or its signed value)."""
    own = S.implicit_margin("pos")
    return top_n(df, _whole(F.abs(S.external_margin()) - (F.abs(own) if mode == "abs_abs" else own)), n)


def by_combined_margin(df: DataFrame, n: int, how: str = "zsum") -> DataFrame:
    """Both margins, standardised and added (zsum), as odds of two logistic probabilities (prob), or by the sum of their ranks (ranksum)."""
    if how not in ("zsum", "prob", "ranksum"):
        raise ValueError(f"no way to combine margins: {how}")
    im, em = S.implicit_margin("pos"), S.external_margin()
    if how == "ranksum":
        ranked = df
        for name, margin in (("_by_im", im), ("_by_em", em)):
            ranked = distributed_rank(ranked, [_whole(margin).asc(), F.col("pair_id").asc()], name)
        return top_n(ranked, F.col("_by_im") + F.col("_by_em"), n).drop("_by_im", "_by_em")
    if how == "prob":
        return top_n(df, F.round(im + em, 6), n)  # the log odds of independent logistic probabilities add up
    stats = df.agg(F.avg(im).alias("im_mean"), F.stddev_pop(im).alias("im_sd"), F.avg(em).alias("em_mean"), F.stddev_pop(em).alias("em_sd")).first()
    z = lambda x, m, sd: (x - F.lit(stats[m])) / F.lit(stats[sd] or 1.0)
    return top_n(df, F.round(z(im, "im_mean", "im_sd") + z(em, "em_mean", "em_sd"), 6), n)


def by_rejected_length(df: DataFrame, n: int, floor: float | None = None) -> DataFrame:
    """Longest rejected responses among pairs whose external margin reaches the floor (its median by default)."""
    margin = _whole(S.external_margin())
    if floor is None:
        cut = df.agg(F.percentile_approx(margin, 0.5, 1_000_000)).first()[0] or 0
    else:
        cut = round(floor * MICRO)
    return top_n(df.where(margin >= cut), F.col("len_l"), n)


def by_ensemble_easiness(df: DataFrame, losses: DataFrame, n: int) -> DataFrame:
    """Pairs of the smallest mean loss over the models that have not seen them; ``losses``: pair_id, model, seen, loss in micro units."""
    mean = losses.where("NOT seen").groupBy("pair_id").agg(F.floor(F.sum("loss") / F.count(F.lit(1))).cast("long").alias("mean_loss"))
    return top_n(df.join(mean, "pair_id"), F.col("mean_loss"), n, ascending=True)


def by_random(df: DataFrame, n: int, seed: int = 1) -> DataFrame:
    return top_n(df, portable_hash(f"order:{seed}:", F.col("pair_id")), n, ascending=True)


def formula_blend(k: int) -> float:
    return (k % 3) / 4 + (k // 3) / 8


def formula_losses(df: DataFrame, models: int = 6, beta: float = 0.1) -> DataFrame:
    """Losses of stand-in reference models, for pairs without text: two halves by three seeds, no two of one formula."""
    rows = []
    m_pos, m_inv = S.implicit_margin("pos"), S.implicit_margin("inv")
    for k in range(models):
        margin = m_pos - m_inv * formula_blend(k)
        seen = portable_hash("half:ensemble:", F.col("pair_id")) % 2 == k // 3 % 2
        rows.append(F.struct(F.lit(k).alias("model"), seen.alias("seen"), _whole(S.pair_loss(margin, beta)).alias("loss")))
    return df.select("pair_id", F.inline(F.array(*rows)))
