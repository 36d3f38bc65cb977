"""Second stage: of the clear pairs, those from which there is most to learn; and the order to learn them in."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import signals as S
from ..functions.columns import portable_hash
from .cutoff import distributed_rank, top_n, top_share


def with_difficulty(df: DataFrame, model: str = "ref") -> DataFrame:
    """``ang`` in whole micro-nats per token; pairs without tokens have none."""
    return df.withColumn("ang", S.nll_gap_micro(model))


def select_hard(df: DataFrame, n: int | None = None, percent: float | None = None, base: int | None = None) -> DataFrame:
    scored = with_difficulty(df)
    return top_n(scored, F.col("ang"), n) if n is not None else top_share(scored, F.col("ang"), percent or 50.0, base)


def calibrate(df: DataFrame, how: str, n: int, seed: int = 1) -> DataFrame:
    """n pairs by the hard, easy or random strategy."""
    scored = with_difficulty(df)
    if how == "random":
        return top_n(scored, portable_hash(f"order:{seed}:", F.col("pair_id")), n, ascending=True)
    return top_n(scored, F.col("ang"), n, ascending={"hard": False, "easy": True}[how])


def k_sweep(df: DataFrame, shares: list[int]) -> DataFrame:
    """Rows, least and mean difficulty kept at each share, from one ranking."""
    scored = with_difficulty(df).where("ang IS NOT NULL").select("pair_id", "ang", "flipped")
    ranked = distributed_rank(scored, [F.col("ang").desc(), F.col("pair_id").asc()])
    total = ranked.count()
    cells = []
    for k in shares:
        inside = F.col("position") <= max(1, total * k // 100)
        cells.append(F.struct(F.lit(k).alias("percent"), F.count_if(inside).alias("n_pairs"), F.min(F.when(inside, F.col("ang"))).alias("least_ang"), F.sum(F.when(inside, F.col("ang"))).alias("sum_ang"), F.count_if(inside & F.col("flipped")).alias("flipped")))
    return ranked.agg(F.array(*cells).alias("rows")).select(F.inline("rows"))


def contrast_profile(df: DataFrame, cut_w: float, cut_l: float) -> DataFrame:
    """Pairs by hard or easy chosen and rejected response, with all subtotals."""
    return df.select((S.avg_nll("w") > cut_w).alias("chosen_hard"), (S.avg_nll("l") > cut_l).alias("rejected_hard")).cube("chosen_hard", "rejected_hard").agg(F.count(F.lit(1)).alias("n_pairs"), F.grouping_id().alias("level"))


def curriculum_order(df: DataFrame, how: str, seed: int = 1) -> DataFrame:
    """``position`` 1..n: random, hard_first or easy_first."""
    order = {
        "random": [portable_hash(f"order:{seed}:", F.col("pair_id")).asc(), F.col("pair_id").asc()],
        "hard_first": [F.col("ang").desc(), F.col("pair_id").asc()],
        "easy_first": [F.col("ang").asc(), F.col("pair_id").asc()],
    }[how]
    return distributed_rank(df, order)
