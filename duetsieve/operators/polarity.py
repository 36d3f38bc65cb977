"""First stage: which pairs have a clear polarity, and which way it points."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import signals as S
from ..functions.columns import MICRO, portable_hash
from .cutoff import distributed_rank, top_n


def _tau_micro(tau: float) -> int:
    if not tau > 0:
        raise ValueError("tau must be above 0")
    return round(tau * MICRO)


def polarity_label(gap_micro: Column, tau: float) -> Column:
    """1 or -1 where the gap's size exceeds tau, else 0; null stays null."""
    t = _tau_micro(tau)
    return F.when(gap_micro > t, 1).when(gap_micro < -t, -1).when(gap_micro.isNotNull(), 0).cast("tinyint")


def labelled(df: DataFrame, tau: float) -> DataFrame:
    gap = S.polarity_gap_micro()
    return df.withColumns({"gap": gap, "phi": polarity_label(gap, tau)})


def swap_sides(df: DataFrame, where: Column) -> DataFrame:
    """Exchanges every sided column, and the texts, where the condition holds."""
    names = [n for n in S.SIDED if f"{n}_w" in df.columns and f"{n}_l" in df.columns]
    sides = [(f"{n}_w", f"{n}_l") for n in names] + [("chosen", "rejected")] * ("chosen" in df.columns)
    moved = {}
    for a, b in sides:
        moved[a] = F.when(where, F.col(b)).otherwise(F.col(a))
        moved[b] = F.when(where, F.col(a)).otherwise(F.col(b))
    return df.withColumns(moved)


def orient_pairs(df: DataFrame, tau: float, reversal: bool = True) -> DataFrame:
    """Clear pairs, those of inverse polarity turned round (or left out); row-local, one projection."""
    clear = labelled(df, tau).where("phi <> 0" if reversal else "phi = 1")
    return swap_sides(clear, F.col("phi") == -1).withColumn("flipped", F.col("phi") == -1)


def polarity_profile(df: DataFrame, tau: float) -> DataFrame:
    """Counts by group and label with subtotals."""
    return labelled(df, tau).rollup("grp", "phi").agg(F.count(F.lit(1)).alias("n_pairs"), F.grouping_id().alias("level"))


def tau_sweep(df: DataFrame, taus: list[float]) -> DataFrame:
    """Kept, turned and dropped pairs of every tau in one pass."""
    gap = S.polarity_gap_micro()
    cells = []
    for tau in taus:
        t = _tau_micro(tau)
        cells.append(F.struct(F.lit(float(tau)).alias("tau"), F.count_if(gap > t).alias("kept"), F.count_if(gap < -t).alias("flipped"), F.count_if(F.abs(gap) <= t).alias("dropped")))
    return df.agg(F.array(*cells).alias("rows")).select(F.inline("rows"))


def tau_grid(df: DataFrame, step: int) -> DataFrame:
    """Thresholds at which the number of kept pairs falls by ``step``: order statistics of the gap's size."""
    sized = df.select("pair_id", F.abs(S.polarity_gap_micro()).alias("size")).where("size IS NOT NULL")
    ranked = distributed_rank(sized, [F.col("size").desc(), F.col("pair_id").asc()])
    at = ranked.where((F.col("position") % step == 1) & (F.col("position") > 1)).select(F.col("position").alias("rank"), "size")
    # Ties at a threshold are dropped, so that fewer may be kept than asked for.
    kept = at.join(ranked.groupBy("size").agg(F.min("position").alias("first")), "size")
    return kept.select((F.col("rank") - 1).alias("asked"), (F.col("first") - 1).alias("retained"), F.col("size").alias("tau_micro"))


FIRST_STAGE = {
    "r_ad": lambda: S.polarity_gap_micro(),
    "pim": lambda: F.col("pos_w") - F.col("ref_w") - F.col("pos_l") + F.col("ref_l"),
    "iim": lambda: -(F.col("inv_w") - F.col("ref_w") - F.col("inv_l") + F.col("ref_l")),
    "em": lambda: F.floor(S.external_margin() * MICRO + 0.5).cast("long"),
}


def first_stage(df: DataFrame, by: str, n: int) -> DataFrame:
    """The n pairs of clearest polarity by one of the signals, turned round where it is negative."""
    score = FIRST_STAGE[by]()
    kept = top_n(df.withColumn("_s", score), F.abs("_s"), n)
    return swap_sides(kept, F.col("_s") < 0).withColumn("flipped", F.col("_s") < 0).drop("_s")


def half_sample(df: DataFrame, seed: int = 1) -> DataFrame:
    """A repeatable half of the pairs, by a hash of their ids."""
    return df.where(portable_hash(f"half:{seed}:", F.col("pair_id")) % 2 == 0)
