"""The whole selection as one plan, with its ablations."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import signals as S
from ..operators.cutoff import top_n
from ..operators.difficulty import curriculum_order, select_hard, with_difficulty
from ..operators.polarity import first_stage, orient_pairs

PRESETS = ("none", "r_ad_no_reversal", "r_ad_only", "ang_only", "full")
OUT = ("pair_id", "gap", "phi", "flipped", "ang", "position")


def select_pairs(
    signals: DataFrame,
    tau: float = 20.0,
    n: int | None = None,
    percent: float | None = 50.0,
    reversal: bool = True,
    stage1: str = "r_ad",
    stage1_n: int | None = None,
    order: str = "easy_first",
) -> DataFrame:
    """Clear pairs, oriented, the hardest of them, in learning order.

    Only ids and numbers go through the funnel; texts are joined to the result by ``with_texts``.
    """
    good = S.usable(signals)
    if stage1 == "r_ad":
        clear = orient_pairs(good, tau, reversal)
    else:
        kept = first_stage(good, stage1, stage1_n if stage1_n is not None else good.count() // 2)
        clear = kept.withColumns({"gap": S.polarity_gap_micro(), "phi": F.when(F.col("flipped"), -1).otherwise(1).cast("tinyint")})
    hard = select_hard(clear, n=n, percent=None if n is not None else percent)
    return curriculum_order(hard, order).select(*OUT)


def preset(signals: DataFrame, name: str, tau: float = 20.0, percent: float = 50.0) -> DataFrame:
    """A named ablation of the method: pairs with their signals, oriented where the preset orients."""
    good = S.usable(signals)
    if name == "none":
        return good.withColumn("flipped", F.lit(False))
    if name == "ang_only":
        scored = with_difficulty(good).withColumn("flipped", F.lit(False))
        return top_n(scored, F.col("ang"), max(1, int(good.count() * percent // 100)))
    clear = orient_pairs(good, tau, reversal=name != "r_ad_no_reversal")
    return select_hard(clear, percent=percent) if name == "full" else clear


def with_texts(selection: DataFrame, pairs: DataFrame) -> DataFrame:
    """Texts for the selected ids, exchanged where the pair was turned round; the only step that reads them."""
    found = selection.join(pairs.select("pair_id", "prompt", "chosen", "rejected"), "pair_id")
    turn = lambda a, b: F.when(F.col("flipped"), F.col(b)).otherwise(F.col(a))
    return found.withColumns({"chosen": turn("chosen", "rejected"), "rejected": turn("rejected", "chosen")})
