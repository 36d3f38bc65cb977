"""Looking at selections: distributions, overlaps, sensitivities, squeezing."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import signals as S


def histogram(df: DataFrame, value: Column, width: float, *by: str) -> DataFrame:
    return df.where(value.isNotNull()).groupBy(*by, (F.floor(value / width) * F.lit(width)).cast("double").alias("bin")).agg(F.count(F.lit(1)).alias("n"))


def margin_joint(df: DataFrame, width: float) -> DataFrame:
    cell = lambda m: (F.floor(S.implicit_margin(m) / width) * width).cast("double").alias(f"{m}_bin")
    return df.groupBy(cell("pos"), cell("inv")).agg(F.count(F.lit(1)).alias("n"))


def compare_distribution(before: DataFrame, after: DataFrame, value: Column, width: float) -> DataFrame:
    """Binned shares before and after, their cumulative shares and the running Kolmogorov-Smirnov distance."""
    from pyspark.sql import Window

    count = lambda df, name: histogram(df, value, width).withColumnRenamed("n", name)
    both = count(before, "n_before").join(count(after, "n_after"), "bin", "full").na.fill(0, ["n_before", "n_after"])
    whole, upto = Window.partitionBy(F.lit(0)), Window.partitionBy(F.lit(0)).orderBy("bin")  # bins, not pairs
    share = lambda c: F.sum(c).over(upto) / F.sum(c).over(whole)
    return both.select("bin", "n_before", "n_after", F.round(F.abs(share("n_before") - share("n_after")), 6).alias("gap"))


def ks_by_group(df: DataFrame, a: Column, b: Column, width: int, by: str) -> DataFrame:
    """Kolmogorov-Smirnov distance of two measurements per group, in bins of ``width`` whole micro-units.

    Bins are counted before the shuffle, so that the running sums go over bins and never over a group's rows.
    """
    from pyspark.sql import Window

    mark = lambda x, first: F.struct(F.floor(x / width).alias("bin"), F.lit(first).alias("first"))
    long = df.select(by, F.explode(F.array(mark(a, True), mark(b, False))).alias("m")).where("m.bin IS NOT NULL")
    bins = long.groupBy(by, F.col("m.bin").alias("bin")).agg(F.count_if(F.col("m.first")).alias("x"), F.count_if(~F.col("m.first")).alias("y"))
    upto, whole = Window.partitionBy(by).orderBy("bin"), Window.partitionBy(by)
    share = lambda c: F.try_divide(F.sum(c).over(upto).cast("double"), F.sum(c).over(whole))
    return bins.select(by, "x", F.abs(share("x") - share("y")).alias("gap")).groupBy(by).agg(F.sum("x").alias("n"), F.round(F.max("gap"), 6).alias("ks"))


def overlap(selections: dict[str, DataFrame], ours: str) -> DataFrame:
    """Share of our pairs that each other selection holds as well: one shuffle of ids for any number of methods."""
    names = sorted(selections)
    marks = None
    for i, name in enumerate(names):
        part = selections[name].select("pair_id", F.lit(1 << i).cast("long").alias("bit"))
        marks = part if marks is None else marks.unionByName(part)
    masks = marks.groupBy("pair_id").agg(F.bit_or("bit").alias("mask")).groupBy("mask").agg(F.count(F.lit(1)).alias("n"))
    mine = 1 << names.index(ours)
    cells = []
    for i, name in enumerate(names):
        both, other = mine | 1 << i, 1 << i
        has = lambda bits: F.col("mask").bitwiseAND(F.lit(bits)) == bits
        total = lambda cond: F.coalesce(F.sum(F.when(cond, F.col("n"))), F.lit(0))
        cells.append(F.struct(F.lit(name).alias("method"), total(has(mine)).alias("n_ours"), total(has(other)).alias("n_other"), total(has(both)).alias("n_both")))
    rows = masks.agg(F.array(*cells).alias("r")).select(F.inline("r"))
    return rows.select("*", F.round(100 * F.try_divide("n_both", "n_ours"), 4).alias("overlap"), F.round(F.try_divide(F.col("n_both").cast("double"), F.col("n_ours") + F.col("n_other") - F.col("n_both")), 6).alias("jaccard"))


def nll_distribution(df: DataFrame, *by: str) -> DataFrame:
    """Mean, spread and quantiles of both responses' average negative log-likelihood."""
    long = df.select(*by, F.inline(F.array(F.struct(F.lit("chosen").alias("side"), S.avg_nll("w").alias("nll")), F.struct(F.lit("rejected").alias("side"), S.avg_nll("l").alias("nll")))))
    return long.where("nll IS NOT NULL").groupBy(*by, "side").agg(
        F.count(F.lit(1)).alias("n"), F.round(F.avg("nll"), 6).alias("mean"), F.round(F.stddev_pop("nll"), 6).alias("sd"), *[F.round(F.percentile("nll", q), 6).alias(f"p{int(q * 100)}") for q in (0.05, 0.5, 0.95)]
    )


def squeeze_index(df: DataFrame, policy: str = "pos") -> DataFrame:
    """Per-token change of both responses' log-probability against the reference; both far below zero is squeezing."""
    per = lambda s: F.avg(F.try_divide(S.implicit_reward(policy, s), F.col(f"n_{s}").cast("double"))).alias(f"drop_{s}")
    return df.agg(per("w"), per("l"))


def length_sensitivity(df: DataFrame) -> DataFrame:
    """Correlation of each score with the length gap, in one pass."""
    gap = (F.col("len_w") - F.col("len_l")).cast("double")
    scores = {"r_ad": S.polarity_gap(), "ang": S.nll_gap(), "ppl_gap": S.ppl_gap(), "im": S.implicit_margin("pos")}
    return df.agg(F.array(*[F.struct(F.lit(k).alias("score"), F.round(F.corr(v, gap), 6).alias("corr")) for k, v in scores.items()]).alias("r")).select(F.inline("r"))


def wrong_direction_rate(selection: DataFrame) -> DataFrame:
    return selection.agg(F.count(F.lit(1)).alias("n"), F.round(F.avg((S.implicit_margin("pos") < 0).cast("double")), 6).alias("wrong"))


def profile(df: DataFrame, dims: list[str]) -> DataFrame:
    return df.cube(*dims).agg(F.count(F.lit(1)).alias("n_pairs"), F.sum("ang").alias("sum_ang"), F.grouping_id().alias("level"))


def near_zero_share(df: DataFrame, value: Column, edge: float) -> DataFrame:
    return df.agg(F.round(F.avg((F.abs(value) <= edge).cast("double")), 6).alias("near_zero"), F.round(F.avg(value), 6).alias("mean"))
