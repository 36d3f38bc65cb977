"""Cut-offs on scores without a global sort: top-n, top share, distributed ranks.

All orders are total: score first, then pair_id.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.stages import materialised

BINS = 4096
#: Up to so many rows are kept by per-task heaps; beyond, the share's bins decide.
HEAP_ROWS = 1_000_000


def top_n(df: DataFrame, score: Column, n: int, ascending: bool = False) -> DataFrame:
    """The n best rows; plans as TakeOrderedAndProject up to HEAP_ROWS."""
    scored = df.withColumn("_score", score).where("_score IS NOT NULL AND NOT isnan(_score)")
    if n <= HEAP_ROWS:
        return scored.orderBy(F.col("_score").asc() if ascending else F.col("_score").desc(), "pair_id").limit(n).drop("_score")
    return _cut(scored, n, ascending).drop("_score")


def top_share(df: DataFrame, score: Column, percent: float, base: int | None = None) -> DataFrame:
    """The best ``percent`` of the rows by a whole-number score (of ``base`` rows, where given)."""
    if not 0 < percent <= 100:
        raise ValueError("the share must be in (0, 100]")
    scored = df.withColumn("_score", score.cast("long")).where("_score IS NOT NULL")
    n = base if base is not None else scored.count()
    return _cut(scored, max(1, int(n * percent // 100)) if n else 0).drop("_score")


def _bins(score: Column, lo, hi) -> Column:
    """0 to about BINS, never falling as the score rises; over the highest value it is above that of the lowest."""
    if isinstance(lo, float):
        lo, hi = max(lo, -1e308), min(hi, 1e308)
        width = hi / BINS - lo / BINS
        if lo + width == lo or not width:  # too narrow to be divided
            return (score >= hi).cast("long")
        return F.floor(F.greatest(F.least(score, F.lit(hi)), F.lit(lo)) / width - lo / width).cast("long")
    # Decimals, as the span of two longs may exceed a long.
    return F.floor((score.cast("decimal(20,0)") - F.lit(lo).cast("decimal(20,0)")).cast("decimal(38,0)") / F.lit(-(-(hi - lo + 1) // BINS)).cast("decimal(20,0)")).cast("long")


def _cut(scored: DataFrame, n: int, ascending: bool = False) -> DataFrame:
    """The n best rows by ``_score``, then pair_id: counts by bin narrow down the bin that holds rank n, heaps settle it.

    Where one score alone holds rank n and too many rows, its rows are cut by pair_id in the same way.
    """
    sure, rest, left, by_id = scored.limit(0), scored, n, False
    while left > 0:
        lo, hi, rows = rest.agg(F.min("_score"), F.max("_score"), F.count(F.lit(1))).first()
        if rows <= left:
            return sure.unionByName(rest)
        if rows <= HEAP_ROWS or (by_id and lo == hi):
            best = F.col("_score").asc() if ascending else F.col("_score").desc()
            return sure.unionByName(rest.orderBy(best, "pair_id").limit(left))
        if lo == hi:
            rest, by_id = rest.withColumn("_score", F.col("pair_id") if ascending else -F.col("pair_id")), True
            sure = sure.withColumn("_score", F.col("pair_id"))
            continue
        binned = rest.withColumn("_bin", _bins(F.col("_score"), lo, hi) * (-1 if ascending else 1))
        counts = dict(binned.groupBy("_bin").count().collect())  # BINS rows
        above = 0
        for b in sorted(counts, reverse=True):
            if above + counts[b] >= left:
                break
            above += counts[b]
        sure = sure.unionByName(binned.where(F.col("_bin") > b).drop("_bin"))
        rest, left = binned.where(F.col("_bin") == b).drop("_bin"), left - above
    return sure


def distributed_rank(df: DataFrame, order: list[Column], name: str = "position") -> DataFrame:
    """``df`` with ranks 1..n: range partitions, sorted within, shifted by the running count of rows before them.

    Partitions are written once before they are counted, since a recomputed range partitioning may differ.
    """
    laid = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_part", F.spark_partition_id())
    laid = materialised(laid, "ranked")
    total, shifts = 0, []
    for part, n in sorted(laid.groupBy("_part").count().collect()):  # a row a partition
        shifts.append((part, total))
        total += n
    spark = df.sparkSession
    offsets = F.broadcast(spark.createDataFrame(shifts, "_part int, _before long"))
    within = F.row_number().over(Window.partitionBy("_part").orderBy(*order))
    return laid.join(offsets, "_part").withColumn(name, F.col("_before") + within).drop("_part", "_before")
