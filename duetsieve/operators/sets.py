"""Selections as sets of pair ids, and ranked reports of them by group, page and quantile."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .cutoff import distributed_rank


def _ids(df: DataFrame) -> DataFrame:
    return df.select("pair_id")


def in_all(selections: list[DataFrame]) -> DataFrame:
    """Pairs that every selection holds."""
    return reduce(DataFrame.intersect, map(_ids, selections))


def in_any(selections: list[DataFrame]) -> DataFrame:
    """Pairs that some selection holds, once each."""
    return reduce(DataFrame.unionByName, map(_ids, selections)).distinct()


def newly_chosen(ours: DataFrame, others: list[DataFrame]) -> DataFrame:
    """Pairs of ours that no other selection holds."""
    return reduce(DataFrame.subtract, map(_ids, others), _ids(ours))


def top_per_group(df: DataFrame, group: str, score: Column, k: int) -> DataFrame:
    """The ``k`` largest of each group, ties to the smaller pair_id; each task keeps ``k`` of a group before the shuffle."""
    order = Window.partitionBy(group).orderBy(score.desc(), F.col("pair_id").asc())
    return df.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k).withColumn("place", F.col("place").cast("long"))


def page(df: DataFrame, order: list[Column], first: int, size: int) -> DataFrame:
    """Rows ``first`` + 1 to ``first`` + ``size`` in ``order``, which must be total."""
    return df.orderBy(*order).offset(first).limit(size)


def distributed_ntile(df: DataFrame, order: list[Column], tiles: int, name: str = "tile") -> DataFrame:
    """Tiles 1..``tiles`` of sizes that differ by one at most, the larger first, without a window over all rows."""
    ranked = distributed_rank(df, order, "_at")
    n = ranked.count()
    small, more = divmod(n, tiles)
    at = F.col("_at") - 1
    early = F.floor(at / (small + 1))
    late = more + F.floor((at - more * (small + 1)) / max(small, 1))
    return ranked.withColumn(name, (F.when(at < more * (small + 1), early).otherwise(late) + 1).cast("int")).drop("_at")
