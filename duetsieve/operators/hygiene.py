"""Cleaning pairs before selection: duplicates, contradictions, benchmark passages."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def drop_duplicate_pairs(pairs: DataFrame) -> DataFrame:
    """One pair (least id) of equal prompt and responses; pairs of equal responses and contradicted pairs go.

    Contradicted: the same prompt with the same two responses the other way round.
    """
    key = lambda a, b: F.md5(F.concat_ws("\x01", F.coalesce("prompt", F.lit("")), F.coalesce(a, F.lit("")), F.coalesce(b, F.lit(""))))
    keyed = pairs.where(~F.col("chosen").eqNullSafe(F.col("rejected"))).withColumns({"_k": key("chosen", "rejected"), "_r": key("rejected", "chosen")})
    first = keyed.groupBy("_k").agg(F.min("pair_id").alias("pair_id"), F.first("_r").alias("_r"))
    sound = first.join(first.select(F.col("_k").alias("_o")), F.col("_r") == F.col("_o"), "left_anti").select("pair_id")
    return pairs.join(sound, "pair_id", "left_semi")


def decontaminate(texts: DataFrame, benchmark: DataFrame, id_col: str, words: int = 8) -> DataFrame:
    """Ids of texts that share a run of ``words`` words with a benchmark item.

    Word runs meet in a hash join on the benchmark's side; equal runs of one text are sent once.
    """
    from ..functions.columns import tokens

    def runs(df: DataFrame, keep: list[str]) -> DataFrame:
        cut = df.select(*keep, tokens(F.col("text")).alias("w")).where(F.size("w") >= words)
        at = F.sequence(F.lit(1), F.size("w") - (words - 1))
        return cut.select(*keep, F.explode(F.array_distinct(F.transform(at, lambda i: F.xxhash64(F.array_join(F.slice("w", i, words), " "))))).alias("run"))

    return runs(texts, [id_col]).join(runs(benchmark, []).distinct(), "run", "left_semi").select(id_col).distinct()
