"""Reading and writing: tables, pairs and signals in several formats with declared schemas, selections out."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.columns import micro
from ..functions.signals import SIGNALS

PAIRS = "pair_id long, grp string, prompt string, chosen string, rejected string"
#: Signals as a scoring job writes them: nats as doubles.
RAW_SIGNALS = SIGNALS.replace("pos_w long, pos_l long, inv_w long, inv_l long, ref_w long, ref_l long", "pos_w double, pos_l double, inv_w double, inv_l double, ref_w double, ref_l double")


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_as(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """parquet, orc, json (lines) or csv with a declared schema; nothing is inferred."""
    reader = spark.read.schema(schema)
    if fmt == "csv":
        reader = reader.option("header", True).option("multiLine", True).option("escape", '"')
    if fmt not in ("parquet", "orc", "json", "csv"):
        raise ValueError(f"unknown format {fmt}")
    return reader.format(fmt).load(path)


def read_pairs(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    return read_as(spark, path, fmt, PAIRS)


def read_signals(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """Precomputed signals in nats; log-probabilities become micro-nats, other than finite ones null."""
    raw = read_as(spark, path, fmt, RAW_SIGNALS)
    return raw.withColumns({f"{m}_{s}": micro(F.col(f"{m}_{s}")) for m in ("pos", "inv", "ref") for s in "wl"})


def write_selection(df: DataFrame, path: str, run_id: str, fmt: str = "parquet") -> None:
    """A run's selection under its own partition; writing it again replaces that partition only."""
    keys = [c for c in ("grp",) if c in df.columns]
    df.write.format(fmt).mode("overwrite").partitionBy(*keys).save(f"{path.rstrip('/')}/run_id={run_id}")


def write_curriculum(df: DataFrame, path: str, shards: int, fmt: str = "json") -> None:
    """Shards whose file order and row order follow ``position``."""
    df.repartitionByRange(shards, "position").sortWithinPartitions("position").write.format(fmt).mode("overwrite").save(path)


def write_bucketed(df: DataFrame, name: str, buckets: int) -> None:
    """A table bucketed and sorted by pair_id: pairs and signals written so join without a shuffle."""
    df.write.bucketBy(buckets, "pair_id").sortBy("pair_id").mode("overwrite").saveAsTable(name)
