"""Selection on streams: the first stage as pairs arrive, rates and drift in windows, running top-k, as-of pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import signals as S
from ..operators.difficulty import with_difficulty
from ..operators.polarity import labelled, orient_pairs


def oriented(stream: DataFrame, tau: float, reversal: bool = True) -> DataFrame:
    """The first stage is row-local: the batch operator serves streams as it is."""
    return with_difficulty(orient_pairs(S.usable(stream), tau, reversal))


def with_signals(pairs: DataFrame, signals: DataFrame) -> DataFrame:
    """Arriving pairs with a static table of signals."""
    return pairs.join(signals, "pair_id")


def without_repeats(stream: DataFrame, ts: str = "ts", late: str = "1 hour") -> DataFrame:
    return stream.withWatermark(ts, late).dropDuplicatesWithinWatermark(["pair_id"])


def label_rates(stream: DataFrame, tau: float, window: str = "1 hour", slide: str | None = None, ts: str = "ts", late: str = "1 hour") -> DataFrame:
    """Kept, turned and dropped pairs per tumbling or sliding window."""
    by = F.window(ts, window, slide) if slide else F.window(ts, window)
    found = labelled(stream.withWatermark(ts, late), tau).groupBy(by.alias("w")).agg(F.count_if(F.col("phi") == 1).alias("kept"), F.count_if(F.col("phi") == -1).alias("flipped"), F.count_if(F.col("phi") == 0).alias("dropped"))
    return found.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "kept", "flipped", "dropped")


def session_rates(stream: DataFrame, tau: float, gap: str = "30 minutes", ts: str = "ts", late: str = "1 hour") -> DataFrame:
    found = labelled(stream.withWatermark(ts, late), tau).groupBy("grp", F.session_window(ts, gap).alias("w")).agg(F.count(F.lit(1)).alias("n_pairs"), F.count_if(F.col("phi") != 0).alias("clear"))
    return found.select("grp", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n_pairs", "clear")


def gap_drift(stream: DataFrame, window: str = "1 day", width: float = 5.0, ts: str = "ts", late: str = "1 hour") -> DataFrame:
    """Histogram of the gap per window in fixed bins, from which quantiles and a new tau can be read."""
    gap = S.polarity_gap()
    found = stream.withWatermark(ts, late).groupBy(F.window(ts, window).alias("w"), (F.floor(gap / width) * width).cast("double").alias("bin")).agg(F.count(F.lit(1)).alias("n"))
    return found.select(F.col("w.start").alias("start"), "bin", "n")


def proposed_tau(drift: DataFrame, width: float = 5.0, share: float = 0.5) -> DataFrame:
    """For each window of ``gap_drift`` the largest bin edge as threshold that still leaves ``share`` of the pairs clear.

    Reads the finished histogram: its rows are bins, whose number the data's range bounds, not pairs.
    """
    from pyspark.sql import Window

    edge = F.when(F.col("bin") >= 0, F.col("bin")).otherwise(-F.col("bin") - width)  # of the bin's end that is nearer to zero
    sized = drift.groupBy("start", edge.alias("tau")).agg(F.sum("n").alias("n"))
    above = F.sum("n").over(Window.partitionBy("start").orderBy(F.col("tau").desc()))
    found = sized.withColumns({"clear": above, "n_pairs": F.sum("n").over(Window.partitionBy("start"))})
    return found.where(F.col("clear") >= share * F.col("n_pairs")).groupBy("start").agg(F.max_by(F.struct("tau", "clear", "n_pairs"), "tau").alias("r")).select("start", "r.*")


def running_top(stream: DataFrame, folder: str, k: int, checkpoint: str):
    """Keeps the k hardest pairs so far, as one finished folder a batch under ``folder``, which ``top_so_far`` reads.

    Each batch starts from the last one finished before it and writes a folder of its own, so that a batch that is
    repeated after a crash changes nothing, and no table is ever overwritten while it is the only copy.
    """

    def merge(batch: DataFrame, number: int) -> None:
        before = top_so_far(batch.sparkSession, folder, number)
        best = batch if before is None else before.unionByName(batch).dropDuplicates(["pair_id"])
        best.orderBy(F.col("ang").desc(), "pair_id").limit(k).write.mode("overwrite").parquet(f"{folder}/batch={number:012d}")

    return stream.writeStream.foreachBatch(merge).option("checkpointLocation", checkpoint).trigger(availableNow=True)


def top_so_far(spark: SparkSession, folder: str, before: int | None = None) -> DataFrame | None:
    """The table of the last finished batch (of number below ``before``, where given); None where there is none."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    files = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    if not files.exists(where):
        return None
    done = [str(x.getPath()) for x in files.listStatus(where) if files.exists(spark.sparkContext._jvm.org.apache.hadoop.fs.Path(x.getPath(), "_SUCCESS"))]
    done = sorted(x for x in done if before is None or int(x.rpartition("=")[2]) < before)
    return spark.read.parquet(done[-1]) if done else None


def session_pairs(purchases: DataFrame, views: DataFrame, within: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Purchases with the same user's latest view before them, like the batch form with ``within``; both sides bounded by watermarks.

    A purchase is given out when the watermark has passed it, so that no later view can change its pair.
    """
    p = purchases.select(F.col("event_id").alias("pair_id"), "user_id", F.col("ts").alias("bought"), F.col("value").alias("ext_w")).withWatermark("bought", late)
    v = views.select(F.col("event_id").alias("view_id"), F.col("user_id").alias("viewer"), F.col("ts").alias("seen"), F.col("value").alias("ext_l")).withWatermark("seen", late)
    earlier = "(seen < bought OR seen = bought AND view_id < pair_id)"
    met = p.join(v, F.expr(f"user_id = viewer AND {earlier} AND seen <= bought AND seen >= bought - INTERVAL {within}"))
    last = met.groupBy("pair_id", "user_id", "bought", "ext_w").agg(F.max(F.struct("seen", "view_id", "ext_l")).alias("v"))
    return last.select("pair_id", "user_id", F.col("bought").alias("ts"), "ext_w", F.col("v.view_id").alias("view_id"), F.col("v.seen").alias("view_ts"), F.col("v.ext_l").alias("ext_l"))
