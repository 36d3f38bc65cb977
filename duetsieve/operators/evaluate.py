"""Accuracy measures over judgements and signals, and costs."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import signals as S


def win_rate(j: DataFrame) -> DataFrame:
    """Mean judged probability of winning per method, in percent; ties count one half."""
    return j.groupBy("method").agg((100 * F.avg("p_win")).alias("wr"), F.count(F.lit(1)).alias("n"))


def mean_length(j: DataFrame) -> DataFrame:
    return j.groupBy("method").agg(F.avg("len_model").alias("length"))


def mean_score(j: DataFrame) -> DataFrame:
    """Judge's scores over turns, then over prompts."""
    return j.groupBy("method", "prompt_id").agg(F.avg("score").alias("s")).groupBy("method").agg(F.avg("s").alias("score"))


def length_controlled_win_rate(j: DataFrame, steps: int = 8, ridge: float = 1e-6) -> DataFrame:
    """Win rate at no length difference: logistic in tanh of the scaled difference, Newton over five sums a step, all methods at once.

    Falls back to the plain win rate (``controlled`` false) where lengths do not vary, or where the last step still
    moves: wins that lengths or nothing at all separate have no finite fit.
    """
    spark = j.sparkSession
    diff = F.col("len_model") - F.col("len_base")
    scale = j.groupBy("method").agg(F.stddev_pop(diff).alias("sd"), F.avg("p_win").alias("wr"), F.count(F.lit(1)).alias("n")).collect()  # a row a method
    state = {r["method"]: [0.0, 0.0] for r in scale if r["sd"]}
    spread = {r["method"]: r["sd"] for r in scale if r["sd"]}
    moved: dict[str, float] = {}
    for _ in range(steps):
        if not state:
            break
        now = spark.createDataFrame([(m, a, b, spread[m]) for m, (a, b) in state.items()], "method string, a double, b double, sd double")
        z = F.tanh((F.col("len_model") - F.col("len_base")) / F.col("sd"))
        x = j.join(F.broadcast(now), "method").withColumn("z", z).withColumn("mu", S.sigmoid(F.col("a") + F.col("b") * F.col("z")))
        r, v = F.col("p_win") - F.col("mu"), F.col("mu") * (1 - F.col("mu"))
        sums = x.groupBy("method").agg(F.sum(r).alias("g0"), F.sum(r * F.col("z")).alias("g1"), F.sum(v).alias("h00"), F.sum(v * F.col("z")).alias("h01"), F.sum(v * F.col("z") * F.col("z")).alias("h11"))
        for row in sums.collect():
            a, b = state[row["method"]]
            h = np.array([[row["h00"] + ridge, row["h01"]], [row["h01"], row["h11"] + ridge]])
            da, db = np.linalg.solve(h, [row["g0"] - ridge * a, row["g1"] - ridge * b])
            moved[row["method"]] = float(abs(da) + abs(db))
            state[row["method"]] = [float(np.clip(a + da, -20, 20)), float(np.clip(b + db, -20, 20))]
    rows = []
    for r in scale:
        a, b = state.get(r["method"], (None, None))
        fitted = a is not None and moved[r["method"]] < 1e-3
        rows.append((r["method"], round(100 / (1 + float(np.exp(-a))) if fitted else 100 * r["wr"], 4), round(100 * r["wr"], 4), bool(fitted)))
    return spark.createDataFrame(rows, "method string, lc double, wr double, controlled boolean")


def harder_set(j: DataFrame, difficulty: str, share: int = 3) -> DataFrame:
    """The judgements of the harder set: of the judged prompts the one in ``share`` with the largest ``difficulty``."""
    cut = j.select("pair_id", difficulty).distinct().agg(F.percentile_approx(difficulty, 1 - 1 / share, 1_000_000)).first()[0]
    return j.where(F.col(difficulty) >= F.lit(cut)) if cut is not None else j


def judged(picks: DataFrame, signals: DataFrame) -> DataFrame:
    """A judgement for each method and pair: the response it prefers against the other, by external reward, ties one half."""
    won = F.when(F.col("ext_w") == F.col("ext_l"), 0.5).otherwise((F.col("pick") == (F.col("ext_w") > F.col("ext_l"))).cast("double"))
    own = lambda a, b: F.when(F.col("pick"), F.col(a)).otherwise(F.col(b))
    return picks.join(signals, "pair_id").select(*picks.columns, won.alias("p_win"), own("len_w", "len_l").alias("len_model"), own("len_l", "len_w").alias("len_base"))


def leaderboard(results: DataFrame) -> DataFrame:
    """Rank of every method for each backbone and metric, larger is better; ties share a rank."""
    return results.withColumn("rank", F.dense_rank().over(Window.partitionBy("backbone", "metric").orderBy(F.col("value").desc())))


def average_improvement(results: DataFrame, base: str = "full") -> DataFrame:
    own = results.where(F.col("method") == base).select("backbone", "metric", F.col("value").alias("base"))
    return results.join(own, ["backbone", "metric"]).groupBy("backbone", "method").agg(F.avg(F.col("value") - F.col("base")).alias("improvement"))


def preference_accuracy(df: DataFrame, policy: str = "pos") -> DataFrame:
    return df.agg(F.avg((S.implicit_margin(policy) > 0).cast("double")).alias("accuracy"), F.count(F.lit(1)).alias("n_pairs"))


def noise_recovery(labels: DataFrame) -> DataFrame:
    """How well label -1 finds the pairs that are known to be swapped."""
    hit, found, true, n = F.count_if((F.col("phi") == -1) & F.col("is_swapped")), F.count_if(F.col("phi") == -1), F.count_if("is_swapped"), F.count(F.lit(1))
    return labels.agg(n.alias("n_pairs"), true.alias("n_swapped"), found.alias("n_inverse"), hit.alias("n_hit")).select(
        "*",
        F.round(F.try_divide("n_hit", "n_inverse"), 6).alias("precision"),
        F.round(F.try_divide("n_hit", "n_swapped"), 6).alias("recall"),
        F.round(F.try_divide(F.try_divide("n_hit", "n_inverse"), F.try_divide("n_swapped", "n_pairs")), 6).alias("lift"),
    )


@dataclass(frozen=True)
class CostModel:
    """Hours of a full training, of one model's pass over all pairs, and of one judged dimension (inferred)."""

    training: float = 32.0
    scoring: float = 5.5
    judging: float = 32.0


#: Trainings (in full trainings), scoring passes, judged dimensions.
WORK = {"implicit_margin": (1, 2, 0), "external_margin": (0, 0, 4), "ensemble_easiest": (3, 12, 0), "two_stage": (2, 3, 0), "two_stage_half": (1, 3, 0)}


def compute_hours(method: str, cost: CostModel = CostModel()) -> float:
    t, s, j = WORK[method]
    return t * cost.training + s * cost.scoring + j * cost.judging


def efficiency(rates: DataFrame, cost: CostModel = CostModel()) -> DataFrame:
    """Average win rate per hour of compute; ``rates``: method and avg_wr."""
    hours = rates.sparkSession.createDataFrame([(m, compute_hours(m, cost)) for m in WORK], "method string, hours double")
    return rates.join(F.broadcast(hours), "method").select("method", "hours", "avg_wr", F.round(F.col("avg_wr") / F.col("hours"), 4).alias("efficiency"))
