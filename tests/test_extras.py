"""Reward model, measured costs, sets, scorers from outside, and the streaming forms against their batch forms."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from duetsieve.functions.columns import judge_scores
from duetsieve.operators import analysis, costs, reward, scorers, sets
from duetsieve.sources import pairs as P
from duetsieve.streaming import selection as stream
from tests.conftest import SMALL


def newton(x, ridge, steps=60):
    w = np.zeros(x.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(x @ w))
        g = x.T @ p - ridge * len(x) * w
        h = (x * (p * (1 - p))[:, None]).T @ x + ridge * len(x) * np.eye(len(w))
        w = w + np.linalg.solve(h, g)
    return w


def test_reward_fit_equals_dense_fit(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(400, 3))
    x[rng.random(400) > 1 / (1 + np.exp(-x @ [1.0, -0.5, 0.0]))] *= -1
    rows = [(i, [float(v) for v in r]) for i, r in enumerate(x)]
    odd = [(-1, None), (-2, [1.0]), (-3, [float("nan"), 0.0, 0.0]), (-4, [None, 0.0, 0.0]), (-5, [float("inf"), 0.0, 0.0])]
    df = spark.createDataFrame(rows + odd, "pair_id long, diff array<double>")
    found = reward.fit_pairwise_reward(df, 3)
    assert found.converged and np.array(found.weights) == pytest.approx(newton(x, 1e-3), abs=1e-6)
    got = reward.reward_accuracy(reward.usable_differences(df, 3), found.margin()).first()
    assert got["n_pairs"] == 400 and got["accuracy"] == pytest.approx(np.mean(x @ np.array(found.weights) > 0))


def test_reward_fit_of_separable_and_of_no_pairs(spark):
    one = spark.createDataFrame([(1, [1.0]), (2, [2.0])], "pair_id long, diff array<double>")
    assert 0 < reward.fit_pairwise_reward(one, 1).weights[0] < 100
    assert reward.fit_pairwise_reward(one.where("false"), 1).weights == (0.0,)


def test_costs_see_shuffles(spark):
    df = spark.range(10000).withColumn("g", F.col("id") % 7)
    plain, grouped = costs.measure("plain", lambda: df), costs.measure("grouped", lambda: df.repartition(5, "g"))
    assert plain.rows == grouped.rows == 10000
    assert plain.shuffle_written == 0 and grouped.shuffle_written > 0 and grouped.shuffle_read == grouped.shuffle_written
    assert plain.tasks > 0 and grouped.stages == 2
    assert spark.sparkContext.getLocalProperty("spark.jobGroup.id") is None


def test_sets_and_tiles(spark):
    ids = lambda *x: spark.createDataFrame([(i,) for i in x], "pair_id long")
    a, b, c = ids(1, 2, 3, 3), ids(2, 3, 4), ids(3, 5)
    got = lambda df: sorted(r[0] for r in df.collect())
    assert got(sets.in_all([a, b, c])) == [3] and got(sets.in_any([a, b, c])) == [1, 2, 3, 4, 5] and got(sets.newly_chosen(a, [b, c])) == [1]
    for n, tiles in ((10, 3), (3, 5), (12, 4), (1, 1)):
        tiled = sets.distributed_ntile(spark.range(n).withColumnRenamed("id", "pair_id"), [F.col("pair_id").asc()], tiles)
        want = [i for i, size in enumerate([n // tiles + (t < n % tiles) for t in range(tiles)], 1) for _ in range(size)]
        assert [r["tile"] for r in tiled.orderBy("pair_id").collect()] == want


def test_ks_by_group(spark):
    rows = [("a", 1, 11), ("a", 2, 12), ("b", 1, 1), ("b", 2, None), ("c", None, None)]
    df = spark.createDataFrame(rows, "grp string, x long, y long")
    got = {r["grp"]: (r["n"], r["ks"]) for r in analysis.ks_by_group(df, F.col("x"), F.col("y"), 1, "grp").collect()}
    assert got == {"a": (2, 1.0), "b": (2, 0.5)}


def test_scorer_from_outside(spark):
    df = spark.createDataFrame([(1, "p", "abc", "d"), (2, None, None, "e e")], "pair_id long, prompt string, chosen string, rejected string")

    def load():
        return lambda prompts, responses: ([float("nan") if not r else -len(r) / 2 for r in responses], [len(r.split()) for r in responses])

    assert sorted(map(tuple, scorers.with_scorer(df, load, "pos", rows=1).collect())) == [(1, -1500000, -500000, 1, 1), (2, None, -1500000, 0, 2)]
    assert scorers.with_scorer(df.where("false"), load).count() == 0
    with pytest.raises(Exception, match="the scorer returned"):
        scorers.with_scorer(df, lambda: lambda p, r: ([], [])).collect()


def test_judges_replies(spark):
    rows = [('{"help": 3, "harm": 0.5}',), ("no json",), (None,), ("{}",)]
    got = [r[0] for r in spark.createDataFrame(rows, "reply string").select(judge_scores(F.col("reply"))).collect()]
    assert got[0] == {"help": 3.0, "harm": 0.5} and got[2] is None and not got[1] and not got[3]


# ---- streams ----------------------------------------------------------------------------------------------


@pytest.fixture
def run(spark, tmp_path):
    """Runs a stream over all that is there, in memory, and returns its table."""
    made = []

    def go(df, mode="append"):
        name = f"out{len(made)}_{abs(hash(str(tmp_path))) % 10**8}"
        made.append(name)
        q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.table(name)

    return go


@pytest.fixture
def arriving(spark, tmp_path):
    """Signals with a time each, as files, and a function that opens them as a stream."""
    signals = P.basket_signals(spark, SMALL).withColumn("ts", F.timestamp_seconds(F.col("pair_id") * 60))
    folder = str(tmp_path / "arriving")
    signals.repartition(3).write.parquet(folder)
    stored = spark.read.parquet(folder)
    return stored, lambda: spark.readStream.schema(stored.schema).parquet(folder)


def test_stream_joins_static_signals(spark, run, arriving):
    stored, opened = arriving
    signals = stored.drop("ts", "grp")
    got = run(stream.with_signals(opened().select("pair_id", "ts", "grp"), signals))
    assert got.count() == stored.count() and got.select(*stored.columns).exceptAll(stored).count() == 0


def test_stream_drops_repeats(spark, run, tmp_path):
    rows = [(1, 0), (1, 5), (2, 6), (2, 6), (3, 7)]
    df = spark.createDataFrame(rows, "pair_id long, at int").select("pair_id", F.timestamp_seconds("at").alias("ts"))
    df.write.parquet(str(tmp_path / "twice"))
    got = run(stream.without_repeats(spark.readStream.schema(df.schema).parquet(str(tmp_path / "twice"))))
    assert sorted(r["pair_id"] for r in got.collect()) == [1, 2, 3]


def test_sliding_and_session_rates(spark, run, arriving):
    stored, opened = arriving
    sliding = lambda df: stream.label_rates(df, 20, "1 hour", "30 minutes")
    assert run(sliding(opened()), "complete").exceptAll(sliding(stored)).count() == 0
    whole = run(stream.session_rates(opened(), 20, "3 minutes"), "complete")
    want = stream.session_rates(stored, 20, "3 minutes")
    assert whole.exceptAll(want).count() == 0 and want.exceptAll(whole).count() == 0
    assert whole.agg(F.sum("n_pairs")).first()[0] == stored.count()


def test_drift_proposes_a_threshold(spark, run, arriving):
    stored, opened = arriving
    drift = run(stream.gap_drift(opened(), "1 day"), "complete")
    assert drift.exceptAll(stream.gap_drift(stored, "1 day")).count() == 0
    for r in stream.proposed_tau(drift).collect():
        assert r["clear"] >= 0.5 * r["n_pairs"]
    rows = [(0, -10.0, 2), (0, -5.0, 1), (0, 0.0, 1), (0, 5.0, 3)]
    small = spark.createDataFrame(rows, "start int, bin double, n long")
    assert [tuple(r) for r in stream.proposed_tau(small).collect()] == [(0, 5.0, 5, 7)]


def test_running_top_and_repeated_batches(spark, tmp_path, arriving):
    stored, opened = arriving
    hard = stream.oriented(opened(), 20).select("pair_id", "ang")
    for _ in range(2):  # the second run finds nothing new
        stream.running_top(hard, str(tmp_path / "top"), 7, str(tmp_path / "c")).start().awaitTermination()
    want = stream.oriented(stored, 20).select("pair_id", "ang").orderBy(F.col("ang").desc(), "pair_id").limit(7)
    got = stream.top_so_far(spark, str(tmp_path / "top"))
    assert got.exceptAll(want).count() == 0 and got.count() == 7
    assert stream.top_so_far(spark, str(tmp_path / "nowhere")) is None


def test_stream_of_purchases_equals_batch(spark, run, tmp_path):
    spark.read.parquet(f"{SMALL}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")).write.parquet(str(tmp_path / "events"))
    kinds = spark.read.parquet(str(tmp_path / "events"))
    opened = lambda kind: spark.readStream.schema(kinds.schema).parquet(str(tmp_path / "events")).where(F.col("event_type") == kind)
    got = run(stream.session_pairs(opened("purchase"), opened("view"))).select("pair_id", "user_id", "view_id")
    want = P.session_pairs(spark, SMALL, "1 day").select("pair_id", "user_id", "view_id")
    assert got.exceptAll(want).count() == 0
    assert got.count() > 0  # what the watermark hasn't passed yet is still open
