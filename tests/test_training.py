"""Trainings, cut-offs in bins, measures and streams against plain Python."""

import datetime

import numpy as np
import pytest
from pyspark.sql import functions as F

from duetsieve import experiments as E
from duetsieve.functions.columns import held_out
from duetsieve.operators import cutoff, evaluate, policy
from duetsieve.sources import pairs as P
from duetsieve.sources.tables import table
from duetsieve.streaming import selection as streams
from tests.conftest import SMALL


@pytest.fixture(scope="module")
def graded(spark):
    cfg = policy.PolicyConfig(vocabulary=64, rounds=3, split="shared", mask=1.0)
    ref = policy.reference(table(spark, SMALL, "documents", "text"), cfg)
    return cfg, ref, policy.materialised(policy.featurise(P.graded_pairs(spark, SMALL), ref, cfg), "graded-features")


def loss_of(rows, ref, cfg, theta):
    """Mean loss of the positive policy, by hand."""
    log_z, out = np.log((ref.mass * np.exp(theta)).sum()), []
    for r in rows:
        margin = sum((x["w"] - x["l"]) * theta[x["feat"]] for x in r["feats"]) - (r["n_w"] - r["n_l"]) * log_z
        out.append(np.log1p(np.exp(-cfg.beta * margin)))
    return np.mean(out)


def test_closed_form_step_is_the_gradient(graded):
    cfg, ref, feats = graded
    rows = feats.where(~held_out(F.col("pair_id"))).collect()
    step = policy.one_step(feats, ref, cfg)
    assert step.theta[1].tolist() == (-step.theta[0]).tolist()
    for f in (0, 1, 5, 40, 63):
        nudge = np.zeros(64)
        nudge[f] = 1e-5
        slope = (loss_of(rows, ref, cfg, nudge) - loss_of(rows, ref, cfg, -nudge)) / 2e-5
        assert step.theta[0][f] == pytest.approx(-0.01 * cfg.rate * slope, rel=1e-4, abs=1e-8)


def test_many_trainings_equal_single_ones(graded):
    cfg, ref, feats = graded
    ids = feats.select("pair_id", (F.col("pair_id") % 3 == 0).alias("flipped"))
    kept = {"all": ids.withColumn("flipped", F.lit(False)), "some": ids.where("pair_id % 2 = 0")}
    many = policy.train_many(feats, ref, kept, cfg)
    for name, df in kept.items():
        one = policy.train_policies(policy.turned(feats, df), ref, policy.PolicyConfig(**{**cfg.__dict__, "eps": 0.0}))
        assert many[name].theta == pytest.approx(one.theta, abs=1e-6)
        assert [h["loss"] for h in many[name].history] == pytest.approx([h["loss"] for h in one.history])


def test_orders_are_batches_and_matter(spark):
    got = {r["how"]: r for r in E.queries()["q_curriculum_effect"](spark, SMALL).collect()}
    assert set(got) == {"random", "hard_first", "easy_first"}
    assert all(r["n_batches"] > 1 for r in got.values()) and len({r["last_loss"] for r in got.values()}) == 3


@pytest.mark.parametrize("kind", ["long", "double"])
@pytest.mark.parametrize("ascending", [True, False])
def test_bins_equal_sorting(spark, monkeypatch, kind, ascending):
    monkeypatch.setattr(cutoff, "HEAP_ROWS", 5)
    base = spark.range(400).select(F.col("id").alias("pair_id"))
    far = [F.col("pair_id") * 7919 % 97, F.col("pair_id") % 2 * 10**13 - 5 * 10**12 + F.col("pair_id") % 3, F.lit(4), F.when(F.col("pair_id") % 9 == 0, 10**13).otherwise(F.col("pair_id") % 50)]
    if kind == "double":
        far += [F.exp(F.col("pair_id") / 5.0), F.when(F.col("pair_id") == 7, float("inf")).otherwise(1 / (F.col("pair_id") + 1))]
    for x in far:
        df = base.withColumn("s", x.cast(kind))
        rows = sorted(map(tuple, df.collect()), key=lambda r: ((r[1] if ascending else -r[1]), r[0]))
        for n in (6, 37, 200, 399, 500):
            got = cutoff.top_n(df, F.col("s"), n, ascending)
            assert got.columns == df.columns and sorted(tuple(r) for r in got.collect()) == sorted(rows[:n])


def test_no_control_where_wins_are_separate(spark):
    rows = [("won", i, 1.0, 10 + i, 20) for i in range(30)] + [("split", i, float(i > 14), 10 + i, 24) for i in range(30)]
    mixed = [("fair", i, float((i * 7 + i // 3) % 2), 10 + i, 20) for i in range(60)]
    j = spark.createDataFrame(rows + mixed, "method string, prompt_id long, p_win double, len_model int, len_base int")
    got = {r["method"]: r for r in evaluate.length_controlled_win_rate(j).collect()}
    assert not got["won"]["controlled"] and got["won"]["lc"] == 100.0
    assert not got["split"]["controlled"] and got["split"]["lc"] == 50.0
    assert got["fair"]["controlled"] and got["fair"]["lc"] == pytest.approx(got["fair"]["wr"], abs=15)


def test_trained_selections_have_their_sizes(spark):
    k = {int(r["setting"]): r for r in E.queries()["q_trained_k"](spark, SMALL).collect()}
    assert sorted(k) == E.SHARES and [k[s]["n_pairs"] for s in E.SHARES] == sorted(r["n_pairs"] for r in k.values())
    assert all(0 <= r["accuracy"] <= 1 and r["length"] > 0 for r in k.values()) and len({r["length"] for r in k.values()}) > 1


def files(spark, df, path):
    df.write.parquet(path)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)


def test_running_top_survives_repeats(spark, tmp_path):
    rows = spark.range(60).select(F.col("id").alias("pair_id"), (F.col("id") * 37 % 61).alias("ang")).repartition(4)
    stream = files(spark, rows, str(tmp_path / "in"))
    streams.running_top(stream, str(tmp_path / "top"), 7, str(tmp_path / "ck")).start().awaitTermination()
    want = sorted(map(tuple, rows.collect()), key=lambda r: (-r[1], r[0]))[:7]
    assert sorted(map(tuple, streams.top_so_far(spark, str(tmp_path / "top")).collect())) == sorted(want)
    # All batches once more, over what is there: the same table.
    streams.running_top(stream, str(tmp_path / "top"), 7, str(tmp_path / "ck2")).start().awaitTermination()
    assert sorted(map(tuple, streams.top_so_far(spark, str(tmp_path / "top")).collect())) == sorted(want)


def test_stream_of_sessions_equals_batch(spark, tmp_path):
    events = table(spark, SMALL, "events", "event_id", "ts", "user_id", "event_type", "value").withColumn("ts", F.col("ts").cast("timestamp"))
    parts = [files(spark, events.where(F.col("event_type") == kind).coalesce(1), str(tmp_path / kind)) for kind in ("purchase", "view")]
    found = streams.session_pairs(*parts, within="1 day")
    found.writeStream.format("memory").queryName("sessions").outputMode("append").option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start().awaitTermination()
    batch = streams.session_pairs(*(events.where(F.col("event_type") == kind) for kind in ("purchase", "view")), within="1 day").collect()
    want = P.session_pairs(spark, SMALL, "1 day").withColumns({c: F.col(c).cast("timestamp") for c in ("ts", "view_ts")}).select("pair_id", "user_id", "ts", "ext_w", "view_id", "view_ts", "ext_l")
    assert sorted(map(tuple, batch)) == sorted(map(tuple, want.collect()))
    given = {tuple(r) for r in spark.table("sessions").collect()}
    last = min(events.where(F.col("event_type") == kind).agg(F.max("ts")).first()[0] for kind in ("purchase", "view"))
    passed = {tuple(r) for r in batch if r["ts"] < last - datetime.timedelta(days=2)}  # the join holds a purchase for a day
    assert passed and passed <= given <= {tuple(r) for r in batch}


def test_stream_static_join_and_repeats(spark, tmp_path):
    rows = spark.range(40).select((F.col("id") % 20).alias("pair_id"), F.timestamp_seconds(F.col("id") * 10).alias("ts"))
    signals = spark.range(15).select(F.col("id").alias("pair_id"), F.lit(1).alias("pos_w"))
    stream = files(spark, rows.coalesce(1), str(tmp_path / "in"))
    out = streams.with_signals(streams.without_repeats(stream), signals)
    out.writeStream.format("memory").queryName("joined").option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start().awaitTermination()
    assert sorted(r["pair_id"] for r in spark.table("joined").collect()) == list(range(15))
