"""Queries against DuckDB on the smallest tables, policies, measures, streams and sinks."""

import os

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from duetsieve import experiments as E
from duetsieve.functions import signals as S
from duetsieve.functions.columns import held_out
from duetsieve.operators import analysis, costs, evaluate, hygiene, lm, policy
from duetsieve.plans.selection import select_pairs, with_texts
from duetsieve.sources import pairs as P
from duetsieve.sources import tables
from duetsieve.streaming import selection as stream
from tests.conftest import SMALL

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations"


def plain(v):
    if isinstance(v, float):
        return round(v, 6)
    if isinstance(v, (list, tuple)):
        return tuple(map(plain, v))
    return v


@pytest.fixture(scope="session")
def duck():
    con = duckdb.connect()
    for t in TABLES.split():
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SMALL}/{t}.parquet')")
    return con


@pytest.mark.parametrize("name", sorted(E.oracle_sql()))
def test_query_equals_oracle(spark, duck, name):
    df, sql = E.queries()[name](spark, SMALL), duck.sql(E.oracle_sql()[name])
    cols = sorted(df.columns)
    assert cols == sorted(sql.columns)
    got = sorted(repr(plain(tuple(r))) for r in df.select(*[f"`{c}`" for c in cols]).collect())
    want = sorted(repr(plain(r)) for r in sql.select(*[f'"{c}"' for c in cols]).fetchall())
    assert got == want


@pytest.mark.parametrize("name", ["q_published_rank", "q_leaderboard_rank", "q_published_claims", "q_efficiency", "q_published_orders", "q_published_costs", "q_base_init"])
def test_spark_reads_the_tables(spark, name):
    found = costs.measure(name, lambda: E.queries()[name](spark, SMALL))
    assert found.rows_read >= spark.read.parquet(f"{SMALL}/lineitem.parquet").count()


def test_texts_follow_orientation(spark):
    pairs, chosen = P.basket_pairs(spark, SMALL), select_pairs(P.basket_signals(spark, SMALL))
    got = with_texts(chosen, pairs).join(pairs.select("pair_id", F.col("chosen").alias("was")), "pair_id")
    assert got.where("flipped AND rejected <> was OR NOT flipped AND chosen <> was").count() == 0
    assert got.count() == chosen.count()


@pytest.fixture(scope="session")
def trained(spark):
    cfg = policy.PolicyConfig(vocabulary=64, rounds=5)
    return E._graded_run(spark, SMALL, cfg)


def test_policy_is_normalised_and_learns(trained):
    _, signals, found, _, ref = trained
    mass = ref.mass * np.exp(found.theta)
    assert (mass.sum(1) / np.exp(found.log_z)) == pytest.approx(np.ones(2), abs=1e-9)
    loss = [h["loss"] for h in found.history if h["policy"] == "pos"]
    assert loss[0] == pytest.approx(np.log(2)) and loss[-1] < loss[0]
    assert signals.where("pos_w IS NULL OR inv_l IS NULL").count() == 0


def test_zero_policy_has_no_margin(spark, trained):
    *_, feats, ref = trained
    blank = policy.Policies(np.zeros((2, 64)), np.zeros(2))
    assert policy.with_policy_scores(feats, blank).where((F.col("pos_w") != F.col("ref_w")) | (F.col("inv_l") != F.col("ref_l"))).count() == 0


def test_gradient_against_differences(spark, trained):
    """One round moves theta along the falling loss."""
    *_, feats, ref = trained
    cfg = policy.PolicyConfig(vocabulary=64, rounds=2, split="shared", rate=0.5)
    found = policy.train_policies(feats, ref, cfg)
    assert found.history[2]["loss"] < found.history[0]["loss"] and found.history[3]["loss"] < found.history[1]["loss"]


def test_ensemble_models_have_not_seen_what_they_judge(spark, trained):
    """Six trained models; a pair's loss of a seed is that of the policy trained on the other half."""
    *_, feats, ref = trained
    cfg = policy.PolicyConfig(vocabulary=64, rounds=2)
    rows = policy.ensemble_losses(feats, ref, cfg).collect()
    train = {r[0] for r in feats.where(~held_out(F.col("pair_id"))).select("pair_id").collect()}
    by_pair, by_model = {}, {}
    for r in rows:
        by_pair.setdefault(r["pair_id"], []).append(r["model"])
        by_model.setdefault(r["model"], {})[r["pair_id"]] = r["loss"]
    assert set(by_pair) == train and sorted(by_model) == list(range(6))
    assert all(sorted(k // 2 for k in models) == [0, 1, 2] for models in by_pair.values())
    for k, losses in by_model.items():
        # Trained by hand on the pairs that model k does not judge, and on nothing else.
        other = feats.where(F.col("pair_id").isin(list(train - set(losses))))
        found = policy.train_policies(other, ref, policy.PolicyConfig(vocabulary=64, rounds=2, split="shared"))
        scored = policy.with_policy_scores(feats, found).where(F.col("pair_id").isin(list(losses)))
        want = {r["pair_id"]: r["loss"] for r in scored.select("pair_id", S.pair_loss(S.implicit_margin("pos"), 0.1).alias("loss")).collect()}
        assert {p: x / 1e6 for p, x in losses.items()} == pytest.approx(want, abs=1e-5)


def test_leaderboard_ensemble_is_trained(spark, monkeypatch):
    """No formula stands in for the six models, each of which is trained on half of the pairs."""
    trained_on, train = [], policy.train_policies
    monkeypatch.setattr(policy, "train_policies", lambda f, ref, cfg, *a, **k: trained_on.append((cfg.sample, cfg.seed)) or train(f, ref, cfg, *a, **k))
    monkeypatch.setattr(E.baselines, "formula_losses", lambda *a, **k: pytest.fail("formula models on graded pairs"))
    got = E.queries()["q_leaderboard"](spark, SMALL)
    assert got.where("method = 'ensemble'").count() == 3
    assert sorted(x for x in trained_on if x[0] != "full") == sorted((h, s) for h in ("half", "rest") for s in (1, 2, 3))


def test_length_control(spark):
    rows = [("a", i, float(i % 2), 10, 10) for i in range(20)] + [("b", i, float(i < 15), 20 + 5 * i, 40) for i in range(30)]
    j = spark.createDataFrame(rows, "method string, prompt_id long, p_win double, len_model int, len_base int")
    got = {r["method"]: r for r in evaluate.length_controlled_win_rate(j).collect()}
    assert not got["a"]["controlled"] and got["a"]["lc"] == 50.0
    assert got["b"]["wr"] == 50.0


def test_cost_model_gives_the_printed_hours():
    want = {"implicit_margin": 43, "external_margin": 128, "ensemble_easiest": 162, "two_stage": 80.5, "two_stage_half": 48.5}
    assert {m: evaluate.compute_hours(m) for m in want} == want


def test_overlap_with_itself_is_whole(spark):
    ids = spark.range(10).withColumnRenamed("id", "pair_id")
    got = {r["method"]: r["overlap"] for r in analysis.overlap({"a": ids, "b": ids.limit(5)}, "a").collect()}
    assert got == {"a": 100.0, "b": 50.0}


def test_avg_nll_does_not_see_repetition(spark):
    df = spark.createDataFrame([(0, -4_000_000, -8_000_000, 4, 8)], "pair_id long, ref_w long, ref_l long, n_w int, n_l int")
    assert df.select(S.nll_gap()).first()[0] == 0


def test_empty_responses_have_no_tokens(spark):
    texts = spark.createDataFrame([("a b a",), (None,), ("",), (" \n",)], "text string")
    assert {(r["tok"], r["n"]) for r in lm.unigram(texts).collect()} == {("a", 2), ("b", 1)}
    assert {tuple(r) for r in lm.bigram(texts).collect()} == {("", "a", 1), ("a", "b", 1), ("b", "a", 1)}


def test_contradicted_pairs_go(spark):
    rows = [(1, "p", "a", "b"), (2, "p", "b", "a"), (3, "q", "a", "b"), (4, "q", "a", "b"), (5, "q", "c", "c"), (6, None, None, "x")]
    df = spark.createDataFrame(rows, "pair_id long, prompt string, chosen string, rejected string")
    assert sorted(r[0] for r in hygiene.drop_duplicate_pairs(df).select("pair_id").collect()) == [3, 6]


def test_pairs_are_compared_as_whole_texts(spark, monkeypatch):
    """Prompts 50 apart and responses that differ from the second word on are other pairs."""
    rows = [(1, "p 1", "a b", "c d"), (51, "p 51", "a b", "c d"), (2, "p 1", "a x", "c d"), (3, "p 1", "a b", "c y"), (4, "p 1", "a b", "c d"), (5, "p 1", "a b", "a z"), (6, "q", "a b", "c d"), (7, "q", "c d", "a b"), (8, "q", "c d", "a z")]
    df = spark.createDataFrame(rows, "pair_id long, prompt string, chosen string, rejected string")
    monkeypatch.setattr(E.P, "basket_pairs", lambda spark, sf_dir: df)
    got = E.queries()["q_dedup_pairs_whole"](spark, SMALL)
    assert sorted(map(tuple, got.select("pair_id", "prompt", "chosen", "rejected").collect())) == sorted(r for r in rows if r[0] not in (4, 6, 7))


def test_unknown_ways_to_combine_margins_are_refused(spark):
    with pytest.raises(ValueError):
        E.baselines.by_combined_margin(P.basket_signals(spark, SMALL), 5, "ranks")


def test_stream_equals_batch(spark, tmp_path):
    signals = P.basket_signals(spark, SMALL).withColumn("ts", F.timestamp_seconds(F.col("pair_id") * 60))
    signals.repartition(3).write.parquet(str(tmp_path / "in"))
    source = lambda: spark.readStream.schema(signals.schema).parquet(str(tmp_path / "in"))
    q = stream.oriented(source(), 20).writeStream.format("memory").queryName("kept").option("checkpointLocation", str(tmp_path / "c1")).trigger(availableNow=True).start()
    q.awaitTermination()
    want = stream.oriented(signals, 20)
    assert spark.table("kept").select("pair_id", "ang").exceptAll(want.select("pair_id", "ang")).count() == 0
    assert spark.table("kept").count() == want.count()
    q = stream.label_rates(source(), 20).writeStream.format("memory").queryName("rates").outputMode("complete").option("checkpointLocation", str(tmp_path / "c2")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("rates").agg(F.sum(F.col("kept") + F.col("flipped") + F.col("dropped"))).first()[0] == signals.count()


def test_sources_and_sinks(spark, tmp_path):
    df = P.basket_pairs(spark, SMALL).select("pair_id", "grp", "prompt", "chosen", "rejected")
    for fmt in ("parquet", "json", "orc", "csv"):
        path = str(tmp_path / fmt)
        df.write.format(fmt).option("header", True).save(path)
        assert tables.read_pairs(spark, path, fmt).exceptAll(df).count() == 0
    with pytest.raises(ValueError):
        tables.read_as(spark, "x", "xml", "a int")
    placed = select_pairs(P.basket_signals(spark, SMALL))
    tables.write_curriculum(placed, str(tmp_path / "order"), 3)
    seen = []
    for name in sorted(x for x in os.listdir(tmp_path / "order") if x.endswith(".json")):
        seen += [r["position"] for r in spark.read.json(str(tmp_path / "order" / name)).collect()]
    assert seen == list(range(1, len(seen) + 1))


def test_plans_stay_local_and_pruned(spark):
    from duetsieve.operators.polarity import orient_pairs

    stored = E.materialised(P.basket_signals(spark, SMALL), "basket")
    plan = orient_pairs(stored, 20).select("pair_id", "flipped")._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "ref_w" not in plan and "PushedFilters" in plan
