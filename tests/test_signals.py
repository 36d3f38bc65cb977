"""Algebra of the signals and the two stages, on literal rows."""

import math

import pytest
from pyspark.sql import functions as F

from duetsieve.functions import signals as S
from duetsieve.functions.columns import micro
from duetsieve.functions.sql import register_expand_pair, register_sql
from duetsieve.operators import cutoff, difficulty, polarity

M = 1_000_000
NAMES = "pair_id long, grp string, pos_w long, pos_l long, inv_w long, inv_l long, ref_w long, ref_l long, n_w int, n_l int, len_w int, len_l int, ext_w double, ext_l double"


def rows(spark, *given):
    out = []
    for i, (pos, inv, ref, n) in enumerate(given):
        out.append((i, "g", *[x * M for x in (*pos, *inv, *ref)], *n, 5, 7, 1.0, 0.5))
    return spark.createDataFrame(out, NAMES)


WORKED = [((-10, -40), (-50, -15), (-30, -20), (10, 10)), ((-30, -25), (-20, -40), (-30, -20), (10, 10)), ((-10, -10), (-10, -10), (-5, -9), (4, 3))]


def test_worked_example(spark):
    found = polarity.labelled(rows(spark, *WORKED), 20).orderBy("pair_id").collect()
    assert [r["gap"] // M for r in found] == [65, -25, 0]
    assert [r["phi"] for r in found] == [1, -1, 0]
    assert [r["phi"] for r in polarity.labelled(rows(spark, *WORKED), 25).orderBy("pair_id").collect()] == [1, 0, 0]  # strict
    ang = difficulty.with_difficulty(polarity.orient_pairs(rows(spark, *WORKED), 20)).orderBy("pair_id").collect()
    assert [r["ang"] for r in ang] == [M, -M]


def test_reference_cancels(spark):
    df = rows(spark, *WORKED).withColumns({"ref_w": F.col("ref_w") - 777, "ref_l": F.col("ref_l") + 99})
    a = [r[0] for r in df.orderBy("pair_id").select(S.polarity_gap("margins")).collect()]
    b = [r[0] for r in df.orderBy("pair_id").select(S.polarity_gap()).collect()]
    assert a == pytest.approx(b)


def test_orientation_is_idempotent_and_clear(spark):
    once = polarity.orient_pairs(rows(spark, *WORKED), 20)
    again = polarity.orient_pairs(once.drop("gap", "phi", "flipped"), 20)
    assert {r["pair_id"] for r in once.collect()} == {r["pair_id"] for r in again.collect()}
    assert not any(r["flipped"] for r in again.collect())
    assert all(r["gap"] > 20 * M for r in again.collect())


def test_without_reversal_is_a_subset(spark):
    df = rows(spark, *WORKED)
    kept = {r[0] for r in polarity.orient_pairs(df, 20, reversal=False).select("pair_id").collect()}
    assert kept < {r[0] for r in polarity.orient_pairs(df, 20).select("pair_id").collect()}


def test_bad_values_go_to_quarantine(spark):
    raw = spark.createDataFrame([(0, float("nan")), (1, float("inf")), (2, None), (3, -2.5)], "id long, x double")
    assert [r[0] for r in raw.orderBy("id").select(micro(F.col("x"))).collect()] == [None, None, None, -2_500_000]
    df = rows(spark, *WORKED).withColumns({"pos_w": F.when(F.col("pair_id") > 0, F.col("pos_w")), "n_l": F.when(F.col("pair_id") == 1, 0).otherwise(F.col("n_l"))})
    assert {(r["pair_id"], r["reason"]) for r in S.quarantine(df).collect()} == {(0, "log-probability missing"), (1, "empty response")}
    assert [r[0] for r in S.usable(df).select("pair_id").collect()] == [2]


def test_tau_must_be_positive(spark):
    for tau in (0, -1, float("nan")):
        with pytest.raises(ValueError):
            polarity.labelled(rows(spark, *WORKED), tau)
    with pytest.raises(ValueError):
        difficulty.select_hard(rows(spark, *WORKED), percent=101)


def test_loss_at_zero_margin_and_symmetry(spark):
    df = rows(spark, ((-5, -5), (-5, -5), (-5, -5), (1, 1)))
    assert S.preference_loss(df, "pos").first()[0] == pytest.approx(math.log(2))
    one = rows(spark, WORKED[0])
    swapped = polarity.swap_sides(one, F.lit(True))
    assert S.preference_loss(one, "pos", 0.1, "inverse").first()[0] == pytest.approx(S.preference_loss(swapped, "pos", 0.1).first()[0])


def test_top_share_equals_sorting(spark, monkeypatch):
    monkeypatch.setattr(cutoff, "HEAP_ROWS", 7)  # so that the bins have to decide
    df = spark.range(500).select(F.col("id").alias("pair_id"), ((F.col("id") * 7919) % 97).alias("s"))
    for percent in (1, 10, 33.3, 50, 100):
        got = [tuple(r) for r in cutoff.top_share(df, F.col("s"), percent).orderBy("pair_id").collect()]
        want = sorted(sorted(map(tuple, df.collect()), key=lambda r: (-r[1], r[0]))[: max(1, int(500 * percent // 100))])
        assert got == want
    same = df.withColumn("s", F.lit(4).cast("long"))
    assert [r[0] for r in cutoff.top_share(same, F.col("s"), 2).orderBy("pair_id").collect()] == list(range(10))
    assert cutoff.top_share(df.limit(0), F.col("s"), 50).count() == 0


@pytest.mark.parametrize("parts", [1, 3, 16])
def test_distributed_rank(spark, parts):
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", parts)
    df = spark.range(300).select(F.col("id").alias("pair_id"), (F.col("id") % 11).alias("s"))
    got = cutoff.distributed_rank(df, [F.col("s").desc(), F.col("pair_id").asc()]).orderBy("position").collect()
    spark.conf.set("spark.sql.shuffle.partitions", before)
    assert [r["position"] for r in got] == list(range(1, 301))
    assert [(-r["s"], r["pair_id"]) for r in got] == sorted((-r["s"], r["pair_id"]) for r in got)


def test_hard_and_easy_halves_are_disjoint(spark):
    df = rows(spark, *[((-10, -40), (-50, -15), (-i, -20), (10, 10)) for i in range(1, 21)])
    clear = polarity.orient_pairs(df, 20)
    hard, easy = (difficulty.calibrate(clear, how, 10) for how in ("hard", "easy"))
    assert hard.join(easy, "pair_id").count() == 0
    assert hard.agg(F.min("ang")).first()[0] >= easy.agg(F.max("ang")).first()[0]


def test_sql_functions_agree(spark):
    register_sql(spark)
    rows(spark, *WORKED).createOrReplaceTempView("worked")
    got = spark.sql("SELECT polarity_gap(pos_w, pos_l, inv_w, inv_l) AS g, polarity_label(polarity_gap(pos_w, pos_l, inv_w, inv_l), 20D) AS l, nll_gap(ref_w, n_w, ref_l, n_l) AS a FROM worked ORDER BY pair_id").collect()
    assert [(r["g"], r["l"]) for r in got] == [(65.0, 1), (-25.0, -1), (0.0, 0)]
    assert [r["a"] for r in got][:2] == [1.0, 1.0]
    assert spark.sql("SELECT polarity_label(double('NaN'), 20D)").first()[0] is None


def test_expand_pair(spark):
    register_expand_pair(spark)
    got = [tuple(r) for r in spark.sql("SELECT * FROM expand_pair('a b', ' c ')").collect()]
    assert got == [("w", 0, "a", ""), ("w", 1, "b", "a"), ("l", 0, "c", "")]
