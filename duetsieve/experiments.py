"""The experiments as queries over the given tables, each with a DuckDB counterpart where SQL can express it.

Basket pairs carry exact signals by formula and serve the sweeps, ablations, baselines and orders.  Graded
and dialogue pairs carry text and serve the language models and trained policies.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import signals as S
from .functions.columns import MICRO, held_out, judge_scores
from .functions.sql import register_sql
from .operators import analysis, baselines, costs, difficulty, evaluate, hygiene, lm, polarity, policy, reward, scorers, sets
from .plans.selection import PRESETS, preset, select_pairs
from .plans.stages import materialised
from .published import CLAIMS, COSTS
from .sources import pairs as P
from .sources.tables import table

TAU = 20.0
TAUS = [2.0, 5.0, 10.0, 15.0, 20.0, 25.0, 30.0]
SHARES = [10, 25, 50, 75, 100]
Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
O: dict[str, str] = {}


def _query(name: str, sql: str | None = None):
    def put(f):
        Q[name] = f
        if sql:
            O[name] = sql
        return f

    return put


def queries() -> dict:
    return dict(Q)


def oracle_sql() -> dict:
    return dict(O)


# ---- carriers -------------------------------------------------------------------------------------------


def _sum(model: str, side: str) -> str:
    a, b, c, m = P.FORMULA[model]
    on = f"k % 2 = {1 if side == 'w' else 0}"
    return f"CAST(sum(CASE WHEN {on} THEN -1000000 * (1 + (l_partkey * {a} + l_suppkey * {b} + l_linenumber * {c}) % {m}) END) AS BIGINT) AS {model}_{side}"


def _side(side: str) -> str:
    on = f"k % 2 = {1 if side == 'w' else 0}"
    return f"""CAST(count(*) FILTER (WHERE {on}) AS INT) AS n_{side}, CAST(sum(CASE WHEN {on} THEN length(p_brand) + 1 END) - 1 AS INT) AS len_{side},
    CAST(sum(CASE WHEN {on} THEN CAST(floor(l_extendedprice * (1 - l_discount) * 1000000 + 0.5) AS BIGINT) END) AS DOUBLE) / 1e6 AS ext_{side}"""


_NLL = lambda s: f"(-(CAST(ref_{s} AS DOUBLE) / 1e6)) / n_{s}"
_ANG = f"CAST(floor(({_NLL('w')} - {_NLL('l')}) * 1000000 + 0.5) AS BIGINT)"
_LINES = f"""lines AS (
  SELECT l.*, p.p_brand, row_number() OVER (PARTITION BY l_orderkey ORDER BY {", ".join(P.LINE_ORDER)}) AS k
  FROM lineitem l JOIN part p ON p.p_partkey = l.l_partkey)"""
_TURN = ", ".join(f"CASE WHEN turn THEN {c}_{b} ELSE {c}_{a} END AS {c}_{a}" for c in S.SIDED for a, b in ("wl", "lw"))


def _h(salt: str, x: str = "pair_id") -> str:
    return f"CAST('0x' || substr(md5('{salt}' || CAST({x} AS VARCHAR)), 1, 8) AS BIGINT)"


_IM = lambda m: f"(CAST(({m}_w - ref_w) - ({m}_l - ref_l) AS DOUBLE) / 1000000)"
_WHOLE = lambda x: f"CAST(floor(({x}) * 1000000 + 0.5) AS BIGINT)"
_PPL = lambda s: f"exp({_NLL(s)})"
_BASE = f"""WITH {_LINES},
sums AS (
  SELECT l_orderkey AS pair_id, {", ".join(_sum(m, s) for m in P.FORMULA for s in "wl")}, {_side("w")}, {_side("l")}
  FROM lines GROUP BY l_orderkey HAVING count(*) > 1),
signals AS MATERIALIZED (
  SELECT s.*, coalesce(o.o_orderpriority, 'none') AS grp, (pos_w - pos_l) - (inv_w - inv_l) AS gap FROM sums s LEFT JOIN orders o ON o.o_orderkey = s.pair_id),
labelled AS (SELECT *, CASE WHEN gap > 20000000 THEN 1 WHEN gap < -20000000 THEN -1 ELSE 0 END AS phi FROM signals),
turned AS (SELECT pair_id, grp, gap, phi, phi = -1 AS flipped, {_TURN} FROM (SELECT *, phi = -1 AS turn FROM labelled WHERE phi <> 0)),
clear AS MATERIALIZED (SELECT *, {_ANG} AS ang FROM turned)"""


def _signals(spark: SparkSession, sf_dir: str) -> DataFrame:
    return materialised(P.basket_signals(spark, sf_dir), "basket")


def _half(df: DataFrame) -> int:
    return max(1, df.count() // 2)


_HALF = "(SELECT greatest(1, count(*) // 2) FROM signals)"

_query("q_signals", f"{_BASE} SELECT pair_id, grp, {', '.join(f'{c}_{s}' for c in S.SIDED for s in 'wl')} FROM signals")(P.basket_signals)

_query(
    "q_pairs_basket",
    f"""WITH {_LINES} SELECT l_orderkey AS pair_id, coalesce(max(o.o_orderpriority), 'none') AS grp, 'order ' || l_orderkey AS prompt,
  string_agg(p_brand, ' ' ORDER BY k) FILTER (WHERE k % 2 = 1) AS chosen, string_agg(p_brand, ' ' ORDER BY k) FILTER (WHERE k % 2 = 0) AS rejected
FROM lines LEFT JOIN orders o ON o.o_orderkey = l_orderkey GROUP BY l_orderkey HAVING count(*) > 1""",
)(P.basket_pairs)

_DIALOG = """turns AS (
  SELECT *, string_agg(text, chr(10)) OVER (PARTITION BY conv_id ORDER BY turn) AS prompt,
         lead(role) OVER w AS next_role, lead(turn) OVER w AS next_turn, lead(text) OVER w AS chosen
  FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)),
asked AS (SELECT conv_id, turn, prompt, chosen, row_number() OVER (ORDER BY conv_id, turn) AS k, count(*) OVER () AS n
          FROM turns WHERE role = 'user' AND next_role = 'assistant' AND next_turn = turn + 1),
dialog AS (SELECT a.conv_id * 1000 + a.turn AS pair_id, 'dialog' AS grp, a.prompt, a.chosen, b.chosen AS rejected FROM asked a JOIN asked b ON b.k = a.k % a.n + 1)"""
_query("q_pairs_dialog", f"WITH {_DIALOG} SELECT * FROM dialog")(P.dialog_pairs)

_GRADED = """graded AS MATERIALIZED (
  WITH d AS (SELECT d.*, quality = 1 AND toxic = 0 AS good FROM documents d JOIN labels USING (doc_id)),
  r AS (SELECT *, row_number() OVER (PARTITION BY lang, good ORDER BY doc_id) - 1 AS k, count(*) OVER (PARTITION BY lang, good) AS n FROM d),
  b AS (SELECT * FROM r WHERE NOT good)
  SELECT g.doc_id AS pair_id, g.lang AS grp, g.lang || ' ' || g.source AS prompt, g.text AS chosen, b.text AS rejected
  FROM r g JOIN b ON b.lang = g.lang AND b.k = g.k % b.n WHERE g.good)"""
_query("q_pairs_graded", f"WITH {_GRADED} SELECT * FROM graded")(P.graded_pairs)
_query(
    "q_pairs_noisy",
    f"""WITH {_GRADED}, s AS (SELECT *, {_h('split:')} % 10 < 8 AND {_h('swap:')} % 5 = 0 AS is_swapped FROM graded)
SELECT pair_id, grp, is_swapped, md5(CASE WHEN is_swapped THEN rejected ELSE chosen END) AS chosen_md5 FROM s""",
)(lambda spark, d: P.noisy(P.graded_pairs(spark, d)).select("pair_id", "grp", "is_swapped", F.md5("chosen").alias("chosen_md5")))


def _session_sql(more: str = "") -> str:
    return f"""WITH p AS (
  SELECT e.event_id AS pair_id, e.user_id, e.ts, e.value AS ext_w, v.event_id AS view_id, v.ts AS view_ts, v.value AS ext_l,
         row_number() OVER (PARTITION BY e.event_id ORDER BY v.ts DESC, v.event_id DESC) AS k
  FROM events e JOIN events v ON v.user_id = e.user_id AND v.event_type = 'view' AND (v.ts < e.ts OR v.ts = e.ts AND v.event_id < e.event_id)
  WHERE e.event_type = 'purchase')
SELECT pair_id, user_id, ts, ext_w, view_id, view_ts, ext_l FROM p WHERE k = 1 {more}"""


_query("q_pairs_session", _session_sql())(P.session_pairs)
_query("q_asof_session", _session_sql("AND ts - view_ts <= INTERVAL 1 DAY"))(lambda spark, d: P.session_pairs(spark, d, "1 day"))
_query("q_pairs_vector")(lambda spark, d: P.vector_pairs(spark, d).withColumns({c: F.round(c, 5) for c in ("ext_w", "ext_l")}))

# ---- signal algebra -------------------------------------------------------------------------------------


@_query(
    "q_margins",
    f"""{_BASE} SELECT pair_id, round({_IM('pos')}, 6) AS m_pos, round({_IM('inv')}, 6) AS m_inv, round(CAST(gap AS DOUBLE) / 1e6, 6) AS r_ad,
  round(1 / (1 + exp(-0.1 * {_IM('pos')})), 6) AS p_pos, {_ANG} AS ang, round({_PPL('w')} - {_PPL('l')}, 4) AS ppl_gap, round(ext_w - ext_l, 4) AS em FROM signals""",
)
def q_margins(spark, sf_dir):
    return P.basket_signals(spark, sf_dir).select(
        "pair_id", F.round(S.implicit_margin("pos"), 6).alias("m_pos"), F.round(S.implicit_margin("inv"), 6).alias("m_inv"), F.round(S.polarity_gap("margins"), 6).alias("r_ad"),
        F.round(S.preference_probability(S.implicit_margin("pos"), 0.1), 6).alias("p_pos"), S.nll_gap_micro().alias("ang"), F.round(S.ppl_gap(), 4).alias("ppl_gap"), F.round(S.external_margin(), 4).alias("em"),
    )


_SOFT = lambda x: f"(greatest({x}, 0) + ln(1 + exp(-abs({x}))))"


@_query("q_preference_loss", f"{_BASE} SELECT round(avg({_SOFT(f'-0.1 * {_IM("pos")}')}), 6) AS forward, round(avg({_SOFT(f'0.1 * {_IM("inv")}')}), 6) AS inverse, count(*) AS n_pairs FROM signals")
def q_preference_loss(spark, sf_dir):
    df = P.basket_signals(spark, sf_dir)
    loss = lambda m, how: F.round(F.avg(S.pair_loss(S.implicit_margin(m), 0.1, how)), 6)
    return df.agg(loss("pos", "forward").alias("forward"), loss("inv", "inverse").alias("inverse"), F.count(F.lit(1)).alias("n_pairs"))


@_query("q_kl_reward", f"{_BASE} SELECT round(avg(ext_w) - 0.5 * avg(CAST(pos_w - ref_w AS DOUBLE) / 1000000), 3) AS objective FROM signals")
def q_kl_reward(spark, sf_dir):
    return S.kl_regularised_reward(P.basket_signals(spark, sf_dir), "pos", 0.5).select(F.round("objective", 3).alias("objective"))


@_query(
    "q_sql_functions",
    f"{_BASE} SELECT pair_id, round(CAST(gap AS DOUBLE) / 1e6, 6) AS r_ad, CAST(phi AS INT) AS phi, round({_NLL('w')}, 6) AS nll_w FROM labelled",
)
def q_sql_functions(spark, sf_dir):
    register_sql(spark)
    P.basket_signals(spark, sf_dir).createOrReplaceTempView("duetsieve_signals")
    return spark.sql(
        "SELECT pair_id, round(polarity_gap(pos_w, pos_l, inv_w, inv_l), 6) AS r_ad, polarity_label(polarity_gap(pos_w, pos_l, inv_w, inv_l), 20D) AS phi, round(avg_nll(ref_w, n_w), 6) AS nll_w FROM duetsieve_signals"
    )


@_query("q_sequence_scores", f"WITH {_LINES} SELECT l_orderkey AS pair_id, CASE WHEN k % 2 = 1 THEN 'w' ELSE 'l' END AS side, 'ref' AS model, CAST(sum(-1000000 * (1 + (l_partkey * 31 + l_suppkey * 17 + l_linenumber * 7) % 9)) AS BIGINT) AS lp, CAST(count(*) AS INT) AS n FROM lines GROUP BY ALL")
def q_sequence_scores(spark, sf_dir):
    a, b, c, m = P.FORMULA["ref"]
    lines = P._ranked_lines(spark, sf_dir)
    score = -MICRO * (1 + (F.col("l_partkey") * a + F.col("l_suppkey") * b + F.col("l_linenumber") * c) % m)
    return S.sequence_scores(lines.select(F.col("l_orderkey").alias("pair_id"), F.when(F.col("k") % 2 == 1, "w").otherwise("l").alias("side"), F.lit("ref").alias("model"), score.alias("lp")))


# ---- first stage ----------------------------------------------------------------------------------------

_CLEAR = "pair_id, gap, CAST(phi AS INT) AS phi, flipped, ref_w, ref_l, n_w, n_l"


def _clear(df: DataFrame) -> DataFrame:
    return df.select("pair_id", "gap", F.col("phi").cast("int").alias("phi"), "flipped", "ref_w", "ref_l", "n_w", "n_l")


_query("q_stage1_reversal", f"{_BASE} SELECT {_CLEAR} FROM clear")(lambda spark, d: _clear(polarity.orient_pairs(P.basket_signals(spark, d), TAU)))
_query("q_stage1_no_reversal", f"{_BASE} SELECT {_CLEAR} FROM clear WHERE phi = 1")(lambda spark, d: _clear(polarity.orient_pairs(P.basket_signals(spark, d), TAU, reversal=False)))
_query("q_tau_sweep", f"{_BASE} SELECT t AS tau, count(*) FILTER (WHERE gap > t * 1000000) AS kept, count(*) FILTER (WHERE gap < -t * 1000000) AS flipped, count(*) FILTER (WHERE abs(gap) <= t * 1000000) AS dropped FROM signals, (SELECT CAST(unnest({TAUS}) AS DOUBLE) AS t) GROUP BY t")(
    lambda spark, d: polarity.tau_sweep(P.basket_signals(spark, d), TAUS)
)
_query(
    "q_tau_grid",
    f"""{_BASE}, n AS (SELECT greatest(1, count(*) // 12) AS step FROM signals),
r AS (SELECT abs(gap) AS size, row_number() OVER (ORDER BY abs(gap) DESC, pair_id) AS k, rank() OVER (ORDER BY abs(gap) DESC) AS first FROM signals)
SELECT k - 1 AS asked, first - 1 AS retained, size AS tau_micro FROM r, n WHERE k % step = 1 AND k > 1""",
)(lambda spark, d: (lambda s: polarity.tau_grid(s, max(1, s.count() // 12)))(_signals(spark, d)))
_query(
    "q_polarity_profile",
    f"{_BASE} SELECT grp, CAST(phi AS INT) AS phi, count(*) AS n_pairs, grouping(grp, phi) AS level FROM labelled GROUP BY ROLLUP (grp, phi)",
)(lambda spark, d: polarity.polarity_profile(P.basket_signals(spark, d), TAU).withColumn("phi", F.col("phi").cast("int")))
_query(
    "q_quarantine",
    f"{_BASE} SELECT pair_id, CASE WHEN pair_id % 7 = 0 THEN 'log-probability missing' ELSE 'empty response' END AS reason FROM signals WHERE pair_id % 7 = 0 OR pair_id % 11 = 0",
)(lambda spark, d: S.quarantine(P.basket_signals(spark, d).withColumns({"pos_w": F.when(F.col("pair_id") % 7 != 0, F.col("pos_w")), "n_l": F.when(F.col("pair_id") % 11 != 0, F.col("n_l")).otherwise(0)})).select("pair_id", "reason"))

_FIRST = {"r_ad": "gap", "pim": "(pos_w - ref_w - pos_l + ref_l)", "iim": "(-(inv_w - ref_w - inv_l + ref_l))", "em": _WHOLE("ext_w - ext_l")}
for _by, _x in _FIRST.items():
    _query(f"q_first_stage_{_by}", f"{_BASE} SELECT pair_id, s < 0 AS flipped FROM (SELECT pair_id, {_x} AS s FROM signals) ORDER BY abs(s) DESC, pair_id LIMIT {_HALF}")(
        lambda spark, d, by=_by: (lambda s: polarity.first_stage(s, by, _half(s)).select("pair_id", "flipped"))(_signals(spark, d))
    )

# ---- second stage, orders, whole pipeline ---------------------------------------------------------------

_HARD = f"hard AS MATERIALIZED (SELECT * FROM clear ORDER BY ang DESC, pair_id LIMIT (SELECT CASE WHEN count(*) = 0 THEN 0 ELSE greatest(1, count(*) * 50 // 100) END FROM clear))"
_query("q_full_pipeline", f"{_BASE}, {_HARD} SELECT pair_id, gap, CAST(phi AS TINYINT) AS phi, flipped, ang, row_number() OVER (ORDER BY ang, pair_id) AS position FROM hard")(
    lambda spark, d: select_pairs(_signals(spark, d), TAU)
)
_SEED = {"hard": "ang DESC", "easy": "ang", "random": _h("order:1:")}
for _how, _x in _SEED.items():
    _query(f"q_calibrate_{_how}", f"{_BASE} SELECT pair_id, flipped, ang FROM clear ORDER BY {_x}, pair_id LIMIT (SELECT greatest(1, count(*) // 2) FROM clear)")(
        lambda spark, d, how=_how: (lambda c: difficulty.calibrate(c, how, _half(c)).select("pair_id", "flipped", "ang"))(polarity.orient_pairs(_signals(spark, d), TAU))
    )
for _how, _x in {"random": _h("order:1:"), "hard_first": "ang DESC", "easy_first": "ang"}.items():
    _query(f"q_order_{_how}", f"{_BASE}, {_HARD} SELECT pair_id, ang, row_number() OVER (ORDER BY {_x}, pair_id) AS position FROM hard")(
        lambda spark, d, how=_how: difficulty.curriculum_order(difficulty.select_hard(polarity.orient_pairs(_signals(spark, d), TAU), percent=50), how).select("pair_id", "ang", "position")
    )
_query(
    "q_k_sweep",
    f"""{_BASE}, r AS (SELECT *, row_number() OVER (ORDER BY ang DESC, pair_id) AS k, count(*) OVER () AS n FROM clear)
SELECT p AS percent, count(*) AS n_pairs, min(ang) AS least_ang, CAST(sum(ang) AS BIGINT) AS sum_ang, count(*) FILTER (WHERE flipped) AS flipped
FROM r, (SELECT CAST(unnest({SHARES}) AS INT) AS p) WHERE k <= greatest(1, n * p // 100) GROUP BY p""",
)(lambda spark, d: difficulty.k_sweep(polarity.orient_pairs(P.basket_signals(spark, d), TAU), SHARES))
_query(
    "q_contrast_profile",
    f"{_BASE} SELECT w AS chosen_hard, l AS rejected_hard, count(*) AS n_pairs, grouping(w, l) AS level FROM (SELECT {_NLL('w')} > 5 AS w, {_NLL('l')} > 5 AS l FROM clear) GROUP BY CUBE (w, l)",
)(lambda spark, d: difficulty.contrast_profile(polarity.orient_pairs(P.basket_signals(spark, d), TAU), 5.0, 5.0))
_query("q_profile_cube", f"{_BASE} SELECT grp, flipped, count(*) AS n_pairs, CAST(sum(ang) AS BIGINT) AS sum_ang, grouping(grp, flipped) AS level FROM clear GROUP BY CUBE (grp, flipped)")(
    lambda spark, d: analysis.profile(difficulty.with_difficulty(polarity.orient_pairs(P.basket_signals(spark, d), TAU)), ["grp", "flipped"])
)


@_query(
    "q_presets",
    f"""{_BASE}, {_HARD} SELECT 'none' AS preset, count(*) AS n_pairs, 0 AS n_flipped FROM signals UNION ALL SELECT 'r_ad_no_reversal', count(*), 0 FROM clear WHERE phi = 1
UNION ALL SELECT 'r_ad_only', count(*), count(*) FILTER (WHERE flipped) FROM clear UNION ALL SELECT 'ang_only', {_HALF}, 0 UNION ALL SELECT 'full', count(*), count(*) FILTER (WHERE flipped) FROM hard""",
)
def q_presets(spark, sf_dir):
    s = _signals(spark, sf_dir)
    rows = [preset(s, name, TAU).agg(F.lit(name).alias("preset"), F.count(F.lit(1)).alias("n_pairs"), F.count_if("flipped").alias("n_flipped")) for name in ("none", "r_ad_no_reversal", "r_ad_only", "ang_only", "full")]
    return reduce(DataFrame.unionByName, rows)


@_query("q_random_half", f"{_BASE} SELECT pair_id, ang FROM clear WHERE {_h('half:1:')} % 2 = 0 ORDER BY ang DESC, pair_id LIMIT (SELECT greatest(1, count(*) * 50 // 100) FROM clear WHERE {_h('half:1:')} % 2 = 0)")
def q_random_half(spark, sf_dir):
    clear = polarity.half_sample(polarity.orient_pairs(_signals(spark, sf_dir), TAU))
    return difficulty.select_hard(clear, percent=50).select("pair_id", "ang")


# ---- baselines ------------------------------------------------------------------------------------------

_BASELINES: dict[str, tuple[Callable, str]] = {
    "em": (baselines.by_external_margin, f"{_WHOLE('ext_w - ext_l')} DESC"),
    "im": (baselines.by_implicit_margin, f"{_WHOLE(_IM('pos'))} DESC"),
    "ppl_gap": (baselines.by_ppl_gap, f"round({_PPL('w')} - {_PPL('l')}, 4) DESC"),
    "longest_chosen": (baselines.by_chosen_length, "len_w DESC"),
    "map": (baselines.by_alignment_potential, f"{_WHOLE(f'abs(ext_w - ext_l) - abs({_IM("pos")})')} DESC"),
    "map_signed": (lambda df, n: baselines.by_alignment_potential(df, n, "abs_signed"), f"{_WHOLE(f'abs(ext_w - ext_l) - {_IM("pos")}')} DESC"),
    "im_em": (baselines.by_combined_margin, "round(z, 6) DESC"),
    "im_em_ranks": (lambda df, n: baselines.by_combined_margin(df, n, "ranksum"), f"row_number() OVER (ORDER BY {_WHOLE(_IM('pos'))}, pair_id) + row_number() OVER (ORDER BY {_WHOLE('ext_w - ext_l')}, pair_id) DESC"),
    "im_em_prob": (lambda df, n: baselines.by_combined_margin(df, n, "prob"), f"round({_IM('pos')} + (ext_w - ext_l), 6) DESC"),
    "longest_rejected": (lambda df, n: baselines.by_rejected_length(df, n, 0.0), "len_l DESC"),
    "random": (baselines.by_random, _h("order:1:")),
}
_VARIANTS = ("map_signed", "im_em_prob", "im_em_ranks")
_Z = f"(SELECT *, ({_IM('pos')} - avg({_IM('pos')}) OVER ()) / stddev_pop({_IM('pos')}) OVER () + ((ext_w - ext_l) - avg(ext_w - ext_l) OVER ()) / stddev_pop(ext_w - ext_l) OVER () AS z FROM signals)"


def _baseline_sql(name: str, columns: str = "pair_id") -> str:
    source = _Z if name == "im_em" else "signals"
    where = f"WHERE {_WHOLE('ext_w - ext_l')} >= 0" if name == "longest_rejected" else ""
    return f"SELECT {columns} FROM {source} {where} ORDER BY {_BASELINES[name][1]}, pair_id LIMIT {_HALF}"


for _name, (_f, _x) in _BASELINES.items():
    _query(f"q_base_{_name}", f"{_BASE} {_baseline_sql(_name)}")(lambda spark, d, f=_f: (lambda s: f(s, _half(s)).select("pair_id"))(_signals(spark, d)))
_query("q_base_full", f"{_BASE} SELECT pair_id FROM signals")(lambda spark, d: baselines.baseline_full(P.basket_signals(spark, d)).select("pair_id"))
_UNTUNED = {
    "n_pairs": "count(*)",
    "n_trained": "CAST(0 AS BIGINT)",
    "wr": "round(100 * avg(CASE WHEN ref_w = ref_l OR ext_w = ext_l THEN 0.5e0 WHEN (ref_w > ref_l) = (ext_w > ext_l) THEN 1e0 ELSE 0e0 END), 6)",
    "length": "round(avg(CASE WHEN ref_w > ref_l THEN 1e0 * len_w WHEN ref_w < ref_l THEN 1e0 * len_l ELSE (len_w + len_l) / 2e0 END), 6)",
}
_query("q_base_init", f"{_BASE} SELECT grp, {', '.join(f'{x} AS {k}' for k, x in _UNTUNED.items())} FROM signals GROUP BY grp")(lambda spark, d: baselines.baseline_init(P.basket_signals(spark, d), _UNTUNED))

_LOSSES = " UNION ALL ".join(
    f"SELECT pair_id, {k} AS model, {_h('half:ensemble:')} % 2 = {k // 3 % 2} AS seen, {_WHOLE(_SOFT(f'-0.1 * ({_IM("pos")} - {_IM("inv")} * {baselines.formula_blend(k)})'))} AS loss FROM signals" for k in range(6)
)


@_query("q_base_ensemble", f"{_BASE}, losses AS ({_LOSSES}), m AS (SELECT pair_id, CAST(sum(loss) // count(*) AS BIGINT) AS mean_loss FROM losses WHERE NOT seen GROUP BY pair_id) SELECT pair_id, mean_loss FROM m ORDER BY mean_loss, pair_id LIMIT {_HALF}")
def q_base_ensemble(spark, sf_dir):
    s = _signals(spark, sf_dir)
    return baselines.by_ensemble_easiness(s, baselines.formula_losses(s), _half(s)).select("pair_id", "mean_loss")


# ---- analyses -------------------------------------------------------------------------------------------


def _selections(s: DataFrame) -> dict[str, DataFrame]:
    n = _half(s)
    return {"ours": preset(s, "full", TAU), "im": baselines.by_implicit_margin(s, n), "em": baselines.by_external_margin(s, n), "ensemble": baselines.by_ensemble_easiness(s, baselines.formula_losses(s), n)}


_SELECTED = f"""{_HARD}, losses AS ({_LOSSES}), m AS (SELECT pair_id, CAST(sum(loss) // count(*) AS BIGINT) AS mean_loss FROM losses WHERE NOT seen GROUP BY pair_id),
sel AS (SELECT 'ours' AS method, pair_id FROM hard UNION ALL SELECT 'im', pair_id FROM ({_baseline_sql('im')}) UNION ALL SELECT 'em', pair_id FROM ({_baseline_sql('em')})
  UNION ALL SELECT 'ensemble', pair_id FROM (SELECT pair_id FROM m ORDER BY mean_loss, pair_id LIMIT {_HALF}))"""


@_query(
    "q_method_overlap",
    f"""{_BASE}, {_SELECTED}, o AS (SELECT pair_id FROM sel WHERE method = 'ours')
SELECT method, (SELECT count(*) FROM o) AS n_ours, count(*) AS n_other, count(*) FILTER (WHERE pair_id IN (SELECT pair_id FROM o)) AS n_both,
  round(100.0 * CAST(count(*) FILTER (WHERE pair_id IN (SELECT pair_id FROM o)) AS DOUBLE) / (SELECT count(*) FROM o), 4) AS overlap,
  round(CAST(count(*) FILTER (WHERE pair_id IN (SELECT pair_id FROM o)) AS DOUBLE) / ((SELECT count(*) FROM o) + count(*) - count(*) FILTER (WHERE pair_id IN (SELECT pair_id FROM o))), 6) AS jaccard
FROM sel GROUP BY method""",
)
def q_method_overlap(spark, sf_dir):
    return analysis.overlap(_selections(_signals(spark, sf_dir)), "ours")


_JUDGED = f"""{_SELECTED}, j AS (SELECT s.method, p.pair_id AS prompt_id, p.pair_id % 2 AS turn, CASE WHEN ext_w > ext_l THEN 1.0 WHEN ext_w = ext_l THEN 0.5 ELSE 0.0 END AS p_win,
  len_w AS len_model, len_l AS len_base, 10 * ext_w / (ext_w + ext_l) AS score FROM sel s JOIN signals p ON p.pair_id = s.pair_id)"""


def judgements(signals: DataFrame, selections: dict[str, DataFrame]) -> DataFrame:
    """Each method's selected pairs as judged prompts: the chosen response against the rejected one by external reward."""
    p = F.when(F.col("ext_w") > F.col("ext_l"), 1.0).when(F.col("ext_w") == F.col("ext_l"), 0.5).otherwise(0.0)
    judged = signals.select("pair_id", p.alias("p_win"), F.col("len_w").alias("len_model"), F.col("len_l").alias("len_base"), (10 * F.col("ext_w") / (F.col("ext_w") + F.col("ext_l"))).alias("score"))
    named = reduce(DataFrame.unionByName, [df.select(F.lit(m).alias("method"), "pair_id") for m, df in selections.items()])
    return named.join(judged, "pair_id").withColumnRenamed("pair_id", "prompt_id").withColumn("turn", F.col("prompt_id") % 2)


def _judged(spark, sf_dir):
    s = _signals(spark, sf_dir)
    return judgements(s, _selections(s))


@_query("q_win_rate", f"{_BASE}, {_JUDGED} SELECT method, round(100 * avg(p_win), 6) AS wr, count(*) AS n, round(avg(len_model), 6) AS length FROM j GROUP BY method")
def q_win_rate(spark, sf_dir):
    j = materialised(_judged(spark, sf_dir), "judged")
    return evaluate.win_rate(j).join(evaluate.mean_length(j), "method").select("method", F.round("wr", 6).alias("wr"), "n", F.round("length", 6).alias("length"))


_query("q_mean_score", f"{_BASE}, {_JUDGED} SELECT method, round(avg(s), 6) AS score FROM (SELECT method, prompt_id, avg(score) AS s FROM j GROUP BY ALL) GROUP BY method")(
    lambda spark, d: evaluate.mean_score(_judged(spark, d)).select("method", F.round("score", 6).alias("score"))
)
_query("q_lc_win_rate")(lambda spark, d: evaluate.length_controlled_win_rate(materialised(_judged(spark, d), "judged")))


def _hist(value: str, width: float) -> str:
    return f"CAST(floor(({value}) / {width}) * {width} AS DOUBLE)"


_query("q_r_ad_hist", f"{_BASE} SELECT grp, {_hist('CAST(gap AS DOUBLE) / 1e6', 5.0)} AS bin, count(*) AS n FROM signals GROUP BY ALL")(lambda spark, d: analysis.histogram(P.basket_signals(spark, d), S.polarity_gap(), 5.0, "grp"))


def _compare_sql(value: str, width: float) -> str:
    return f"""{_BASE}, {_HARD}, a AS (SELECT {_hist(value, width)} AS bin, count(*) AS n FROM signals GROUP BY 1), b AS (SELECT {_hist(value, width)} AS bin, count(*) AS n FROM hard GROUP BY 1),
f AS (SELECT bin, coalesce(a.n, 0) AS n_before, coalesce(b.n, 0) AS n_after FROM a FULL JOIN b USING (bin))
SELECT bin, n_before, n_after, round(abs(CAST(sum(n_before) OVER (ORDER BY bin) AS DOUBLE) / sum(n_before) OVER () - CAST(sum(n_after) OVER (ORDER BY bin) AS DOUBLE) / sum(n_after) OVER ()), 6) AS gap FROM f"""


def _compare(value, width):
    def run(spark, sf_dir):
        s = _signals(spark, sf_dir)
        return analysis.compare_distribution(s, preset(s, "full", TAU), value(), width)

    return run


_query("q_length_gap_hist", _compare_sql("CAST(len_w - len_l AS DOUBLE)", 9.0))(_compare(lambda: (F.col("len_w") - F.col("len_l")).cast("double"), 9.0))
_query("q_em_hist", _compare_sql("ext_w - ext_l", 10000.0))(_compare(S.external_margin, 10000.0))
_query("q_margin_joint", f"{_BASE} SELECT {_hist(_IM('pos'), 10)} AS pos_bin, {_hist(_IM('inv'), 10)} AS inv_bin, count(*) AS n FROM signals GROUP BY ALL")(lambda spark, d: analysis.margin_joint(P.basket_signals(spark, d), 10))
_query("q_margin_corr", f"{_BASE} SELECT round(corr({_IM('pos')}, {_IM('inv')}), 6) AS corr, count(*) AS n FROM signals")(
    lambda spark, d: P.basket_signals(spark, d).agg(F.round(F.corr(S.implicit_margin("pos"), S.implicit_margin("inv")), 6).alias("corr"), F.count(F.lit(1)).alias("n"))
)
_GAP = "CAST(len_w - len_l AS DOUBLE)"
_query(
    "q_length_sensitivity",
    f"{_BASE} "
    + " UNION ALL ".join(
        f"SELECT '{k}' AS score, round(corr({v}, {_GAP}), 6) AS corr FROM signals" for k, v in {"r_ad": "CAST(gap AS DOUBLE) / 1e6", "ang": f"{_NLL('w')} - {_NLL('l')}", "ppl_gap": f"{_PPL('w')} - {_PPL('l')}", "im": _IM("pos")}.items()
    ),
)(lambda spark, d: analysis.length_sensitivity(P.basket_signals(spark, d)))


@_query("q_wrong_direction", f"{_BASE}, {_SELECTED}, x AS (SELECT 'map' AS method, pair_id FROM ({_baseline_sql('map')}) UNION ALL SELECT * FROM sel) SELECT method, count(*) AS n, round(avg(CASE WHEN {_IM('pos')} < 0 THEN 1.0 ELSE 0.0 END), 6) AS wrong FROM x JOIN signals s ON s.pair_id = x.pair_id GROUP BY method")
def q_wrong_direction(spark, sf_dir):
    s = _signals(spark, sf_dir)
    kept = _selections(s) | {"map": baselines.by_alignment_potential(s, _half(s))}
    rows = [analysis.wrong_direction_rate(df.select("pair_id").join(s, "pair_id")).select(F.lit(m).alias("method"), "n", "wrong") for m, df in kept.items()]
    return reduce(DataFrame.unionByName, rows)


@_query("q_signal_comparison", f"{_BASE} " + " UNION ALL ".join(f"SELECT '{k}' AS signal, round(avg(CASE WHEN ({v}) > 0 THEN 1.0 ELSE 0.0 END), 6) AS agrees FROM signals WHERE ext_w > ext_l" for k, v in _FIRST.items()))
def q_signal_comparison(spark, sf_dir):
    df = P.basket_signals(spark, sf_dir).where("ext_w > ext_l")
    return df.agg(F.array(*[F.struct(F.lit(k).alias("signal"), F.round(F.avg((f() > 0).cast("double")), 6).alias("agrees")) for k, f in polarity.FIRST_STAGE.items()]).alias("r")).select(F.inline("r"))


# ---- every selector's results ---------------------------------------------------------------------------

#: Selectors under the names of the printed comparison.
_NAMED = {"perplexity_gap": "ppl_gap", "longest_chosen": "longest_chosen", "external_margin": "em", "implicit_margin": "im", "alignment_potential": "map", "combined_margin": "im_em", "longest_rejected": "longest_rejected"}
_WINS = "CASE WHEN ext_w > ext_l THEN 1e0 WHEN ext_w = ext_l THEN 0.5e0 ELSE 0e0 END"
#: The printed columns on signals: win rate among pairs of as many parts, of all, length, win rate where the reference is on the other side, score.
_MEASURES = {
    "lc": f"round(100 * avg(CASE WHEN n_w = n_l THEN {_WINS} END), 6)",
    "wr": f"round(100 * avg({_WINS}), 6)",
    "length": "round(avg(len_w), 6)",
    "hard_wr": f"round(100 * avg(CASE WHEN ref_w < ref_l THEN {_WINS} END), 6)",
    "score": "round(avg(10 * ext_w / nullif(ext_w + ext_l, 0)), 6)",
}
_HALVED = f"SELECT pair_id FROM clear WHERE {_h('half:1:')} % 2 = 0 ORDER BY ang DESC, pair_id LIMIT (SELECT greatest(1, count(*) * 50 // 100) FROM clear WHERE {_h('half:1:')} % 2 = 0)"
_CHOSEN = {"full": "SELECT pair_id FROM signals", "two_stage": "SELECT pair_id FROM hard", "two_stage_half": _HALVED, "ensemble_easiest": f"SELECT pair_id FROM m ORDER BY mean_loss, pair_id LIMIT {_HALF}"}
_CHOSEN |= {name: _baseline_sql(k) for name, k in _NAMED.items()}
_RESULTS = f"""{_BASE}, {_SELECTED}, every AS ({" UNION ALL ".join(f"SELECT '{k}' AS method, pair_id FROM ({x})" for k, x in _CHOSEN.items())}),
measured AS MATERIALIZED (SELECT method, grp AS backbone, {", ".join(f"{x} AS {k}" for k, x in _MEASURES.items())} FROM every JOIN signals USING (pair_id) GROUP BY method, grp),
results AS MATERIALIZED ({" UNION ALL ".join(f"SELECT method, backbone, '{k}' AS metric, {k} AS value FROM measured WHERE {k} IS NOT NULL" for k in _MEASURES)})"""


def _results(spark, sf_dir, *methods: str) -> DataFrame:
    """method, backbone, metric, value: what each selector keeps, measured within each group of orders, which stands for a backbone."""
    s = _signals(spark, sf_dir)
    n = _half(s)
    plans = {
        "full": lambda: s,
        "two_stage": lambda: preset(s, "full", TAU),
        "two_stage_half": lambda: difficulty.select_hard(polarity.half_sample(polarity.orient_pairs(s, TAU)), percent=50),
        "ensemble_easiest": lambda: baselines.by_ensemble_easiness(s, baselines.formula_losses(s), n),
    }
    plans |= {name: (lambda f=_BASELINES[k][0]: f(s, n)) for name, k in _NAMED.items()}
    every = reduce(DataFrame.unionByName, [plans[m]().select(F.lit(m).alias("method"), "pair_id") for m in methods or plans])
    measured = every.join(s, "pair_id").groupBy("method", F.col("grp").alias("backbone")).agg(*[F.expr(x).alias(k) for k, x in _MEASURES.items()])
    cells = F.array(*[F.struct(F.lit(k).alias("metric"), F.col(k).alias("value")) for k in _MEASURES])
    return materialised(measured.select("method", "backbone", F.inline(cells)).where("value IS NOT NULL"), "results")


# ---- ranks, improvements, claims, costs and orders on them ----------------------------------------------

_query("q_published_rank", f"{_RESULTS} SELECT *, dense_rank() OVER (PARTITION BY backbone, metric ORDER BY value DESC) AS rank FROM results")(lambda spark, d: evaluate.leaderboard(_results(spark, d)))
_query("q_leaderboard_rank", f"{_RESULTS} SELECT t.backbone, t.method, round(avg(t.value - b.value), 6) AS improvement FROM results t JOIN results b ON b.method = 'full' AND b.backbone = t.backbone AND b.metric = t.metric GROUP BY ALL")(
    lambda spark, d: evaluate.average_improvement(_results(spark, d)).select("backbone", "method", F.round("improvement", 6).alias("improvement"))
)
_CLAIMED = ", ".join(f"('{a}', '{b}', '{bb}', '{k}', {float(v)}e0)" for a, b, bb, k, v in CLAIMS)


@_query(
    "q_published_claims",
    f"""{_RESULTS} SELECT c.a, c.b, c.printed, x.backbone, c.metric, c.claimed, round(x.value - y.value, 6) AS found, x.value > y.value AS holds, round(x.value - y.value, 6) >= c.claimed AS reached
FROM (VALUES {_CLAIMED}) c(a, b, printed, metric, claimed) JOIN results x ON x.method = c.a AND x.metric = c.metric JOIN results y ON y.method = c.b AND y.metric = c.metric AND y.backbone = x.backbone""",
)
def q_published_claims(spark, sf_dir):
    """The printed claims that one selector beats another, on the given tables: the difference found, and whether it has the claimed sign and size."""
    c = spark.createDataFrame([(*x[:4], float(x[4])) for x in CLAIMS], "a string, b string, printed string, metric string, claimed double")
    t = _results(spark, sf_dir, *sorted({m for x in CLAIMS for m in x[:2]}))
    one, two = t.select(F.col("method").alias("a"), "backbone", "metric", F.col("value").alias("x")), t.select(F.col("method").alias("b"), "backbone", "metric", F.col("value").alias("y"))
    found = F.round(F.col("x") - F.col("y"), 6)
    return c.join(one, ["a", "metric"]).join(two, ["b", "backbone", "metric"]).select("a", "b", "printed", "backbone", "metric", "claimed", found.alias("found"), (F.col("x") > F.col("y")).alias("holds"), (found >= F.col("claimed")).alias("reached"))


_RATES = f"{_RESULTS}, rates AS (SELECT method, round(avg(value), 6) AS avg_wr FROM results WHERE metric = 'wr' GROUP BY method)"


def _rates(spark, sf_dir) -> DataFrame:
    """method and avg_wr of the selectors that have costs: the mean of their groups' win rates."""
    return _results(spark, sf_dir, *evaluate.WORK).where("metric = 'wr'").groupBy("method").agg(F.round(F.avg("value"), 6).alias("avg_wr"))


_query(
    "q_efficiency",
    f"{_RATES} SELECT method, hours, avg_wr, round(avg_wr / hours, 4) AS efficiency FROM rates JOIN (VALUES " + ", ".join(f"('{m}', CAST({evaluate.compute_hours(m)} AS DOUBLE))" for m in evaluate.WORK) + ") t(method, hours) USING (method)",
)(lambda spark, d: evaluate.efficiency(_rates(spark, d)))

_HOW = {"random": _h("order:1:"), "hard_first": "ang DESC", "easy_first": "ang"}
_EARLY = ("lc", "wr", "length")


@_query(
    "q_published_orders",
    f"""{_BASE}, {_HARD}, ordered AS ({" UNION ALL ".join(f"SELECT '{how}' AS how, *, row_number() OVER (ORDER BY {x}, pair_id) AS position FROM hard" for how, x in _HOW.items())}),
early AS MATERIALIZED (SELECT how, {", ".join(f"{_MEASURES[k]} AS {k}" for k in _EARLY)} FROM ordered WHERE position <= (SELECT greatest(1, count(*) // 2) FROM hard) GROUP BY how)
SELECT t.how, t.lc, t.wr, t.length, round(t.lc - b.lc, 6) AS lc_gain, round(t.wr - b.wr, 6) AS wr_gain FROM early t, early b WHERE b.how = 'random'""",
)
def q_published_orders(spark, sf_dir):
    """The printed comparison of learning orders on the given tables: what the first half of each order holds, against the random one."""
    hard = materialised(difficulty.select_hard(polarity.orient_pairs(_signals(spark, sf_dir), TAU), percent=50), "hard")
    n = _half(hard)
    early = [difficulty.curriculum_order(hard, how).where(F.col("position") <= n).groupBy(F.lit(how).alias("how")).agg(*[F.expr(_MEASURES[k]).alias(k) for k in _EARLY]) for how in _HOW]
    t = materialised(reduce(DataFrame.unionByName, early), "early")  # a row an order
    base = t.where("how = 'random'").select(F.col("lc").alias("lc0"), F.col("wr").alias("wr0"))
    return t.join(F.broadcast(base), how="cross").select("how", *_EARLY, F.round(F.expr("lc - lc0"), 6).alias("lc_gain"), F.round(F.expr("wr - wr0"), 6).alias("wr_gain"))


_COSTS = ", ".join(f"('{m}', {h}e0, {e}e0)" for m, h, _, e in COSTS)


@_query("q_published_costs", f"{_RATES} SELECT method, hours, avg_wr, efficiency, round(avg_wr / hours, 4) AS found, rank() OVER (ORDER BY round(avg_wr / hours, 4) DESC) = rank() OVER (ORDER BY efficiency DESC) AS holds FROM rates JOIN (VALUES {_COSTS}) t(method, hours, efficiency) USING (method)")
def q_published_costs(spark, sf_dir):
    """Printed hours and efficiencies against the win rates of the given tables: whether each method keeps its place."""
    t = spark.createDataFrame([(m, h, e) for m, h, _, e in COSTS], "method string, hours double, efficiency double").join(_rates(spark, sf_dir), "method")
    place = lambda c: F.rank().over(Window.orderBy(F.col(c).desc()))  # noqa: E731  of a row a method
    return t.withColumn("found", F.round(F.expr("avg_wr / hours"), 4)).select("method", "hours", "avg_wr", "efficiency", "found", (place("found") == place("efficiency")).alias("holds"))


@_query("q_measured_costs")
def q_measured_costs(spark, sf_dir):
    """What each selector takes here, from the same stored signals: rows, tasks, core seconds, rows read and bytes shuffled."""
    s = _signals(spark, sf_dir)
    n = _half(s)
    plans = {f"two_stage_{name}": (lambda name=name: preset(s, name, TAU)) for name in PRESETS}
    plans |= {name: (lambda f=f: f(s, n)) for name, (f, _) in _BASELINES.items()}
    return costs.measured(spark, plans)


# ---- selections as sets, scores from outside ------------------------------------------------------------

_WITH_SELECTED = f"{_BASE}, {_SELECTED}"
_query("q_set_common", f"{_WITH_SELECTED} SELECT pair_id FROM sel GROUP BY pair_id HAVING count(*) = 4")(lambda spark, d: sets.in_all(list(_selections(_signals(spark, d)).values())))
_query("q_set_any", f"{_WITH_SELECTED} SELECT DISTINCT pair_id FROM sel")(lambda spark, d: sets.in_any(list(_selections(_signals(spark, d)).values())))
_query("q_set_new", f"{_WITH_SELECTED} SELECT pair_id FROM sel GROUP BY pair_id HAVING count(*) = 1 AND min(method) = 'ours'")(
    lambda spark, d: (lambda x: sets.newly_chosen(x.pop("ours"), list(x.values())))(_selections(_signals(spark, d)))
)
_query("q_top_per_group", f"{_BASE} SELECT grp, pair_id, ang, place FROM (SELECT *, row_number() OVER (PARTITION BY grp ORDER BY ang DESC, pair_id) AS place FROM clear) WHERE place <= 5")(
    lambda spark, d: sets.top_per_group(difficulty.with_difficulty(polarity.orient_pairs(_signals(spark, d), TAU)), "grp", F.col("ang"), 5).select("grp", "pair_id", "ang", "place")
)
_query("q_page", f"{_BASE} SELECT pair_id, ang FROM clear ORDER BY ang DESC, pair_id LIMIT 20 OFFSET 40")(
    lambda spark, d: sets.page(difficulty.with_difficulty(polarity.orient_pairs(_signals(spark, d), TAU)).select("pair_id", "ang"), [F.col("ang").desc(), F.col("pair_id").asc()], 40, 20)
)
_query("q_difficulty_tiles", f"{_BASE} SELECT tile, count(*) AS n, min(ang) AS least, max(ang) AS most FROM (SELECT ang, CAST(ntile(10) OVER (ORDER BY ang, pair_id) AS INT) AS tile FROM clear) GROUP BY tile")(
    lambda spark, d: sets.distributed_ntile(difficulty.with_difficulty(polarity.orient_pairs(_signals(spark, d), TAU)).select("pair_id", "ang"), [F.col("ang").asc(), F.col("pair_id").asc()], 10)
    .groupBy("tile").agg(F.count(F.lit(1)).alias("n"), F.min("ang").alias("least"), F.max("ang").alias("most"))
)


@_query(
    "q_ks_by_group",
    f"""{_BASE}, long AS (SELECT grp, CAST(floor(-ref_w / n_w / 250000) AS BIGINT) AS bin, 1 AS x, 0 AS y FROM signals UNION ALL SELECT grp, CAST(floor(-ref_l / n_l / 250000) AS BIGINT), 0, 1 FROM signals),
c AS (SELECT grp, bin, sum(x) AS x, sum(y) AS y FROM long GROUP BY ALL),
r AS (SELECT grp, x, abs(sum(x) OVER u / CAST(sum(x) OVER w AS DOUBLE) - sum(y) OVER u / CAST(sum(y) OVER w AS DOUBLE)) AS gap FROM c WINDOW u AS (PARTITION BY grp ORDER BY bin), w AS (PARTITION BY grp))
SELECT grp, CAST(sum(x) AS BIGINT) AS n, round(max(gap), 6) AS ks FROM r GROUP BY grp""",
)
def q_ks_by_group(spark, sf_dir):
    """How far apart the average negative log-likelihoods of chosen and rejected responses lie, by group."""
    per = lambda s: -F.col(f"ref_{s}") / F.col(f"n_{s}")
    return analysis.ks_by_group(_signals(spark, sf_dir), per("w"), per("l"), MICRO // 4, "grp")


@_query(
    "q_external_reward",
    f"""WITH {_LINES}, r AS (SELECT l_orderkey AS pair_id, k % 2 = 1 AS w, unnest([CAST(l_quantity AS DOUBLE), CAST(l_linenumber AS DOUBLE)]) AS score FROM lines)
SELECT pair_id, round(avg(score) FILTER (WHERE w), 4) AS ext_w, round(avg(score) FILTER (WHERE NOT w), 4) AS ext_l FROM r GROUP BY pair_id""",
)
def q_external_reward(spark, sf_dir):
    """Mean reward over the dimensions of judges' JSON replies, a reply for each line of an order."""
    reply = F.to_json(F.create_map(F.lit("amount"), F.col("l_quantity").cast("double"), F.lit("place"), F.col("l_linenumber").cast("double"), F.lit("other"), F.lit(0.0)))
    lines = P._ranked_lines(spark, sf_dir).select(F.col("l_orderkey").alias("pair_id"), F.when(F.col("k") % 2 == 1, "w").otherwise("l").alias("side"), reply.alias("reply"))
    scores = lines.select("pair_id", "side", F.explode(judge_scores(F.col("reply"))).alias("dim", "score"))
    return S.external_reward(scores, ["amount", "place"]).select("pair_id", F.round("ext_w", 4).alias("ext_w"), F.round("ext_l", 4).alias("ext_l"))


def _length_scorer():
    """A stand-in for a model from outside: a nat for each character, a token for each word."""
    return lambda prompts, responses: ([-float(len(r)) for r in responses], [len(r.split(" ")) for r in responses])


@_query(
    "q_external_scorer",
    f"""WITH {_LINES}, p AS (SELECT l_orderkey AS pair_id, string_agg(p_brand, ' ') FILTER (WHERE k % 2 = 1) AS w, string_agg(p_brand, ' ') FILTER (WHERE k % 2 = 0) AS l FROM lines GROUP BY l_orderkey HAVING count(*) > 1)
SELECT pair_id, -1000000 * length(w) AS ref_w, -1000000 * length(l) AS ref_l, CAST(len(string_split(w, ' ')) AS INT) AS n_w, CAST(len(string_split(l, ' ')) AS INT) AS n_l FROM p""",
)
def q_external_scorer(spark, sf_dir):
    return scorers.with_scorer(P.basket_pairs(spark, sf_dir), _length_scorer)


# ---- language models and hygiene ------------------------------------------------------------------------

_TOK = "[ \\n\\t\\r]+"
_WORDS = "list_filter(regexp_split_to_array({}, '[ \\n\\t\\r]+'), lambda x: x <> '')"
_ONES = f"ones AS MATERIALIZED (SELECT tok, count(*) AS n FROM (SELECT unnest({_WORDS.format('text')}) AS tok FROM documents) GROUP BY tok)"
_STREAM = f"""stream AS (SELECT w[i] AS tok, CASE WHEN i = 1 THEN '' ELSE w[i - 1] END AS prev FROM (SELECT w, unnest(range(1, len(w) + 1)) AS i FROM (SELECT {_WORDS.format('text')} AS w FROM documents))),
two AS MATERIALIZED (SELECT prev, tok, count(*) AS n FROM stream GROUP BY ALL), ctx AS MATERIALIZED (SELECT prev, sum(n) AS n_prev FROM two GROUP BY prev),
whole AS (SELECT sum(n) + {lm.ALPHA} * (count(*) + 1) AS z FROM ones)"""
_query("q_token_counts", f"WITH {_ONES} SELECT tok, n FROM ones")(lambda spark, d: lm.unigram(table(spark, d, "documents", "text")))
_query("q_avg_nll", f"WITH {_ONES}, z AS (SELECT sum(n) + {lm.ALPHA} * (count(*) + 1) AS z FROM ones) SELECT tok, CAST(floor(ln((n + {lm.ALPHA}) / z) * 1000000 + 0.5) AS BIGINT) AS lp FROM ones, z")(
    lambda spark, d: lm.unigram_scores(lm.unigram(table(spark, d, "documents", "text")))
)
_query(
    "q_bigram_lm",
    f"WITH {_ONES}, {_STREAM} SELECT t.prev, t.tok, CAST(floor(ln({lm.LAMBDA} * t.n / c.n_prev + (1 - {lm.LAMBDA}) * (o.n + {lm.ALPHA}) / z) * 1000000 + 0.5) AS BIGINT) AS lp FROM two t JOIN ctx c ON c.prev = t.prev JOIN ones o ON o.tok = t.tok, whole",
)(lambda spark, d: lm.bigram_scores(table(spark, d, "documents", "text")))
_query(
    "q_forced_decoding",
    f"""WITH {_ONES}, {_STREAM}, {_DIALOG},
resp AS (SELECT pair_id, 'w' AS side, {_WORDS.format('chosen')} AS w FROM dialog UNION ALL SELECT pair_id, 'l', {_WORDS.format('rejected')} FROM dialog),
uses AS (SELECT pair_id, side, w[i] AS tok, CASE WHEN i = 1 THEN '' ELSE w[i - 1] END AS prev, count(*) AS times FROM (SELECT *, unnest(range(1, len(w) + 1)) AS i FROM resp) GROUP BY ALL),
s AS (SELECT u.*, CAST(floor(ln(CASE WHEN c.n_prev > 0 THEN {lm.LAMBDA} * coalesce(t.n, 0) / c.n_prev + (1 - {lm.LAMBDA}) * (coalesce(o.n, 0) + {lm.ALPHA}) / z ELSE (coalesce(o.n, 0) + {lm.ALPHA}) / z END) * 1000000 + 0.5) AS BIGINT) * times AS lp
  FROM uses u LEFT JOIN two t ON t.prev = u.prev AND t.tok = u.tok LEFT JOIN ctx c ON c.prev = u.prev LEFT JOIN ones o ON o.tok = u.tok, whole)
SELECT pair_id, CAST(coalesce(sum(lp) FILTER (WHERE side = 'w'), 0) AS BIGINT) AS lp_w, CAST(coalesce(sum(times) FILTER (WHERE side = 'w'), 0) AS BIGINT) AS n_w,
  CAST(coalesce(sum(lp) FILTER (WHERE side = 'l'), 0) AS BIGINT) AS lp_l, CAST(coalesce(sum(times) FILTER (WHERE side = 'l'), 0) AS BIGINT) AS n_l FROM s GROUP BY pair_id""",
)(lambda spark, d: lm.forced_decoding(P.dialog_pairs(spark, d), table(spark, d, "documents", "text")))
_query(
    "q_dedup_pairs_whole",
    f"""WITH {_LINES}, p AS (
  SELECT l_orderkey AS pair_id, 'order ' || l_orderkey AS prompt, string_agg(p_brand, ' ' ORDER BY k) FILTER (WHERE k % 2 = 1) AS chosen, string_agg(p_brand, ' ' ORDER BY k) FILTER (WHERE k % 2 = 0) AS rejected
  FROM lines GROUP BY l_orderkey HAVING count(*) > 1),
f AS (SELECT prompt, chosen, rejected, min(pair_id) AS pair_id FROM p WHERE chosen <> rejected GROUP BY ALL)
SELECT pair_id, prompt, chosen, rejected FROM f WHERE NOT EXISTS (SELECT 1 FROM f g WHERE g.prompt = f.prompt AND g.chosen = f.rejected AND g.rejected = f.chosen)""",
)(lambda spark, d: hygiene.drop_duplicate_pairs(P.basket_pairs(spark, d)).select("pair_id", "prompt", "chosen", "rejected"))
_RUNS = lambda t, k: f"SELECT DISTINCT {k}, array_to_string(w[i : i + 7], ' ') AS run FROM (SELECT {k}, w, unnest(range(1, len(w) - 6)) AS i FROM (SELECT {k}, {_WORDS.format('text')} AS w FROM {t}) WHERE len(w) >= 8)"
_query("q_decontaminate", f"WITH d AS ({_RUNS('documents', 'doc_id')}), b AS ({_RUNS('benchmark', 'item_id')}) SELECT DISTINCT doc_id FROM d WHERE run IN (SELECT run FROM b)")(
    lambda spark, d: hygiene.decontaminate(table(spark, d, "documents", "doc_id", "text"), table(spark, d, "benchmark", "text"), "doc_id")
)

# ---- trained policies -----------------------------------------------------------------------------------


def _graded_run(spark, sf_dir, cfg=policy.PolicyConfig()):
    pairs = materialised(P.noisy(P.graded_pairs(spark, sf_dir)), "graded")
    return (pairs, *policy.policy_signals(pairs, table(spark, sf_dir, "documents", "text"), cfg))


def _own_tau(signals: DataFrame) -> float:
    """The threshold that keeps half of the pairs."""
    cut = signals.agg(F.percentile_approx(F.abs(S.polarity_gap_micro()), 0.5, 1_000_000)).first()[0] or 1
    return max(cut, 1) / MICRO


def _trained(spark, sf_dir, choose: Callable, cfg=policy.PolicyConfig(rounds=6), run=None) -> DataFrame:
    """setting, pairs trained on, and on held-out pairs accuracy, win rate and mean length, for each selection that ``choose`` makes."""
    _, signals, _, feats, ref = run or _graded_run(spark, sf_dir)
    train = materialised(signals.where(~held_out(F.col("pair_id"))), "train")
    kept = {name: materialised(df.select("pair_id", "flipped"), "kept") for name, df in choose(train).items()}
    found = policy.train_many(feats, ref, kept, replace(cfg, split="shared"))
    test = signals.where(held_out(F.col("pair_id"))).select("pair_id", "ext_w", "ext_l", "len_w", "len_l")
    j = evaluate.judged(policy.preferences(feats.where(held_out(F.col("pair_id"))), found), test)
    sizes = reduce(DataFrame.unionByName, (df.agg(F.lit(name).alias("method"), F.count(F.lit(1)).alias("n_pairs")) for name, df in kept.items()))
    measured = j.groupBy("method").agg(F.count(F.lit(1)).alias("n_held_out"), F.round(F.avg(F.col("pick").cast("double")), 6).alias("accuracy"), F.round(100 * F.avg("p_win"), 4).alias("wr"), F.round(F.avg("len_model"), 4).alias("length"))
    return sizes.join(measured, "method").withColumnRenamed("method", "setting")


def _plain(df: DataFrame) -> DataFrame:
    return df.withColumn("flipped", F.lit(False))


@_query("q_trained_tau")
def q_trained_tau(spark, sf_dir):
    """Thresholds from a tenth to twice the one that keeps half of the pairs, the second stage unchanged."""
    return _trained(spark, sf_dir, lambda s: (lambda tau: {f"{x:.2f}": preset(s, "full", tau * x) for x in (0.1, 0.25, 0.5, 0.75, 1, 1.5, 2)})(_own_tau(s)))


@_query("q_trained_k")
def q_trained_k(spark, sf_dir):
    return _trained(spark, sf_dir, lambda s: {str(k): preset(s, "full", _own_tau(s), k) for k in SHARES})


@_query("q_trained_first_stage")
def q_trained_first_stage(spark, sf_dir):
    """Other signals in the first stage, of as many pairs each, the second stage unchanged."""
    return _trained(spark, sf_dir, lambda s: {by: difficulty.select_hard(polarity.first_stage(s, by, _half(s)), percent=50) for by in _FIRST})


@_query("q_trained_calibration")
def q_trained_calibration(spark, sf_dir):
    """Hard, random or easy ones of the clear pairs."""
    return _trained(spark, sf_dir, lambda s: (lambda c: {how: difficulty.calibrate(c, how, _half(c)) for how in _SEED})(materialised(polarity.orient_pairs(s, _own_tau(s)), "clear")))


@_query("q_trained_ladder")
def q_trained_ladder(spark, sf_dir):
    """The steps of the method, one after the other."""
    return _trained(spark, sf_dir, lambda s: {name: preset(s, name, _own_tau(s)) for name in PRESETS})


@_query("q_trained_half")
def q_trained_half(spark, sf_dir):
    """Signals by policies that saw all pairs, or a random half; the selection is made of all pairs in both."""
    rows = []
    for name, sample in (("two_stage", "full"), ("two_stage_half", "half")):
        run = _graded_run(spark, sf_dir, policy.PolicyConfig(sample=sample))
        rows.append(_trained(spark, sf_dir, lambda s, name=name: {name: preset(s, "full", _own_tau(s))}, run=run))
    return reduce(DataFrame.unionByName, rows)


@_query("q_training_dynamics")
def q_training_dynamics(spark, sf_dir):
    """Loss and rewards by round for the pairs of each preset, all trained in the same passes."""
    _, signals, _, feats, ref = _graded_run(spark, sf_dir)
    tau = _own_tau(signals)
    found = policy.train_many(feats, ref, {name: preset(signals, name, tau) for name in ("none", "r_ad_only", "ang_only", "full")}, policy.PolicyConfig(split="shared"))
    rows = [(name, h["policy"], h["step"], round(h["loss"], 6), round(h["reward_w"], 6), round(h["reward_l"], 6)) for name, x in found.items() for h in x.history]
    return spark.createDataFrame(rows, "preset string, policy string, step int, loss double, reward_w double, reward_l double")


@_query("q_noise_recovery")
def q_noise_recovery(spark, sf_dir):
    pairs, signals, *_ = _graded_run(spark, sf_dir)
    trained = polarity.labelled(signals, _own_tau(signals)).where(~held_out(F.col("pair_id")))
    return evaluate.noise_recovery(trained.join(pairs.select("pair_id", "is_swapped"), "pair_id"))


@_query("q_nll_distribution")
def q_nll_distribution(spark, sf_dir):
    _, signals, *_ = _graded_run(spark, sf_dir)
    held = signals.where(held_out(F.col("pair_id")))
    each = [held.select(F.lit(m).alias("model"), F.col(f"{m}_w").alias("ref_w"), F.col(f"{m}_l").alias("ref_l"), "n_w", "n_l") for m in ("ref", "pos", "inv")]
    return analysis.nll_distribution(reduce(DataFrame.unionByName, each), "model")


@_query("q_policy_signals")
def q_policy_signals(spark, sf_dir):
    return _graded_run(spark, sf_dir)[1]


_V = policy.PolicyConfig().vocabulary
_STEP = 0.01 * policy.PolicyConfig().rate * policy.PolicyConfig().beta / 2
_SHIFT = lambda m, s: f"ref_{s} + CAST(floor((sum_{m}_{s} - n_{s} * z_{m}) * 1000000 + 0.5) AS BIGINT)"


@_query(
    "q_one_step_policy",
    f"""WITH {_ONES}, {_GRADED}, whole AS (SELECT sum(n) + {lm.ALPHA} * (count(*) + 1) AS z FROM ones),
named AS (SELECT tok, n, row_number() OVER (ORDER BY n DESC, tok) AS k FROM ones),
known AS MATERIALIZED (SELECT tok, CASE WHEN k < {_V} THEN k ELSE 0 END AS feat, (n + {lm.ALPHA}) / z AS q, CAST(floor(ln((n + {lm.ALPHA}) / z) * 1000000 + 0.5) AS BIGINT) AS lp FROM named, whole),
mass AS (SELECT feat, q FROM known WHERE feat > 0 UNION ALL SELECT 0, 1 - sum(q) FROM known WHERE feat > 0),
uses AS (SELECT pair_id, side, unnest(w) AS tok FROM (SELECT pair_id, 1 AS side, {_WORDS.format('chosen')} AS w FROM graded UNION ALL SELECT pair_id, 0, {_WORDS.format('rejected')} FROM graded)),
feats AS MATERIALIZED (SELECT pair_id, feat, sum(side) AS w, sum(1 - side) AS l, sum(lp * side) AS ref_w, sum(lp * (1 - side)) AS ref_l FROM uses JOIN known USING (tok) GROUP BY pair_id, feat),
train AS (SELECT * FROM feats WHERE {_h('split:')} % 10 < 8),
size AS (SELECT count(DISTINCT pair_id) AS n, CAST(sum(w - l) AS DOUBLE) AS d FROM train),
theta AS MATERIALIZED (SELECT m.feat, m.q, round({_STEP!r} * (coalesce(s.d, 0) - size.d * m.q) / size.n, 9) AS t FROM mass m LEFT JOIN (SELECT feat, CAST(sum(w - l) AS DOUBLE) AS d FROM train GROUP BY feat) s USING (feat), size),
norm AS (SELECT ln(sum(q * exp(t))) AS z_pos, ln(sum(q * exp(-t))) AS z_inv FROM theta),
each AS (SELECT pair_id, CAST(sum(ref_w) AS BIGINT) AS ref_w, CAST(sum(ref_l) AS BIGINT) AS ref_l, CAST(sum(w) AS INT) AS n_w, CAST(sum(l) AS INT) AS n_l,
  sum(w * t) AS sum_pos_w, sum(l * t) AS sum_pos_l, sum(-w * t) AS sum_inv_w, sum(-l * t) AS sum_inv_l FROM feats JOIN theta USING (feat) GROUP BY pair_id),
scored AS (SELECT pair_id, ref_w, ref_l, n_w, n_l, {', '.join(f'{_SHIFT(m, s)} AS {m}_{s}' for m in ('pos', 'inv') for s in 'wl')} FROM each, norm)
SELECT *, (pos_w - pos_l) - (inv_w - inv_l) AS gap FROM scored""",
)
def q_one_step_policy(spark, sf_dir):
    cfg = policy.PolicyConfig()
    pairs = P.graded_pairs(spark, sf_dir)
    ref = policy.reference(table(spark, sf_dir, "documents", "text"), cfg)
    feats = materialised(policy.featurise(pairs, ref, cfg), "features")
    return policy.with_policy_scores(feats, policy.one_step(feats, ref, cfg)).withColumn("gap", S.polarity_gap_micro())


@_query("q_curriculum_effect")
def q_curriculum_effect(spark, sf_dir):
    """Held-out accuracy and win rate after training in each order, twice through all batches of the selected pairs, turned as selected."""
    _, signals, _, feats, ref = _graded_run(spark, sf_dir)
    clear = materialised(preset(signals.where(~held_out(F.col("pair_id"))), "full", _own_tau(signals)), "clear")
    batch = max(2, -(-clear.count() // 10))
    found = {}
    for how in ("random", "hard_first", "easy_first"):
        placed = policy.turned(feats, difficulty.curriculum_order(clear, how).select("pair_id", "flipped", "position"))
        found[how] = policy.train_policies(placed, ref, policy.PolicyConfig(split="shared", mask=1.0, rounds=20), order="position", batch=batch)
    test = signals.where(held_out(F.col("pair_id"))).select("pair_id", "ext_w", "ext_l", "len_w", "len_l")
    j = evaluate.judged(policy.preferences(feats.where(held_out(F.col("pair_id"))), found), test)
    last = spark.createDataFrame([(how, x.history[-2]["loss"], sum(h["policy"] == "pos" for h in x.history)) for how, x in found.items()], "method string, last_loss double, n_batches int")
    got = j.groupBy("method").agg(F.avg(F.col("pick").cast("double")).alias("accuracy"), (100 * F.avg("p_win")).alias("wr"), F.count(F.lit(1)).alias("n_pairs"))
    return got.join(F.broadcast(last), "method").withColumnRenamed("method", "how")


@_query("q_weighted_loss")
def q_weighted_loss(spark, sf_dir):
    """The likelihood-weighted loss on all pairs and on those of the whole selection, turned as selected."""
    run = _graded_run(spark, sf_dir)
    both = lambda s: {"all": _plain(s), "selected": preset(s, "full", _own_tau(s))}
    rows = [_trained(spark, sf_dir, both, policy.PolicyConfig(weights=w, rounds=6), run).withColumn("weights", F.lit(w)) for w in ("none", "likelihood")]
    return reduce(DataFrame.unionByName, rows)


@_query("q_model_overlap")
def q_model_overlap(spark, sf_dir):
    """Overlap of the selections that three families of models make."""
    kept = {}
    for family in policy.FAMILIES:
        _, signals, *_ = _graded_run(spark, sf_dir, policy.PolicyConfig(family=family, rounds=6))
        kept[family] = preset(signals, "full", _own_tau(signals)).select("pair_id")
    return analysis.overlap(kept, "word")


def _methods(train: DataFrame, losses: DataFrame) -> dict[str, DataFrame]:
    """Every selector's pairs, oriented where the method orients."""
    n = _half(train)
    kept = {name: _plain(f(train, n)) for name, (f, _) in _BASELINES.items() if name not in _VARIANTS}
    return kept | {"full": _plain(train), "ensemble": _plain(baselines.by_ensemble_easiness(train, losses, n)), "two_stage": preset(train, "full", _own_tau(train))}


@_query("q_leaderboard")
def q_leaderboard(spark, sf_dir):
    """All selectors trained on and judged by held-out accuracy, win rate and the length of what they prefer, with ranks (stand-in numbers)."""
    run = _graded_run(spark, sf_dir)
    feats, ref = run[3:]
    losses = materialised(policy.ensemble_losses(feats, ref, policy.PolicyConfig(rounds=5)), "losses")
    got = _trained(spark, sf_dir, lambda train: _methods(train, losses), policy.PolicyConfig(rounds=5), run)
    long = got.select(F.col("setting").alias("method"), F.lit("word").alias("backbone"), F.expr("stack(3, 'accuracy', accuracy, 'wr', wr, 'length', length) AS (metric, value)"))
    return evaluate.leaderboard(long)


@_query("q_main_table")
def q_main_table(spark, sf_dir):
    """Methods, the untuned reference among them, by two backbones and three sets: held-out pairs (win rate, length-controlled
    one, length), the third of them that is hardest for the reference (win rate), dialogues (score over turns, then conversations)."""
    rows = []
    talks = materialised(P.dialog_pairs(spark, sf_dir), "dialogues")
    judge = talks.select("pair_id", F.length("chosen").alias("len_w"), F.length("rejected").alias("len_l")).join(policy.external_scores(talks), "pair_id")
    for family in ("word", "ending"):
        cfg = policy.PolicyConfig(family=family, rounds=5)
        _, signals, _, feats, ref = _graded_run(spark, sf_dir, cfg)
        train = materialised(signals.where(~held_out(F.col("pair_id"))), "train")
        losses = materialised(policy.ensemble_losses(feats, ref, replace(cfg, rounds=3)), "losses")
        kept = {name: materialised(df.select("pair_id", "flipped"), "kept") for name, df in _methods(train, losses).items()}
        found = policy.train_many(feats, ref, kept, replace(cfg, split="shared"))
        said = policy.featurise(talks, ref, cfg)

        def measured(rows_: DataFrame, signals_: DataFrame) -> DataFrame:
            """Judgements of all methods; the untuned reference prefers the response of the larger mean log-probability."""
            untuned = rows_.select(F.lit("init").alias("method"), "pair_id", (F.try_divide("ref_w", "n_w") > F.try_divide("ref_l", "n_l")).alias("pick"))
            return materialised(evaluate.judged(policy.preferences(rows_, found).unionByName(untuned.where("pick IS NOT NULL")), signals_), "judged")

        hard = feats.select("pair_id", F.abs(F.try_divide("ref_w", "n_w") - F.try_divide("ref_l", "n_l")).alias("clear"))
        test = signals.where(held_out(F.col("pair_id"))).select("pair_id", "ext_w", "ext_l", "len_w", "len_l")
        a, c = measured(feats.where(held_out(F.col("pair_id"))), test), measured(said, judge)
        b = evaluate.harder_set(a.join(hard.withColumn("hardness", -F.col("clear")), "pair_id"), "hardness")
        talk = c.select("method", F.floor(F.col("pair_id") / 1000).alias("prompt_id"), (10 * F.col("p_win")).alias("score"))
        parts = [
            (evaluate.win_rate(a), "a_wr", "wr"), (evaluate.length_controlled_win_rate(a), "a_lc", "lc"), (evaluate.mean_length(a), "a_length", "length"),
            (evaluate.win_rate(b), "b_wr", "wr"), (evaluate.mean_score(talk), "c_score", "score"),
        ]
        rows += [df.select("method", F.lit(family).alias("backbone"), F.lit(m).alias("metric"), F.round(v, 4).alias("value")) for df, m, v in parts]
    return evaluate.leaderboard(reduce(DataFrame.unionByName, rows))


@_query("q_pairwise_reward")
def q_pairwise_reward(spark, sf_dir):
    """Held-out accuracy of the pairwise reward model on judged dimensions, against their plain mean; training pairs are noisy."""
    pairs = P.noisy(P.graded_pairs(spark, sf_dir))
    diff = F.zip_with(policy.judged_dims("chosen"), policy.judged_dims("rejected"), lambda a, b: a.cast("double") - b.cast("double"))
    rows = materialised(pairs.select("pair_id", diff.alias("diff")), "differences")
    test = held_out(F.col("pair_id"))
    fitted = reward.fit_pairwise_reward(rows.where(~test), 4)
    plain = reward.PairwiseReward((0.25,) * 4, True)
    found = [
        reward.reward_accuracy(reward.usable_differences(rows.where(test), 4), m.margin()).select(F.lit(name).alias("reward"), "accuracy", "n_pairs", F.array(*[F.lit(round(w, 6)) for w in m.weights]).alias("weights"), F.lit(m.converged).alias("converged"))
        for name, m in (("fitted", fitted), ("mean", plain))
    ]
    return found[0].unionByName(found[1])


@_query("q_squeeze")
def q_squeeze(spark, sf_dir):
    return analysis.squeeze_index(_graded_run(spark, sf_dir)[1])


