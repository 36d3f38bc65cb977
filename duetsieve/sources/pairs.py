"""Preference pairs from the given tables, and exact signals for one of them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.columns import MICRO, cosine, held_out, portable_hash
from ..operators.cutoff import distributed_rank
from .tables import table

#: Multipliers of part, supplier, line number and the modulus, by policy.
FORMULA = {"ref": (31, 17, 7, 9), "pos": (37, 11, 5, 23), "inv": (41, 13, 3, 29)}
LINE_ORDER = ("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice", "l_quantity")


def _ranked_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem", "l_orderkey", *LINE_ORDER, "l_discount")
    brands = table(spark, sf_dir, "part", "p_partkey", "p_brand")
    return lines.join(brands, lines.l_partkey == brands.p_partkey).withColumn("k", F.row_number().over(Window.partitionBy("l_orderkey").orderBy(*LINE_ORDER)))


def _groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders", F.col("o_orderkey").alias("pair_id"), F.col("o_orderpriority").alias("grp"))


def basket_signals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Canonical signals of orders' lines: odd ranks chosen, even ranks rejected, log-probabilities by formula.

    One shuffle by order serves the ranking and the sums; no text is built.
    """
    lines = _ranked_lines(spark, sf_dir)
    odd = F.col("k") % 2 == 1
    sides = {"w": odd, "l": ~odd}
    sums = []
    for model, (a, b, c, m) in FORMULA.items():
        score = -MICRO * (1 + (F.col("l_partkey") * a + F.col("l_suppkey") * b + F.col("l_linenumber") * c) % m)
        sums += [F.sum(F.when(on, score)).alias(f"{model}_{s}") for s, on in sides.items()]
    gain = F.floor(F.col("l_extendedprice") * (1 - F.col("l_discount")) * MICRO + 0.5).cast("long")
    for s, on in sides.items():
        sums += [F.count_if(on).cast("int").alias(f"n_{s}"), (F.sum(F.when(on, F.length("p_brand") + 1)) - 1).cast("int").alias(f"len_{s}"), (F.sum(F.when(on, gain)) / MICRO).alias(f"ext_{s}")]
    pairs = lines.groupBy(F.col("l_orderkey").alias("pair_id")).agg(*sums).where("n_l > 0")
    out = pairs.join(_groups(spark, sf_dir), "pair_id", "left").withColumn("grp", F.coalesce("grp", F.lit("none")))
    return out.select("pair_id", "grp", *[f"{c}_{s}" for c in ("pos", "inv", "ref", "n", "len", "ext") for s in "wl"])


def basket_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = _ranked_lines(spark, sf_dir)
    text = lambda on: F.array_join(F.transform(F.array_sort(F.collect_list(F.when(on, F.struct("k", "p_brand")))), lambda x: x["p_brand"]), " ")
    pairs = lines.groupBy(F.col("l_orderkey").alias("pair_id")).agg(text(F.col("k") % 2 == 1).alias("chosen"), text(F.col("k") % 2 == 0).alias("rejected"), F.max("k").alias("n")).where("n > 1")
    out = pairs.join(_groups(spark, sf_dir), "pair_id", "left")
    return out.select("pair_id", F.coalesce("grp", F.lit("none")).alias("grp"), F.concat(F.lit("order "), F.col("pair_id").cast("string")).alias("prompt"), "chosen", "rejected")


def dialog_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A user turn with its answer; the rejected answer is the next pair's, in order of dialogue and turn."""
    turns = table(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text")
    ordered = Window.partitionBy("conv_id").orderBy("turn")
    seen = turns.withColumns(
        {
            "before": F.collect_list("text").over(ordered.rowsBetween(Window.unboundedPreceding, 0)),
            "next_role": F.lead("role").over(ordered),
            "next_turn": F.lead("turn").over(ordered),
            "answer": F.lead("text").over(ordered),
        }
    )
    asked = seen.where("role = 'user' AND next_role = 'assistant' AND next_turn = turn + 1").select("conv_id", "turn", F.array_join("before", "\n").alias("prompt"), F.col("answer").alias("chosen"))
    ranked = distributed_rank(asked, [F.col("conv_id").asc(), F.col("turn").asc()])
    n = ranked.count()
    after = ranked.select(F.when(F.col("position") == 1, F.lit(n)).otherwise(F.col("position") - 1).alias("position"), F.col("chosen").alias("rejected"))
    return ranked.join(after, "position").select((F.col("conv_id") * 1000 + F.col("turn")).alias("pair_id"), F.lit("dialog").alias("grp"), "prompt", "chosen", "rejected")


def graded_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A good document against another of its language that isn't, matched by rank modulo their number."""
    docs = table(spark, sf_dir, "documents", "doc_id", "lang", "source", "text").join(table(spark, sf_dir, "labels", "doc_id", "quality", "toxic"), "doc_id")
    good = (F.col("quality") == 1) & (F.col("toxic") == 0)
    ids = distributed_rank(docs.select("doc_id", "lang", good.alias("good")), [F.col("lang").asc(), F.col("good").asc(), F.col("doc_id").asc()])
    starts = ids.groupBy("lang", "good").agg(F.min("position").alias("start"), F.count(F.lit(1)).alias("n"))  # few languages
    ranked = ids.join(F.broadcast(starts), ["lang", "good"]).withColumn("k", F.col("position") - F.col("start"))
    bad = starts.where("NOT good").select("lang", F.col("n").alias("n_bad"))
    left = ranked.where("good").join(F.broadcast(bad), "lang").select(F.col("doc_id").alias("pair_id"), "lang", (F.col("k") % F.col("n_bad")).alias("k"))
    right = ranked.where("NOT good").select("lang", "k", F.col("doc_id").alias("other"))
    matched = left.join(right, ["lang", "k"]).select("pair_id", "other")
    one, two = docs.select(F.col("doc_id").alias("pair_id"), "lang", "source", F.col("text").alias("chosen")), docs.select(F.col("doc_id").alias("other"), F.col("text").alias("rejected"))
    return matched.join(one, "pair_id").join(two, "other").select("pair_id", F.col("lang").alias("grp"), F.concat_ws(" ", "lang", "source").alias("prompt"), "chosen", "rejected")


def noisy(pairs: DataFrame) -> DataFrame:
    """Every fifth training pair, by hash, with its responses exchanged; ``is_swapped`` keeps the truth."""
    swap = ~held_out(F.col("pair_id")) & (portable_hash("swap:", F.col("pair_id")) % 5 == 0)
    return pairs.withColumns({"is_swapped": swap, "chosen": F.when(swap, F.col("rejected")).otherwise(F.col("chosen")), "rejected": F.when(swap, F.col("chosen")).otherwise(F.col("rejected"))})


def session_pairs(spark: SparkSession, sf_dir: str, within: str | None = None) -> DataFrame:
    """A purchase against the same user's latest earlier view (as-of), ``within`` an interval where given."""
    events = table(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type", "value")
    past = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    view = F.when(F.col("event_type") == "view", F.struct("event_id", "ts", "value"))
    seen = events.where("event_type IN ('view', 'purchase')").withColumn("v", F.last(view, ignorenulls=True).over(past)).where("event_type = 'purchase' AND v IS NOT NULL")
    if within:
        seen = seen.where(f"ts - v.ts <= INTERVAL '{within}'")
    return seen.select(F.col("event_id").alias("pair_id"), "user_id", "ts", F.col("value").alias("ext_w"), F.col("v.event_id").alias("view_id"), F.col("v.ts").alias("view_ts"), F.col("v.value").alias("ext_l"))


def vector_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A label's member against a member of the next label, rewarded by cosine with the label's centroid."""
    rows = table(spark, sf_dir, "embeddings", "vec_id", "embedding", "label")
    means = rows.select("label", F.posexplode("embedding").alias("i", "v")).groupBy("label", "i").agg(F.avg(F.col("v").cast("double")).alias("m"))
    centroids = means.groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "m"))), lambda x: x["m"]).alias("centre"))
    ids = distributed_rank(rows.select("vec_id", "label"), [F.col("label").asc(), F.col("vec_id").asc()])
    starts = ids.groupBy("label").agg(F.min("position").alias("start"), F.count(F.lit(1)).alias("n"))  # few labels
    labels = starts.select("label").withColumn("next", F.coalesce(F.lead("label").over(Window.partitionBy(F.lit(0)).orderBy("label")), F.min("label").over(Window.partitionBy(F.lit(0)))))
    ranked = ids.join(F.broadcast(starts), "label").withColumn("k", F.col("position") - F.col("start"))
    sizes = starts.select(F.col("label").alias("next"), F.col("n").alias("n_next"))
    left = ranked.select("vec_id", "label", "k").join(F.broadcast(labels), "label").join(F.broadcast(sizes), "next").withColumn("k", F.col("k") % F.col("n_next"))
    right = ranked.select(F.col("label").alias("next"), "k", F.col("vec_id").alias("other"))
    matched = left.join(right, ["next", "k"]).select("vec_id", "label", "other")
    one, two = rows.select("vec_id", F.col("embedding").alias("a")), rows.select(F.col("vec_id").alias("other"), F.col("embedding").alias("b"))
    return (
        matched.join(one, "vec_id").join(two, "other").join(F.broadcast(centroids), "label")
        .select(F.col("vec_id").alias("pair_id"), F.col("label").cast("string").alias("grp"), "other", cosine(F.col("a"), F.col("centre")).alias("ext_w"), cosine(F.col("b"), F.col("centre")).alias("ext_l"))
    )
