"""Stand-in policies: exactly normalised log-linear tilts of a count-based reference.

A policy gives token v the probability ref(v) * exp(theta[feature(v)]) / Z.  Features are the most frequent
tokens; all others share feature 0.  With a context-free reference Z is one number, so that a response's
log-probability is exact from its feature counts alone.  The two policies, trained on the preference loss
and on the loss with the responses exchanged, go through the pairs together: per round one pass over compact
feature rows, two vectors of gradients back, no text.

Both would mirror each other if they saw the same pairs from the same start, so that by default each trains
on its own half of the pairs with its own mask of features (``split='crossfit'``).  Families differ in what
counts as a token: words, word pairs, or word endings.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field, replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import signals as S
from ..functions.columns import MICRO, held_out, micro, portable_hash, tokens
from ..plans.stages import materialised
from . import lm

FAMILIES = ("word", "pair", "ending")


def family_tokens(text: Column, family: str) -> Column:
    words = tokens(text)
    if family == "word":
        return words
    if family == "pair":
        return F.zip_with(words, F.concat(F.slice(words, 2, F.greatest(F.size(words) - 1, F.lit(0))), F.array(F.lit("."))), lambda a, b: F.concat_ws(" ", a, b))
    return F.transform(words, lambda w: F.substring(w, -3, 3))


@dataclass(frozen=True)
class PolicyConfig:
    beta: float = 0.1
    rate: float = 8.0
    rounds: int = 12
    vocabulary: int = 512
    mask: float = 0.7
    split: str = "crossfit"  # or "shared"
    sample: str = "full"  # or "half", or "rest", the other half of the same seed
    weights: str = "none"  # or "likelihood"
    family: str = "word"
    seed: int = 7
    eps: float = 1e-5


@dataclass
class Reference:
    """Features with their reference mass, and token scores in micro-nats."""

    scores: DataFrame  # tok, lp, feat
    mass: np.ndarray
    unseen: int


@dataclass
class Policies:
    theta: np.ndarray  # (2, V): positive, inverse
    log_z: np.ndarray  # (2,)
    history: list[dict] = field(default_factory=list)


def reference(texts: DataFrame, cfg: PolicyConfig, text: str = "text") -> Reference:
    """Context-free add-alpha reference of the family, with the feature of each token."""
    counts = materialised(texts.select(F.explode(family_tokens(F.col(text), cfg.family)).alias("tok")).groupBy("tok").agg(F.count(F.lit(1)).alias("n")), "counts")
    n, kinds = lm.totals(counts)
    whole = n + lm.ALPHA * (kinds + 1)
    top = counts.orderBy(F.col("n").desc(), "tok").limit(cfg.vocabulary - 1).collect()  # the vocabulary's size
    spark = texts.sparkSession
    named = spark.createDataFrame([(r["tok"], i + 1) for i, r in enumerate(top)], "tok string, feat int")
    scores = counts.join(F.broadcast(named), "tok", "left").select("tok", micro(F.ln((F.col("n") + lm.ALPHA) / F.lit(whole))).alias("lp"), F.coalesce("feat", F.lit(0)).alias("feat"))
    mass = np.zeros(cfg.vocabulary)
    for i, r in enumerate(top):
        mass[i + 1] = (r["n"] + lm.ALPHA) / whole
    mass[0] = 1 - mass.sum()
    return Reference(scores, mass, round(float(np.log(lm.ALPHA / whole)) * MICRO))


def featurise(pairs: DataFrame, ref: Reference, cfg: PolicyConfig) -> DataFrame:
    """pair_id, ref_w, ref_l, n_w, n_l and ``feats``: (feat, in chosen, in rejected), one shuffle by token and one by pair."""
    side = lambda c, s: pairs.select("pair_id", F.lit(s).alias("side"), F.explode(family_tokens(F.col(c), cfg.family)).alias("tok"))
    uses = side("chosen", 1).unionByName(side("rejected", 0)).groupBy("pair_id", "tok").agg(F.sum("side").alias("w"), F.sum(1 - F.col("side")).alias("l"))
    scored = uses.join(ref.scores, "tok", "left").select("pair_id", "w", "l", F.coalesce("lp", F.lit(ref.unseen)).alias("lp"), F.coalesce("feat", F.lit(0)).alias("feat"))
    by_feat = scored.groupBy("pair_id", "feat").agg(F.sum("w").alias("w"), F.sum("l").alias("l"), F.sum(F.col("lp") * F.col("w")).alias("ref_w"), F.sum(F.col("lp") * F.col("l")).alias("ref_l"))
    return by_feat.groupBy("pair_id").agg(
        F.sum("ref_w").alias("ref_w"), F.sum("ref_l").alias("ref_l"), F.sum("w").cast("int").alias("n_w"), F.sum("l").cast("int").alias("n_l"),
        F.sort_array(F.collect_list(F.struct("feat", "w", "l"))).alias("feats"),
    )


def _masks(cfg: PolicyConfig) -> np.ndarray:
    rng = np.random.default_rng(cfg.seed)
    return np.ones((2, cfg.vocabulary)) if cfg.split == "shared" else (rng.random((2, cfg.vocabulary)) < cfg.mask).astype(float)


def in_sample(cfg: PolicyConfig) -> Column:
    """Whether a training pair belongs to the sample that the policies are trained on."""
    if cfg.sample == "full":
        return F.lit(True)
    return portable_hash(f"half:{cfg.seed}:", F.col("pair_id")) % 2 == {"half": 0, "rest": 1}[cfg.sample]


def train_policies(features: DataFrame, ref: Reference, cfg: PolicyConfig, order: str | None = None, batch: int = 256) -> Policies:
    """Trains both policies; ``order`` names a position column for training in that order, a batch a round."""
    rows = features.where(~held_out(F.col("pair_id")) & in_sample(cfg))
    half = portable_hash("cross:", F.col("pair_id")) % 2
    rows = materialised(rows.select("feats", "n_w", "n_l", "ref_w", "ref_l", half.cast("int").alias("half"), (F.col(order) if order else F.lit(0)).cast("long").alias("at")), "training")
    v, masks = cfg.vocabulary, _masks(cfg)
    theta, log_z = np.zeros((2, v)), np.zeros(2)
    power, mass = np.zeros((2, v)), ref.mass
    out = Policies(theta, log_z)

    def gradients(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q = mass * np.exp(theta - log_z[:, None])
        total, stats = np.zeros((2, v)), np.zeros((2, 5))
        for b in batches:
            feats = b.column("feats")
            n = np.diff(feats.offsets.to_numpy())
            flat = feats.flatten()
            row = np.repeat(np.arange(len(n)), n)
            f, w, l = (flat.field(c).to_numpy() for c in ("feat", "w", "l"))  # noqa: E741
            nw, nl, half_ = (b.column(c).to_numpy() for c in ("n_w", "n_l", "half"))
            for p, sign in enumerate((1.0, -1.0)):
                reward_w = np.bincount(row, w * theta[p, f], len(n)) - nw * log_z[p]
                reward_l = np.bincount(row, l * theta[p, f], len(n)) - nl * log_z[p]
                margin = reward_w - reward_l
                mine = np.ones(len(n)) if cfg.split == "shared" else (half_ == p).astype(float)
                if cfg.weights == "likelihood":
                    mine = mine * likelihood_weight(b)
                z = sign * cfg.beta * margin
                pull = mine * sign * cfg.beta / (1 + np.exp(np.clip(z, -30, 30)))
                total[p] += np.bincount(f, pull[row] * (w - l), v) - (pull * (nw - nl)).sum() * q[p]
                stats[p] += [mine.sum(), (mine * (np.maximum(-z, 0) + np.log1p(np.exp(-np.abs(z))))).sum(), (mine * reward_w).sum(), (mine * reward_l).sum(), (mine * (margin > 0)).sum()]
        yield pa.RecordBatch.from_arrays([pa.array([np.concatenate([total.ravel(), stats.ravel()]).tolist()], pa.list_(pa.float64()))], ["sums"])

    n_batches = 1
    if order:
        n_batches = max(1, -(-(rows.agg(F.max("at")).first()[0] or 1) // batch))
    for step in range(max(cfg.rounds, n_batches) if order else cfg.rounds):
        part = rows if not order else rows.where(F.col("at").between(step % n_batches * batch + 1, (step % n_batches + 1) * batch))
        sums = np.sum([r["sums"] for r in part.mapInArrow(gradients, "sums array<double>").collect()] or [np.zeros(2 * v + 10)], axis=0)  # a vector a task
        grad, stats = sums[: 2 * v].reshape(2, v), sums[2 * v :].reshape(2, 5)
        grad = grad / np.maximum(stats[:, :1], 1e-9) * masks
        power = 0.9 * power + 0.1 * grad * grad
        theta = np.round(theta + cfg.rate * 0.01 * grad / (np.sqrt(power) + 1e-6), 9)
        log_z = np.log((mass * np.exp(theta)).sum(1))
        out.theta, out.log_z = theta, log_z
        n = np.maximum(stats[:, 0], 1e-9)
        for p, name in enumerate(("pos", "inv")):
            out.history.append({"policy": name, "step": step, "loss": float(stats[p, 1] / n[p]), "reward_w": float(stats[p, 2] / n[p]), "reward_l": float(stats[p, 3] / n[p]), "accuracy": float(stats[p, 4] / n[p])})
        if step > 2 and not order and abs(out.history[-2]["loss"] - out.history[-4]["loss"]) < cfg.eps:
            break
    return out


def one_step(features: DataFrame, ref: Reference, cfg: PolicyConfig) -> Policies:
    """The first gradient step from the reference, in closed form: every pair weighs one half, so that theta is a plain
    aggregate, and the inverse policy's its negative."""
    rows = features.where(~held_out(F.col("pair_id")))
    n, extra = rows.agg(F.count(F.lit(1)), F.sum(F.col("n_w") - F.col("n_l"))).first()
    diffs = rows.select(F.inline("feats")).groupBy("feat").agg(F.sum(F.col("w") - F.col("l")).alias("d")).collect()  # a row a feature
    sums = np.zeros(cfg.vocabulary)
    for r in diffs:
        sums[r["feat"]] = r["d"]
    step = np.round(0.01 * cfg.rate * cfg.beta / 2 * (sums - (extra or 0) * ref.mass) / max(n, 1), 9)
    theta = np.stack([step, -step])
    return Policies(theta, np.log((ref.mass * np.exp(theta)).sum(1)))


def turned(features: DataFrame, kept: DataFrame) -> DataFrame:
    """Feature rows of the pairs in ``kept`` (pair_id, flipped, more), with both responses exchanged where flipped."""
    turn = lambda x: F.struct(x["feat"].alias("feat"), F.when(F.col("flipped"), x["l"]).otherwise(x["w"]).alias("w"), F.when(F.col("flipped"), x["w"]).otherwise(x["l"]).alias("l"))
    swap = {a: F.when(F.col("flipped"), F.col(b)).otherwise(F.col(a)) for a, b in (("n_w", "n_l"), ("n_l", "n_w"), ("ref_w", "ref_l"), ("ref_l", "ref_w"))}
    return features.join(kept, "pair_id").withColumns({"feats": F.transform("feats", turn), **swap})


def train_many(features: DataFrame, ref: Reference, kept: dict[str, DataFrame], cfg: PolicyConfig) -> dict[str, Policies]:
    """Trains both policies on each selection (pair_id, flipped) in one pass a round: a bit for each selection goes with the rows."""
    names, v = list(kept), cfg.vocabulary
    if len(names) > 60:
        raise ValueError("at most 60 selections at once")
    marks = reduce(DataFrame.unionByName, (df.select("pair_id", F.lit(1 << k).cast("long").alias("member"), F.when(F.col("flipped"), 1 << k).otherwise(0).cast("long").alias("turn")) for k, df in enumerate(kept.values())))
    marks = marks.groupBy("pair_id").agg(F.bit_or("member").alias("member"), F.bit_or("turn").alias("turn"))
    rows = features.where(~held_out(F.col("pair_id")) & in_sample(cfg)).join(marks, "pair_id")
    rows = materialised(rows.select("feats", "n_w", "n_l", "ref_w", "ref_l", "member", "turn"), "trainings")
    theta, log_z = np.zeros((len(names), 2, v)), np.zeros((len(names), 2))
    power, mass, masks = np.zeros((len(names), 2, v)), ref.mass, _masks(cfg)
    history: dict[str, list[dict]] = {name: [] for name in names}

    def gradients(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q = mass * np.exp(theta - log_z[:, :, None])
        total, stats = np.zeros(theta.shape), np.zeros((len(names), 2, 5))
        for b in batches:
            feats = b.column("feats")
            n = np.diff(feats.offsets.to_numpy())
            flat, each = feats.flatten(), np.repeat(np.arange(len(n)), n)
            f, w, l = (flat.field(c).to_numpy() for c in ("feat", "w", "l"))  # noqa: E741
            nw, nl, member, turn = (b.column(c).to_numpy() for c in ("n_w", "n_l", "member", "turn"))
            weight = np.ones(len(n))
            if cfg.weights == "likelihood":
                weight = likelihood_weight(b)
            for r in range(len(names)):
                mine = ((member >> r) & 1) * weight
                side = 1.0 - 2.0 * ((turn >> r) & 1)
                for p, sign in enumerate((1.0, -1.0)):
                    reward_w = np.bincount(each, w * theta[r, p, f], len(n)) - nw * log_z[r, p]
                    reward_l = np.bincount(each, l * theta[r, p, f], len(n)) - nl * log_z[r, p]
                    margin = side * (reward_w - reward_l)
                    z = sign * cfg.beta * margin
                    pull = mine * side * sign * cfg.beta / (1 + np.exp(np.clip(z, -30, 30)))
                    total[r, p] += np.bincount(f, pull[each] * (w - l), v) - (pull * (nw - nl)).sum() * q[r, p]
                    won, lost = np.where(side > 0, reward_w, reward_l), np.where(side > 0, reward_l, reward_w)
                    stats[r, p] += [mine.sum(), (mine * (np.maximum(-z, 0) + np.log1p(np.exp(-np.abs(z))))).sum(), (mine * won).sum(), (mine * lost).sum(), (mine * (margin > 0)).sum()]
        yield pa.RecordBatch.from_arrays([pa.array([np.concatenate([total.ravel(), stats.ravel()]).tolist()], pa.list_(pa.float64()))], ["sums"])

    for step in range(cfg.rounds):
        sums = np.sum([r["sums"] for r in rows.mapInArrow(gradients, "sums array<double>").collect()] or [np.zeros(len(names) * (2 * v + 10))], axis=0)  # a vector a task
        grad, stats = sums[: theta.size].reshape(theta.shape), sums[theta.size :].reshape(len(names), 2, 5)
        n = np.maximum(stats[:, :, 0], 1e-9)
        grad = grad / n[:, :, None] * masks
        power = 0.9 * power + 0.1 * grad * grad
        theta = np.round(theta + cfg.rate * 0.01 * grad / (np.sqrt(power) + 1e-6), 9)
        log_z = np.log((mass * np.exp(theta)).sum(2))
        for r, name in enumerate(names):
            for p, which in enumerate(("pos", "inv")):
                loss, won, lost, right = (float(x) for x in stats[r, p, 1:] / n[r, p])
                history[name].append({"policy": which, "step": step, "loss": loss, "reward_w": won, "reward_l": lost, "accuracy": right})
    return {name: Policies(theta[r], log_z[r], history[name]) for r, name in enumerate(names)}


def likelihood_weight(b: pa.RecordBatch) -> np.ndarray:
    """Geometric mean of the two responses' token probabilities under the reference, the weight of a pair."""
    each = [b.column(f"ref_{s}").to_numpy() / np.maximum(b.column(f"n_{s}").to_numpy(), 1) / MICRO for s in "wl"]
    return np.exp(np.clip((each[0] + each[1]) / 2, -30, 0))


def preferences(features: DataFrame, found: dict[str, Policies]) -> DataFrame:
    """method, pair_id, pick for each pair and positive policy: whether it prefers the chosen response; one pass for all policies."""
    known = features.sparkSession.sparkContext.broadcast({k: (x.theta[0], float(x.log_z[0])) for k, x in found.items()})

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            feats = b.column("feats")
            n = np.diff(feats.offsets.to_numpy())
            flat, each = feats.flatten(), np.repeat(np.arange(len(n)), n)
            f, diff = flat.field("feat").to_numpy(), flat.field("w").to_numpy() - flat.field("l").to_numpy()
            extra = b.column("n_w").to_numpy() - b.column("n_l").to_numpy()
            for name, (theta, log_z) in known.value.items():
                margin = np.bincount(each, diff * theta[f], len(n)) - extra * log_z
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(n), pa.string()), b.column("pair_id"), pa.array(margin > 0)], ["method", "pair_id", "pick"])

    return features.select("pair_id", "feats", "n_w", "n_l").mapInArrow(work, "method string, pair_id long, pick boolean")


def with_policy_scores(features: DataFrame, found: Policies) -> DataFrame:
    """Adds pos_w, pos_l, inv_w, inv_l in micro-nats: an array lookup per feature, no join."""
    spark = features.sparkSession
    known = spark.sparkContext.broadcast((found.theta, found.log_z))

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        theta, log_z = known.value
        for b in batches:
            feats = b.column("feats")
            n = np.diff(feats.offsets.to_numpy())
            flat, row = feats.flatten(), np.repeat(np.arange(len(n)), n)
            f = flat.field("feat").to_numpy()
            cols = [b.column(c) for c in ("pair_id", "ref_w", "ref_l", "n_w", "n_l")]
            for p in range(2):
                for s in "wl":
                    shift = np.bincount(row, flat.field(s).to_numpy() * theta[p, f], len(n)) - b.column(f"n_{s}").to_numpy() * log_z[p]
                    cols.append(pa.array(b.column(f"ref_{s}").to_numpy() + np.floor(shift * MICRO + 0.5).astype(np.int64)))
            yield pa.RecordBatch.from_arrays(cols, ["pair_id", "ref_w", "ref_l", "n_w", "n_l", "pos_w", "pos_l", "inv_w", "inv_l"])

    return features.select("pair_id", "ref_w", "ref_l", "n_w", "n_l", "feats").mapInArrow(score, "pair_id long, ref_w long, ref_l long, n_w int, n_l int, pos_w long, pos_l long, inv_w long, inv_l long")


def ensemble_losses(features: DataFrame, ref: Reference, cfg: PolicyConfig = PolicyConfig(), seeds: tuple[int, ...] = (1, 2, 3)) -> DataFrame:
    """pair_id, model, seen, loss in micro units of trained reference models: a seed's two complementary halves, by three seeds.

    Each model scores the training pairs of the half that it was not trained on, so that a pair has one loss a seed.
    """
    train, rows = features.where(~held_out(F.col("pair_id"))), []
    for seed in seeds:
        for sample in ("half", "rest"):
            mine = replace(cfg, split="shared", sample=sample, seed=seed)
            scored = with_policy_scores(train.where(~in_sample(mine)), train_policies(features, ref, mine))
            rows.append(scored.select("pair_id", F.lit(len(rows)).alias("model"), F.lit(False).alias("seen"), micro(S.pair_loss(S.implicit_margin("pos"), cfg.beta)).alias("loss")))
    return reduce(DataFrame.unionByName, rows)


def judged_dims(c: str) -> Column:
    """Four judged dimensions of a response from the texts alone, 0 to 1: prompt overlap, variety, length, plain characters."""
    words = tokens(F.col(c))
    n = F.greatest(F.size(words), F.lit(1))
    overlap = F.size(F.array_intersect(words, tokens(F.col("prompt")))) / F.greatest(F.size(F.array_distinct(tokens(F.col("prompt")))), F.lit(1))
    plain = F.length(F.regexp_replace(c, "[^A-Za-z .,]", "")) / F.greatest(F.length(c), F.lit(1))
    return F.array(overlap, F.size(F.array_distinct(words)) / n, F.least(n, F.lit(400)) / 400, plain)


def external_scores(pairs: DataFrame) -> DataFrame:
    """The mean of each response's judged dimensions."""
    mean = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + x.cast("double")) / 4
    return pairs.select("pair_id", F.round(mean(judged_dims("chosen")), 6).alias("ext_w"), F.round(mean(judged_dims("rejected")), 6).alias("ext_l"))


def policy_signals(pairs: DataFrame, texts: DataFrame, cfg: PolicyConfig = PolicyConfig()) -> tuple[DataFrame, Policies, DataFrame, Reference]:
    """Canonical signals of text pairs by trained policies; also the policies, the feature rows and the reference."""
    ref = reference(texts, cfg)
    feats = materialised(featurise(pairs, ref, cfg), "features")
    found = train_policies(feats, ref, cfg)
    lengths = pairs.select("pair_id", "grp", F.length("chosen").alias("len_w"), F.length("rejected").alias("len_l"))
    signals = with_policy_scores(feats, found).join(lengths, "pair_id").join(external_scores(pairs), "pair_id")
    return materialised(signals, "signals"), found, feats, ref
