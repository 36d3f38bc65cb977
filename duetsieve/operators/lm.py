"""Count-based language models as the reference: counts, interpolated probabilities, forced decoding.

Log-probabilities are whole micro-nats per token, so that their sums do not depend on order or engine.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.columns import micro, tokens

LAMBDA = 0.6
ALPHA = 0.5


def token_stream(texts: DataFrame, text: str = "text") -> DataFrame:
    """(tok, prev) of every token; the first has the empty string before it."""
    words = texts.select(tokens(F.col(text)).alias("w"))
    return words.select(F.inline(F.arrays_zip(F.col("w").alias("tok"), F.concat(F.array(F.lit("")), F.slice("w", 1, F.greatest(F.size("w") - 1, F.lit(0)))).alias("prev")))).where("tok IS NOT NULL")


def unigram(texts: DataFrame, text: str = "text") -> DataFrame:
    return texts.select(F.explode(tokens(F.col(text))).alias("tok")).groupBy("tok").agg(F.count(F.lit(1)).alias("n"))


def bigram(texts: DataFrame, text: str = "text") -> DataFrame:
    return token_stream(texts, text).groupBy("prev", "tok").agg(F.count(F.lit(1)).alias("n"))


def totals(counts: DataFrame) -> tuple[int, int]:
    """Tokens and distinct tokens."""
    row = counts.agg(F.sum("n"), F.count(F.lit(1))).first()
    return int(row[0] or 0), int(row[1])


def unigram_scores(counts: DataFrame, alpha: float = ALPHA) -> DataFrame:
    """(tok, lp): add-alpha over the seen tokens and one unseen one, which has the null token's row."""
    n, kinds = totals(counts)
    whole = n + alpha * (kinds + 1)
    return counts.select("tok", micro(F.ln((F.col("n") + alpha) / F.lit(whole))).alias("lp"))


def bigram_scores(texts: DataFrame, text: str = "text", lam: float = LAMBDA, alpha: float = ALPHA) -> DataFrame:
    """(prev, tok, lp) of seen bigrams: share in context, interpolated with the add-alpha unigram."""
    pairs, ones = bigram(texts, text), unigram(texts, text)
    n, kinds = totals(ones)
    whole = n + alpha * (kinds + 1)
    contexts = pairs.groupBy("prev").agg(F.sum("n").alias("n_prev"))
    p = lam * F.col("n") / F.col("n_prev") + (1 - lam) * (F.col("n_tok") + alpha) / whole
    return pairs.join(contexts, "prev").join(ones.select("tok", F.col("n").alias("n_tok")), "tok").select("prev", "tok", micro(F.ln(p)).alias("lp"))


def forced_decoding(pairs: DataFrame, texts: DataFrame, lam: float = LAMBDA, alpha: float = ALPHA) -> DataFrame:
    """(pair_id, lp_w, n_w, lp_l, n_l): both responses' log-probabilities under the interpolated bigram model.

    Unseen bigrams and tokens fall back to the interpolation's second part, so that every token has a score.
    """
    ones, two = unigram(texts), bigram(texts)
    n, kinds = totals(ones)
    whole = n + alpha * (kinds + 1)
    contexts = two.groupBy("prev").agg(F.sum("n").alias("n_prev"))
    side = lambda c, s: pairs.select("pair_id", F.lit(s).alias("side"), tokens(F.col(c)).alias("w"))
    stream = side("chosen", "w").unionByName(side("rejected", "l")).select(
        "pair_id", "side", F.inline(F.arrays_zip(F.col("w").alias("tok"), F.concat(F.array(F.lit("")), F.slice("w", 1, F.greatest(F.size("w") - 1, F.lit(0)))).alias("prev")))
    )
    # Equal bigrams of one response are scored once and weighed by their number.
    uses = stream.where("tok IS NOT NULL").groupBy("pair_id", "side", "prev", "tok").agg(F.count(F.lit(1)).alias("times"))
    joined = uses.join(two, ["prev", "tok"], "left").join(contexts, "prev", "left").join(ones.select("tok", F.col("n").alias("n_tok")), "tok", "left")
    z = lambda c: F.coalesce(F.col(c), F.lit(0))
    p = F.when(z("n_prev") > 0, lam * z("n") / F.col("n_prev") + (1 - lam) * (z("n_tok") + alpha) / whole).otherwise((z("n_tok") + alpha) / whole)
    scored = joined.select("pair_id", "side", "times", (micro(F.ln(p)) * F.col("times")).alias("lp"))
    of = lambda c, s: F.coalesce(F.sum(F.when(F.col("side") == s, F.col(c))), F.lit(0)).cast("long")
    return scored.groupBy("pair_id").agg(of("lp", "w").alias("lp_w"), of("times", "w").alias("n_w"), of("lp", "l").alias("lp_l"), of("times", "l").alias("n_l"))
