"""Line dedup: an exact set-similarity join of lines by their words; later matches go.

A line is the set of its distinct words.  A line with a word is removed where an earlier line (smaller
doc_id, or same document and smaller number) has a Jaccard similarity of ``num / den`` or more.  Earlier
lines count as they stand in the input, removed or not, so that the result needs no order of work.

* Words are ranked by how often they occur in all documents, by hashed counters of fixed number
  (``COUNTERS``), ties by hash.  A line's rarest ``size - least overlap + 1`` words are its prefix, and of
  similar lines the first word in common is in the prefix of both.
* A word that occurs ``FREQUENT`` times or more would make a long list.  Behind such a word all others are
  frequent too, and the second word in common comes one place later at most: the key is then the two
  words together.  So lists stay short as the corpus grows.
* Lines that share a key are paired under the length bound, the position bound of the first word in common, and
  the parity of their hashed words, of which similar lines differ in few bits.  Pairs are verified on the words.
* Before that join each line meets a few earlier lines for each of a few pairs of words: the first line with this
  pair and the ones just before.  Lines of equal sets and most of a group of near copies are settled there
  in one sort, and settled lines need no further partner.  Keys of frequent words are salted, so that no sort holds
  more than a bounded share of a group; what a salt parts is left to the join.
* Lines are cut once, to a saved row each; all that follows reads those rows, and texts only of candidates.

DataFrame functions only.  Lines are of equal sets when size, 64 bits of the set's hash and its parity agree;
words are compared as they are.  Defined cases: a null or empty text has one line without words; lines without
words are never removed; rows without id stay as they are and match nothing; rows of one id are one
document, whose lines of one number are held to be the same place; of equal lines the earliest place stays;
very long texts are cut into lines like others, and a very long line is one set; other columns pass through
``deduped`` untouched; an empty table gives an empty result.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import discard, documents, saved, setting
from .rules import WS_CLASS

COUNTERS = 1 << 18  # numbers in the plan, whatever the input
MARKS = 1 << 16  # likewise; of 64 bits each
FREQUENT = 4096  # occurrences from which on a word alone is no key
GROUP = 4096  # occurrences of its rarest word for each salt of a key in the first round
LONG = 32  # words from which on a line has twice the parity bits
NEAR_KEYS = 4  # pairs of words of each line in the first round,
NEAR_LINES = 3  # earlier lines just before, beside the first one, for each of them, and
NEAR_TRIED = 2  # the nearest of all these, whose words are compared
INK = r"[^ \t\n\x0B\f\r]"
_FAST = "spark.sql.codegen.aggregate.fastHashMap.capacityBit"
ODD = "\t\x0B\f\r"


def _words(text: Column) -> Column:
    """Words of a line; single blanks, the usual case, need no pattern."""
    return F.array_remove(F.when(text.rlike(f"[{ODD}]"), F.split(text, WS_CLASS)).otherwise(F.split(text, " ")), "")


def _cut(docs: DataFrame) -> DataFrame:
    """(doc_id, line, t) of lines with a word, in which only blanks part words: whole texts are rid of other white space at once."""
    text = F.when(functools.reduce(Column.__or__, (F.contains("text", F.lit(c)) for c in ODD)), F.translate("text", ODD, " " * len(ODD))).otherwise(F.col("text"))
    lines = docs.where("doc_id IS NOT NULL AND text IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id"), F.posexplode(F.split(text, "\n")).alias("line", "t"))
    return lines.where(F.trim("t") != "")


def _slot(w: Column) -> Column:
    return F.hash(w).bitwiseAND(F.lit(COUNTERS - 1))


def rarity(docs: DataFrame) -> Column:
    """A level for each hashed counter: the logarithm of its words' occurrences in all documents.

    Words are cut at single blanks and line ends here; other white space only blurs the order.
    """
    words = docs.select(F.explode(F.split("text", "\n")).alias("t")).select(F.explode(F.split("t", " ")).alias("w"))
    counts = words.groupBy(_slot(F.col("w")).alias("slot")).agg(F.count(F.lit(1)).alias("n"))
    with setting(docs.sparkSession, _FAST, str(COUNTERS.bit_length() - 1)):  # room for all counters
        return _listed(counts, COUNTERS, F.least(F.lit(127), F.floor(5 * F.log2(F.col("n") + 1))))


def _listed(found: DataFrame, n: int, value: Column) -> Column:
    """An array of ``n`` whole numbers by ``slot``, 0 where ``found`` has none; a constant of the plan, of fixed size."""
    slots = found.sparkSession.range(n).select(F.col("id").alias("slot"))
    filled = slots.join(found.select(F.col("slot").cast("long").alias("slot"), value.cast("long").alias("v")), "slot", "left").select("slot", F.coalesce("v", F.lit(0)).alias("v"))
    text = filled.agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("slot", "v"))), lambda x: x["v"].cast("string")), ",").alias("t")).first()["t"]
    return F.split(F.lit(text), ",").cast("array<long>")


def signatures(docs: DataFrame, num: int, den: int) -> DataFrame:
    """A compact row for every line with a word: size, set hash, parity bits, and its prefix and one word more, rarest first."""
    levels = rarity(docs)
    # Level in the upper 7 bits, 56 bits of the hash below.  Spark interprets what is done for each word, so that it is one short step.
    level = lambda w: F.coalesce(F.get(levels, _slot(w)), F.lit(0).cast("long"))
    rank = lambda w: F.shiftleft(level(w), 56).bitwiseOR(F.shiftrightunsigned(F.xxhash64(w), 8))
    words = F.array_except(F.transform(F.split("t", " "), rank), F.array(rank(F.lit(""))))
    ranked = _cut(docs).select("doc_id", "line", F.sort_array(words).alias("r"))
    n = F.size("r")
    bits = F.array(*(F.lit(1 << i if i < 63 else -(1 << 63)) for i in range(64)))
    bit = lambda a, w: a.bitwiseXOR(F.get(bits, w.bitwiseAND(F.lit(63))))
    half = lambda is_set: F.aggregate(F.filter("r", lambda w: (w.bitwiseAND(F.lit(64)) != 0) == F.lit(is_set)), F.lit(0).cast("long"), bit)
    first = F.when(n < LONG, F.aggregate("r", F.lit(0).cast("long"), bit)).otherwise(half(False))
    second = F.when(n < LONG, F.lit(0).cast("long")).otherwise(half(True))
    prefix = F.slice("r", 1, n - F.ceil(n * num / den - 1e-9).cast("int") + 2)
    return ranked.select("doc_id", "line", n.alias("n"), F.xxhash64("r").alias("s"), first.alias("p"), second.alias("q"), prefix.alias("keys"))


def _apart() -> Column:
    """Differing parity bits of x and y, never more than differing words: of 128 where both are long, of 64 otherwise."""
    return F.expr(f"CASE WHEN abs(n_x) >= {LONG} AND abs(n_y) >= {LONG} THEN bit_count(p_x ^ p_y) + bit_count(q_x ^ q_y) ELSE bit_count(p_x ^ q_x ^ p_y ^ q_y) END")


def _met(known: DataFrame, num: int, den: int) -> DataFrame:
    """(doc_id_y, line_y, copy, doc_id_x, line_x): lines with an equal one before them, and else the nearest ones that may be similar."""
    # Words that stand next to each other in the prefix, from its end: the rarest words of a copy are often odd ones.
    word = lambda i: F.get("keys", F.size("keys") - i)
    two = [F.when(F.size("keys") > i, F.xxhash64(word(i), word(i + 1))) for i in range(1, NEAR_KEYS + 1)]
    salts = F.greatest(F.lit(1), F.pow(F.lit(2.0), F.shiftrightunsigned(F.get("keys", F.lit(0)), 56) / 5) / GROUP).cast("long")
    salt = F.when(salts > 1, F.pmod(F.xxhash64("doc_id"), salts)).otherwise(0)
    held = known.select("doc_id", "line", "n", "p", "q", salt.alias("salt"), F.posexplode(F.array("s", *two)).alias("kind", "key")).where("key IS NOT NULL")
    held = held.select("doc_id", "line", "n", "p", "q", (F.col("kind") == 0).alias("whole"), F.when(F.col("salt") > 0, F.xxhash64("key", "salt")).otherwise(F.col("key")).alias("key"))
    names = ("doc_id", "line", "n", "p", "q", "whole")
    own, by = F.struct(*names), Window.partitionBy("key").orderBy("doc_id", "line")
    near = held.select("*", F.first(own).over(by).alias("x0"), *(F.lag(own, i).over(by).alias(f"x{i}") for i in range(1, NEAR_LINES + 1))).where("x1 IS NOT NULL")
    before = F.array(*(f"x{i}" for i in range(1, NEAR_LINES + 1)), F.when(F.col(f"x{NEAR_LINES}").isNotNull(), F.col("x0")))  # nulls go below
    pairs = near.select(*(F.col(c).alias(f"{c}_y") for c in names), F.explode(F.when(F.col("whole"), F.array("x1")).otherwise(before)).alias("x"))
    pairs = pairs.select("*", *(F.col(f"x.{c}").alias(f"{c}_x") for c in names)).where("doc_id_x < doc_id_y OR line_x < line_y")
    equal = F.expr("whole_x AND whole_y AND n_x = n_y AND p_x = p_y AND q_x = q_y")
    alike = (den * F.least("n_x", "n_y") >= num * F.greatest("n_x", "n_y")) & ((num + den) * _apart() <= (den - num) * (F.col("n_x") + F.col("n_y")))
    found = pairs.where(alike).select("doc_id_y", "line_y", equal.alias("copy"), F.struct(_apart().alias("apart"), "doc_id_x", "line_x").alias("h"))
    best = found.groupBy("doc_id_y", "line_y").agg(F.max("copy").alias("copy"), F.slice(F.sort_array(F.collect_set("h")), 1, NEAR_TRIED).alias("h"))  # of a few lines for each key
    return best.select("doc_id_y", "line_y", "copy", F.explode(F.when(F.col("copy"), F.slice("h", 1, 1)).otherwise(F.col("h"))).alias("h")).select("doc_id_y", "line_y", "copy", "h.doc_id_x", "h.line_x")


def _pairs(known: DataFrame, copies: DataFrame, quick: DataFrame, num: int, den: int) -> DataFrame:
    """(doc_id_x, line_x, doc_id_y, line_y): every earlier line and later one not settled that may be similar."""
    frequent = int(5 * math.log2(FREQUENT + 1)) << 56 if 2 * num > den else (1 << 63) - 1  # else one word may be all that is shared
    # Equal lines go; other settled ones have a negative size, which no second line may have: both sides are the same rows, shuffled once.
    settled = copies.withColumn("sign", F.lit(0)).union(quick.withColumn("sign", F.lit(-1)))
    marked = known.join(settled.select(F.col("doc_id_y").alias("doc_id"), F.col("line_y").alias("line"), "sign"), ["doc_id", "line"], "left").withColumn("sign", F.coalesce("sign", F.lit(1))).where("sign <> 0")
    # A word alone, or with each word that may be the second in common.
    alone = (F.col("n") == 1) | (F.col("w") < frequent)
    held = marked.select("doc_id", "line", "n", "p", "q", "sign", "keys", F.posexplode("keys").alias("i", "w")).where(f"i <= n - cast(ceil(n * {num} / {den} - 1e-9) AS INT)")
    held = held.select("*", F.posexplode(F.when(alone, F.array(F.lit(0).cast("long"))).otherwise(F.expr("slice(keys, i + 2, size(keys))"))).alias("j", "v"))
    key = F.when(alone, F.col("w")).otherwise(F.xxhash64("w", "v"))
    rows = held.select("doc_id", "line", (F.col("n") * F.col("sign")).alias("n"), "p", "q", (F.col("i") + F.col("j")).alias("pos"), key.alias("key"))
    x, y = (rows.select("key", *(F.col(c).alias(f"{c}_{s}") for c in rows.columns if c != "key")) for s in "xy")
    n_x = F.abs("n_x")
    total = n_x + F.abs("n_y")
    earlier = (F.col("doc_id_x") < F.col("doc_id_y")) | ((F.col("doc_id_x") == F.col("doc_id_y")) & (F.col("line_x") < F.col("line_y")))
    size = den * F.least(n_x, "n_y") >= num * F.greatest(n_x, "n_y")  # false where n_y is negative
    place = (num + den) * F.least(n_x - F.col("pos_x"), F.abs("n_y") - F.col("pos_y")) >= num * total
    alike = (num + den) * _apart() <= (den - num) * total
    return x.join(y, (x.key == y.key) & earlier & size & place & alike).select("doc_id_x", "line_x", "doc_id_y", "line_y").distinct()


def _verified(docs: DataFrame, pairs: DataFrame, num: int, den: int) -> DataFrame:
    """(doc_id_y, line_y) of the pairs whose words, not their hashes, are similar; ``pairs`` is a saved table and goes."""
    places = pairs.select(F.col("doc_id_x").alias("doc_id"), F.col("line_x").alias("line")).union(pairs.select("doc_id_y", "line_y")).distinct()
    slot = lambda: F.xxhash64("doc_id", "line").bitwiseAND(F.lit(64 * MARKS - 1))
    marks = places.groupBy(F.shiftright(slot(), 6).alias("slot")).agg(F.bit_or(F.expr("shiftleft(1L, cast(xxhash64(doc_id, line) & 63 AS INT))")).alias("bits"))
    listed = _listed(marks, MARKS, F.col("bits"))
    marked = F.call_function("shiftrightunsigned", F.get(listed, F.shiftright(slot(), 6).cast("int")), slot().bitwiseAND(F.lit(63)).cast("int")).bitwiseAND(F.lit(1)) == 1
    lines = docs.where("text IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id"), F.posexplode(F.split("text", "\n")).alias("line", "t"))
    texts = saved(lines.where(marked).join(places, ["doc_id", "line"], "left_semi"), "line-texts")
    a, b = (texts.select(*(F.col(c).alias(f"{c}_{s}") for c in ("doc_id", "line", "t"))) for s in "xy")
    found = pairs.join(a, ["doc_id_x", "line_x"]).join(b, ["doc_id_y", "line_y"])
    both = found.select("doc_id_y", "line_y", F.array_distinct(_words(F.col("t_x"))).alias("p"), F.array_distinct(_words(F.col("t_y"))).alias("q"))
    sizes = both.select("doc_id_y", "line_y", (F.size("p") + F.size("q")).alias("total"), F.size(F.array_intersect("p", "q")).alias("shared"))
    out = saved(sizes.groupBy("doc_id_y", "line_y").agg(F.max((num + den) * F.col("shared") - num * F.col("total")).alias("best")).where("best >= 0").select("doc_id_y", "line_y"), "line-matches")
    discard(texts, pairs)
    return out


def similar_lines(docs: DataFrame, num: int = 80, den: int = 100) -> DataFrame:
    """(doc_id, line) of the lines to remove."""
    known = saved(signatures(docs, num, den), "line-signatures")
    met = saved(_met(known, num, den), "line-met")
    quick = _verified(docs, saved(met.where("NOT copy").drop("copy"), "line-heads"), num, den)
    copies = met.where("copy").select("doc_id_y", "line_y")
    late = _verified(docs, saved(_pairs(known, copies, quick, num, den), "line-pairs"), num, den)
    gone = saved(copies.union(quick).union(late).distinct().select(F.col("doc_id_y").alias("doc_id"), F.col("line_y").alias("line")), "line-removals")
    discard(known, met, quick, late)
    return gone


def removals(docs: DataFrame, num: int = 80, den: int = 100) -> DataFrame:
    """doc_id and ``gone``, the sorted numbers of the lines to remove, of documents that have any."""
    return similar_lines(docs, num, den).groupBy("doc_id").agg(F.sort_array(F.collect_set("line")).alias("gone"))


def deduped(docs: DataFrame, num: int = 80, den: int = 100) -> DataFrame:
    """``docs`` with the removed lines gone from ``text``; documents left without a word go; n_chars follows the text."""
    packed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.struct("*").alias("row"))  # other columns can't clash
    found = packed.join(removals(docs.select("doc_id", "text"), num, den), "doc_id", "left")
    same, text = F.col("gone").isNull(), F.col("row")["text"]
    kept = F.array_join(F.filter(F.split(text, "\n"), lambda t, i: ~F.array_contains("gone", i)), "\n")
    out = found.withColumn("kept", F.when(~same, kept)).where(same | F.col("kept").rlike(INK))
    changed = {"text": F.col("kept"), "n_chars": F.length("kept")}
    return out.select(*[F.when(same, F.col("row")[c]).otherwise(changed[c].cast(docs.schema[c].dataType)).alias(c) if c in changed else F.col("row")[c].alias(c) for c in docs.columns])


def op6_linedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text")
    counted = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.size(F.split(F.coalesce("text", F.lit("")), "\n")).cast("long").alias("n_lines"))
    return counted.join(removals(docs), "doc_id", "left").select(
        "doc_id", "n_lines", F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("n_removed"), F.coalesce(F.array_join("gone", ","), F.lit("")).alias("removed")
    )


_CUT = r"[\x20\x09-\x0D]+"
ORACLES = {
    "op6_linedup": rf"""
WITH lines AS (
  SELECT CAST(doc_id AS BIGINT) AS doc_id, unnest(range(0, len(l))) AS line, unnest(l) AS t FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS l FROM documents)),
sets AS MATERIALIZED (
  SELECT doc_id, line, list_sort(list_distinct(list_filter(regexp_split_to_array(t, '{_CUT}'), lambda x: x <> ''))) AS w FROM lines),
classes AS MATERIALIZED (
  SELECT row_number() OVER () AS c, w, min(struct_pack(doc_id := doc_id, line := line)) AS f FROM sets WHERE len(w) > 0 GROUP BY w),
words AS (SELECT c, unnest(w) AS word FROM classes),
freq AS (SELECT word, count(*) AS n FROM words GROUP BY word),
ranked AS (SELECT w.c, w.word, row_number() OVER (PARTITION BY w.c ORDER BY f.n, w.word) AS k FROM words w JOIN freq f ON f.word = w.word),
heads AS MATERIALIZED (SELECT r.c, r.word FROM ranked r JOIN classes s ON s.c = r.c WHERE r.k <= len(s.w) - ceil(len(s.w) * 0.8 - 1e-9) + 1),
pairs AS (SELECT DISTINCT a.c AS x, b.c AS y FROM heads a JOIN heads b ON a.word = b.word AND a.c <> b.c),
alike AS (
  SELECT DISTINCT q.f AS f FROM pairs JOIN classes p ON p.c = x JOIN classes q ON q.c = y
  WHERE p.f < q.f AND 10 * least(len(p.w), len(q.w)) >= 8 * greatest(len(p.w), len(q.w))
    AND 100 * len(list_intersect(p.w, q.w)) >= 80 * (len(p.w) + len(q.w) - len(list_intersect(p.w, q.w)))),
gone AS (
  SELECT f.doc_id AS doc_id, f.line AS line FROM alike
  UNION
  SELECT s.doc_id, s.line FROM sets s JOIN classes c ON c.w = s.w WHERE struct_pack(doc_id := s.doc_id, line := s.line) <> c.f),
listed AS (SELECT doc_id, count(*) AS n, string_agg(CAST(line AS VARCHAR), ',' ORDER BY line) AS removed FROM gone GROUP BY doc_id)
SELECT d.doc_id, CAST(len(string_split(coalesce(d.text, ''), chr(10))) AS BIGINT) AS n_lines, CAST(coalesce(g.n, 0) AS BIGINT) AS n_removed, coalesce(g.removed, '') AS removed
FROM documents d LEFT JOIN listed g ON g.doc_id = d.doc_id"""
}
QUERIES: dict[str, Callable] = {"op6_linedup": op6_linedup}
