"""Column building blocks: quantised log-probabilities, portable hashes, tokens."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

MICRO = 1_000_000
#: Text splits on these; no other character is white space here.
TOKEN_CUT = "[ \n\t\r]+"


def micro(x: Column) -> Column:
    """Nats to whole micro-nats; null where the value isn't finite."""
    usable = x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))
    return F.when(usable, F.floor(x * MICRO + 0.5)).cast("long")


def nats(x: Column) -> Column:
    return x.cast("double") / MICRO


def portable_hash(salt: str, value: Column) -> Column:
    """32 bits of an MD5 of salt and value, alike in any engine."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(salt), value.cast("string"))), 1, 8), 16, 10).cast("long")


def tokens(text: Column) -> Column:
    return F.array_remove(F.split(text, TOKEN_CUT), "")


def judge_scores(reply: Column) -> Column:
    """A judge's JSON reply as a map of dimension to score; null where it is no JSON object of numbers."""
    return F.from_json(reply, "map<string,double>", {"mode": "PERMISSIVE"})


def held_out(pair_id: Column) -> Column:
    return portable_hash("split:", pair_id) % 10 >= 8


def cosine(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return F.try_divide(dot(a, b), F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))
