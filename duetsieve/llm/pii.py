"""Personal data: patterns propose spans, checksums confirm them, context words move the score.

Base kinds (email, ip, card, phone) always stay.  The method adds two kinds of its own: bank account
numbers confirmed by mod 97 (``iban``) and credentials (``secret``), which need either a fixed vendor
prefix or a context word in front.  Each span has a score: a prior of its kind, raised by a confirmed
checksum and by context words within ``window`` code points before it.

Defined cases: a null or empty text has no span; repeated rows are judged one by one; other columns of
the input are ignored, whatever their names; an empty table gives an empty result.  Every scanner is
linear in the text, so that very long texts cost in proportion.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, text_lists

KINDS = ("email", "ip", "card", "phone", "iban", "secret")
BASE = KINDS[:4]

# The patterns of the contract, in linear form.
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])")
_SECRET = re.compile(r"(?<![A-Za-z0-9])(?:AKIA[0-9A-Z]{16}|gh[pousr]_[A-Za-z0-9]{36}|(?:password|passwd|secret|token|api_key|apikey)[=:][^\s,;]{8,})(?![A-Za-z0-9])")
_SECRET_HINTS = ("AKIA", "gh", "passw", "secret", "token", "api")

# Prior score of a kind, and its context words.
PRIORS = {"email": 0.8, "ip": 0.5, "card": 0.6, "phone": 0.6, "iban": 0.6, "secret": 0.7}
CONTEXT = {
    "email": ("mail", "contact", "write", "correo", "courriel"),
    "ip": ("ip", "host", "server", "address", "adresse"),
    "card": ("card", "visa", "credit", "karte", "carte", "tarjeta", "payment"),
    "phone": ("phone", "tel", "call", "mobile", "fax", "telefon", "fono"),
    "iban": ("iban", "bank", "account", "konto", "compte", "cuenta"),
    "secret": ("key", "secret", "login", "credential", "token"),
}


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def mod97(account: str) -> bool:
    """True where the rearranged account number leaves 1 after division by 97."""
    plain = account.replace(" ", "")
    if not 15 <= len(plain) <= 34:
        return False
    return int("".join(str(int(c, 36)) for c in plain[4:] + plain[:4])) % 97 == 1


def _emails(text: str) -> Iterator[tuple[int, int]]:
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        found = _DOMAIN.match(text, at + 1) if start < at else None
        if found:
            done = found.end()
            yield start, done
        at = text.find("@", max(done, at + 1))


def _digits(text: str) -> str:
    return "".join(c for c in text if "0" <= c <= "9")


def find_spans(text: str) -> list[tuple[str, int, int, bool]]:
    """(kind, start, end, confirmed by a checksum), by kind as listed, then start."""
    spans = [("email", a, b, False) for a, b in _emails(text)]
    if "." in text:
        spans += [("ip", m.start(), m.end(), False) for m in _IP.finditer(text) if all(len(x.lstrip("0")) <= 3 and int(x.lstrip("0") or 0) <= 255 for x in m[0].split("."))]
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 13 and 13 <= len(d := _digits(m[0])) <= 19 and luhn(d):
            spans.append(("card", m.start(), m.end(), True))
    if "+" in text:
        spans += [("phone", m.start(), m.end(), False) for m in _PHONE.finditer(text) if 9 <= len(_digits(m[0])) <= 15]
    spans += [("iban", m.start(), m.end(), True) for m in _IBAN.finditer(text) if mod97(m[0])]
    if any(x in text for x in _SECRET_HINTS):
        spans += [("secret", m.start(), m.end(), False) for m in _SECRET.finditer(text)]
    return spans


def score_span(text: str, kind: str, start: int, confirmed: bool, window: int = 40) -> float:
    before = text[max(0, start - window) : start].lower()
    return round(min(1.0, PRIORS[kind] + 0.2 * confirmed + 0.15 * any(x in before for x in CONTEXT[kind])), 4)


_SCHEMA = "doc_id long, spans array<struct<kind:string,start:long,end:long,confirmed:boolean,score:double>>"
_SPAN = pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("confirmed", pa.bool_()), ("score", pa.float64())])


def detect(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", window: int = 40) -> DataFrame:
    """All spans of every text as structs; offsets are code points, ends exclusive."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in text_lists(batches):
            rows = [[{"kind": k, "start": a, "end": b, "confirmed": c, "score": score_span(t, k, a, c, window)} for k, a, b, c in find_spans(t)] for t in texts]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(rows, pa.list_(_SPAN))], ["doc_id", "spans"])

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(scan, _SCHEMA)


def redact(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", least: float = 0.5) -> DataFrame:
    """Texts with each span scored ``least`` or more replaced by its kind in brackets; overlapping spans merge."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in text_lists(batches):
            out = []
            for t in texts:
                parts, done = [], 0
                for a, b, k in sorted((a, b, k) for k, a, b, c in find_spans(t) if score_span(t, k, a, c) >= least):
                    if a >= done:
                        parts += [t[done:a], f"[{k}]"]
                    done = max(done, b)
                out.append("".join(parts) + t[done:])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(out, pa.string())], ["doc_id", "text"])

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(scan, "doc_id long, text string")


def digest(found: DataFrame) -> DataFrame:
    """The contract's columns from ``detect``'s spans."""
    listed = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    of = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return found.select(
        "doc_id",
        *[of(k) for k in BASE],
        F.sha2(listed(F.filter("spans", lambda s: s["kind"].isin(*BASE))), 256).alias("base_sha256"),
        listed(F.col("spans")).alias("spans"),
        F.coalesce(F.array_max(F.transform("spans", lambda s: s["score"])), F.lit(0.0)).alias("top_score"),
    )


def op1_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(detect(documents(spark, sf_dir)))


QUERIES = {"op1_pii": op1_pii}
