"""Piece encoding and decoding for merge-type vocabularies, checked against the sentencepiece library.

A text is normalised as the vocabulary file asks (blank to the visible blank, one put in front), cut
where no piece of the vocabulary can reach across, and each fragment is merged by an agenda: adjacent
symbol pairs wait in a heap ordered by piece score, then by place; the best live pair merges, and its two
new neighbours enter.  Symbols that end up outside the vocabulary fall back to bytes.

Fragments recur, so that each Python worker keeps their ids for one run of a query (``budget`` fragments
at most, then it starts anew).  All fragments that are new in an Arrow batch are encoded and decoded by the
library as well, in one call each, before the batch is handed on; a difference in ids is settled for the
library and counted in ``agenda_misses`` (of the worker so far, a report and no measure of the rows), one in
the decoded text is an error.  Vocabularies for which the cuts aren't provably safe are refused.

Every document's ids are decoded, from the ids alone: pieces are put together, bytes become characters, and
the blank that normalising put in front goes.

Defined cases: a null or empty text has the end id only and decodes to the empty text; a very long text is
handled like others, in memory that follows its length; repeated rows are encoded one by one; other columns are
ignored, whatever their names; an empty table gives an empty result.
"""

from __future__ import annotations

import heapq
import re
import uuid
from collections.abc import Callable, Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, kept, lean, text_array, text_lists

BLANK = "▁"
_RUNS = re.compile(f"{BLANK}+[^{BLANK}]*")


class Vocabulary:
    """Scores, ids and strings of a merge-type vocabulary file, read through the library."""

    def __init__(self, path: str):
        import sentencepiece

        self.library = lib = sentencepiece.SentencePieceProcessor(model_file=path)
        self.score, self.ids, self.strings, self.bytes = {}, {}, [], {}
        for i in range(lib.get_piece_size()):
            piece = lib.id_to_piece(i)
            self.strings.append("" if lib.is_control(i) else piece)
            if lib.is_byte(i):
                self.bytes[int(piece[3:-1], 16)] = i
            elif lib.is_unused(i):
                raise ValueError("vocabularies with unused pieces need re-segmentation and aren't supported")
            elif not (lib.is_control(i) or lib.is_unknown(i)):
                self.score[piece], self.ids[piece] = -lib.get_score(i), i
        #: Text of each id as written in a list of ids; bytes above 127 as the surrogates that stand for single bytes.
        self.surface = {str(i): s.replace(BLANK, " ") for i, s in enumerate(self.strings)}
        self.surface.update((str(i), bytes([b]).decode("utf-8", "surrogateescape")) for b, i in self.bytes.items())
        self.end, self.unknown = lib.eos_id(), lib.unk_id()
        self.surface[str(self.unknown)] = " \u2047 "  # as the library writes it
        pairs = {p[k : k + 2] for p in self.ids for k in range(len(p) - 1)}
        if len(self.bytes) != 256 or any(p[1] == BLANK != p[0] or "\n" in p for p in pairs):
            raise ValueError("cutting before blanks and at line ends isn't safe for this vocabulary")
        if lib.encode("  a b ") != self.merge(f"{BLANK}" * 3 + f"a{BLANK}b{BLANK}"):
            raise ValueError("this vocabulary normalises texts in another way")
        #: Whether a full stop or comma at the end of a fragment can merge with what stands before it.
        self.pairs = pairs

    def merge(self, text: str) -> list[int]:
        """Ids of a normalised fragment by the agenda."""
        symbols = list(text)
        n = len(symbols)
        right, left = list(range(1, n + 1)), list(range(-1, n - 1))
        score, agenda = self.score.get, []
        for i in range(n - 1):
            pair = symbols[i] + symbols[i + 1]
            if (s := score(pair)) is not None:
                agenda.append((s, i, pair))
        heapq.heapify(agenda)
        while agenda:
            _, i, pair = heapq.heappop(agenda)
            j = right[i]
            if j >= n or not symbols[i] or symbols[i] + symbols[j] != pair:
                continue  # one of the two has merged meanwhile
            symbols[i], symbols[j] = pair, ""
            k = right[i] = right[j]
            if k < n:
                left[k] = i
                if (s := score(pair + symbols[k])) is not None:
                    heapq.heappush(agenda, (s, i, pair + symbols[k]))
            h = left[i]
            if h >= 0 and (s := score(symbols[h] + pair)) is not None:
                heapq.heappush(agenda, (s, h, symbols[h] + pair))
        out: list[int] = []
        for x in symbols:
            if x:
                found = self.ids.get(x)
                if found is None:
                    out.extend(self.bytes[b] for b in x.encode())
                else:
                    out.append(found)
        return out

    def decode(self, ids: str) -> bytes:
        """UTF-8 of decimal ids: control ids leave no text, bytes stand as they are, the leading blank goes."""
        if not ids:
            return b""
        text = "".join(map(self.surface.__getitem__, ids.split(" "))).encode("utf-8", "surrogateescape")
        return text[1:] if text[:1] == b" " else text


@lru_cache(maxsize=2)
def vocabulary(path: str) -> Vocabulary:
    return Vocabulary(path)


class _Fragments(dict):
    """Fragment to its ids as text, made on first use; ``fresh`` holds what awaits the library's check."""

    def __init__(self, voc: Vocabulary, before: str):
        super().__init__()
        self.voc, self.before, self.fresh = voc, before, []

    def __missing__(self, word: str) -> str:
        whole = self.before + word
        stem, last = whole[:-1], whole[-1:]
        if last in (".", ",") and len(word) > 1 and stem[-1] + last not in self.voc.pairs:  # nothing reaches across
            ids = [int(x) for x in self[word[:-1]].split(" ")] + self.voc.merge(last)
        else:
            ids = self.voc.merge(whole)
        found = self[word] = " ".join(map(str, ids))
        self.fresh.append(word)
        return found


class Encoder:
    """One worker's encoder: fragments known so far, whole texts put together from them."""

    def __init__(self, path: str, budget: int):
        self.voc, self.budget, self.misses = vocabulary(path), budget, 0
        self._anew()

    def _anew(self) -> None:
        #: After a blank; at a line's start; after several blanks.
        self.led, self.bare, self.runs = (_Fragments(self.voc, b) for b in (BLANK, "", ""))

    def _fragments(self, text: str) -> Iterator[tuple[_Fragments, list[str]]]:
        """Per line: a table and the fragments to look up in it."""
        for n, line in enumerate(text.replace(" ", BLANK).split("\n")):
            if n:
                yield self.bare, ["\n"]
            else:
                line = BLANK + line
            if BLANK + BLANK in line:
                at = line.find(BLANK)
                if at:
                    yield self.bare, [line[:at]]
                yield self.runs, _RUNS.findall(line)
            else:
                first, *rest = line.split(BLANK)
                if first:
                    yield self.bare, [first]
                yield self.led, rest

    def encode(self, text: str) -> str:
        """Decimal ids joined by blanks, the end id last."""
        out = []
        if text:
            for table, words in self._fragments(text):
                out += [table[w] for w in words]
        out.append(str(self.voc.end))
        return " ".join(out)

    def check(self) -> bool:
        """Compares what is new with the library; True where nothing had to be put right."""
        good = True
        for table, lead in ((self.led, ""), (self.bare, "\n"), (self.runs, None)):
            fresh, table.fresh = table.fresh, []
            if not fresh:
                continue
            asked = [w[1:] if lead is None else lead + w for w in fresh]
            skip = 2 if lead else 0
            for word, sent, ids in zip(fresh, asked, self.voc.library.encode(asked, num_threads=1), strict=True):
                want = " ".join(map(str, ids[skip:] if sent else self.voc.merge(BLANK)))
                if table[word] != want:
                    table[word], good = want, False
                    self.misses += 1
            known = [table[w] for w in fresh]
            for ids, text in zip(known, self.voc.library.decode([[int(x) for x in k.split(" ")] for k in known], num_threads=1), strict=True):
                if self.voc.decode(ids).decode("utf-8", "replace") != text:
                    raise ValueError(f"ids {ids} decode to another text than the library's")
        return good

    def batch(self, texts: list[str]) -> list[str]:
        if len(self.led) + len(self.bare) + len(self.runs) > self.budget:
            self._anew()
        out = [self.encode(t) for t in texts]
        return out if self.check() else self.batch(texts)


def encoder(run: str, path: str, budget: int) -> Encoder:
    """This worker's encoder for one run of a query."""
    return kept(run, lambda: Encoder(path, budget))


def encode_texts(docs: DataFrame, path: str, keep: list[str], budget: int = 1_200_000, with_ids: bool = True) -> DataFrame:
    """``keep`` columns with n_tokens, ids (text of decimals; optional), decoded, and the worker's agenda_misses so far."""
    run = uuid.uuid4().hex

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = encoder(run, path, budget)
        for batch in batches:
            texts = text_array(batch.column("text"))
            for at in range(0, len(texts), 512):
                part = texts.slice(at, 512).to_pylist()
                ids = found.batch(part)
                cols = [batch.column(c).slice(at, len(part)) for c in keep]
                cols += [pa.array([x.count(" ") + 1 for x in ids], pa.int64()), pa.array(ids, pa.string()), pa.array([found.voc.decode(x).decode("utf-8", "replace") for x in ids], pa.string()), pa.array([found.misses] * len(part), pa.int64())]
                yield pa.RecordBatch.from_arrays(cols, [*keep, "n_tokens", "ids", "decoded", "agenda_misses"])

    schema = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in keep)
    out = docs.select(*keep, *(["text"] if "text" not in keep else [])).mapInArrow(lean(work, run), f"{schema}, n_tokens long, ids string, decoded string, agenda_misses long")
    return out if with_ids else out.drop("ids")


def decode_ids(encoded: DataFrame, path: str, ids: str = "ids") -> DataFrame:
    """``decoded`` from a column of decimal ids; control ids leave no text, the leading blank goes."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        voc = vocabulary(path)
        for batch, texts in text_lists(batches, ids):
            back = [voc.decode(t).decode("utf-8", "replace") for t in texts]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(back, pa.string())], [*batch.schema.names, "decoded"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in encoded.schema)
    return encoded.mapInArrow(lean(work), f"{schema}, decoded string")


def digest_texts(docs: DataFrame, path: str, budget: int = 1_200_000) -> DataFrame:
    """The contract's digests, made beside the ids so that these never leave the worker."""
    import hashlib

    run = uuid.uuid4().hex
    sha = lambda x: hashlib.sha256(x).hexdigest()

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = encoder(run, path, budget)
        for batch in batches:
            texts, cols = text_array(batch.column("text")), [[], [], []]
            for at in range(0, len(texts), 512):
                ids = found.batch(texts.slice(at, 512).to_pylist())
                cols[0] += [x.count(" ") + 1 for x in ids]
                cols[1] += [sha(x.encode()) for x in ids]
                cols[2] += [sha(found.voc.decode(x)) for x in ids]  # of valid texts, so that the bytes are those of a text
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.string()), pa.array(cols[2], pa.string()), pa.array([found.misses] * len(texts), pa.int64())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "agenda_misses"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(lean(work, run), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, agenda_misses long")


def piece_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def op3_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest_texts(documents(spark, sf_dir), piece_model())


QUERIES: dict[str, Callable] = {"op3_pieces": op3_pieces}
