"""Token ids in files: shards of concatenated ids whose document boundaries are Elias-Fano coded.

A shard holds a run of documents in ascending ``doc_id`` order (null ids first, then ties in order of
text): all ids as 16- or 32-bit little-endian integers, whichever the vocabulary needs, then the document ids
and the boundaries as Elias-Fano sequences, and a tail of fixed size.  Shards follow one another in that order; a
manifest with one line a shard (documents, ids) gives each shard's global start by a running sum.

Writing range-partitions the texts by ``doc_id``, streams each partition's ids to a file of its own and moves the
finished shard into place, so that a repeated task attempt writes the same file once more.  Reading takes the
boundaries of a run of documents by select and then their ids, a bounded block at a time.

Encoding asks the tokenizers library for every fragment that a worker has not met in the present run, many
words to a call, with line ends between them, which no word can reach across; fragments are cut only where the
vocabulary's word pattern cuts as well.  A text that holds the string of an added token goes to the library as
it is, which makes that token of it.

Defined cases: a null or empty text has the end id only; a very long text is one document like others, held in
memory by itself; repeated rows are written one by one; other columns are ignored, whatever their names; an empty
table writes no shard and reads back as no row.
"""

from __future__ import annotations

import json
import os
import re
import struct
import uuid
import zlib
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import eliasfano
from .common import documents, shared_dir, text_lists

MAGIC = b"DSTOK1\0\0"
_TAIL = struct.Struct("<8sQQQQBxxxxxxx")  # magic, documents, ids, bytes of doc ids, bytes of boundaries, id width
_CALL = 256  # words in a call of the library
_BLOCK = 4096  # documents read at once

# Fixed value: the characters that count as white space in the vocabulary's word pattern.
_WS = "\t\n\x0b\x0c\r \x85\xa0  -     　"
_FRAGMENT = re.compile(f" ?[^{_WS}]+|[{_WS}]+(?![^{_WS}])|[{_WS}]+")
#: Where a text has these, the pattern cuts it; elsewhere single blanks and line ends do.
_PAIRS = ("  ", " \n", "\n ", "\n\n")
_ODD_ASCII = [c for c in _WS if c.isascii() and c not in " \n"]
_ODD = re.compile(f"[{_WS.replace(' ', '').replace(chr(10), '')}]")


class WordEncoder:
    """Ids of texts by the tokenizers library, fragment by fragment."""

    def __init__(self, path: str, end: int, budget: int):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        os.environ["RAYON_NUM_THREADS"] = "1"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.added = [x.content for x in self.library.get_added_tokens_decoder().values()]
        if any(c.isspace() for x in self.added for c in x):
            raise ValueError("added tokens with white space could reach across words")
        self.width = 2 if self.library.get_vocab_size() <= 1 << 16 else 4
        self.dtype = np.dtype(f"<u{self.width}")
        self.end, self.budget = self._raw([end]), budget
        self.line = self._ask(["\n"])[0]
        self.line_id = int.from_bytes(self.line, "little")
        if len(self.line) != self.width:
            raise ValueError("a line end is more than one token of this vocabulary")
        self.ends = dict(zip(".,", self._ask([".", ","]), strict=True))
        #: Ids of words after a blank, or with the line end that stands before them; and of other fragments.
        self.words: dict[str, bytes] = {}
        self.bare: dict[str, bytes] = {}

    def _raw(self, ids: list[int]) -> bytes:
        return np.array(ids, self.dtype).tobytes()

    def _ask(self, fragments: list[str]) -> list[bytes]:
        return [self._raw(e.ids) for e in self.library.encode_batch_fast(fragments, add_special_tokens=False)]

    def _ask_words(self, words: list[str]) -> list[bytes]:
        """Ids of words without white space but for a leading blank, many to a call."""
        out = []
        joined = ["\n".join(words[at : at + _CALL]) for at in range(0, len(words), _CALL)]
        for raw in self._ask(joined):
            cut = np.flatnonzero(np.frombuffer(raw, self.dtype) == self.line_id) * self.width
            ends = [*cut.tolist(), len(raw)]
            out += [raw[a:b] for a, b in zip([0, *(cut + self.width).tolist()], ends, strict=True)]
        return out

    @staticmethod
    def plain(text: str) -> list[str] | None:
        """Words of a text, each line's first one with a line end before it; None where the pattern has to cut the text."""
        if text[:1] in (" ", "\n") or text[-1:] in (" ", "\n") or any(x in text for x in _PAIRS):
            return None
        if any(c in text for c in _ODD_ASCII) if text.isascii() else _ODD.search(text):
            return None
        return f"\n{text}".replace("\n", " \n").split(" ")[1:]

    def learn(self, fresh: set[str]) -> None:
        """Asks for words.  A full stop or comma after a letter is a fragment of its own, so that most ends cost no call."""
        stems = {w: w[:-1] for w in fresh if len(w) > 2 and w[-1] in ".," and w[-2].isalpha()}
        ask = sorted({x for x in (*(fresh - stems.keys()), *stems.values()) if x not in self.words})
        first = [w for w in ask if w[0] == "\n"]  # sorted: these come before all others
        self.words.update(zip(first, (self.line + ids for ids in self._ask_words([w[1:] for w in first])), strict=True))
        self.words.update(zip(ask[len(first) :], self._ask_words([" " + w for w in ask[len(first) :]]), strict=True))
        for w, stem in stems.items():
            self.words[w] = self.words[stem] + self.ends[w[-1]]

    def batch(self, texts: list[str]) -> list[bytes]:
        if len(self.words) + len(self.bare) > self.budget:
            self.words, self.bare = {}, {}
        out: list = []
        fresh: set[str] = set()
        open_: list[tuple[int, list, list[str], dict]] = []
        odd: set[str] = set()
        for t in texts:
            if any(x in t for x in self.added):
                out.append(self._ask([t])[0] + self.end)
                continue
            words = self.plain(t) if t else []
            table, skip = self.words, self.width  # the line end that was put before the text
            if words is None:
                words, table, skip = _FRAGMENT.findall(t), self.bare, 0
            parts = list(map(table.get, words))
            if None in parts:
                (fresh if skip else odd).update([w for w, p in zip(words, parts, strict=True) if p is None])
                open_.append((len(out), parts, words, table))
                out.append(skip)
            else:
                out.append(b"".join(parts)[skip:] + self.end)
        self.learn(fresh)
        ask = sorted(odd)
        self.bare.update(zip(ask, self._ask(ask), strict=True))
        for k, parts, words, table in open_:
            out[k] = b"".join([p or table[w] for p, w in zip(parts, words, strict=True)])[out[k] :] + self.end
        return out


_ENCODERS: dict[str, WordEncoder] = {}


def _encoder(run: str, *args) -> WordEncoder:
    if run not in _ENCODERS:
        _ENCODERS.clear()
        _ENCODERS[run] = WordEncoder(*args)
    return _ENCODERS[run]


@lru_cache(maxsize=4)
def _store(uri: str):
    """File system and path of a folder, local or any store that pyarrow opens."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri if "://" in uri else f"file://{uri}" if uri.startswith("/") else uri.replace("file:/", "file:///", 1))


def shard_tail(ids: np.ndarray, bounds: np.ndarray, n_ids: int, width: int) -> bytes:
    """``ids``: document ids in ascending order; ``bounds``: starts of the documents and the end."""
    a, b = eliasfano.encode(ids), eliasfano.encode(bounds)
    return a + b + _TAIL.pack(MAGIC, len(ids), n_ids, len(a), len(b), width)


class Shard:
    """A shard read back: ids of any document by select, without a table of offsets.

    ``data``: its bytes, or a file open for random access; only the coded boundaries are kept.
    """

    def __init__(self, data: pa.NativeFile | pa.Buffer | bytes):
        self.file = data if isinstance(data, pa.NativeFile) else pa.BufferReader(data)
        size = self.file.size()
        magic, self.n_docs, self.n_ids, a, b, self.width = _TAIL.unpack(self.file.read_at(_TAIL.size, size - _TAIL.size))
        if magic != MAGIC:
            raise ValueError("not a shard of token ids")
        coded = memoryview(self.file.read_at(a + b, size - _TAIL.size - a - b))
        self.doc_ids, self.bounds = eliasfano.Reader(coded[:a]), eliasfano.Reader(coded[a:])

    def ids(self, a: int, b: int) -> np.ndarray:
        return np.frombuffer(self.file.read_at((b - a) * self.width, a * self.width), f"<u{self.width}")

    def document(self, k: int) -> np.ndarray:
        return self.ids(self.bounds.select(k), self.bounds.select(k + 1))


def write_tokens(docs: DataFrame, path: str, end: int, out: str, shards: int | None = None, budget: int = 1_500_000) -> DataFrame:
    """Writes shards under ``out``; returns the manifest (shard, n_null_ids, n_docs, n_ids, start), start by running sum."""
    spark = docs.sparkSession
    run = uuid.uuid4().hex
    n = shards or int(spark.conf.get("spark.sql.shuffle.partitions"))
    laid = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").repartitionByRange(n, F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), F.col("text").asc_nulls_first())

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        words = _encoder(run, path, end, budget)
        part = TaskContext.get().partitionId()
        doc_ids, lengths, file = [], [], None
        for batch, texts in text_lists(batches):
            if file is None:
                fs, root = _store(out)
                fs.create_dir(root, recursive=True)
                tried = f"{root}/.{part:06d}-{uuid.uuid4().hex}"
                file = fs.open_output_stream(tried)
            doc_ids.append(batch.column("doc_id"))
            for at in range(0, len(texts), 512):
                made = words.batch(texts[at : at + 512])
                lengths.append(np.fromiter(map(len, made), np.int64, len(made)) // words.width)
                file.write(b"".join(made))
        if file is None:
            return
        ids = pa.chunked_array(doc_ids)
        nulls, least = ids.null_count, pc.min(ids).as_py() or 0  # nulls come first
        bounds = np.concatenate([[0], *lengths]).cumsum()
        file.write(shard_tail(ids.fill_null(least).to_numpy(), bounds, int(bounds[-1]), words.width))
        file.close()
        fs.move(tried, f"{root}/{part:06d}.ids")
        yield pa.RecordBatch.from_arrays([pa.array([x], pa.int64()) for x in (part, nulls, len(ids), int(bounds[-1]))], ["shard", "n_null_ids", "n_docs", "n_ids"])

    rows = sorted(laid.mapInArrow(work, "shard long, n_null_ids long, n_docs long, n_ids long").collect())  # a row a shard
    total, lines = 0, []
    for r in rows:
        lines.append((*r, total))
        total += r["n_ids"]
    fs, root = _store(out)
    fs.create_dir(root, recursive=True)
    with fs.open_output_stream(f"{root}/manifest.json") as f:
        f.write("".join(json.dumps(dict(zip(("shard", "n_null_ids", "n_docs", "n_ids", "start"), x, strict=True))) + "\n" for x in lines).encode())
    return spark.createDataFrame(lines, "shard long, n_null_ids long, n_docs long, n_ids long, start long")


def read_tokens(manifest: DataFrame, out: str, with_ids: bool = False) -> DataFrame:
    """One row a document from the shard files: doc_id, start, n_tokens, ids_crc32, and the ids on request."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = _store(out)
        for batch in batches:
            for shard, nulls, base in zip(*(batch.column(c).to_pylist() for c in ("shard", "n_null_ids", "start")), strict=True):
                with fs.open_input_file(f"{root}/{shard:06d}.ids") as f:
                    found, at = Shard(f), 0
                    while at < found.n_docs:
                        bounds = found.bounds.some(at, min(found.n_docs, at + _BLOCK) + 1)
                        n = max(1, int(np.searchsorted(bounds - bounds[0], _BLOCK << 9, side="right")) - 1)  # of ids that fit in memory, or one longer document
                        bounds = bounds[: n + 1]
                        ids, body = found.doc_ids.some(at, at + n), found.ids(int(bounds[0]), int(bounds[-1])).astype("<u4")
                        each = [body[a:b] for a, b in zip(bounds[:-1] - bounds[0], bounds[1:] - bounds[0], strict=True)]
                        yield block(ids, np.arange(at, at + n) < nulls, bounds + base, each)
                        at += n

    def block(ids: np.ndarray, null: np.ndarray, bounds: np.ndarray, each: list[np.ndarray]) -> pa.RecordBatch:
        cols = [pa.array(ids, pa.int64(), mask=null), pa.array(bounds[:-1], pa.int64()), pa.array(np.diff(bounds), pa.int64()), pa.array([zlib.crc32(x) for x in each], pa.int64())]
        names = ["doc_id", "start", "n_tokens", "ids_crc32"]
        if with_ids:
            cols.append(pa.array([x.astype(np.int64) for x in each], pa.list_(pa.int64())))
            names.append("ids")
        return pa.RecordBatch.from_arrays(cols, names)

    schema = "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<long>" * with_ids
    spread = manifest.select("shard", "n_null_ids", "start").repartition(max(1, manifest.count()), "shard")
    return spread.mapInArrow(work, schema)


def byte_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op4_tokenfile(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = f"{shared_dir(spark).rstrip('/')}/tokens-{uuid.uuid4().hex}"
    return read_tokens(write_tokens(documents(spark, sf_dir), byte_model(), 2, out), out)


QUERIES: dict[str, Callable] = {"op4_tokenfile": op4_tokenfile}
