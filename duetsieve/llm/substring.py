"""Removal of repeated passages: windows repeated at one length are extended to twice that length.

* 10 words.  Every 20-word window names the 10-word window of least hash in it, so that one place in about
  six has to be counted, and equal long windows name equal places.  Places whose content is counted once
  only are dropped, and with them all long windows that name them.
* 20 words.  What is left is extended to twice the length, under the hash of the place.  Inside the rows of
  one place's content, sorted by document and start, a 20-word window that has been seen before is repeated:
  it starts earlier in the sorted order.

Longer passages need no further level for this result, since a word is removed when any 20-word window
covers it: no candidate survives the last level.

Repeats inside one block of texts are settled where the block is read, and of a block's equal places or
windows only the first travels under their hash, so that one passage in a third of all documents sends one
row a block to the task that holds it.  The texts are dealt out by id once, for the second level and for the
result alike.

Defined cases: a null or empty text has no words; rows without id stay as they are and make nothing
repeated; rows of one id with equal texts are one document, with different texts they follow one another in
the order of a hash of the text; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import documents, lean, text_array
from .wordhash import Hasher, U, blocks, mix

_WORD = re.compile("[^\x20\x09-\x0d]+")


def _named(h: np.ndarray, doc: np.ndarray, first: int, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts of all windows of ``length`` words, the place each names, and the hashes at all places."""
    n = len(h) - length + 1
    if n <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, U)
    small = _HASHER.windows(h, first)
    at, width, want = np.arange(len(small)), 1, length - first + 1
    while width < want:
        step = min(width, want - width)
        a, b = at[:-step], at[step:]
        at, width = np.where(small[b] < small[a], b, a), width + step
    starts = np.flatnonzero(doc[:n] == doc[length - 1 :])
    return starts, at[starts], small


_HASHER = Hasher(2)


def _places(docs: DataFrame, first: int, length: int) -> DataFrame:
    """(key, doc_id, pos, known): the named places of every document; ``known`` where the block has the content twice.

    Of equal places in a block the first goes under its key; the others, known to be repeated, under others.
    """

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column("doc_id").to_numpy(zero_copy_only=False)
            for a, _, flat, ends in blocks(text_array(batch.column("text")), 1 << 22):
                doc, _, h = _HASHER.words_of(flat, ends)
                _, at, small = _named(h, doc, first, length)
                at = np.unique(at)
                begin = np.searchsorted(doc, np.arange(len(ends)))
                key = small[at]
                _, lead, back, count = np.unique(key, return_index=True, return_inverse=True, return_counts=True)
                again = lead[back] != np.arange(len(at))
                key = np.where(again, mix(key + at.astype(U) + U(a)), key)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(key.view(np.int64)), pa.array(ids[a + doc[at]], pa.int64()), pa.array((at - begin[doc[at]]).astype(np.int32)), pa.array(count[back] > 1)], ["key", "doc_id", "pos", "known"]
                )

    return docs.where("doc_id IS NOT NULL").select("doc_id", "text").mapInArrow(lean(work), "key long, doc_id long, pos int, known boolean")


_ROWS = "key long, doc_id long, mark long, start int, n int, windows array<long>"


def _extended(docs: DataFrame, first: int, length: int) -> DataFrame:
    """Rows of candidate windows under the hash of the place they name; a null key marks windows settled here.

    ``docs`` has the places that survived as ``places``, null where none did.
    """

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, marks = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("doc_id", "mark"))
            places = batch.column("places")
            for a, b, flat, ends in blocks(text_array(batch.column("text")), 1 << 22):
                doc, _, h = _HASHER.words_of(flat, ends)
                starts, at, small = _named(h, doc, first, length)
                if not len(starts):
                    continue
                begin = np.searchsorted(doc, np.arange(len(ends)))
                mine = places.slice(a, b - a)
                of = np.repeat(np.arange(b - a), mine.value_lengths().fill_null(0).to_numpy(zero_copy_only=False))
                alive = np.zeros(len(h), bool)
                place = mine.flatten().to_numpy() + begin[of]
                alive[place[place < len(h)]] = True
                keep = alive[at]
                starts, at = starts[keep], at[keep]
                if not len(starts):
                    continue
                ten = small[at]
                whole = _HASHER.windows(h, length)[starts]
                d = doc[starts]
                pos = starts - begin[d]
                # Settled here: windows whose content starts earlier within this block.
                content = mix(whole ^ mix(ten))
                order = np.lexsort((pos, marks[a + d], ids[a + d], content))
                new = np.ones(len(order), bool)
                new[1:] = content[order][1:] != content[order][:-1]
                lead = order[np.maximum.accumulate(np.where(new, np.arange(len(order)), 0))]
                same = (ids[a + d[lead]] == ids[a + d[order]]) & (marks[a + d[lead]] == marks[a + d[order]]) & (pos[lead] == pos[order])
                settled = np.zeros(len(order), bool)
                settled[order] = ~same
                # A row is a run of windows of one place.
                group = np.ones(len(starts), bool)
                group[1:] = (at[1:] != at[:-1]) | (starts[1:] != starts[:-1] + 1)
                cut = np.flatnonzero(group)
                size = np.diff(np.append(cut, len(starts)))
                open_ = np.add.reduceat(~settled, cut) > 0
                each = np.repeat(open_, size)
                offsets = np.concatenate([[0], np.cumsum(np.where(open_, size, 0))]).astype(np.int32)
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(ten[cut].view(np.int64), mask=~open_),
                        pa.array(ids[a + d[cut]], pa.int64()),
                        pa.array(marks[a + d[cut]], pa.int64()),
                        pa.array(pos[cut].astype(np.int32)),
                        pa.array(size.astype(np.int32)),
                        pa.ListArray.from_arrays(pa.array(offsets), pa.array(whole[each].view(np.int64))),
                    ],
                    ["key", "doc_id", "mark", "start", "n", "windows"],
                )

    return docs.select("doc_id", "mark", "text", "places").mapInArrow(lean(work), _ROWS)


def _repeated(rows: DataFrame) -> DataFrame:
    """(doc_id, mark, start, n): runs of windows whose content starts earlier somewhere."""
    laid = rows.withColumn("to", F.coalesce("key", F.xxhash64("doc_id", "start"))).repartition("to").sortWithinPartitions("key", "doc_id", "mark", "start").drop("to")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        carried, seen, owner = None, np.zeros(0, U), {}
        for batch in batches:
            ids, marks, start, n = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("doc_id", "mark", "start", "n"))
            known = batch.column("key")
            done = np.asarray(known.is_null())
            key = known.fill_null(0).to_numpy()
            out = [(ids[done], marks[done], start[done], n[done])]
            live = np.flatnonzero(~done)
            if len(live):
                win = batch.column("windows").take(pa.array(live))
                size = win.value_lengths().to_numpy()
                row = np.repeat(live, size)
                content = mix(win.flatten().to_numpy().view(U) ^ mix(key[row].view(U)))
                at = start[row] + np.arange(len(row)) - np.repeat(np.cumsum(size) - size, size)
                _, first, back = np.unique(content, return_index=True, return_inverse=True)
                lead = first[back]
                again = (ids[row] != ids[row[lead]]) | (marks[row] != marks[row[lead]]) | (at != at[lead])
                if carried is not None and (cont := key[row] == carried).any():
                    again |= cont & np.isin(content, seen)
                    for i in np.flatnonzero(cont & again & (ids[row] == owner["id"]) & (marks[row] == owner["mark"])):
                        # An equal row that a batch's end has cut off from its twin.
                        again[i] = owner["at"].get(int(content[i])) != int(at[i]) or not owner["at"]
                last = key[live[-1]]
                ours = key[row] == last
                seen = np.union1d(seen, content[ours]) if carried == last else np.unique(content[ours])
                tail = live[-1]
                mine = ours & (ids[row] == ids[tail]) & (marks[row] == marks[tail])
                kept = owner.get("at", {}) if carried == last and owner.get("id") == ids[tail] and owner.get("mark") == marks[tail] else {}
                owner = {"id": ids[tail], "mark": marks[tail], "at": kept | {int(c): int(p) for c, p, g in zip(content[mine], at[mine], again[mine], strict=True) if not g}}
                carried = last
                row, at = row[again], at[again]
                if len(row):
                    new = np.ones(len(row), bool)
                    new[1:] = (row[1:] != row[:-1]) | (at[1:] != at[:-1] + 1)
                    cut = np.flatnonzero(new)
                    out.append((ids[row[cut]], marks[row[cut]], at[cut], np.diff(np.append(cut, len(row)))))
            cols = [np.concatenate(x) for x in zip(*out, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(c.astype(t)) for c, t in zip(cols, (np.int64, np.int64, np.int32, np.int32), strict=True)], ["doc_id", "mark", "start", "n"])

    return laid.mapInArrow(lean(work), "doc_id long, mark long, start int, n int")


def _marked(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("mark"))


def repeated_runs(own: DataFrame, length: int = 20) -> DataFrame:
    """doc_id and ``runs``: structs of mark (hash of the text), first start and number of repeated windows in a row.

    ``own`` comes from ``_marked``; it is dealt out by doc_id alone, as the caller may do again at no cost.
    """
    first = length // 2
    if length != 2 * first:
        raise ValueError("the window must be twice the first length")
    places = _places(own, first, length)
    shared = places.withColumn("c", F.count(F.lit(1)).over(Window.partitionBy("key"))).where("known OR c > 1")
    alive = shared.groupBy("doc_id").agg(F.collect_list("pos").alias("places"))
    rows = _extended(own.join(alive, "doc_id", "left"), first, length)
    return _repeated(rows).groupBy("doc_id").agg(F.collect_list(F.struct("mark", "start", "n")).alias("runs"))


def _strip(texts: list[str], marks: list[int], runs: list, length: int) -> Iterator[tuple[list[str], list[str]]]:
    """Words of each text, and those that stay."""
    for text, mark, found in zip(texts, marks, runs, strict=True):
        words = _WORD.findall(text)
        found = [r for r in found or () if r["mark"] == mark]
        if not found:
            yield words, words
            continue
        edge = np.zeros(len(words) + 1, np.int32)
        for r in found:
            edge[r["start"]] += 1
            edge[r["start"] + r["n"] + length - 1] -= 1
        gone = np.cumsum(edge[:-1]) > 0
        yield words, [w for w, g in zip(words, gone.tolist(), strict=True) if not g]


def remove_repeats(docs: DataFrame, length: int = 20, digest: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed and the words that stay, joined by blanks (or that text's sha256)."""
    name = "kept_sha256" if digest else "kept"

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, gone, out = [], [], []
            for words, kept in _strip(text_array(batch.column("text")).to_pylist(), batch.column("mark").to_pylist(), batch.column("runs").to_pylist(), length):
                n.append(len(words))
                gone.append(len(words) - len(kept))
                text = " ".join(kept)
                out.append(hashlib.sha256(text.encode()).hexdigest() if digest else text)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(out, pa.string())], ["doc_id", "n_words", "n_removed", name])

    own = _marked(docs)
    return own.join(repeated_runs(own, length), "doc_id", "left").select("doc_id", "text", "mark", "runs").mapInArrow(lean(work), f"doc_id long, n_words long, n_removed long, {name} string")


def op10_substring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(documents(spark, sf_dir), digest=True)


_CUT = r"[\x20\x09-\x0D]+"
ORACLES = {
    "op10_substring": rf"""
WITH words AS (
  SELECT CAST(doc_id AS BIGINT) AS doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '{_CUT}'), lambda x: x <> '') AS w FROM documents),
windows AS (
  SELECT doc_id, s, array_to_string(w[s : s + 19], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 18)) AS s FROM words WHERE len(w) >= 20)),
repeated AS (SELECT doc_id, s FROM (SELECT doc_id, s, row_number() OVER (PARTITION BY g ORDER BY doc_id, s) AS k FROM windows) WHERE k > 1),
gone AS (SELECT DISTINCT doc_id, s + k AS i FROM repeated, (SELECT unnest(range(0, 20)) AS k)),
each AS (SELECT doc_id, generate_subscripts(w, 1) AS i, unnest(w) AS word FROM words),
kept AS (SELECT e.doc_id, string_agg(e.word, ' ' ORDER BY e.i) AS t, count(*) AS n FROM each e ANTI JOIN gone g ON g.doc_id = e.doc_id AND g.i = e.i GROUP BY e.doc_id)
SELECT w.doc_id, CAST(len(w.w) AS BIGINT) AS n_words, CAST(len(w.w) - coalesce(k.n, 0) AS BIGINT) AS n_removed, sha256(coalesce(k.t, '')) AS kept_sha256
FROM words w LEFT JOIN kept k ON k.doc_id = w.doc_id"""
}
QUERIES: dict[str, Callable] = {"op10_substring": op10_substring}
