"""Jaccard join of word n-gram sets, split by size: subsets for small sets, inverted lists for large ones.

A document's set holds its distinct shingles as 64-bit hashes.  Documents of equal sets form one class at
once.  Between classes:

* A *small* set, whose threshold allows one differing shingle at most, lists its whole set and its subsets
  of one shingle less as keys.  Similar small sets share a key.
* A *large* set puts its rarest shingles into inverted lists.  With the shingles of every set in one global
  order, rarest first, similar sets share one among their first ``size - least overlap + 1``; size and
  position bounds drop most other pairs.
* Sets that may be similar across the boundary take part in both.  The boundary is the cheaper of the
  possible ones, by number of keys against expected length of the lists read.

Rarity comes from a table of counts by hash, over all documents, of fixed size (``SKETCH`` counters); two
shingles in one counter only blur the order, which stays total, so that no pair is lost.

Links are found in two rounds.  First every member of a list is held against the list's least document
alone, and verified links are closed to components.  Then only lists that still hold several components
are looked at, in pairs between components.  Pairs inside a component cannot change the result, so that a
group of thousands of near copies costs in proportion to its size.  Bit parities of the sets (the number of
differing bits never exceeds the number of differing shingles) drop pairs before the sets are compared.

Defined cases: a null or empty text has an empty set and no link; with fewer words than a shingle the whole
sequence is the one shingle; a row without id has no component; rows of the same id count as one document;
other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, lean, saved, text_array
from .components import components
from .wordhash import Hasher, U, blocks, mix

SKETCH = 1 << 20  # counters; 4 MB whatever the input
_CHUNK = 1 << 12
_PARITY = 16  # 64-bit words of a set's parity
_BLOCK = 256  # sets of a component that are counted together
_SLICE = 1 << 14  # shingles in a matrix at once: 16 MB a block


@dataclass(frozen=True)
class Similar:
    """Sets are similar when den * intersection >= num * union."""

    words: int = 3
    num: int = 90
    den: int = 100
    fold: bool = True

    def least_own(self, m):
        """Shingles of a set of ``m`` that a similar set shares at least."""
        return -(-m * self.num // self.den)

    def prefix(self, m):
        return m - self.least_own(m) + 1

    def small_bounds(self) -> list[int]:
        """Largest sizes with no, and with one differing shingle allowed."""
        out = []
        for d in (0, 1):
            m = 1
            while m + 1 - self.least_own(m + 1) <= d:
                m += 1
            out.append(m)
        return out


def shingle_sets(texts: pa.LargeStringArray, how: Similar, hasher: Hasher) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(from, to, document index within, hash) of each document's distinct shingles, by document, then hash."""
    k = how.words
    for a, b, flat, ends in blocks(texts):
        doc, _, h = hasher.words_of(flat, ends)
        n = np.bincount(doc, minlength=b - a) if len(doc) else np.zeros(b - a, np.int64)
        full = hasher.windows(h, k)
        inside = doc[: len(full)] == doc[k - 1 :] if len(full) else np.zeros(0, bool)
        docs, hashes = [doc[: len(full)][inside]], [full[inside]]
        firsts = np.concatenate([[0], np.cumsum(n)])
        for short in range(1, k):
            at = firsts[:-1][n == short]
            if len(at):
                docs.append(doc[at])
                hashes.append(hasher.windows(h, short)[at])
        d, s = np.concatenate(docs), np.concatenate(hashes)
        order = np.lexsort((s, d))
        d, s = d[order], s[order]
        new = np.ones(len(d), bool)
        new[1:] = (d[1:] != d[:-1]) | (s[1:] != s[:-1])
        yield a, b, d[new], s[new]


def rarity(docs: DataFrame, how: Similar) -> tuple[np.ndarray, dict[int, int]]:
    """Counts of shingles by hash over all documents, and the number of documents of each small size."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher, total, sizes = Hasher(1, how.fold), np.zeros(SKETCH, np.int64), np.zeros(64, np.int64)
        for batch in batches:
            for _, _, d, s in shingle_sets(text_array(batch.column("text")), how, hasher):
                total += np.bincount((s >> U(44)).astype(np.int64), minlength=SKETCH)
                sizes += np.bincount(np.minimum(np.unique(d, return_counts=True)[1], 63), minlength=64)
        yield pa.RecordBatch.from_arrays([pa.array([*range(SKETCH // _CHUNK), -1], pa.int32()), pa.array([*(np.minimum(x, 2**31 - 1).astype("<i4").tobytes() for x in total.reshape(-1, _CHUNK)), sizes.astype("<i4").tobytes()], pa.binary())], ["chunk", "counts"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for c, x in zip(batch.column("chunk").to_pylist(), batch.column("counts").to_pylist(), strict=True):
                v = np.frombuffer(x, "<i4").astype(np.int64)
                sums[c] = sums[c] + v if c in sums else v
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([np.minimum(x, 2**31 - 1).astype("<i4").tobytes() for x in sums.values()], pa.binary())], ["chunk", "counts"])

    rows = docs.select("text").mapInArrow(lean(count), "chunk int, counts binary").repartition(16, "chunk").mapInArrow(lean(add), "chunk int, counts binary").collect()  # of fixed size
    table, sizes = np.zeros(SKETCH, np.int64), np.zeros(64, np.int64)
    for c, x in rows:
        v = np.frombuffer(x, "<i4")
        if c < 0:
            sizes += v
        else:
            table[c * _CHUNK : (c + 1) * _CHUNK] += v
    return np.minimum(table, 2**32 - 1).astype(np.uint32), {m: int(n) for m, n in enumerate(sizes) if n}


def boundary(table: np.ndarray, sizes: dict[int, int], how: Similar) -> int:
    """The size up to which subsets are cheaper than lists."""
    c = table.astype(float)
    length = max(0.0, (c @ c) / c.sum() - c.mean()) if c.sum() else 0.0  # of the list of a random shingle

    def cost(b: int) -> float:
        top = how.small_bounds()[1]
        light = sum(n * (1 + m * (m > how.least_own(m))) for m, n in sizes.items() if m <= min(b, top))
        heavy = sum(n * how.prefix(m) * (1 + length) for m, n in sizes.items() if how.least_own(b + 1) <= m <= top)
        return light + heavy

    return min((0, *how.small_bounds()), key=cost)


_PROFILE = "doc_id long, m int, s1 long, s2 long, parity array<long>, keys array<struct<key:long,pos:int>>"


def profiles(docs: DataFrame, how: Similar, table: np.ndarray, small: int) -> DataFrame:
    """Size, signature, parity and keys of every document's set."""
    known = docs.sparkSession.sparkContext.broadcast(table)  # of fixed size

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher, counts = Hasher(1, how.fold), known.value
        for batch in batches:
            texts = text_array(batch.column("text"))
            for a, b, d, s in shingle_sets(texts, how, hasher):
                n = b - a
                m = np.bincount(d, minlength=n)
                first = np.concatenate([[0], np.cumsum(m)])
                g1, g2 = mix(s ^ U(0x5851F42D4C957F2D)), mix(s + U(0x14057B7EF767814F))
                run1, run2 = (np.concatenate([np.zeros(1, U), np.cumsum(g, dtype=U)]) for g in (g1, g2))
                s1, s2 = run1[first[1:]] - run1[first[:-1]], run2[first[1:]] - run2[first[:-1]]
                parity = np.zeros((n, _PARITY), U)
                np.bitwise_xor.at(parity, (d, (g2 >> U(60)).astype(np.int64)), U(1) << (g2 & U(63)))
                rank = counts[(s >> U(44)).astype(np.int64)]
                order = np.lexsort((s, rank, d))
                ranked, place = s[order], np.arange(len(s)) - first[d]
                take = (place < how.prefix(m)[d]) & (m[d] >= how.least_own(small + 1))
                key_doc, key, pos = [d[take]], [ranked[take]], [place[take]]
                if small:
                    light = np.flatnonzero((m > 0) & (m <= small))
                    salt = lambda x, size: mix(mix(x) + size.astype(U))
                    key_doc.append(light)
                    key.append(salt(s1[light], m[light]))
                    one = np.flatnonzero((m[d] <= small) & (m[d] > how.least_own(m[d])))
                    key_doc.append(d[one])
                    key.append(salt(s1[d[one]] - g1[one], m[d[one]] - 1))
                    pos += [np.zeros(len(light), np.int64), np.zeros(len(one), np.int64)]
                kd, kk, kp = np.concatenate(key_doc), np.concatenate(key), np.concatenate(pos)
                by = np.argsort(kd, kind="stable")
                ends = np.concatenate([[0], np.cumsum(np.bincount(kd, minlength=n))]).astype(np.int32)
                keys = pa.ListArray.from_arrays(pa.array(ends), pa.StructArray.from_arrays([pa.array(kk[by].view(np.int64)), pa.array(kp[by].astype(np.int32))], ["key", "pos"]))
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id").slice(a, n), pa.array(m.astype(np.int32)), pa.array(s1.view(np.int64)), pa.array(s2.view(np.int64)), pa.ListArray.from_arrays(pa.array(np.arange(0, (n + 1) * _PARITY, _PARITY, dtype=np.int32)), pa.array(parity.view(np.int64).ravel())), keys],
                    ["doc_id", "m", "s1", "s2", "parity", "keys"],
                )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(lean(work), _PROFILE)


def _sets(docs: DataFrame, ids: DataFrame, how: Similar) -> DataFrame:
    """(doc_id, shingles) of the documents named: sorted hashes as bytes."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = Hasher(1, how.fold)
        for batch in batches:
            for a, b, d, s in shingle_sets(text_array(batch.column("text")), how, hasher):
                cut = np.searchsorted(d, np.arange(b - a + 1))
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(a, b - a), pa.array([s[i:j].tobytes() for i, j in zip(cut[:-1], cut[1:], strict=True)], pa.binary())], ["doc_id", "shingles"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(ids, "doc_id", "left_semi").mapInArrow(lean(work), "doc_id long, shingles binary")


def _verified(pairs: DataFrame, docs: DataFrame, how: Similar, name: str) -> DataFrame:
    """The pairs (x, y) whose sets are similar, by the sets themselves."""
    pairs = saved(pairs, f"{name}-pairs")
    ids = pairs.select(F.col("x").alias("doc_id")).union(pairs.select("y")).distinct()
    sets = saved(_sets(docs, ids, how), f"{name}-sets")
    one, two = (sets.select(F.col("doc_id").alias(c), F.col("shingles").alias(f"of_{c}")) for c in "xy")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = []
            for p, q in zip(batch.column("of_x"), batch.column("of_y"), strict=True):
                u, v = (np.frombuffer(x.as_buffer(), U) for x in (p, q))
                at = np.searchsorted(v, u)
                shared = int((v[np.minimum(at, len(v) - 1)] == u).sum()) if len(v) else 0
                good.append(how.den * shared >= how.num * (len(u) + len(v) - shared))
            yield batch.select(["x", "y"]).filter(pa.array(good, pa.bool_()))

    return pairs.join(one, "x").join(two, "y").select("x", "y", "of_x", "of_y").mapInArrow(lean(work), "x long, y long").distinct()


def _fits(how: Similar, mx: str, my: str, px: str, py: str) -> str:
    """Size and position bounds of a pair that shares a key, as SQL."""
    total = how.num + how.den
    return f"{how.den} * least({mx}, {my}) >= {how.num} * greatest({mx}, {my}) AND {total} * (1L + least({mx} - 1 - {px}, {my} - 1 - {py})) >= {how.num} * ({mx} + {my})"


def _near(how: Similar, mx: str, my: str, a: str, b: str) -> str:
    """At most so many differing bits as similar sets may have differing shingles, as SQL."""
    bits = " + ".join(f"bit_count({a}[{i}] ^ {b}[{i}])" for i in range(_PARITY))
    return f"{how.num + how.den} * ({bits}) <= {how.den - how.num} * ({mx} + {my})"


def similar_groups(docs: DataFrame, how: Similar = Similar()) -> DataFrame:
    """doc_id, n_shingles, component_id of every row."""
    return _grouped(docs.select("doc_id", "text"), how).select("doc_id", "n_shingles", "component_id")


def _grouped(docs: DataFrame, how: Similar) -> DataFrame:
    """The same with ``rep``, the least document of equal set (null for an empty set or a row without id)."""
    table, sizes = rarity(docs, how)
    found = saved(profiles(docs, how, table, boundary(table, sizes, how)), "profiles")
    sets = ("m", "s1", "s2")
    classes = found.where("m > 0 AND doc_id IS NOT NULL").groupBy(*sets).agg(F.min("doc_id").alias("rep"))
    reps = found.join(classes, list(sets)).where("doc_id = rep")
    keys = reps.select("doc_id", "m", F.inline("keys"))
    # Keys that two documents share at least, with the list's least document.
    least = keys.groupBy("key").agg(F.min(F.struct("doc_id", "m", "pos")).alias("hub"), F.max("doc_id").alias("top")).where("hub.doc_id < top").drop("top")
    lists = saved(keys.join(least, "key"), "lists")
    bits = saved(reps.select("doc_id", "parity").join(lists.select("doc_id").distinct(), "doc_id", "left_semi"), "parities")
    one, two = (bits.select(F.col("doc_id").alias(c), F.col("parity").alias(f"bits_{c}")) for c in "xy")
    stars = (
        lists.where(f"doc_id <> hub.doc_id AND {_fits(how, 'm', 'hub.m', 'pos', 'hub.pos')}")
        .select(F.col("hub.doc_id").alias("x"), F.col("doc_id").alias("y"), F.col("hub.m").alias("mx"), F.col("m").alias("my"))
        .distinct()
        .join(one, "x")
        .join(two, "y")
        .where(_near(how, "mx", "my", "bits_x", "bits_y"))
        .select("x", "y")
    )
    first = saved(_verified(stars, docs, how, "stars"), "star-links")
    joined = components(first, "star-components")
    # Lists that still hold several components.
    placed = lists.drop("hub").join(joined.withColumnRenamed("node", "doc_id"), "doc_id", "left").withColumn("component", F.coalesce("component", "doc_id"))
    mixed = placed.groupBy("key").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo < hi").select("key")
    left = saved(placed.join(mixed, "key").join(bits, "doc_id"), "open-lists")
    a, b = (left.select("key", *(F.col(c).alias(f"{c}_{s}") for c in ("doc_id", "m", "pos", "component", "parity"))) for s in "xy")
    apart = a.join(b, "key").where(f"doc_id_x < doc_id_y AND component_x <> component_y AND {_fits(how, 'm_x', 'm_y', 'pos_x', 'pos_y')} AND {_near(how, 'm_x', 'm_y', 'parity_x', 'parity_y')}")
    apart = apart.select(F.col("doc_id_x").alias("x"), F.col("doc_id_y").alias("y")).distinct()
    second = _verified(apart, docs, how, "open")
    links = saved(first.union(second), "links")
    final = components(links, "final-components").withColumnRenamed("node", "rep")
    named = classes.join(final, "rep", "left").select(*sets, "rep", F.coalesce("component", "rep").alias("component_id"))
    rows = found.select("doc_id", *sets)
    return rows.join(named, list(sets), "left").select(
        "doc_id",
        F.col("m").cast("long").alias("n_shingles"),
        F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id")).alias("component_id"),
        F.when(F.col("doc_id").isNotNull(), F.col("rep")).alias("rep"),
    )


def _shared(u: np.ndarray, v: np.ndarray, ends_u: np.ndarray, ends_v: np.ndarray) -> np.ndarray:
    """Shingles that each set of one block shares with each of the other, by products of 0/1 matrices, a slice of shingles at a time."""
    known, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    row_u, row_v = (np.repeat(np.arange(len(e) - 1), np.diff(e)) for e in (ends_u, ends_v))
    at_u, at_v = at[: len(u)], at[len(u) :]
    out = np.zeros((len(ends_u) - 1, len(ends_v) - 1), np.int64)
    for start in range(0, len(known), _SLICE):
        one, two = (np.zeros((len(e) - 1, min(_SLICE, len(known) - start)), np.float32) for e in (ends_u, ends_v))
        for m, row, col in ((one, row_u, at_u), (two, row_v, at_v)):
            inside = (col >= start) & (col < start + m.shape[1])
            m[row[inside], col[inside] - start] = 1
        out += (one @ two.T).astype(np.int64)
    return out


def link_counts(docs: DataFrame, how: Similar = Similar()) -> DataFrame:
    """doc_id, n_shingles, component_id, n_links of every row: links of its set to other sets, each counted once.

    Links never leave a component, so that each is found among the pairs of its component.  Components are cut
    into blocks by hash, and every two blocks of one component meet in a group of their own: all pairs are
    compared, by the sets themselves, and none is written.
    """
    docs = docs.select("doc_id", "text")
    rows = saved(_grouped(docs, how), "grouped")
    reps = rows.where("doc_id = rep").select("doc_id", "component_id").distinct()
    large = reps.groupBy("component_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("component_id", F.ceil(F.col("n") / _BLOCK).cast("int").alias("nb"))
    placed = saved(reps.join(large, "component_id").withColumn("b", F.pmod(F.xxhash64("doc_id"), "nb").cast("int")), "linked")
    sets = _sets(docs, placed.select("doc_id"), how).dropDuplicates(["doc_id"])
    meets = F.explode(F.transform(F.sequence(F.lit(0), F.col("nb") - 1), lambda o: F.struct(F.least("b", o).alias("i"), F.greatest("b", o).alias("j"))))
    dealt = placed.join(sets, "doc_id").select("component_id", "doc_id", "shingles", "b", meets.alias("at")).select("component_id", "at.i", "at.j", "b", "doc_id", "shingles")

    def count(block: pa.Table) -> pa.Table:
        i, j = block.column("i")[0].as_py(), block.column("j")[0].as_py()
        parts = []
        for b in (i, j):
            part = block.filter(pa.array(block.column("b").to_numpy() == b))
            raw = part.column("shingles").to_pylist()
            ends = np.concatenate([[0], np.cumsum([len(x) // 8 for x in raw])]).astype(np.int64)
            parts.append((part.column("doc_id").to_numpy(), np.frombuffer(b"".join(raw), U), ends))
        (x, u, ends_u), (y, v, ends_v) = parts
        both = _shared(u, v, ends_u, ends_v)
        near = how.den * both >= how.num * (np.diff(ends_u)[:, None] + np.diff(ends_v)[None, :] - both)
        if i == j:
            np.fill_diagonal(near, False)
            found = [(x, near.sum(1))]
        else:
            found = [(x, near.sum(1)), (y, near.sum(0))]
        return pa.table({"rep": np.concatenate([f[0] for f in found]), "n": np.concatenate([f[1] for f in found]).astype(np.int64)})

    ends = dealt.groupBy("component_id", "i", "j").applyInArrow(count, "rep long, n long").groupBy("rep").agg(F.sum("n").alias("n_links"))
    return rows.join(ends, "rep", "left").select("doc_id", "n_shingles", "component_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"))


def one_of_each(docs: DataFrame, how: Similar) -> DataFrame:
    """Keeps each group's document of the least id, with all its columns; rows without id stay."""
    groups = similar_groups(docs, how).where("doc_id <> component_id").select("doc_id").distinct()
    return docs.join(groups, "doc_id", "left_anti")


def op8_setjoin(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar_groups(documents(spark, sf_dir))


def op8_setjoin_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link_counts(documents(spark, sf_dir))


_CUT = r"[\x20\x09-\x0D]+"
ORACLES = {
    "op8_setjoin": rf"""
WITH RECURSIVE words AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{_CUT}'), lambda x: x <> '') AS w FROM documents),
grams AS (
  SELECT DISTINCT doc_id, array_to_string(w[i : i + 2], ' ') AS g
  FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 1, 2))) AS i FROM words WHERE len(w) > 0)),
sizes AS (SELECT doc_id, count(*) AS n FROM grams GROUP BY doc_id),
shared AS (
  SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS o FROM grams a JOIN grams b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
links AS (
  SELECT x, y FROM shared JOIN sizes p ON p.doc_id = x JOIN sizes q ON q.doc_id = y WHERE 100 * o >= 90 * (p.n + q.n - o)),
reach AS (SELECT doc_id, doc_id AS other FROM documents UNION SELECT r.doc_id, l.y FROM reach r JOIN links l ON l.x = r.other),
named AS (SELECT doc_id, min(other) AS component_id FROM reach GROUP BY doc_id)
SELECT d.doc_id, CAST(coalesce(s.n, 0) AS BIGINT) AS n_shingles, c.component_id
FROM documents d LEFT JOIN sizes s ON s.doc_id = d.doc_id JOIN named c ON c.doc_id = d.doc_id""",
    "op8_setjoin_links": rf"""
WITH RECURSIVE words AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{_CUT}'), lambda x: x <> '') AS w FROM documents),
grams AS (
  SELECT DISTINCT doc_id, array_to_string(w[i : i + 2], ' ') AS g
  FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 1, 2))) AS i FROM words WHERE len(w) > 0)),
sizes AS (SELECT doc_id, count(*) AS n, string_agg(g, chr(10) ORDER BY g) AS whole FROM grams GROUP BY doc_id),
shared AS (
  SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS o FROM grams a JOIN grams b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
links AS (
  SELECT x, y, q.whole AS other, p.whole <> q.whole AS apart FROM shared JOIN sizes p ON p.doc_id = x JOIN sizes q ON q.doc_id = y WHERE 100 * o >= 90 * (p.n + q.n - o)),
counts AS (SELECT x AS doc_id, count(DISTINCT other) AS n_links FROM links WHERE apart GROUP BY x),
reach AS (SELECT doc_id, doc_id AS other FROM documents UNION SELECT r.doc_id, l.y FROM reach r JOIN links l ON l.x = r.other),
named AS (SELECT doc_id, min(other) AS component_id FROM reach GROUP BY doc_id)
SELECT d.doc_id, CAST(coalesce(s.n, 0) AS BIGINT) AS n_shingles, c.component_id, CAST(coalesce(k.n_links, 0) AS BIGINT) AS n_links
FROM documents d LEFT JOIN sizes s ON s.doc_id = d.doc_id LEFT JOIN counts k ON k.doc_id = d.doc_id JOIN named c ON c.doc_id = d.doc_id""",
}
QUERIES: dict[str, Callable] = {"op8_setjoin": op8_setjoin, "op8_setjoin_links": op8_setjoin_links}
