"""Substring dedup over paths of token k-mers cut at minimizers, which stand in for a compacted De Bruijn graph.

No edge, degree or branching node is computed and neighbouring paths are not joined.  A path of ``window`` words is cut out
at its smallest k-mer hash: consecutive windows of a document that share that k-mer make one
path (a super-window of about window + (window - k) / 2 words), which is compacted
to one row (k-mer, path hash, document).  Equal windows have the same smallest k-mer, so they
lie in paths of the same k-mer.

* A k-mer with one row is unique: none of its windows repeats.
* Equal paths are one class.  Every member after its first document repeats all its windows.
* Where a k-mer has several classes its paths branch: the first member of each class is opened into
  windows, which are compared by Spark joins, and the source coordinates (document, start) decide which is first.
* Windows that repeat inside one document are found there.

Only k-mers with two rows or more pass the joins.  Keys are two independent 64-bit hashes (k-mer and
path, or k-mer and window); equal hashes count as equal words and no text is compared.  No group is gathered: counts and minima are partial aggregates, and what is
joined back comes from written tables, so that adaptive execution splits hot k-mers.

Edge cases: null texts and texts of fewer than ``window`` words lose nothing; rows that repeat a doc_id are one
document in order, so no row is earlier than its repetition; null ids sort first; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, functions as F

from tilemine.llm.common import NULL_ID, id_key, park, table

WINDOW, KMER = 20, 8
_BASE = np.uint64(0x9E3779B97F4A7C15)
_BASE_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 2**64))


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def _least(x: np.ndarray, width: int) -> np.ndarray:
    """Minima of all stretches of ``width`` values."""
    size = 1
    while 2 * size <= width:
        x = np.minimum(x[:-size], x[size:])
        size *= 2
    rest = width - size
    return np.minimum(x[: len(x) - rest], x[rest:]) if rest else x


class Words(dict):
    """64-bit hashes of words, as signed numbers; the table is emptied at ``most`` words."""

    def __init__(self, most: int = 500_000):
        super().__init__()
        self.most = most

    def __missing__(self, word: bytes) -> int:
        value = xxhash.xxh64_intdigest(word)
        self[word] = value = value - (value >> 63 << 64)
        return value

    def hashes(self, ws: list[bytes]) -> np.ndarray:
        if len(self) > self.most:
            self.clear()
        return np.fromiter(map(self.__getitem__, ws), np.int64, len(ws)).view(np.uint64)


class Paths:
    """The windows and compacted paths of one document's word hashes."""

    def __init__(self, h: np.ndarray, window: int = WINDOW, k: int = KMER):
        n = len(h) - window + 1
        self.n = max(n, 0)
        if n < 1:
            return
        power = np.full(len(h) + 1, _BASE, np.uint64)
        power[0] = 1
        power = np.multiply.accumulate(power)
        inverse = np.full(len(h) + 1, _BASE_INVERSE, np.uint64)
        inverse[0] = 1
        inverse = np.multiply.accumulate(inverse)
        total = np.concatenate((np.zeros(1, np.uint64), np.cumsum(h * inverse[:-1], dtype=np.uint64)))
        self._total, self._power = total, power
        kmer = _mix(self._gram(np.arange(len(h) - k + 1), k))
        least = _least(kmer, window - k + 1)
        self.window = _mix(self._gram(np.arange(n), window) + np.uint64(window))
        self.begin = np.flatnonzero(np.concatenate(([True], least[1:] != least[:-1])))
        self.end = np.concatenate((self.begin[1:], [n]))
        self.kmer = least[self.begin].view(np.int64)
        words = (self.end - self.begin + window - 1).astype(np.uint64)
        self.path = _mix((total[self.end + window - 1] - total[self.begin]) * power[self.begin] + words * np.uint64(0xD6E8FEB86659FD93)).view(np.int64)
        self.window = self.window.view(np.int64)

    def _gram(self, start: np.ndarray, size: int) -> np.ndarray:
        return (self._total[start + size] - self._total[start]) * self._power[start]

    def repeats_inside(self) -> np.ndarray:
        """Windows that occur earlier in this document."""
        again = np.ones(self.n, bool)
        again[np.unique(self.window, return_index=True)[1]] = False
        return again


def _bodies(docs: DataFrame) -> DataFrame:
    return docs.select(id_key().alias("k"), F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("body"))


def _per_document(rows, schema: pa.Schema, window: int, k: int):
    """mapInArrow: ``rows(row, words, paths)`` gives arrays for the schema's columns, or None."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = Words()
        for batch in batches:
            held: list[list[np.ndarray]] = []
            size = 0
            for i in range(batch.num_rows):
                row = {n: batch.column(j)[i] for j, n in enumerate(batch.schema.names)}
                ws = row["body"].as_py().split()
                out = rows(row, ws, Paths(names.hashes(ws), window, k))
                if out is not None:
                    held.append(out)
                    size += len(out[0])
                if size > 200_000:
                    yield _gather(held, schema)
                    held, size = [], 0
            if held:
                yield _gather(held, schema)

    return run


def _gather(held: list[list[np.ndarray]], schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.concatenate([h[i] for h in held])) for i in range(len(schema))], schema=schema)


def paths(docs: DataFrame, window: int = WINDOW, k: int = KMER) -> DataFrame:
    """(m, c, k): k-mer hash, path hash and document, once for each distinct path of a row."""
    schema = pa.schema([("m", pa.int64()), ("c", pa.int64()), ("k", pa.int64())])

    def rows(row, ws, p: Paths):
        if not p.n:
            return None
        one = np.unique(p.path, return_index=True)[1]
        return [p.kmer[one], p.path[one], np.full(len(one), row["k"].as_py())]

    return _bodies(docs).mapInArrow(_per_document(rows, schema, window, k), "m long, c long, k long")


def repeated_paths(docs: DataFrame, window: int = WINDOW, k: int = KMER) -> DataFrame:
    """(k, whole, open): per document its paths that occur in an earlier document, and those to be opened."""
    found = park(paths(docs, window, k), "paths")
    shared = found.groupBy("m").agg(F.min("c").alias("c1"), F.max("c").alias("c2"), F.min("k").alias("k1"), F.max("k").alias("k2")).where("c1 <> c2 OR k1 <> k2")
    shared = park(shared.select("m", (F.col("c1") != F.col("c2")).alias("branches"), F.col("k1").alias("first")), "kmers")
    met = park(found.join(shared, "m").select("m", "c", "k", "branches", "first").where("branches OR k > first"), "kmer-paths")
    simple = met.where("NOT branches").select("k", "c", F.lit(True).alias("whole"))
    branching = met.where("branches").select("m", "c", "k")
    firsts = park(branching.groupBy("m", "c").agg(F.min("k").alias("first")), "kmer-classes")
    rest = branching.join(firsts, ["m", "c"]).select("k", "c", (F.col("k") > F.col("first")).alias("whole"))
    marks = simple.unionByName(rest).groupBy("k").agg(F.collect_list(F.when(F.col("whole"), F.col("c"))).alias("whole"), F.collect_list(F.when(~F.col("whole"), F.col("c"))).alias("open"))
    return park(marks, "path-marks")


def _opened(texts: DataFrame, marks: DataFrame, window: int, k: int) -> DataFrame:
    """(m, w, k): the windows of opened paths, once for each document."""
    schema = pa.schema([("m", pa.int64()), ("w", pa.int64()), ("k", pa.int64())])

    def rows(row, ws, p: Paths):
        if not p.n:
            return None
        open_ = np.isin(p.path, row["open"].values.to_numpy())
        at = np.repeat(open_, p.end - p.begin)
        if not at.any():
            return None
        m = np.repeat(p.kmer, p.end - p.begin)[at]
        w, one = np.unique(p.window[at], return_index=True)
        return [m[one], w, np.full(len(w), row["k"].as_py())]

    some = marks.where(F.size("open") > 0).select("k", "open")
    return texts.join(some, "k").select("k", "body", "open").mapInArrow(_per_document(rows, schema, window, k), "m long, w long, k long")


def removals(docs: DataFrame, window: int = WINDOW, k: int = KMER) -> DataFrame:
    """Texts with what marks their repeated windows: (k, body, whole, later)."""
    marks = repeated_paths(docs, window, k)
    texts = _bodies(docs)
    opened = park(_opened(texts, marks, window, k), "windows")
    firsts = park(opened.groupBy("m", "w").agg(F.min("k").alias("first"), F.max("k").alias("last")).where("first <> last").select("m", "w", "first"), "window-firsts")
    later = opened.join(firsts, ["m", "w"]).where("k > first").groupBy("k").agg(F.collect_list("w").alias("later"))
    return texts.join(marks.select("k", "whole"), "k", "left").join(later, "k", "left").select("k", "body", "whole", "later")


def _removed_words(row, n_words: int, p: Paths, window: int) -> np.ndarray:
    gone = p.repeats_inside()
    if row["whole"].is_valid:
        gone |= np.repeat(np.isin(p.path, row["whole"].values.to_numpy()), p.end - p.begin)
    if row["later"].is_valid:
        gone |= np.isin(p.window, row["later"].values.to_numpy())
    edge = np.zeros(n_words + 1, np.int64)
    edge[: p.n] += gone
    edge[window : window + p.n] -= gone
    return np.cumsum(edge[:-1]) > 0


def deduplicate(docs: DataFrame, window: int = WINDOW, k: int = KMER) -> DataFrame:
    """Per row: doc_id, number of words, removed words, the kept words joined by a space, and their SHA-256."""
    schema = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept", pa.string()), ("kept_sha256", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = Words()
        for batch in batches:
            out: list[list] = [[] for _ in schema]
            for i in range(batch.num_rows):
                row = {n: batch.column(j)[i] for j, n in enumerate(batch.schema.names)}
                ws = row["body"].as_py().split()
                p = Paths(names.hashes(ws), window, k)
                gone = _removed_words(row, len(ws), p, window) if p.n else np.zeros(len(ws), bool)
                kept = b" ".join([w for w, g in zip(ws, gone.tolist()) if not g] if gone.any() else ws)
                key = row["k"].as_py()
                for column, x in zip(out, (None if key == NULL_ID else key, len(ws), int(gone.sum()), kept.decode(), hashlib.sha256(kept).hexdigest())):
                    column.append(x)
                if (i + 1) % 256 == 0 or i + 1 == batch.num_rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(out, schema)], schema=schema)
                    out = [[] for _ in schema]

    return removals(docs, window, k).mapInArrow(run, "doc_id long, n_words long, n_removed long, kept string, kept_sha256 string")


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return deduplicate(table(spark, sf_dir, "documents")).drop("kept")


SQL = r"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda w: w <> '') AS w FROM documents),
g AS (SELECT doc_id, i, array_to_string(list_slice(w, i, i + 19), ' ') AS s FROM d, unnest(generate_series(1, len(w) - 19)) AS t(i)),
f AS (SELECT doc_id, i, row_number() OVER (PARTITION BY s ORDER BY doc_id, i) AS n FROM g),
r AS (SELECT DISTINCT doc_id, unnest(generate_series(i, i + 19)) AS p FROM f WHERE n > 1),
u AS (SELECT doc_id, w[p] AS x, p FROM d, unnest(generate_series(1, len(w))) AS t(p)),
k AS (SELECT u.doc_id, count(r.p) AS n_removed, string_agg(CASE WHEN r.p IS NULL THEN x END, ' ' ORDER BY u.p) AS kept FROM u LEFT JOIN r ON u.doc_id = r.doc_id AND u.p = r.p GROUP BY u.doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM d LEFT JOIN k USING (doc_id)
"""
