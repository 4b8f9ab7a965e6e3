"""Kernels over labelled descriptors (code, v): each is one pass whose tasks give small partial results.

The rows never move: a task applies broadcast splits to its batches with matrix products and sums
in numpy; what is shuffled is a row for each open node, child and dimension and task, and it is
merged with Spark's partial aggregates.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T


def vectors(column: pa.Array) -> np.ndarray:
    """A list column of equal lengths as a matrix of doubles."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not len(column):
        return np.zeros((0, 0))
    return np.asarray(column.flatten().to_numpy(zero_copy_only=False), float).reshape(len(column), -1)


def by_code(codes: pa.Array) -> Iterator[tuple[str, np.ndarray]]:
    """(code, places of its rows)."""
    coded = codes.dictionary_encode()
    index = coded.indices.to_numpy()
    order = np.argsort(index, kind="stable")
    bounds = np.searchsorted(index[order], np.arange(len(coded.dictionary) + 1))
    for i, code in enumerate(coded.dictionary.to_pylist()):
        if bounds[i] < bounds[i + 1]:
            yield code, order[bounds[i] : bounds[i + 1]]


Split = tuple[np.ndarray, float]
_SUMS = "code string, child int, n long, sq double, s array<double>, ss array<double>"


def assign(x: np.ndarray, split: Split) -> np.ndarray:
    """Child of each row: 1 strictly beyond the bisector w.x = b."""
    return (x @ split[0] > split[1]).astype(np.int32)


@dataclass
class Under:
    """Rows (id, code, v, ..) whose codes go on by ``splits``: those found since the codes were written.  A kernel finds the rest of a
    code as it reads a row, so that growing a level copies no vectors."""

    rows: DataFrame
    splits: dict[str, Split] = field(default_factory=dict)

    def only(self, codes: list[str]) -> Under:
        """Rows that may lie in one of ``codes``: their written code is a prefix of one."""
        prefixes = {c[:i] for c in codes for i in range(len(c) + 1)}
        return Under(self.rows.where(F.col("code").isin(*prefixes)), self.splits)


def deepen(codes: pa.Array, x: np.ndarray, splits: dict[str, Split]) -> Iterator[tuple[str, np.ndarray]]:
    """(code, places of its rows), codes followed down the splits."""
    front = list(by_code(codes))
    while front:
        code, at = front.pop()
        split = splits.get(code)
        if split is None:
            yield code, at
            continue
        bit = assign(x[at], split)
        front += [(f"{code}{b}", at[bit == b]) for b in (1, 0) if (bit == b).any()]


def _sent(labelled: DataFrame | Under, *more):
    """The rows, and what the tasks get: the splits since the rows' codes were written, and more."""
    held = labelled if isinstance(labelled, Under) else Under(labelled)
    return held.rows, held.rows.sparkSession.sparkContext.broadcast((held.splits, *more))


def sums(labelled: DataFrame | Under, splits: dict[str, Split] | None = None, combine: bool = True) -> dict[tuple[str, int], dict]:
    """n, sum of squared norms, sums and sums of squares by dimension, for each (code, child) of ``splits``, or for
    each code (child 0) if there are none.  ``combine=False`` sends every row instead of a task's sums."""
    rows, sent = _sent(labelled, splits)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        below, splits = sent.value
        held: dict[tuple[str, int], list] = {}

        def emit(items):
            return pa.RecordBatch.from_arrays([pa.array([k[0] for k, _ in items]), pa.array([k[1] for k, _ in items], pa.int32()), pa.array([v[0] for _, v in items], pa.int64()), pa.array([v[1] for _, v in items], pa.float64()), pa.array([v[2] for _, v in items], pa.list_(pa.float64())), pa.array([v[3] for _, v in items], pa.list_(pa.float64()))], names=["code", "child", "n", "sq", "s", "ss"])

        for batch in batches:
            x = vectors(batch.column(1))
            for code, at in deepen(batch.column(0), x, below):
                if splits is not None and code not in splits:
                    continue
                own = x[at]
                child = assign(own, splits[code]) if splits is not None else np.zeros(len(at), np.int32)
                for c in np.unique(child):
                    part = own[child == c]
                    if not combine:
                        yield emit([((code, int(c)), (1, float(r @ r), r, r * r)) for r in part])
                        continue
                    total = held.setdefault((code, int(c)), [0, 0.0, 0.0, 0.0])
                    total[0] += len(part)
                    total[1] += float((part * part).sum())
                    total[2] = total[2] + part.sum(0)
                    total[3] = total[3] + (part * part).sum(0)
        if held:
            yield emit(list(held.items()))

    partial = rows.select("code", "v").mapInArrow(run, _SUMS)
    if not combine:
        partial = partial.repartition("code", "child")
    long = partial.select("code", "child", "n", "sq", F.posexplode(F.arrays_zip("s", "ss")).alias("dim", "x"))
    merged = long.groupBy("code", "child", "dim").agg(F.sum("n").alias("n"), F.sum("sq").alias("sq"), F.sum("x.s").alias("s"), F.sum("x.ss").alias("ss"))
    out: dict[tuple[str, int], dict] = {}
    found = merged.collect()  # nodes x children x dimensions, bounded by the frontier's budget
    size = 1 + max((r.dim for r in found), default=-1)
    for r in found:
        node = out.setdefault((r.code, r.child), {"n": r.n, "sq": r.sq, "s": np.zeros(size), "ss": np.zeros(size)})
        node["s"][r.dim], node["ss"][r.dim] = r.s, r.ss
    return out


def relabel(labelled: DataFrame | Under, splits: dict[str, Split] | None = None) -> DataFrame:
    """The rows with their codes written out, followed down ``splits`` too, and v as doubles; narrow."""
    held = labelled if isinstance(labelled, Under) else Under(labelled)
    rows, sent = _sent(Under(held.rows, held.splits | (splits or {})))
    names = rows.columns
    at_code, at_v = names.index("code"), names.index("v")
    schema = T.StructType([T.StructField("v", T.ArrayType(T.DoubleType())) if f.name == "v" else f for f in rows.schema])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = vectors(batch.column(at_v))
            codes = np.empty(len(x), object)
            for code, at in deepen(batch.column(at_code), x, sent.value[0]):
                codes[at] = code
            double = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(x.ravel())) if len(x) else pa.array([], pa.list_(pa.float64()))
            columns = [pa.array(codes.tolist(), pa.string()) if i == at_code else double if i == at_v else batch.column(i) for i in range(len(names))]
            yield pa.RecordBatch.from_arrays(columns, names=names)

    return rows.mapInArrow(run, schema)


def best(labelled: DataFrame | Under, score: Callable[[str, np.ndarray, np.ndarray], np.ndarray], codes: set[str]) -> dict[str, tuple[int, np.ndarray, float]]:
    """The row of each code with the smallest score (then smallest id): code -> (id, v, score).  A task sends one row for each code and batch."""
    return {code: found for (code, _), found in bests(labelled, score, codes).items()}


def bests(labelled: DataFrame | Under, score: Callable[[str, np.ndarray, np.ndarray], np.ndarray], codes: set[str]) -> dict[tuple[str, int], tuple[int, np.ndarray, float]]:
    """As ``best`` for scores of several trials, a row of them each: (code, trial) -> (id, v, score), in one pass."""
    source, wanted = _sent(labelled, codes, score)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        below, codes, score = wanted.value
        for batch in batches:
            x, ids = vectors(batch.column(2)), batch.column(0).to_numpy()
            rows = []
            for code, at in deepen(batch.column(1), x, below):
                if code in codes:
                    for trial, s in enumerate(np.atleast_2d(score(code, ids[at], x[at]))):
                        i = np.lexsort((ids[at], s))[0]
                        rows.append((code, trial, float(s[i]), int(ids[at][i]), x[at][i].tolist()))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int32() if i == 1 else None) for i, c in enumerate(zip(*rows))], names=["code", "trial", "score", "id", "v"])

    found = source.select("id", "code", "v").mapInArrow(run, "code string, trial int, score double, id long, v array<double>")
    rows = found.groupBy("code", "trial").agg(F.min_by(F.struct("id", "v", "score"), F.struct("score", "id")).alias("x")).collect()
    return {(r.code, r.trial): (r.x.id, np.array(r.x.v), r.x.score) for r in rows}


def costs(labelled: DataFrame | Under, centres: dict[str, list[np.ndarray]]) -> dict[str, tuple[float, np.ndarray]]:
    """For each code of ``centres``: the sum of squared distances to the nearest centre, and the rows nearest to each one.  A row a task
    and centre is shuffled."""
    source, sent = _sent(labelled, {c: np.array(v) for c, v in centres.items()})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        below, centres = sent.value
        held: dict[str, tuple[np.ndarray, np.ndarray]] = {}
        for batch in batches:
            x = vectors(batch.column(1))
            for code, at in deepen(batch.column(0), x, below):
                if code in centres:
                    near, d = nearest(x[at], centres[code])
                    cost, n = held.setdefault(code, (np.zeros(len(centres[code])), np.zeros(len(centres[code]), np.int64)))
                    cost += np.bincount(near, d, len(cost))
                    n += np.bincount(near, minlength=len(n))
        rows = [(code, i, float(cost[i]), int(n[i])) for code, (cost, n) in held.items() for i in range(len(n))]
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows]), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows]), pa.array([r[3] for r in rows], pa.int64())], names=["code", "i", "cost", "n"])

    found = source.select("code", "v").mapInArrow(run, "code string, i int, cost double, n long").groupBy("code", "i").agg(F.sum("cost").alias("cost"), F.sum("n").alias("n")).collect()
    out: dict[str, tuple[float, np.ndarray]] = {c: (0.0, np.zeros(len(v), np.int64)) for c, v in centres.items()}
    for r in sorted(found, key=lambda r: (r.code, r.i)):
        out[r.code][1][r.i] = r.n
        out[r.code] = (out[r.code][0] + r.cost, out[r.code][1])
    return out


def nearest(x: np.ndarray, centres: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Place of each row's nearest centre (the first of equal ones) and its squared distance."""
    d = np.array([((x - c) ** 2).sum(1) for c in centres])
    near = d.argmin(0)
    return near, d[near, np.arange(len(x))]


def draw(labelled: DataFrame | Under, chosen: Callable[[str, np.ndarray, np.ndarray], np.ndarray], codes: set[str]) -> dict[str, list[tuple[int, np.ndarray]]]:
    """The rows of each code that ``chosen`` takes, by id.  It is to take few: they reach the driver."""
    source, sent = _sent(labelled, codes, chosen)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        below, codes, chosen = sent.value
        for batch in batches:
            x, ids = vectors(batch.column(2)), batch.column(0).to_numpy()
            for code, at in deepen(batch.column(1), x, below):
                if code in codes:
                    took = at[chosen(code, ids[at], x[at])]
                    if len(took):
                        yield pa.RecordBatch.from_arrays([pa.array([code] * len(took)), pa.array(ids[took]), pa.array(x[took].tolist(), pa.list_(pa.float64()))], names=["code", "id", "v"])

    out: dict[str, list[tuple[int, np.ndarray]]] = {}
    for r in source.select("id", "code", "v").mapInArrow(run, "code string, id long, v array<double>").collect():
        out.setdefault(r.code, []).append((r.id, np.array(r.v)))
    return {c: sorted(v, key=lambda r: r[0]) for c, v in out.items()}
