"""k-means with broadcast centroids: assignment with a local combine, update, stop by movement."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, functions as F, types as T

from tilemine.functions import vector
from tilemine.operators import seeds
from tilemine.operators.passes import vectors
from tilemine.sources.storage import park


@dataclass
class Model:
    centroids: np.ndarray
    counts: list[int]
    wcss: float
    iterations: int
    moves: list[float] = field(default_factory=list)
    cost: dict[str, int] = field(default_factory=dict)


def nearest(centroids: np.ndarray, v: str = "v") -> Column:
    """Index of the nearest centroid (the first of equal ones) as an expression: the flat encoder's rule."""
    x = F.transform(v, lambda a: a.cast("double"))
    pairs = [F.struct(vector.sqdist(x, F.array(*map(F.lit, map(float, c)))).alias("d"), F.lit(i).alias("i")) for i, c in enumerate(centroids)]
    return F.array_min(F.array(*pairs))["i"]


def _assign(x: np.ndarray, norms: np.ndarray, centroids: np.ndarray) -> np.ndarray:
    """argmin of |x|^2 - 2 x.y + |y|^2; the first term is the same for all centroids of a row."""
    return np.argmin((centroids * centroids).sum(1) - 2 * (x @ centroids.T), axis=1)


def assign(df: DataFrame, centroids: np.ndarray) -> DataFrame:
    """Adds cid; narrow, centroids are sent to the tasks."""
    sent = df.sparkSession.sparkContext.broadcast(np.asarray(centroids, float))
    at, names = df.columns.index("v"), df.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = vectors(batch.column(at))
            cid = _assign(x, (x * x).sum(1), sent.value) if len(x) else np.zeros(0, int)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(cid, pa.int32())], names=[*names, "cid"])

    return df.mapInArrow(run, T.StructType([*df.schema.fields, T.StructField("cid", T.IntegerType())]))


def partial_sums(df: DataFrame, centroids: np.ndarray, combine: bool = True, layout: str = "dense", dims: int | None = None) -> DataFrame:
    """(cid, dim, s, n, sq, far): the assignment step's key/value records; with ``combine`` a task's sums, without it a record for each row."""
    sent = df.sparkSession.sparkContext.broadcast(np.asarray(centroids, float))
    columns = ["v"] if layout == "dense" else ["idx", "val"]

    def dense(batch: pa.RecordBatch) -> np.ndarray:
        return vectors(batch.column(0))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        y = sent.value
        norm = (y * y).sum(1)
        total, n, sq, cost = np.zeros_like(y), np.zeros(len(y), np.int64), np.zeros(len(y)), np.zeros(len(y))

        def records(totals, counts, squares, costs):
            cid = np.flatnonzero(counts)
            return pa.RecordBatch.from_arrays([pa.array(cid.astype(np.int32)), pa.array(counts[cid]), pa.array(squares[cid]), pa.array(costs[cid]), pa.array(totals[cid].tolist(), pa.list_(pa.float64()))], names=["cid", "n", "sq", "cost", "s"])

        for batch in batches:
            if not batch.num_rows:
                continue
            if layout == "dense":
                x = dense(batch)
                scores = norm - 2 * (x @ y.T)
                rows_sq = (x * x).sum(1)
            else:  # work on the entries that are not zero
                idx, val = batch.column(0), np.asarray(batch.column(1).flatten().to_numpy(zero_copy_only=False), float)
                flat = np.asarray(idx.flatten().to_numpy(zero_copy_only=False))
                row = np.repeat(np.arange(batch.num_rows), np.diff(idx.offsets.to_numpy()))
                products = np.zeros((batch.num_rows, len(y)))
                for c in range(len(y)):
                    products[:, c] = np.bincount(row, val * y[c, flat], batch.num_rows)
                scores, rows_sq = norm - 2 * products, np.bincount(row, val * val, batch.num_rows)
            cid = np.argmin(scores, axis=1)
            far = scores[np.arange(len(cid)), cid] + rows_sq
            if not combine:
                for i, c in enumerate(cid):
                    one, k, q, f = np.zeros_like(y), np.zeros_like(n), np.zeros_like(sq), np.zeros_like(cost)
                    k[c], q[c], f[c] = 1, rows_sq[i], far[i]
                    if layout == "dense":
                        one[c] = x[i]
                    else:
                        one[c, flat[row == i]] = val[row == i]
                    yield records(one, k, q, f)
                continue
            if layout == "dense":
                np.add.at(total, cid, x)
            else:
                np.add.at(total, (cid[row], flat), val)
            n += np.bincount(cid, minlength=len(y))
            sq += np.bincount(cid, rows_sq, len(y))
            cost += np.bincount(cid, far, len(y))
        if combine and n.any():
            yield records(total, n, sq, cost)

    out = df.select(*columns).mapInArrow(run, "cid int, n long, sq double, cost double, s array<double>")
    if not combine:
        out = out.repartition("cid")
    return out.select("cid", "n", "sq", "cost", F.posexplode("s").alias("dim", "x"))


def update(partials: DataFrame, shape: tuple[int, int]) -> tuple[np.ndarray, np.ndarray, float]:
    """Sums by centroid and dimension, merged; (sums, counts, total cost)."""
    rows = partials.groupBy("cid", "dim").agg(F.sum("x").alias("x"), F.sum("n").alias("n"), F.sum("cost").alias("cost")).collect()
    s, n, cost = np.zeros(shape), np.zeros(shape[0], np.int64), np.zeros(shape[0])
    for r in rows:
        s[r.cid, r.dim], n[r.cid], cost[r.cid] = r.x, r.n, r.cost
    return s, n, float(cost.sum())


def start(df: DataFrame, k: int, init: str = "farthest", seed: int = 0) -> np.ndarray:
    found = seeds.centres(df.select("id", F.lit("").alias("code"), F.transform("v", lambda a: a.cast("double")).alias("v")), {""}, init, seed, k)
    return np.array(found[""])


def fit(df: DataFrame, k: int, init: str | np.ndarray = "farthest", tol: float = 1e-6, max_iter: int = 20, combine: bool = True, materialise: str = "memory", layout: str = "dense", seed: int = 0) -> Model:
    """Lloyd's iterations; one job each.  ``materialise``: 'memory' keeps the rows in executors' memory, 'dfs' writes and rereads the
    assigned rows after every iteration, 'none' reads the source again each time."""
    centroids = np.asarray(init, float) if not isinstance(init, str) else start(df, k, init, seed)
    rows = df.persist(StorageLevel.MEMORY_AND_DISK) if materialise == "memory" else df
    moves: list[float] = []
    counts, iterations = np.zeros(len(centroids), np.int64), 0
    try:
        for iterations in range(1, max_iter + 1):
            s, counts, _ = update(partial_sums(rows, centroids, combine, layout), centroids.shape)
            moved = np.where(counts[:, None] > 0, s / np.maximum(counts, 1)[:, None], centroids)
            moves.append(float(np.abs(moved - centroids).max()))
            centroids = moved
            if materialise == "dfs":
                rows = park(assign(df.drop("cid"), centroids) if layout == "dense" else rows, "kmeans")
            if moves[-1] <= tol:
                break
        _, counts, wcss = update(partial_sums(rows, centroids, True, layout), centroids.shape)
    finally:
        if materialise == "memory":
            rows.unpersist()
    return Model(centroids, counts.tolist(), wcss, iterations, moves, {"k": len(centroids), "d": centroids.shape[1], "i": iterations})
