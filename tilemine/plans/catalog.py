"""SQL access: views of an index, scalar functions, a table function."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
from pyspark.sql import SparkSession, functions as F

from tilemine.operators.tsvq import Index, codebook


#: Scalar functions as SQL expressions, so that they stay in generated code.
FUNCTIONS = {
    "vq_sqdist(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)",
    "vq_side(x ARRAY<DOUBLE>, w ARRAY<DOUBLE>, b DOUBLE) RETURNS INT": "CAST(aggregate(zip_with(x, w, (p, q) -> p * q), 0D, (s, p) -> s + p) > b AS INT)",
    "polsar_entropy(p1 DOUBLE, p2 DOUBLE, p3 DOUBLE) RETURNS DOUBLE": "aggregate(array(p1, p2, p3), 0D, (s, p) -> s - if(p > 0, p * ln(if(p > 0, p, 1D)), 0D)) / ln(3D)",
    "polsar_anisotropy(l2 DOUBLE, l3 DOUBLE) RETURNS DOUBLE": "if(l2 + l3 > 0, (l2 - l3) / if(l2 + l3 > 0, l2 + l3, 1D), 0D)",
}


class _VqSearch:
    """SELECT * FROM vq_search(TABLE(candidates) PARTITION BY code, query, k): the k nearest candidate rows (id, v) of each partition, in a
    heap of k; ORDER BY dist, id LIMIT k over them merges.  Without PARTITION BY one task gets all rows."""

    def __init__(self):
        self.best: list[tuple[float, int]] = []

    def eval(self, row, query, k: int):
        d = float(((np.asarray(row["v"]) - np.asarray(query)) ** 2).sum())
        (heapq.heappush if len(self.best) < k else heapq.heappushpop)(self.best, (-d, -row["id"]))

    def terminate(self) -> Iterator[tuple[int, int, float]]:
        for rank, (d, i) in enumerate(sorted(self.best, reverse=True), 1):
            yield rank, -i, -d


class _Ancestors:
    """The codes from the root down to a leaf."""

    def eval(self, code: str):
        for n in range(len(code) + 1):
            yield (code[:n],)


def register(spark: SparkSession, index: Index | None = None) -> None:
    """Views tiles, nodes, codebook; functions vq_sqdist, vq_side, polsar_entropy, polsar_anisotropy; table functions vq_search, vq_path."""
    if index is not None:
        index.labelled.createOrReplaceTempView("tiles")
        index.table(spark).createOrReplaceTempView("nodes")
        codebook(index, spark).createOrReplaceTempView("codebook")
    for head, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("vq_search", F.udtf(_VqSearch, returnType="rank int, id long, dist double"))
    spark.udtf.register("vq_path", F.udtf(_Ancestors, returnType="code string"))
