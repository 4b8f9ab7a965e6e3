"""A small logical plan of a search, rewritten before Spark sees it.

``nearest`` becomes an equality or prefix condition on ``code`` (pushed to the scan of an index sorted by code);
metadata conditions go before ranking, or after it, where fewer than k may be left.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import Column, DataFrame, functions as F

from tilemine.operators.tsvq import Index, descend_one, near_leaves


@dataclass(frozen=True)
class RetrievePlan:
    vectors: tuple[tuple[float, ...], ...]
    k: int = 10
    probes: int = 1
    backoff: bool = False
    metric: str = "sqeuclid"
    combine: str = "min"
    where: Column | None = None
    mode: str = "pre"
    codes: tuple[str, ...] = field(default=())
    prefix: str | None = None

    def resolve(self, index: Index) -> RetrievePlan:
        """Descend for each signature; choose leaves or, with back-off, the smallest subtree of at least k rows."""
        found: list[str] = []
        prefix = None
        splits = {c: n.split for c, n in index.nodes.items() if n.split is not None} if self.probes > 1 else {}
        for v in self.vectors:
            x = np.array(v, float)
            code = descend_one(x, index.nodes)
            found += [c for c, _ in near_leaves(x, splits, self.probes)] if self.probes > 1 else [code]
            if self.backoff:
                while code and index.nodes[code].n < self.k:
                    code = code[:-1]
                prefix = code if prefix is None else _common(prefix, code)
        return replace(self, codes=tuple(dict.fromkeys(found)), prefix=prefix)

    def candidates(self, rows: DataFrame) -> DataFrame:
        if self.prefix is not None:
            return rows.where(F.col("code").startswith(self.prefix)) if self.prefix else rows
        return rows.where(F.col("code") == self.codes[0] if len(self.codes) == 1 else F.col("code").isin(*self.codes))


def _common(a: str, b: str) -> str:
    n = next((i for i, (x, y) in enumerate(zip(a, b)) if x != y), min(len(a), len(b)))
    return a[:n]
