"""Cost and accuracy measures: distortion, tree shape, retrieval quality, scaling fits, cost-benefit, counters."""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F

from tilemine.functions.vector import sqnorm
from tilemine.operators.passes import nearest, vectors
from tilemine.operators.tsvq import Index


def timed(fn: Callable[[], object], repeat: int = 3) -> dict[str, float]:
    took = []
    for _ in range(repeat):
        began = time.perf_counter()
        fn()
        took.append(time.perf_counter() - began)
    took.sort()
    return {"min": took[0], "median": took[len(took) // 2], "max": took[-1]}


def wcss(df: DataFrame, by: str = "code") -> DataFrame:
    """Within-cluster sum of squares from sufficient statistics: sum of squared norms minus |sum|^2 / n."""
    x = F.transform("v", lambda a: a.cast("double"))
    long = df.select(by, sqnorm(x).alias("q"), F.posexplode(x).alias("dim", "x")).groupBy(by, "dim").agg(F.sum("x").alias("s"), F.count("*").alias("n"), F.sum("q").alias("sq"))
    return long.groupBy(by).agg(F.max("n").alias("n"), (F.max("sq") - F.sum(F.col("s") * F.col("s") / F.col("n"))).alias("wcss"))


def check_cells(assigned: DataFrame, codebook: DataFrame) -> DataFrame:
    """Violations of the nearest-codeword rule and of one cell a row: both are 0 for a Voronoi partition.  The codebook (k x d numbers, which
    coding sends to every task anyway) meets each batch of rows as a matrix."""
    book = codebook.select("cid", "c").orderBy("cid").collect()
    sent = assigned.sparkSession.sparkContext.broadcast((np.array([r.cid for r in book]), np.array([r.c for r in book], float)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, y = sent.value
        for batch in batches:
            x, own = vectors(batch.column(2)), batch.column(1).to_numpy(zero_copy_only=False)
            if len(x):
                near, _ = nearest(x, y)
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(names[near] != own)], names=["id", "cid", "farther"])

    told = assigned.select(F.col("id").cast("long"), F.col("cid").cast("int"), "v").mapInArrow(run, "id long, cid int, farther boolean")
    per = told.groupBy("id").agg(F.max("farther").alias("farther"), F.min("cid").alias("a"), F.max("cid").alias("b"))
    return per.agg(F.count("*").alias("n_rows"), F.count_if("farther").alias("n_farther"), F.count_if(F.col("a") != F.col("b")).alias("n_overlaps"))


def rate_curve(index: Index) -> list[dict]:
    """Total distortion and average code length after each split, in growing order."""
    leaves = {"": index.nodes[""]}
    n = leaves[""].n
    out = [{"step": 0, "wcss": leaves[""].wcss, "code_length": 0.0}]
    for code in sorted((c for c, x in index.nodes.items() if x.split is not None), key=lambda c: (len(c), c)):
        leaves.pop(code)
        leaves |= {f"{code}{b}": index.nodes[f"{code}{b}"] for b in (0, 1)}
        out.append({"step": len(out), "wcss": sum(x.wcss for x in leaves.values()), "code_length": sum(len(c) * x.n for c, x in leaves.items()) / n})
    return out


def tree_shape(nodes: DataFrame) -> DataFrame:
    leaf = F.col("is_leaf")
    return nodes.agg(
        F.count("*").alias("n_nodes"), F.count_if(leaf).alias("n_leaves"), F.max("depth").alias("depth"), F.min(F.when(leaf, F.col("n"))).alias("least_leaf"), F.max(F.when(leaf, F.col("n"))).alias("largest_leaf"),
        F.round(F.sum(F.when(leaf, F.col("n") * F.col("depth"))) / F.sum(F.when(leaf, F.col("n"))), 6).alias("mean_code_length"),
    )


def distance_evals(labelled: DataFrame) -> DataFrame:
    """For queries by every row: evaluations of a descent (two a branch), with its leaf's ranking, and of a scan."""
    per = labelled.groupBy("code").agg(F.count("*").alias("n")).withColumn("depth", F.length("code"))
    total = F.sum("n")
    return per.agg(F.sum(F.col("n") * 2 * F.col("depth")).alias("descent"), F.sum(F.col("n") * (2 * F.col("depth") + F.col("n"))).alias("descent_and_leaf"), (total * total).alias("scan"))


def kmeans_ops(n: int, d: int, k: int, i: int, nnz: int) -> dict[str, float]:
    """Predicted operations of dense and sparse k-means; nnz is the total of non-zero entries."""
    return {"dense": n * d * k * i, "sparse": (nnz + n) * k * i, "mean_nnz": nnz / max(n, 1)}


def precision_at(results: DataFrame, labels: DataFrame, k: int = 10) -> DataFrame:
    """Share of results, without the query itself, that have the query's label: (n_queries, n_results, n_same, precision)."""
    own = labels.select(F.col("id").alias("query_id"), F.col("label").alias("q_label"))
    hits = results.where((F.col("rank") <= k) & (F.col("id") != F.col("query_id"))).join(own, "query_id").join(labels.select("id", "label"), "id")
    return hits.agg(F.countDistinct("query_id").alias("n_queries"), F.count("*").alias("n_results"), F.count_if(F.col("label") == F.col("q_label")).alias("n_same"), F.round(F.avg((F.col("label") == F.col("q_label")).cast("double")), 6).alias("precision"))


def recall_at(results: DataFrame, exact: DataFrame, k: int = 10) -> DataFrame:
    """Share of the exact top k that was found."""
    a, b = results.where(F.col("rank") <= k).select("query_id", "id"), exact.where(F.col("rank") <= k).select("query_id", "id")
    found = b.join(a.withColumn("found", F.lit(1)), ["query_id", "id"], "left")
    return found.agg(F.count("*").alias("n_exact"), F.count("found").alias("n_found"), F.round(F.count("found") / F.count("*"), 6).alias("recall"))


def agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """Jaccard overlap of two result sets by query."""
    both = a.select("query_id", "id").withColumn("a", F.lit(1)).join(b.select("query_id", "id").withColumn("b", F.lit(1)), ["query_id", "id"], "full")
    return both.groupBy("query_id").agg(F.count(F.col("a") + F.col("b")).alias("n_both"), F.count("*").alias("n_any"), F.round(F.count(F.col("a") + F.col("b")) / F.count("*"), 6).alias("jaccard"))


def relative(runs: DataFrame, ref: str, basis: str = "rate") -> DataFrame:
    """(config, nodes, minutes, time_gain_pct, cost_change_pct) against the reference configuration.  ``rate`` compares hourly cost, ``run`` the cost of the run."""
    cost = F.col("nodes") * F.col("rate") * (F.col("minutes") / 60 if basis == "run" else F.lit(1.0))
    runs = runs.withColumn("cost", cost)
    base = F.broadcast(runs.where(F.col("config") == ref).select(F.col("minutes").alias("m0"), F.col("cost").alias("c0")))
    return runs.crossJoin(base).select("config", "nodes", "minutes", F.round((F.col("m0") - F.col("minutes")) / F.col("m0") * 100, 6).alias("time_gain_pct"), F.round((F.col("cost") - F.col("c0")) / F.col("c0") * 100, 6).alias("cost_change_pct"))


def tradeoff(rel: DataFrame) -> DataFrame:
    """Gain over the line of equal gain and cost; positive is worth it, the largest is best."""
    rel = rel.withColumn("tradeoff", F.round(F.col("time_gain_pct") - F.col("cost_change_pct"), 6))
    best = rel.agg(F.max_by("config", F.struct("tradeoff", "config")).alias("best"))
    return rel.crossJoin(F.broadcast(best)).select("config", "tradeoff", (F.col("tradeoff") > 0).alias("beneficial"), (F.col("config") == F.col("best")).alias("is_best"))


def fit(runs: DataFrame, x: str = "nodes", y: str = "minutes") -> DataFrame:
    return runs.agg(F.round(F.regr_slope(y, x), 6).alias("slope"), F.round(F.regr_intercept(y, x), 6).alias("intercept"), F.round(F.regr_r2(y, x), 6).alias("r2"), F.count("*").alias("n"))


def _beta_fraction(a: float, b: float, x: float) -> float:
    """Continued fraction of the incomplete beta function."""
    tiny, c, d = 1e-300, 1.0, 1 - (a + b) * x / (a + 1)
    d = 1 / (d if abs(d) > tiny else tiny)
    out = d
    for m in range(1, 300):
        for numerator in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 + numerator * d
            d = 1 / (d if abs(d) > tiny else tiny)
            c = 1 + numerator / c
            c = c if abs(c) > tiny else tiny
            out *= d * c
        if abs(d * c - 1) < 1e-14:
            break
    return out


def t_tail(t: float, df: float) -> float:
    """Two-sided tail of Student's distribution."""
    x = df / (df + t * t)
    if x >= 1:
        return 1.0
    a, b = df / 2, 0.5
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x))
    return front * _beta_fraction(a, b, x) / a if x < (a + 1) / (a + b + 2) else 1 - front * _beta_fraction(b, a, 1 - x) / b


def t_quantile(two_sided: float, df: float) -> float:
    lo, hi = 0.0, 1.0
    while t_tail(hi, df) > two_sided:
        hi *= 2
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if t_tail(mid, df) > two_sided else (lo, mid)
    return (lo + hi) / 2


def bonferroni_outliers(runs: DataFrame, x: str = "nodes", y: str = "minutes", alpha: float = 0.05) -> DataFrame:
    """Every run with its externally studentised residual and whether it passes the cut-off t(alpha / n, n - 3), both sides."""
    s = runs.agg(F.count("*").alias("n"), F.avg(x).alias("mx"), F.regr_sxx(y, x).alias("sxx"), F.regr_slope(y, x).alias("b"), F.regr_intercept(y, x).alias("a"), F.regr_syy(y, x).alias("syy"), F.regr_sxy(y, x).alias("sxy")).first()
    cut = t_quantile(alpha / s.n, s.n - 3)
    sse = s.syy - s.sxy**2 / s.sxx
    e = F.col(y) - s.a - s.b * F.col(x)
    h = 1 / s.n + (F.col(x) - s.mx) * (F.col(x) - s.mx) / s.sxx
    loo = (F.lit(sse) - e * e / (1 - h)) / (s.n - 3)
    t = e / F.sqrt(F.greatest(loo, F.lit(1e-12)) * (1 - h))
    return runs.select("*", F.round(t, 4).alias("t_resid"), (F.abs(t) > cut).alias("outlier"))


def speedup(runs: DataFrame, x: str = "nodes", y: str = "minutes") -> DataFrame:
    base = F.broadcast(runs.agg(F.min(F.struct(x, y)).alias("b")).select(F.col(f"b.{x}").alias("n1"), F.col(f"b.{y}").alias("t1")))
    return runs.crossJoin(base).select(x, y, F.round(F.col("t1") / F.col(y), 6).alias("speedup"), F.round(F.col("t1") / F.col(y) * F.col("n1") / F.col(x), 6).alias("efficiency"))


def plan_facts(df: DataFrame) -> dict[str, int]:
    """What the executed plan holds: exchanges, joins, Python nodes, pushed filters."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return {k: text.count(k) for k in ("Exchange", "BroadcastHashJoin", "SortMergeJoin", "BroadcastNestedLoopJoin", "CartesianProduct", "HashAggregate", "MapInArrow", "BatchEvalPython", "ArrowEvalPython", "TakeOrderedAndProject", "WindowGroupLimit", "EqualTo", "StringStartsWith")}


def volumes(df: DataFrame, raw_bytes_per_row: int, by: list[Column | str]) -> DataFrame:
    """Raw bytes and descriptor bytes by group and their ratio."""
    return df.groupBy(*by).agg((F.count("*") * raw_bytes_per_row).alias("raw_bytes"))
