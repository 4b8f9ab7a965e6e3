import math

import numpy as np
from pyspark.sql import functions as F

from tilemine.operators import ingest, measures


def queue(spark, rows):
    return spark.createDataFrame(rows, "task_id long, t string, service_s double, fails_first boolean").select("task_id", F.col("t").cast("timestamp_ntz").alias("arrived"), "service_s", "fails_first")


def test_lease_that_never_completes(spark):
    rows = ingest.lease_replay(queue(spark, [(1, "1970-01-01 00:00:00", 1500.0, False), (2, "1970-01-01 00:00:05", 10.0, True), (3, "1970-01-01 00:00:07", 10.0, False)]), 1000, 3).collect()
    assert sorted((r.task_id, r.attempt, r.leased_s, r.outcome) for r in rows) == [(1, 1, 0, "visible again"), (1, 2, 1000, "visible again"), (1, 3, 2000, "given up"), (2, 1, 5, "visible again"), (2, 2, 1005, "done"), (3, 1, 7, "done")]


def test_depth_ends_at_zero(spark):
    rows = ingest.depth(queue(spark, [(i, f"1970-01-01 0{i}:30:00", 4000.0, False) for i in range(5)])).orderBy("bucket").collect()
    assert rows[-1].depth == 0 and max(r.depth for r in rows) >= 1


def test_discover_leaves_known_pointers_out(spark):
    pages = spark.createDataFrame([(1, '<a href="/x">'), (2, '<a href="/x"><a href="/y">'), (3, None)], "page_id long, html string")
    assert sorted(map(tuple, ingest.discover(pages).collect())) == [("/x", 1), ("/y", 2)]
    assert [r.url for r in ingest.discover(pages, spark.createDataFrame([("/x",)], "url string")).collect()] == ["/y"]


def runs(spark, rows):
    return spark.createDataFrame([(f"n{n}", n, float(m), 1.0) for n, m in rows], "config string, nodes int, minutes double, rate double")


def test_cost_of_two_configurations(spark):
    r = runs(spark, [(2, 10), (3, 6)])
    rate, run = ({x.config: x for x in measures.relative(r, "n2", basis).collect()}["n3"] for basis in ("rate", "run"))
    assert (rate.time_gain_pct, rate.cost_change_pct) == (40, 50) and (run.time_gain_pct, run.cost_change_pct) == (40, -10)
    best = {x.config: x for x in measures.tradeoff(measures.relative(r, "n2")).collect()}
    assert best["n2"].is_best and not best["n3"].beneficial


def test_line_and_its_outlier(spark):
    clean = runs(spark, [(3, 9), (4, 8), (5, 7), (6, 6)])
    f = measures.fit(clean).first()
    assert (f.slope, f.intercept, f.r2) == (-1, 12, 1)
    noisy = runs(spark, [(1, 40), (2, 11.02), (3, 8.97), (4, 8.01), (5, 7.03), (6, 5.98), (7, 5.01), (8, 3.99)])
    assert [r.config for r in measures.bonferroni_outliers(noisy).collect() if r.outlier] == ["n1"]
    assert [x.efficiency for x in measures.speedup(runs(spark, [(1, 8), (2, 4)])).orderBy("nodes").collect()] == [1, 1]


def test_student_quantiles():
    for p, df, t in ((0.05, 10, 2.228139), (0.01, 4, 4.604095), (0.1, 1, 6.313752), (0.05, 120, 1.979930)):
        assert abs(measures.t_quantile(p, df) - t) < 1e-5


def test_operation_counts():
    ops = measures.kmeans_ops(10, 100, 2, 3, 50)
    assert ops["dense"] == 6000 and ops["sparse"] == 360 and ops["mean_nnz"] == 5


def test_precision_and_agreement(spark):
    res = spark.createDataFrame([(1, 1, 1), (1, 2, 2), (1, 3, 3), (2, 1, 3)], "query_id long, rank int, id long")
    labels = spark.createDataFrame([(1, "a"), (2, "a"), (3, "b")], "id long, label string")
    p = measures.precision_at(res, labels).first()
    assert (p.n_queries, p.n_results, p.n_same) == (2, 3, 1) and math.isclose(p.precision, 1 / 3, abs_tol=1e-6)
    assert {r.query_id: r.jaccard for r in measures.agreement(res, res.where("id <> 2")).collect()} == {1: np.round(2 / 3, 6), 2: 1.0}


def test_timer():
    assert set(measures.timed(lambda: None)) == {"min", "median", "max"}


def test_tasks_wait_for_their_worker(spark):
    rows = [(i, f"2024-01-01 00:00:{(i * 7) % 50:02d}", float(5 + i % 4)) for i in range(40)]
    q = spark.createDataFrame(rows, "task_id long, arrived string, service_s double").withColumn("arrived", F.col("arrived").cast("timestamp_ntz"))
    got = {r.task_id: r for r in ingest.served(q, 3).collect()}
    free = {}
    for i, t, s in sorted(rows, key=lambda r: (r[1], r[0])):
        at = got[i].arrived_s
        begin = max(at, free.get(i % 3, at))
        free[i % 3] = begin + int(s)
        assert (got[i].started_s, got[i].finished_s, got[i].wait_s) == (begin, begin + s, begin - at)
    w = ingest.waits(ingest.served(q, 3)).first()
    assert w.tasks == 40 and w.max_wait_s > 0 and 0 < w.utilisation <= 1


def test_workers_follow_what_was_used(spark):
    work = spark.createDataFrame([(0, 4, 7200), (1, 9, 20000), (2, 1, 100), (6, 1, 3600)], "bucket long, tasks long, work_s long")
    got = [(r.bucket, r.workers, r.backlog_s) for r in ingest.by_feedback(work).orderBy("bucket").collect()]
    assert got == [(0, 2, 0), (1, 3, 9200), (2, 4, 0), (3, 4, 0), (4, 1, 0), (5, 1, 0), (6, 1, 0)]
    assert ingest.by_feedback(work.limit(0)).count() == 0
