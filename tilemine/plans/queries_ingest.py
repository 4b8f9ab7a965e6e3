"""Queries over the task queue, crawling, scaling policies and run measurements, with their SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, functions as F

from tilemine.operators import ingest, measures
from tilemine.sources import storage
from tilemine.sources.archives import LETTERS, table
from tilemine.streaming import live


def _tasks(spark: SparkSession, d: str) -> DataFrame:
    return ingest.tasks(table(spark, d, "events"))


def q01_crawl(spark: SparkSession, d: str) -> DataFrame:
    pages = table(spark, d, "pages")
    return ingest.discover(pages, pages.select("url"))


def q02_polling(spark: SparkSession, d: str) -> DataFrame:
    """Pages that arrive as a stream of micro-batches: every pointer is found once."""
    source, target, checkpoint = (storage.new_folder(spark, f"crawl-{x}") for x in ("source", "target", "checkpoint"))
    pages = table(spark, d, "pages").select("page_id", "html", F.expr("TIMESTAMP '2024-01-01 00:00:00'").alias("ts"))
    pages.repartition(3, "page_id").write.parquet(source)
    found = live.crawl_stream(live.event_stream(spark, source, "page_id long, html string, ts timestamp"))
    found.writeStream.format("parquet").option("path", target).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("url string").parquet(target)


def q155_hourly_stream(spark: SparkSession, d: str) -> DataFrame:
    """Events that arrive as a stream, by hour: the windows of the batch."""
    source = storage.new_folder(spark, "events-source")
    table(spark, d, "events").select("ts", "value").repartition(3).write.parquet(source)
    windows, name = live.hourly(live.event_stream(spark, source, "ts timestamp_ntz, value double"), "30 days"), f"hourly_{uuid.uuid4().hex}"
    windows.writeStream.format("memory").queryName(name).outputMode("complete").trigger(availableNow=True).start().awaitTermination()
    return spark.table(name).select(F.date_format("start", "yyyy-MM-dd HH").alias("hour"), "n", F.round("work", 4).alias("work"))


def q02_queue_depth(spark: SparkSession, d: str) -> DataFrame:
    return ingest.depth(_tasks(spark, d))


def q02_queue_report(spark: SparkSession, d: str) -> DataFrame:
    return ingest.report(_tasks(spark, d))


def q02_served(spark: SparkSession, d: str) -> DataFrame:
    """Four workers, one task at a time each: when tasks start and end and how long they wait."""
    return ingest.served(_peak(spark, d), 4)


def q02_waits(spark: SparkSession, d: str) -> DataFrame:
    return ingest.waits(ingest.served(_peak(spark, d), 4))


def _peak(spark: SparkSession, d: str) -> DataFrame:
    """Tasks ten times as long as usual, so that the workers are short of time."""
    return ingest.tasks(table(spark, d, "events"), 100.0)


def q05_feedback_under_load(spark: SparkSession, d: str) -> DataFrame:
    """The same policy where the work is more than the first workers can do."""
    return ingest.by_feedback(ingest.load(_peak(spark, d)))


def q03_leases(spark: SparkSession, d: str) -> DataFrame:
    return ingest.lease_replay(_tasks(spark, d))


def q04_scale_by_queue(spark: SparkSession, d: str) -> DataFrame:
    return ingest.by_queue(ingest.depth(_tasks(spark, d)))


def q05_scale_by_feedback(spark: SparkSession, d: str) -> DataFrame:
    return ingest.by_feedback(ingest.load(_tasks(spark, d)))


def q06_scale_by_cost(spark: SparkSession, d: str) -> DataFrame:
    return ingest.by_cost(ingest.load(_tasks(spark, d)))


def q07_choose_workers(spark: SparkSession, d: str) -> DataFrame:
    return ingest.choose_type(ingest.load(_tasks(spark, d)), ingest.worker_types(spark))


def q07_peak_load(spark: SparkSession, d: str) -> DataFrame:
    """A new archive arrives at once, then nothing: the same tasks with all arrivals in the first hour."""
    events = table(spark, d, "events").withColumn("ts", F.expr("make_timestamp_ntz(2024, 1, 1, 0, 0, 0)"))
    return ingest.by_queue(ingest.depth(ingest.tasks(events)), per_worker=100)


def q160_map(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


def q161_reduce(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("quantity"), F.min("l_extendedprice").alias("least"), F.max("l_extendedprice").alias("most"))


def q162_map_reduce(spark: SparkSession, d: str) -> DataFrame:
    letters = F.filter(F.split(F.lower("text"), ""), lambda c: F.contains(F.lit(LETTERS), c))
    return table(spark, d, "documents").select(F.explode(letters).alias("letter")).where("letter <> ''").groupBy("letter").agg(F.count("*").alias("n"))


def runs(spark: SparkSession, d: str) -> DataFrame:
    """A deterministic table of runs: line numbers as node counts, quantities as minutes."""
    line = table(spark, d, "lineitem").groupBy(F.col("l_linenumber").alias("nodes")).agg((F.sum(F.col("l_quantity").cast("long")) / 1000).alias("minutes"))
    return line.select(F.concat(F.lit("n"), F.col("nodes").cast("string")).alias("config"), F.col("nodes").cast("int").alias("nodes"), "minutes", F.lit(0.1).alias("rate"))


def q75_relative_cost(spark: SparkSession, d: str) -> DataFrame:
    return measures.relative(runs(spark, d), "n2")


def q75_relative_run_cost(spark: SparkSession, d: str) -> DataFrame:
    return measures.relative(runs(spark, d), "n2", "run")


def q76_tradeoff(spark: SparkSession, d: str) -> DataFrame:
    return measures.tradeoff(measures.relative(runs(spark, d), "n2"))


def q77_linear_fit(spark: SparkSession, d: str) -> DataFrame:
    return measures.fit(runs(spark, d))


def q78_outliers(spark: SparkSession, d: str) -> DataFrame:
    return measures.bonferroni_outliers(runs(spark, d)).select("config", "t_resid", "outlier")


def q79_speedup(spark: SparkSession, d: str) -> DataFrame:
    return measures.speedup(runs(spark, d))


def q84_volumes(spark: SparkSession, d: str) -> DataFrame:
    """Raw bytes (64 a pixel) and descriptor bytes (4 a bin, 512 bins) of each product's tiles of 8 x 8."""
    n = table(spark, d, "lineitem").groupBy(F.col("l_suppkey").alias("product_id")).agg(F.count("*").alias("n"))
    rows = F.ceil(F.col("n") / 32)
    return n.select("product_id", (F.col("n") * 64).alias("raw_bytes"), (F.ceil(rows / 8) * 4 * 2048).cast("long").alias("descriptor_bytes_at_most"))


QUERIES = {f.__name__: f for f in (q01_crawl, q02_polling, q155_hourly_stream, q02_queue_depth, q02_queue_report, q02_served, q02_waits, q03_leases, q04_scale_by_queue, q05_scale_by_feedback, q05_feedback_under_load, q06_scale_by_cost, q07_choose_workers, q07_peak_load, q160_map, q161_reduce, q162_map_reduce, q75_relative_cost, q75_relative_run_cost, q76_tradeoff, q77_linear_fit, q78_outliers, q79_speedup, q84_volumes)}

_TASKS = "t AS (SELECT event_id AS task_id, CAST(floor(epoch(ts)) AS BIGINT) AS s, value * 10.0::DOUBLE AS v, event_type = 'error' AS f FROM events)"
_DEPTH = """steps AS (SELECT s // 3600 AS bucket, 1 AS d FROM t UNION ALL SELECT CAST((s + ceil(v)) AS BIGINT) // 3600, -1 FROM t),
per AS (SELECT bucket, count(*) FILTER (d > 0) AS arrived, count(*) FILTER (d < 0) AS finished FROM steps GROUP BY bucket),
q AS (SELECT *, CAST(sum(arrived - finished) OVER (ORDER BY bucket) AS BIGINT) AS depth FROM per)"""
_LOAD = "w AS (SELECT s // 3600 AS bucket, count(*) AS tasks, CAST(sum(ceil(v)) AS BIGINT) AS work_s FROM t GROUP BY 1)"
_PEAK = _TASKS.replace("10.0", "100.0")
_SERVED = "o AS (SELECT task_id, task_id % 4 AS worker, s AS arrived_s, CAST(ceil(v) AS BIGINT) AS work FROM t), c AS (SELECT *, CAST(sum(work) OVER (PARTITION BY worker ORDER BY arrived_s, task_id) AS BIGINT) AS sum FROM o), e AS (SELECT *, sum + max(arrived_s - sum + work) OVER (PARTITION BY worker ORDER BY arrived_s, task_id) AS finished_s FROM c), served AS (SELECT task_id, worker, arrived_s, finished_s - work AS started_s, finished_s, finished_s - work - arrived_s AS wait_s FROM e)"
_FEED = """h AS (SELECT CAST(b AS BIGINT) AS bucket, coalesce(tasks, 0) AS tasks, coalesce(work_s, 0) AS work_s FROM unnest(generate_series((SELECT min(bucket) FROM w), (SELECT max(bucket) FROM w))) AS g(b) LEFT JOIN w ON w.bucket = b),
f AS (SELECT bucket, tasks, work_s, CAST(2 AS BIGINT) AS workers, greatest(0, work_s - 7200) AS backlog_s, least(work_s, 7200) AS used FROM h WHERE bucket = (SELECT min(bucket) FROM h)
UNION ALL SELECT bucket, tasks, work_s, n, greatest(0, backlog_s + work_s - n * 3600), least(backlog_s + work_s, n * 3600) FROM (SELECT h.bucket, h.tasks, h.work_s, f.backlog_s, CAST(greatest(1, least(8, (5 * f.used + 14399) // 14400)) AS BIGINT) AS n FROM f JOIN h ON h.bucket = f.bucket + 1))"""
_FED = "SELECT bucket, tasks, work_s, CAST(workers AS INTEGER) AS workers, backlog_s, (backlog_s + workers - 1) // workers AS wait_s, round(used / (workers * 3600.0::DOUBLE), 6) AS utilisation FROM f"
_LEASE = """r AS (SELECT task_id, s, v, CASE WHEN v <= 1000 AND NOT f THEN 1 WHEN v <= 1000 THEN 2 END AS good FROM t),
l AS (SELECT task_id, CAST(i AS INTEGER) AS attempt, s + (i - 1) * 1000 AS leased_s, CASE WHEN i = good THEN 'done' WHEN i = 3 THEN 'given up' ELSE 'visible again' END AS outcome FROM r, unnest(generate_series(1, least(coalesce(good, 3), 3))) AS g(i))"""
_TYPES = "k(id, vcpu, rate) AS (VALUES " + ", ".join(f"('{t[0]}', {t[3]}, {t[6]}::DOUBLE)" for t in ingest.TYPES) + ")"
_RUNS = "r AS (SELECT 'n' || l_linenumber AS config, CAST(l_linenumber AS INTEGER) AS nodes, CAST(sum(l_quantity) AS BIGINT) / 1000 AS minutes, 0.1::DOUBLE AS rate FROM lineitem GROUP BY l_linenumber)"


def _rel(cost: str) -> str:
    return f"{_RUNS}, c AS (SELECT *, {cost} AS cost FROM r), z AS (SELECT minutes AS m0, cost AS c0 FROM c WHERE config = 'n2'), rel AS (SELECT config, nodes, minutes, round((m0 - minutes) / m0 * 100, 6) AS time_gain_pct, round((cost - c0) / c0 * 100, 6) AS cost_change_pct FROM c, z)"


SQL = {
    "q01_crawl": """WITH l AS (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS url FROM pages) SELECT url, min(page_id) AS found_on FROM l WHERE url NOT IN (SELECT url FROM pages) GROUP BY url""",
    "q02_polling": """SELECT DISTINCT unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS url FROM pages""",
    "q155_hourly_stream": "SELECT strftime(ts, '%Y-%m-%d %H') AS hour, count(*) AS n, round(sum(value), 4) AS work FROM events GROUP BY 1",
    "q02_queue_depth": f"WITH {_TASKS}, {_DEPTH} SELECT * FROM q",
    "q02_queue_report": f"WITH {_TASKS}, {_LEASE} SELECT count(*) AS deliveries, count(*) FILTER (attempt > 1) AS redeliveries, count(*) FILTER (outcome = 'done') AS done, count(*) FILTER (outcome = 'given up') AS given_up, (SELECT round(sum(least(v, 1000)) / 3600, 2) FROM t) AS busy_hours FROM l",
    "q03_leases": f"WITH {_TASKS}, {_LEASE} SELECT * FROM l",
    "q04_scale_by_queue": f"WITH {_TASKS}, {_DEPTH} SELECT *, CAST(greatest(1, least(8, ceil(depth / 2.0))) AS INTEGER) AS workers FROM q",
    "q02_served": f"WITH {_PEAK}, {_SERVED} SELECT * FROM served",
    "q02_waits": f"WITH {_PEAK}, {_SERVED} SELECT count(*) AS tasks, round(avg(wait_s), 6) AS mean_wait_s, max(wait_s) AS max_wait_s, round(avg(CAST(wait_s > 0 AS DOUBLE)), 6) AS waited, round(sum(finished_s - started_s) / ((max(finished_s) - min(arrived_s)) * count(DISTINCT worker)), 6) AS utilisation, round(count(*) * 3600 / (max(finished_s) - min(arrived_s)), 6) AS tasks_per_hour FROM served",
    "q05_scale_by_feedback": f"WITH RECURSIVE {_TASKS}, {_LOAD}, {_FEED} {_FED}",
    "q05_feedback_under_load": f"WITH RECURSIVE {_PEAK}, {_LOAD}, {_FEED} {_FED}",
    "q06_scale_by_cost": f"WITH {_TASKS}, {_LOAD}, x AS (SELECT *, CASE WHEN bucket % 24 >= 8 AND bucket % 24 < 20 THEN 4 ELSE 0 END AS wanted FROM w), y AS (SELECT *, sum(wanted) OVER (ORDER BY bucket) AS spent FROM x) SELECT bucket, work_s, CAST(CASE WHEN spent <= 1000 THEN wanted ELSE 0 END AS INTEGER) AS workers FROM y",
    "q07_choose_workers": f"WITH {_TASKS}, {_LOAD}, {_TYPES}, p AS (SELECT bucket, work_s, id, rate, CAST(greatest(1, ceil(work_s / (vcpu * 3600.0::DOUBLE))) AS INTEGER) AS workers FROM w, k), o AS (SELECT *, round(workers * rate, 4) AS cost, row_number() OVER (PARTITION BY bucket ORDER BY round(workers * rate, 4), id) AS n FROM p) SELECT bucket, work_s, id AS type, workers, cost FROM o WHERE n = 1",
    "q07_peak_load": f"WITH t AS (SELECT CAST(epoch(TIMESTAMP '2024-01-01') AS BIGINT) AS s, value * 10.0::DOUBLE AS v FROM events), {_DEPTH} SELECT *, CAST(greatest(1, least(8, ceil(depth / 100.0))) AS INTEGER) AS workers FROM q",
    "q160_map": "SELECT l_orderkey, l_linenumber, l_partkey, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem",
    "q161_reduce": "SELECT count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS quantity, min(l_extendedprice) AS least, max(l_extendedprice) AS most FROM lineitem",
    "q162_map_reduce": f"WITH c AS (SELECT unnest(string_split(lower(text), '')) AS letter FROM documents) SELECT letter, count(*) AS n FROM c WHERE letter <> '' AND contains('{LETTERS}', letter) GROUP BY letter",
    "q75_relative_cost": f"WITH {_rel('nodes * rate')} SELECT * FROM rel",
    "q75_relative_run_cost": f"WITH {_rel('nodes * rate * minutes / 60')} SELECT * FROM rel",
    "q76_tradeoff": f"WITH {_rel('nodes * rate')}, t AS (SELECT config, round(time_gain_pct - cost_change_pct, 6) AS tradeoff FROM rel) SELECT config, tradeoff, tradeoff > 0 AS beneficial, config = (SELECT config FROM t ORDER BY tradeoff DESC, config DESC LIMIT 1) AS is_best FROM t",
    "q77_linear_fit": f"WITH {_RUNS} SELECT round(regr_slope(minutes, nodes), 6) AS slope, round(regr_intercept(minutes, nodes), 6) AS intercept, round(regr_r2(minutes, nodes), 6) AS r2, count(*) AS n FROM r",
    "q79_speedup": f"WITH {_RUNS}, b AS (SELECT nodes AS n1, minutes AS t1 FROM r ORDER BY nodes LIMIT 1) SELECT nodes, minutes, round(t1 / minutes, 6) AS speedup, round(t1 / minutes * n1 / nodes, 6) AS efficiency FROM r, b",
    "q84_volumes": "SELECT l_suppkey AS product_id, count(*) * 64 AS raw_bytes, CAST(ceil(ceil(count(*) / 32.0) / 8.0) * 8192 AS BIGINT) AS descriptor_bytes_at_most FROM lineitem GROUP BY 1",
    "q78_outliers": f"""WITH {_RUNS}, s AS (SELECT count(*) AS n, avg(nodes) AS mx, regr_sxx(minutes, nodes) AS sxx, regr_slope(minutes, nodes) AS b, regr_intercept(minutes, nodes) AS a, regr_syy(minutes, nodes) - regr_sxy(minutes, nodes) ** 2 / regr_sxx(minutes, nodes) AS sse FROM r),
      e AS (SELECT config, n, minutes - a - b * nodes AS e, 1.0 / n + (nodes - mx) ** 2 / sxx AS h, sse FROM r, s), t AS (SELECT config, e / sqrt(greatest((sse - e * e / (1 - h)) / (n - 3), 1e-12) * (1 - h)) AS t FROM e)
      SELECT config, round(t, 4) AS t_resid, abs(t) > {measures.t_quantile(0.05 / 7, 4)} AS outlier FROM t""",
}
