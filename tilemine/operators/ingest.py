"""Ingestion in batch form: crawling, the task queue, leases, scaling policies, choice of workers."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

HREF = r'href="([^"]+)"'


def discover(pages: DataFrame, known: DataFrame | None = None) -> DataFrame:
    """Pointers found in pages that are not known yet: (url, found_on), the smallest page that links there."""
    found = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit(HREF), 1)).alias("url")).groupBy("url").agg(F.min("page_id").alias("found_on"))
    return found.join(known.select("url"), "url", "left_anti") if known is not None else found


def tasks(events: DataFrame, factor: float = 10.0) -> DataFrame:
    """(task_id, arrived, service_s, fails_first): every event is a product pointer found at its time."""
    return events.select(F.col("event_id").alias("task_id"), F.col("ts").alias("arrived"), (F.col("value") * factor).alias("service_s"), (F.col("event_type") == "error").alias("fails_first"))


def seconds(column: Column) -> Column:
    """Whole seconds since 1970 of a timestamp without time zone, the same in every session."""
    return F.timestamp_diff("SECOND", F.expr("TIMESTAMP_NTZ '1970-01-01 00:00:00'"), column)


def depth(queue: DataFrame, bucket_s: int = 3600) -> DataFrame:
    """(bucket, arrived, finished, depth) when each task is served at once: tasks open at the end of each bucket.
    Events are summed by bucket first; the running sum goes over the few buckets."""
    steps = queue.select(F.floor(seconds(F.col("arrived")) / bucket_s).alias("bucket"), F.lit(1).alias("d")).unionByName(
        queue.select(F.floor((seconds(F.col("arrived")) + F.ceil("service_s")) / bucket_s).alias("bucket"), F.lit(-1).alias("d"))
    )
    per = steps.groupBy("bucket").agg(F.count_if(F.col("d") > 0).alias("arrived"), F.count_if(F.col("d") < 0).alias("finished"))
    return per.withColumn("depth", F.sum(F.col("arrived") - F.col("finished")).over(Window.orderBy("bucket")))


def lease_replay(queue: DataFrame, timeout_s: int = 1000, max_attempts: int = 3) -> DataFrame:
    """(task_id, attempt, leased_s, outcome): an attempt that fails or outlasts the lease leaves the task visible again after the timeout."""
    ends = F.col("service_s") <= timeout_s
    good = F.when(ends & ~F.col("fails_first"), 1).when(ends, 2)
    tries = F.least(F.coalesce(good, F.lit(max_attempts)), F.lit(max_attempts))
    rows = queue.select("task_id", seconds(F.col("arrived")).alias("at"), good.alias("good"), F.explode(F.sequence(F.lit(1), tries)).alias("attempt"))
    outcome = F.when(F.col("attempt") == F.col("good"), "done").when(F.col("attempt") == max_attempts, "given up").otherwise("visible again")
    return rows.select("task_id", "attempt", (F.col("at") + (F.col("attempt") - 1) * timeout_s).alias("leased_s"), outcome.alias("outcome"))


def report(queue: DataFrame, timeout_s: int = 1000, max_attempts: int = 3) -> DataFrame:
    """Deliveries, repeated deliveries, tasks done and given up, busy hours."""
    runs = lease_replay(queue, timeout_s, max_attempts)
    out = runs.agg(F.count("*").alias("deliveries"), F.count_if(F.col("attempt") > 1).alias("redeliveries"), F.count_if(F.col("outcome") == "done").alias("done"), F.count_if(F.col("outcome") == "given up").alias("given_up"))
    hours = queue.agg(F.round(F.sum(F.least(F.col("service_s"), F.lit(float(timeout_s)))) / 3600, 2).alias("busy_hours"))
    return out.crossJoin(hours)


def load(queue: DataFrame, bucket_s: int = 3600) -> DataFrame:
    """(bucket, tasks, work_s): arriving work by bucket."""
    return queue.groupBy(F.floor(seconds(F.col("arrived")) / bucket_s).alias("bucket")).agg(F.count("*").alias("tasks"), F.sum(F.ceil("service_s")).cast("long").alias("work_s"))


def by_queue(queue_depth: DataFrame, per_worker: int = 2, lo: int = 1, hi: int = 8) -> DataFrame:
    """Workers wanted by queue length."""
    return queue_depth.withColumn("workers", F.greatest(F.lit(lo), F.least(F.lit(hi), F.ceil(F.col("depth") / per_worker))).cast("int"))


def served(queue: DataFrame, workers: int = 4) -> DataFrame:
    """(task_id, worker, arrived_s, started_s, finished_s, wait_s): each worker takes its tasks (dealt by id) in order of arrival and one at a
    time, so tasks wait.  The k-th finish is the greatest, over all tasks before, of its arrival plus all service since, which a
    running maximum gives: one shuffle by worker, no loop."""
    rows = queue.select("task_id", F.pmod("task_id", F.lit(workers)).alias("worker"), seconds(F.col("arrived")).alias("arrived_s"), F.ceil("service_s").cast("long").alias("work"))
    order = Window.partitionBy("worker").orderBy("arrived_s", "task_id")
    done = rows.withColumn("sum", F.sum("work").over(order))
    done = done.withColumn("finished_s", F.col("sum") + F.max(F.col("arrived_s") - F.col("sum") + F.col("work")).over(order))
    started = F.col("finished_s") - F.col("work")
    return done.select("task_id", "worker", "arrived_s", started.alias("started_s"), "finished_s", (started - F.col("arrived_s")).alias("wait_s"))


def waits(tasks_served: DataFrame) -> DataFrame:
    """Tasks, mean and greatest wait, share that waited, busy share of the workers' time, tasks an hour."""
    span = F.max("finished_s") - F.min("arrived_s")
    return tasks_served.agg(
        F.count("*").alias("tasks"), F.round(F.avg("wait_s"), 6).alias("mean_wait_s"), F.max("wait_s").alias("max_wait_s"), F.round(F.avg((F.col("wait_s") > 0).cast("double")), 6).alias("waited"),
        F.round(F.sum(F.col("finished_s") - F.col("started_s")) / (span * F.countDistinct("worker")), 6).alias("utilisation"), F.round(F.count("*") * 3600 / span, 6).alias("tasks_per_hour"),
    )


def every_bucket(work: DataFrame) -> DataFrame:
    """The work with the buckets in between that have none."""
    ends = work.agg(F.min("bucket").alias("a"), F.max("bucket").alias("b")).where("a IS NOT NULL")
    return ends.select(F.explode(F.sequence("a", "b")).alias("bucket")).join(work, "bucket", "left").na.fill(0, ["tasks", "work_s"])


def by_feedback(work: DataFrame, workers: int = 2, target: tuple[int, int] = (4, 5), lo: int = 1, hi: int = 8, bucket_s: int = 3600) -> DataFrame:
    """(bucket, tasks, work_s, workers, backlog_s, wait_s, utilisation): a queue whose workers follow the measured utilisation.  What the workers
    of a bucket can't do stays in the queue; the next bucket has as many workers as would have been used to ``target``.  Each bucket depends on
    the one before, so one task goes through the buckets, of which there are few at any number of tasks."""
    part, of = target

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, backlog = workers, 0
        for batch in batches:
            out = []
            for bucket, tasks, work_s in zip(*(c.to_pylist() for c in batch.columns)):
                capacity, asked = now * bucket_s, backlog + work_s
                used, backlog = min(asked, capacity), max(0, asked - capacity)
                out.append((bucket, tasks, work_s, now, backlog, -(-backlog // now), round(used / capacity, 6)))
                now = max(lo, min(hi, -(-of * used // (part * bucket_s))))
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*out)] if out else [pa.array([]) for _ in range(7)], names=["bucket", "tasks", "work_s", "workers", "backlog_s", "wait_s", "utilisation"])

    buckets = every_bucket(work).select("bucket", "tasks", "work_s").repartition(1).sortWithinPartitions("bucket")
    return buckets.mapInArrow(run, "bucket long, tasks long, work_s long, workers long, backlog_s long, wait_s long, utilisation double").withColumn("workers", F.col("workers").cast("int"))


def by_cost(work: DataFrame, open_from: int = 8, open_to: int = 20, workers: int = 4, budget: int = 1000) -> DataFrame:
    """Intermittent service: no workers outside opening hours or when the worker-hours are used up."""
    hour = (F.col("bucket") % 24).cast("int")
    wanted = F.when((hour >= open_from) & (hour < open_to), workers).otherwise(0)
    spent = F.sum("wanted").over(Window.orderBy("bucket"))
    return work.withColumn("wanted", wanted).withColumn("spent", spent).select("bucket", "work_s", F.when(F.col("spent") <= budget, F.col("wanted")).otherwise(0).cast("int").alias("workers"))


#: Worker types of the evaluation: id, clock GHz, cache MB, vCPU, memory GB, bandwidth Mbps; the last, an hourly rate, is invented.
TYPES = [
    ("m1.small", 1.80, 30, 1, 1.70, 300, 0.05),
    ("m1.medium", 2.00, 20, 1, 3.75, 850, 0.10),
    ("m1.large", 1.80, 30, 2, 7.50, 850, 0.20),
    ("m1.xlarge", 1.80, 30, 4, 15.00, 1000, 0.40),
    ("c1.medium", 1.80, 30, 2, 1.70, 850, 0.12),
    ("c1.xlarge", 2.00, 20, 8, 7.00, 1000, 0.58),
]


def worker_types(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(TYPES, "id string, ghz double, cache_mb int, vcpu int, mem_gb double, net_mbps int, rate double")


def choose_type(work: DataFrame, types: DataFrame, cpu_s_per_hour: int = 3600) -> DataFrame:
    """The cheapest type and number for each bucket's work; few types, sent to every task."""
    pairs = work.crossJoin(F.broadcast(types.select("id", "vcpu", "rate"))).withColumn("count", F.greatest(F.lit(1), F.ceil(F.col("work_s") / (F.col("vcpu") * cpu_s_per_hour))).cast("int"))
    best = F.min(F.struct(F.round(F.col("count") * F.col("rate"), 4).alias("cost"), "id", "count"))
    return pairs.groupBy("bucket", "work_s").agg(best.alias("x")).select("bucket", "work_s", F.col("x.id").alias("type"), F.col("x.count").alias("workers"), F.col("x.cost").alias("cost"))
