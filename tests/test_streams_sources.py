import struct

import numpy as np
from pyspark.sql import functions as F

from tilemine.operators import ingest, tsvq
from tilemine.operators.tsvq import Stop
from tilemine.plans import catalog
from tilemine.sources import archives, connectors, storage
from tilemine.streaming import live


def run(stream, name, mode="append"):
    stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.table(name)


def event_files(spark, sf, tmp_path, shuffled=False):
    """Events in six files in order of time; with late rows, a few go to a later file."""
    e = spark.read.parquet(f"{sf}/events.parquet").withColumn("part", F.ntile(6).over(__import__("pyspark").sql.Window.orderBy("ts")))
    if shuffled:
        e = e.withColumn("part", F.when((F.col("event_id") % 50 == 0) & (F.col("part") < 5), F.col("part") + 2).otherwise(F.col("part")))
    schema = e.drop("part").schema
    for i in range(1, 7):
        e.where(F.col("part") == i).drop("part").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    return f"{tmp_path}/in", schema.simpleString()[7:-1].replace(":", " ")


def test_windows_equal_their_batch_twin(spark, sf, tmp_path):
    folder, schema = event_files(spark, sf, tmp_path)
    got = {r.start: r.n for r in run(live.hourly(live.event_stream(spark, folder, schema)), "hours").collect()}
    e = spark.read.parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))
    want = {r.start: r.n for r in e.groupBy(F.window("ts", "1 hour").start.alias("start")).agg(F.count("*").alias("n")).collect()}
    assert got and all(want[k] == n for k, n in got.items()) and len(want) - len(got) <= 4


def test_late_rows_are_dropped_and_counted_out(spark, sf, tmp_path):
    folder, schema = event_files(spark, sf, tmp_path, shuffled=True)
    got = sum(r.n for r in run(live.hourly(live.event_stream(spark, folder, schema)), "late_hours").collect())
    assert 0 < got < spark.read.parquet(folder).count()


def test_sessions_and_sliding_windows(spark, sf, tmp_path):
    folder, schema = event_files(spark, sf, tmp_path)
    assert run(live.sessions(live.event_stream(spark, folder, schema), "6 hours"), "sessions_").count() > 0
    assert run(live.hourly(live.event_stream(spark, folder, schema), slide="30 minutes"), "sliding_").count() > 0


def test_crawl_stream_finds_each_pointer_once(spark, tmp_path):
    pages = spark.createDataFrame([(i, f'<a href="/p{i % 3}">', f"2024-01-01 00:0{i}:00") for i in range(6)], "page_id long, html string, ts string").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    for i in range(0, 6, 2):
        pages.where(F.col("page_id").between(i, i + 1)).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    found = run(live.crawl_stream(live.event_stream(spark, f"{tmp_path}/in", "page_id long, html string, ts timestamp_ntz")), "crawled")
    assert sorted(r.url for r in found.collect()) == ["/p0", "/p1", "/p2"]


def test_leases_expire_and_complete(spark, tmp_path):
    rows = [(1, "2024-01-01 00:00:00", "task"), (2, "2024-01-01 00:00:10", "task"), (2, "2024-01-01 00:05:00", "done"), (9, "2024-01-01 01:00:00", "task"), (9, "2024-01-01 01:00:01", "done"), (8, "2024-01-01 03:00:00", "task"), (8, "2024-01-01 03:00:01", "done")]
    m = spark.createDataFrame(rows, "task_id long, t string, kind string").select("task_id", F.col("t").cast("timestamp_ntz").alias("ts"), "kind")
    for lo, hi in ((0, 1), (1, 2), (2, 4)):
        m.where((F.hour("ts") >= lo) & (F.hour("ts") < hi)).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    out = run(live.lease_stream(live.event_stream(spark, f"{tmp_path}/in", "task_id long, ts timestamp_ntz, kind string")), "leases").collect()
    told = {}
    for r in sorted(out, key=lambda r: (r.at_s, r.attempt)):
        told.setdefault(r.task_id, []).append(r.outcome)
    assert told[2] == ["leased", "done"] and told[1][0] == "leased" and told[1][1] == "leased again"


def test_early_completions_wait_for_their_task_and_state_ends(spark, tmp_path):
    rows = [(1, "2024-01-01 00:00:05", "done"), (1, "2024-01-01 00:00:07", "task"), (2, "2024-01-01 00:00:05", "task"), (2, "2024-01-01 00:00:09", "done"), (2, "2024-01-01 00:00:30", "task"), (9, "2024-01-01 01:00:00", "task"), (9, "2024-01-01 01:00:01", "done"), (8, "2024-01-01 02:00:00", "task"), (8, "2024-01-01 02:00:01", "done"), (2, "2024-01-01 03:00:00", "task"), (2, "2024-01-01 03:00:05", "done")]
    m = spark.createDataFrame(rows, "task_id long, t string, kind string").select("task_id", F.col("t").cast("timestamp_ntz").alias("ts"), "kind")
    for hour in range(4):
        m.where(F.hour("ts") == hour).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    out = run(live.lease_stream(live.event_stream(spark, f"{tmp_path}/in", "task_id long, ts timestamp_ntz, kind string")), "early").collect()
    told = {}
    for r in sorted(out, key=lambda r: (r.at_s, r.outcome == "done")):
        told.setdefault(r.task_id, []).append(r.outcome)
    assert told[1] == ["leased", "done"]  # its completion came first
    assert told[2] == ["leased", "done", "leased", "done"]  # a repeated message at once starts nothing, one after the state has gone does


def test_completions_within_their_lease(spark, tmp_path):
    tasks = spark.createDataFrame([(1, "2024-01-01 00:00:00"), (2, "2024-01-01 00:00:00")], "task_id long, ts string").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    done = spark.createDataFrame([(1, "2024-01-01 00:10:00"), (2, "2024-01-01 00:40:00")], "task_id long, ts string").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    tasks.coalesce(1).write.parquet(f"{tmp_path}/a")
    done.coalesce(1).write.parquet(f"{tmp_path}/b")
    schema = "task_id long, ts timestamp_ntz"
    joined = live.completions_in_lease(live.event_stream(spark, f"{tmp_path}/a", schema), live.event_stream(spark, f"{tmp_path}/b", schema).withColumnRenamed("ts", "done_at"))
    assert [r.task_id for r in run(joined, "in_lease").collect()] == [1]


def test_live_index_and_restart(spark, sf, tmp_path):
    all_ = archives.vec_embeddings(spark, sf).select("id", "v")
    index = tsvq.grow(all_.where("id % 2 = 0"), Stop(n_min=60))
    new = all_.where("id % 2 = 1")
    for part in (1, 3):
        new.where(F.col("id") % 4 == part).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        stream = live.event_stream(spark, f"{tmp_path}/in", "id long, v array<double>")
        live.live_index(stream, index, f"{tmp_path}/out", f"{tmp_path}/checkpoint").awaitTermination()
    grown = live.with_live(index, spark, f"{tmp_path}/out")
    assert grown.nodes[""].n == all_.count() and grown.labelled.count() == all_.count()
    bulk = {r.id: r.code for r in tsvq.descend(tsvq.prepare(all_), index.nodes).collect()}
    assert {r.id: r.code for r in grown.labelled.collect()} == bulk


def test_raster_and_queue_sources(spark):
    connectors.register(spark)
    px = spark.read.format("polraster").option("products", 2).option("rows", 20).option("cols", 5).load()
    assert px.count() == 200 and px.rdd.getNumPartitions() == 4
    q = spark.readStream.format("taskqueue").option("total", 25).load()
    query = q.writeStream.format("memory").queryName("queue_").start()
    try:
        for _ in range(60):
            query.processAllAvailable()
            if spark.table("queue_").count() == 25:
                break
    finally:
        query.stop()
    assert spark.table("queue_").count() == 25 and spark.table("queue_").distinct().count() == 25


def test_binary_rasters_and_foreign_files(spark, sf, tmp_path):
    values = np.arange(2 * 3 * 8, dtype=float)
    (tmp_path / "scene_7.bin").write_bytes(struct.pack(f"<{len(values)}d", *values))
    px = connectors.rasters_of_files(spark, f"file://{tmp_path}/*.bin", 3)
    assert px.count() == 6 and px.where("row = 1 AND col = 2").first().vv_im == 47 and px.first().product_id == 7
    nation = spark.read.parquet(f"{sf}/nation.parquet")
    for kind in ("csv", "json", "orc", "parquet"):
        writer = nation.write.format(kind)
        (writer.option("header", True) if kind == "csv" else writer).save(f"{tmp_path}/{kind}")
        back = connectors.read_foreign(spark, f"{tmp_path}/{kind}", kind, nation.schema.simpleString()[7:-1].replace(":", " "))
        assert sorted(map(tuple, back.collect())) == sorted(map(tuple, nation.collect())), kind
    nation.select("n_name").write.text(f"{tmp_path}/text")
    assert connectors.read_foreign(spark, f"{tmp_path}/text", "text").count() == 25


def test_layouts(spark, sf, tmp_path):
    rows = spark.read.parquet(f"{sf}/part.parquet")
    storage.write(rows, f"{tmp_path}/p", partition_by=["p_size"], max_records=10)
    plan = spark.read.parquet(f"{tmp_path}/p").where("p_size = 3")._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(p_size" in plan
    assert storage.stage_in(spark, f"{sf}/part.parquet", f"{tmp_path}/copy")["rows"] == 200
    assert storage.elastic_conf(1, 9)["spark.dynamicAllocation.maxExecutors"] == "9"


def test_sql_functions_and_table_functions(spark, sf):
    index = tsvq.grow(archives.vec_parts(spark, sf), Stop(h_max=2))
    catalog.register(spark, index)
    assert spark.sql("SELECT count(*) AS n FROM codebook").first().n == len(index.leaves)
    assert spark.sql("SELECT vq_side(array(3D), array(1D), 2D) AS s, round(polsar_entropy(0.5D, 0.25D, 0.25D), 6) AS h, polsar_anisotropy(2D, 1D) AS a").first()[0:2] == (1, 0.946395)
    assert [r.code for r in spark.sql("SELECT * FROM vq_path('010')").collect()] == ["", "0", "01", "010"]
    v = index.labelled.orderBy("id").first()
    q = ", ".join(f"{x}D" for x in v.v)
    rows = spark.sql(f"SELECT * FROM vq_search(TABLE(SELECT id, v FROM tiles WHERE code = '{v.code}') WITH SINGLE PARTITION, array({q}), 3)").collect()
    assert rows[0].id == v.id and rows[0].dist == 0 and len(rows) == 3


def test_crawled_tasks(spark, sf):
    assert ingest.tasks(spark.read.parquet(f"{sf}/events.parquet")).count() == 1000
