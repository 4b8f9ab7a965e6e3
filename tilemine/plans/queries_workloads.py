"""The experiment workloads re-expressed on the given tables, as queries; with SQL where the result is a function of the tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from tilemine.operators import haa, ingest, kmeans, measures, merge, search, tiling, tsvq
from tilemine.operators.tsvq import Stop
from tilemine.plans import queries_ingest
from tilemine.plans.queries_index import VP, _archive, _doc_results, _index, _sparse
from tilemine.plans.queries_pixels import HAA, PX
from tilemine.sources import archives, storage
from tilemine.sources.archives import table


def w01_ingest_archive(spark: SparkSession, d: str) -> DataFrame:
    """Every product with its region: pixels, tiles of 8 x 8, valid multilook cells, raw bytes."""
    px = archives.scene_lineitem(spark, d)
    tiles = tiling.tiles(tiling.cut(px, 8)).groupBy("product_id").agg(F.sum("n_px").alias("n_px"), F.count("*").alias("n_tiles"))
    cells = haa.haa(px).groupBy("product_id").agg(F.count("*").alias("n_cells"))
    place = table(spark, d, "supplier").join(F.broadcast(table(spark, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return tiles.join(cells, "product_id").join(place.select(F.col("s_suppkey").alias("product_id"), "r_name"), "product_id").select("product_id", "r_name", "n_px", "n_tiles", "n_cells", (F.col("n_px") * 64).alias("raw_bytes"))


def w02_tile_sizes(spark: SparkSession, d: str) -> DataFrame:
    """Tiles and mean occupancy by side and overlap."""
    px, out = archives.scene_lineitem(spark, d), None
    for side, overlap in ((4, 0), (8, 0), (16, 0), (4, 2), (8, 4), (16, 8)):
        t = tiling.tiles(tiling.cut(px, side, overlap))
        one = t.agg(F.lit(side).alias("side"), F.lit(overlap).alias("overlap"), F.count("*").alias("n_tiles"), F.sum("n_px").alias("n_px"))
        out = one if out is None else out.unionByName(one)
    return out


def w08_cost_benefit(spark: SparkSession, d: str) -> DataFrame:
    """Gain, cost change and trade-off of each configuration, and which is best."""
    rel = measures.relative(queries_ingest.runs(spark, d), "n2")
    return rel.join(measures.tradeoff(rel), "config")


def w09_weak_labels(spark: SparkSession, d: str) -> DataFrame:
    """Documents judged by the quality label, which the letters do not see, against its chance level."""
    labels = table(spark, d, "labels").select(F.col("doc_id").alias("id"), F.col("quality").cast("string").alias("label"))
    chance = labels.groupBy("label").count().agg(F.round(F.sum(F.col("count") * F.col("count")) / (F.sum("count") * F.sum("count")), 6).alias("chance"))
    return measures.precision_at(_doc_results(spark, d, 8, True), labels).crossJoin(chance)


def w10_ten_queries(spark: SparkSession, d: str) -> DataFrame:
    """Ten documents over the languages, ten results each: how many share the language."""
    docs = archives.text_docs(spark, d)
    ids = docs.groupBy("label").agg(F.slice(F.array_sort(F.collect_set("id")), 1, 3).alias("ids")).select(F.explode("ids").alias("id"))
    index = _index(spark, d, "docs", schedule="hybrid", stop=Stop(n_min=64), max_iter=20, tol=1e-6)
    queries = docs.join(F.broadcast(ids), "id").orderBy("id").limit(10).select(F.col("id").alias("query_id"), "v", F.col("label").alias("own"))
    found = search.batch(index, queries.select("query_id", "v"), 10, 8, exact=True)
    return found.join(docs.select("id", "label"), "id").join(queries.select("query_id", "own"), "query_id").groupBy("query_id", "own").agg(F.count("*").alias("n"), F.count_if(F.col("label") == F.col("own")).alias("n_same"))


def w12_constrained(spark: SparkSession, d: str) -> DataFrame:
    """A search limited to parts of one type that were seen in one region since a day."""
    line = table(spark, d, "lineitem").where("l_shipdate >= TIMESTAMP_NTZ '1995-01-01 00:00:00'")
    asia = table(spark, d, "supplier").join(F.broadcast(table(spark, d, "nation").join(F.broadcast(table(spark, d, "region").where("r_name = 'ASIA'")), F.col("n_regionkey") == F.col("r_regionkey"))), F.col("s_nationkey") == F.col("n_nationkey"))
    seen = line.join(asia.select("s_suppkey"), F.col("l_suppkey") == F.col("s_suppkey"), "left_semi").select(F.col("l_partkey").alias("id"))
    kind = table(spark, d, "part").where("p_size < 30").select(F.col("p_partkey").alias("id"))
    v = archives.vec_parts(spark, d).orderBy("id").first().v
    return search.constrained(_index(spark, d), v, seen.join(kind, "id", "left_semi"), 10).select("rank", "id")


def w13_elastic_run(spark: SparkSession, d: str) -> DataFrame:
    """Deliveries by hour with the workers each policy asks for."""
    tasks = ingest.tasks(table(spark, d, "events"))
    depth = ingest.by_queue(ingest.depth(tasks)).select("bucket", F.col("workers").alias("by_queue"))
    work = ingest.load(tasks)
    fed, cost = ingest.by_feedback(work).select("bucket", F.col("workers").alias("by_feedback")), ingest.by_cost(work).select("bucket", F.col("workers").alias("by_cost"))
    return work.join(depth, "bucket", "left").join(fed, "bucket").join(cost, "bucket").select("bucket", "tasks", "by_queue", "by_feedback", "by_cost")


def w15_sparse_and_dense(spark: SparkSession, d: str) -> DataFrame:
    """Cost, operations and share of non-zero entries of both layouts on documents."""
    docs = archives.text_docs(spark, d)
    rows = []
    stats = docs.agg(F.count("*").alias("n"), F.max(F.size("v")).alias("d"), F.sum(F.size(F.filter("v", lambda x: x != 0))).alias("nnz")).first()
    for layout, frame in (("dense", docs), ("sparse", _sparse(docs))):
        model = kmeans.fit(frame, 2, "farthest", 0.0, 5, layout=layout)
        rows.append((layout, round(model.wcss, 2), float(measures.kmeans_ops(stats.n, stats.d, 2, 5, stats.nnz)[layout])))
    return spark.createDataFrame(rows, "layout string, wcss double, operations double")


def w16_stop_rules(spark: SparkSession, d: str) -> DataFrame:
    """Leaves, code length and remaining cost by greatest height, on parts."""
    rows = []
    for h in (1, 2, 3, 4):
        index = _index(spark, d, stop=Stop(h_max=h), schedule="hybrid")
        rows.append((h, len(index.leaves), round(sum(len(n.code) * n.n for n in index.leaves) / index.nodes[""].n, 6), round(sum(n.wcss for n in index.leaves) / index.nodes[""].wcss, 6)))
    return spark.createDataFrame(rows, "h_max int, n_leaves int, code_length double, cost_share double")


def w16_stop_grid(spark: SparkSession, d: str) -> DataFrame:
    """Leaves, code length, remaining cost and recall of the scan's ten from one and eight leaves by smallest node, least cost (as a share
    of the root's) and height, on documents and embeddings."""
    rows = []
    for archive in ("docs", "embeddings"):
        frame = _archive(spark, d, archive)
        queries = frame.where("id % 100 = 0").select(F.col("id").alias("query_id"), "v")
        exact = storage.park(search.scan_topk(frame, queries, 10), "exact")
        root = _index(spark, d, archive, schedule="hybrid", stop=Stop(h_max=0)).nodes[""]
        for rule, value, stop in (("n_min", 64.0, Stop(n_min=64)), ("n_min", 256.0, Stop(n_min=256)), ("wcss_min", 0.01, Stop(wcss_min=0.01 * root.wcss)), ("wcss_min", 0.05, Stop(wcss_min=0.05 * root.wcss)), ("h_max", 3.0, Stop(h_max=3)), ("h_max", 6.0, Stop(h_max=6))):
            index = _index(spark, d, archive, schedule="hybrid", stop=stop, max_iter=20, tol=1e-6)
            recall = [measures.recall_at(search.batch(index, queries, 10, m), exact).first().recall for m in (1, 8)]
            rows.append((archive, rule, value, len(index.leaves), sum(len(n.code) * n.n for n in index.leaves) / root.n, sum(n.wcss for n in index.leaves) / root.wcss, *recall))
    return spark.createDataFrame(rows, "archive string, rule string, value double, n_leaves int, code_length double, cost_share double, recall_1 double, recall_8 double")


def w19_richer_descriptors(spark: SparkSession, d: str) -> DataFrame:
    """Letters with length and line features in one vector: precision by language."""
    docs = archives.text_docs(spark, d)
    extra = table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.array(100 * F.log1p(F.char_length("text").cast("double")), 10 * F.log1p((F.size(F.split("text", "\n")) - 1).cast("double"))).alias("more"))
    rich = docs.join(extra, "id").select("id", F.concat(F.transform("v", lambda x: x.cast("double")), F.col("more")).alias("v"), "label")
    index = tsvq.grow(rich, Stop(n_min=64), schedule="hybrid")
    found = search.batch(index, rich.where("id % 100 = 0").select(F.col("id").alias("query_id"), "v"), 10, 8, exact=True)
    return measures.precision_at(found, rich.select("id", "label"))


def w20_merged_indexes(spark: SparkSession, d: str) -> DataFrame:
    """Node statistics of two halves of the archive under one tree, merged: those of the whole."""
    index = _index(spark, d)
    halves = []
    for part in (0, 1):
        rows = index.labelled.where(F.col("id") % 2 == part)
        half = tsvq._restat(tsvq.Index({c: tsvq.Node(c, 0, n.s * 0, 0.0, n.ss * 0, n.closed, n.split) for c, n in index.nodes.items()}, rows), rows, 1)
        halves.append(tsvq.Index(half, rows).table(spark))
    return merge.merge_nodes(*halves).select("code", "n", F.round("sq", 4).alias("sq"))


def w21_group_means(spark: SparkSession, d: str) -> DataFrame:
    out = merge.group_means(archives.vec_parts(spark, d).withColumn("g", F.col("id") % 7), "g")
    return out.select("g", F.posexplode("mean").alias("dim", "mean")).withColumn("mean", F.round("mean", 6))


QUERIES = {name: f for name, f in list(globals().items()) if name[:1] == "w" and name[1:3].isdigit()}

from tilemine.plans.queries_index import _LAB, _Q, _TENTHS, _TREE, VD, kmeans_sql, nearest_sql, tree_sql  # noqa: E402

_SIZES = ((4, 0), (8, 0), (16, 0), (4, 2), (8, 4), (16, 8))


def _sweep(side: int, overlap: int) -> str:
    step = side - overlap
    first = lambda c: f"greatest(0, CAST(floor(({c} - {side}) / {step}.0) AS BIGINT) + 1)"
    row = '"row"'
    return f"SELECT {side} AS side, {overlap} AS overlap, count(DISTINCT (product_id, tr, tc)) AS n_tiles, count(*) AS n_px FROM px, unnest(generate_series({first(row)}, {row} // {step})) AS a(tr), unnest(generate_series({first('col')}, col // {step})) AS b(tc)"


_I = queries_ingest
SQL = {
    "w01_ingest_archive": f"""WITH {HAA}, p AS (SELECT product_id, count(*) AS n_px, count(DISTINCT ("row" // 8, col // 8)) AS n_tiles FROM px GROUP BY 1), c AS (SELECT product_id, count(*) AS n_cells FROM attr GROUP BY 1)
       SELECT product_id, r_name, n_px, n_tiles, n_cells, n_px * 64 AS raw_bytes FROM p JOIN c USING (product_id) JOIN supplier ON s_suppkey = product_id JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey""",
    "w02_tile_sizes": f"WITH {PX} " + " UNION ALL ".join(_sweep(*x) for x in _SIZES),
    "w08_cost_benefit": f"WITH {_I._rel('nodes * rate')}, t AS (SELECT *, round(time_gain_pct - cost_change_pct, 6) AS tradeoff FROM rel) SELECT *, tradeoff > 0 AS beneficial, config = (SELECT config FROM t ORDER BY tradeoff DESC, config DESC LIMIT 1) AS is_best FROM t",
    "w12_constrained": f"WITH {_TREE}, {_Q}, dist AS (SELECT id, sum((x - y) ** 2) AS dist FROM v JOIN q USING (dim) GROUP BY id), hit AS (SELECT id, dist FROM dist JOIN {_LAB} USING (id) WHERE code = (SELECT code FROM {_LAB} WHERE id = (SELECT min(id) FROM vi)) AND id IN (SELECT l_partkey FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN part ON p_partkey = l_partkey WHERE r_name = 'ASIA' AND l_shipdate >= TIMESTAMP '1995-01-01' AND p_size < 30)) SELECT CAST(row_number() OVER (ORDER BY dist, id) AS INTEGER) AS rank, id FROM hit ORDER BY dist, id LIMIT 10",
    "w13_elastic_run": f"WITH RECURSIVE {_I._TASKS}, {_I._DEPTH}, {_I._LOAD}, {_I._FEED}, a AS (SELECT bucket, CAST(greatest(1, least(8, ceil(depth / 2.0))) AS INTEGER) AS by_queue FROM q), x AS (SELECT *, CASE WHEN bucket % 24 >= 8 AND bucket % 24 < 20 THEN 4 ELSE 0 END AS wanted FROM w), y AS (SELECT bucket, CAST(CASE WHEN sum(wanted) OVER (ORDER BY bucket) <= 1000 THEN wanted ELSE 0 END AS INTEGER) AS by_cost FROM x) SELECT w.bucket, w.tasks, by_queue, CAST(f.workers AS INTEGER) AS by_feedback, by_cost FROM w LEFT JOIN a USING (bucket) JOIN f USING (bucket) JOIN y USING (bucket)",
    "w09_weak_labels": f"WITH {VD}, {_TENTHS}, {nearest_sql('vq', 'v')}, j AS (SELECT query_id, a.quality = b.quality AS same FROM r JOIN labels a ON a.doc_id = query_id JOIN labels b ON b.doc_id = r.id WHERE r.id <> query_id), g AS (SELECT quality, count(*) AS n FROM labels GROUP BY quality) SELECT count(DISTINCT query_id) AS n_queries, count(*) AS n_results, count(*) FILTER (same) AS n_same, round(avg(CAST(same AS DOUBLE)), 6) AS precision, (SELECT round(sum(n * n) / (sum(n) * sum(n)), 6) FROM g) AS chance FROM j",
    "w10_ten_queries": f"WITH {VD}, d AS (SELECT DISTINCT id, lang FROM v), e AS (SELECT id, lang FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY id) AS n FROM d) WHERE n <= 3 ORDER BY id LIMIT 10), eq AS (SELECT v.* FROM v JOIN e USING (id)), {nearest_sql('eq', 'v')} SELECT query_id, e.lang AS own, count(*) AS n, count(*) FILTER (d.lang = e.lang) AS n_same FROM r JOIN d ON d.id = r.id JOIN e ON e.id = query_id GROUP BY ALL",
    "w15_sparse_and_dense": f"WITH {kmeans_sql(2, 5, VD + ', vi AS (SELECT DISTINCT id FROM v)')}, f AS (SELECT round(sum(d), 2) AS wcss FROM (SELECT id, min(d) AS d FROM (SELECT id, cid, sum((x - c) ** 2) AS d FROM v JOIN c5 USING (dim) GROUP BY ALL) GROUP BY id)), n AS (SELECT count(DISTINCT id) AS n, count(DISTINCT dim) AS d, count(*) FILTER (x <> 0) AS nnz FROM v) SELECT layout, wcss, CAST(CASE layout WHEN 'dense' THEN n * d * 10 ELSE (nnz + n) * 10 END AS DOUBLE) AS operations FROM f, n, unnest(['dense', 'sparse']) AS t(layout)",
    "w16_stop_rules": f"WITH {tree_sql(4)}, root AS (SELECT n AS t, wcss AS e FROM nodes WHERE code = '') SELECT depth AS h_max, CAST(count(*) AS INTEGER) AS n_leaves, round(sum(depth * n) / max(t), 6) AS code_length, round(sum(wcss) / max(e), 6) AS cost_share FROM nodes, root WHERE depth > 0 AND n > 0 GROUP BY depth",
    "w19_richer_descriptors": f"WITH {VD}, m AS (SELECT doc_id AS id, text FROM documents WHERE doc_id IN (SELECT id FROM v)), w AS (SELECT id, dim, x FROM v UNION ALL SELECT id, 1000, 100 * ln(1 + length(text)) FROM m UNION ALL SELECT id, 1001, 10 * ln(1 + (length(text) - length(replace(text, chr(10), '')))) FROM m), wq AS (SELECT * FROM w WHERE id % 100 = 0), {nearest_sql('wq', 'w')}, j AS (SELECT query_id, a.lang = b.lang AS same FROM r JOIN documents a ON a.doc_id = query_id JOIN documents b ON b.doc_id = id WHERE id <> query_id) SELECT count(DISTINCT query_id) AS n_queries, count(*) AS n_results, count(*) FILTER (same) AS n_same, round(avg(CAST(same AS DOUBLE)), 6) AS precision FROM j",
    "w20_merged_indexes": f"WITH {_TREE} SELECT code, n, round(sq, 4) AS sq FROM nodes",
    "w21_group_means": f"WITH {VP} SELECT id % 7 AS g, dim, round(avg(x), 6) AS mean FROM v GROUP BY ALL",
}
