"""Queries over vector quantisation, the tree index, searching and its measures, with their SQL.

The SQL unrolls a fixed number of iterations over (id, dim, x) rows; the engine runs the same number of
updates.  Descriptors are the whole-number histograms of parts (32 bins), so sums agree exactly.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from tilemine.functions import vector
from tilemine.operators import haa, kmeans, measures, search, tsvq
from tilemine.operators.tsvq import Index, Stop
from tilemine.plans.queries_pixels import HAA, _BIN
from tilemine.plans.retrieve import RetrievePlan
from tilemine.sources import archives, storage
from tilemine.sources.archives import table
from tilemine.streaming import live

UPDATES, LEVELS = 3, 2
_held: dict[tuple, Index] = {}
_described: dict[tuple, DataFrame] = {}


def _parts(spark: SparkSession, d: str) -> DataFrame:
    return archives.vec_parts(spark, d)


def _archive(spark: SparkSession, d: str, archive: str) -> DataFrame:
    """Descriptors of an archive; those of texts and embeddings are made once for all indexes of the session."""
    if archive == "parts":
        return archives.vec_parts(spark, d)
    key = (spark.sparkContext.applicationId, id(spark.sparkContext), d, archive)
    if key not in _described:
        _described[key] = storage.park({"docs": archives.text_docs, "embeddings": archives.vec_embeddings}[archive](spark, d), archive)
    return _described[key]


def _index(spark: SparkSession, d: str, archive: str = "parts", **how) -> Index:
    """Indexes of this session by folder and settings; rows are kept in the shared folder, not in memory."""
    key = (spark.sparkContext.applicationId, id(spark.sparkContext), d, archive, *sorted(how.items()))
    if key not in _held:
        made = _archive(spark, d, archive)
        how = {"stop": Stop(h_max=LEVELS), "tol": 0.0, "max_iter": UPDATES} | how
        grown: list[Index] = []

        def labelled() -> DataFrame:
            # written first: its partitions are then as many as its size asks for, not as many as the shuffles behind it
            grown.append(tsvq.grow(storage.park(made, archive) if archive == "parts" else made, **how))
            return grown[0].labelled

        rows = storage.park_only(spark, labelled, "index")
        grown[0].labelled.unpersist()
        _held[key] = Index(grown[0].nodes, rows, grown[0].manifest)
    return _held[key]


def _d(column: str = "v"):
    return F.transform(column, lambda x: x.cast("double"))


def _first_two(spark: SparkSession, d: str, k: int = 2) -> list[list[int]]:
    return [r.v for r in _parts(spark, d).orderBy("id").limit(k).collect()]


def _lit(v) -> F.Column:
    return F.array(*[F.lit(float(x)) for x in v])


def q30_distortion(spark: SparkSession, d: str) -> DataFrame:
    y = _lit(_first_two(spark, d)[0])
    return _parts(spark, d).select("id", F.round(vector.sqdist(_d(), y), 6).alias("dist"))


def q31_distortion_from_norms(spark: SparkSession, d: str) -> DataFrame:
    y = _lit(_first_two(spark, d)[0])
    return _parts(spark, d).withColumn("q", vector.sqnorm(_d())).select("id", F.round(vector.sqdist_cached(_d(), F.col("q"), y, vector.sqnorm(y)), 6).alias("dist"))


def q32_bisector(spark: SparkSession, d: str) -> DataFrame:
    a, b = (np.array(v, float) for v in _first_two(spark, d))
    return _parts(spark, d).select("id", vector.side(_d(), _lit(b - a), F.lit(float((b @ b - a @ a) / 2))).alias("side"))


def _codebook(spark: SparkSession, d: str) -> np.ndarray:
    return np.array(_first_two(spark, d, 4), float)


def q33_flat_encode(spark: SparkSession, d: str) -> DataFrame:
    return _parts(spark, d).select("id", kmeans.nearest(_codebook(spark, d)).alias("cid"))


def q34_decode(spark: SparkSession, d: str) -> DataFrame:
    book = _codebook(spark, d)
    table_ = spark.createDataFrame([(i, c.tolist()) for i, c in enumerate(book)], "cid int, c array<double>")
    coded = kmeans.assign(_parts(spark, d), book).select("id", "cid")
    return coded.join(F.broadcast(table_), "cid").select("id", "cid", F.posexplode("c").alias("dim", "x"))


def q35_voronoi_check(spark: SparkSession, d: str) -> DataFrame:
    book = _codebook(spark, d)
    table_ = spark.createDataFrame([(i, c.tolist()) for i, c in enumerate(book)], "cid int, c array<double>")
    return measures.check_cells(kmeans.assign(_parts(spark, d), book), table_)


def q36_root(spark: SparkSession, d: str) -> DataFrame:
    return _parts(spark, d).select(F.posexplode("v").alias("dim", "x")).groupBy("dim").agg(F.round(F.avg("x"), 6).alias("centroid"))


def q37_assign(spark: SparkSession, d: str) -> DataFrame:
    return kmeans.assign(_parts(spark, d), _codebook(spark, d)).select("id", "cid")


def _sums(spark: SparkSession, d: str, combine: bool) -> DataFrame:
    parts = kmeans.partial_sums(_parts(spark, d), _codebook(spark, d), combine)
    return parts.groupBy("cid", "dim").agg(F.sum("n").alias("n"), F.round(F.sum("x"), 6).alias("s"))


def q38_combined_sums(spark: SparkSession, d: str) -> DataFrame:
    return _sums(spark, d, True)


def q38_uncombined_sums(spark: SparkSession, d: str) -> DataFrame:
    return _sums(spark, d, False)


def q39_update(spark: SparkSession, d: str) -> DataFrame:
    return _sums(spark, d, True).select("cid", "dim", F.round(F.col("s") / F.col("n"), 6).alias("centroid"))


def _model_rows(spark: SparkSession, model: kmeans.Model) -> DataFrame:
    return spark.createDataFrame([(i, j, int(n), round(float(x), 6)) for i, (c, n) in enumerate(zip(model.centroids, model.counts)) for j, x in enumerate(c)], "cid int, dim int, n long, centroid double")


def q40_kmeans(spark: SparkSession, d: str) -> DataFrame:
    return _model_rows(spark, kmeans.fit(_parts(spark, d), 2, "farthest", 0.0, UPDATES))


def q40_kmeans_on_disk(spark: SparkSession, d: str) -> DataFrame:
    return _model_rows(spark, kmeans.fit(_parts(spark, d), 2, "farthest", 0.0, UPDATES, materialise="dfs"))


def q40_kmeans_uncached(spark: SparkSession, d: str) -> DataFrame:
    return _model_rows(spark, kmeans.fit(_parts(spark, d), 2, "farthest", 0.0, UPDATES, materialise="none"))


def q41_kmeans_of_three(spark: SparkSession, d: str) -> DataFrame:
    return _model_rows(spark, kmeans.fit(_parts(spark, d), 3, "farthest", 0.0, UPDATES))


def _sparse(df: DataFrame) -> DataFrame:
    places = F.filter(F.sequence(F.lit(0), F.size("v") - 1), lambda i: F.get("v", i) != 0)
    return df.withColumn("idx", places).withColumn("val", F.transform("idx", lambda i: F.get("v", i).cast("double")))


def q42_sparse_kmeans(spark: SparkSession, d: str) -> DataFrame:
    return _model_rows(spark, kmeans.fit(_sparse(_parts(spark, d)), 2, "farthest", 0.0, UPDATES, layout="sparse"))


def q43_wcss(spark: SparkSession, d: str) -> DataFrame:
    out = measures.wcss(kmeans.assign(_parts(spark, d), _codebook(spark, d)), "cid")
    return out.select("cid", "n", F.round("wcss", 4).alias("wcss"))


def q44_tree_labels(spark: SparkSession, d: str) -> DataFrame:
    return _index(spark, d).labelled.select("id", "code")


def q44_leaf_at_a_time(spark: SparkSession, d: str) -> DataFrame:
    return _index(spark, d, schedule="leaf").labelled.select("id", "code")


def q44_last_leaf_first(spark: SparkSession, d: str) -> DataFrame:
    return _index(spark, d, schedule="leaf", order="lifo").labelled.select("id", "code")


def q44_hybrid(spark: SparkSession, d: str) -> DataFrame:
    return _index(spark, d, schedule="hybrid", local_rows=1500).labelled.select("id", "code")


def q44_greedy(spark: SparkSession, d: str) -> DataFrame:
    return _index(spark, d, schedule="greedy", max_leaves=4).labelled.select("id", "code")


def q44_on_disk(spark: SparkSession, d: str) -> DataFrame:
    return _index(spark, d, materialise="dfs").labelled.select("id", "code")


def _nodes(spark: SparkSession, d: str, **how) -> DataFrame:
    return _index(spark, d, **how).table(spark)


def q45_nodes(spark: SparkSession, d: str) -> DataFrame:
    return _nodes(spark, d).select("code", "depth", "n", F.round("sq", 4).alias("sq"), F.round("wcss", 4).alias("wcss"), "is_leaf")


#: Each rule alone, then two together; all close within DEEP levels on the tables of 2,000 parts or fewer, as far as the SQL unrolls.
DEEP = 4
STOPS = (("h_max", Stop(h_max=2)), ("n_min", Stop(n_min=900, h_max=DEEP)), ("wcss_min", Stop(wcss_min=4000.0, h_max=DEEP)), ("any", Stop(n_min=500, h_max=2)))


def q46_stop_rules(spark: SparkSession, d: str) -> DataFrame:
    """Close reasons under each rule alone."""
    out = None
    for name, stop in STOPS:
        one = _nodes(spark, d, stop=stop, schedule="hybrid").where("is_leaf").groupBy("close_reason").agg(F.count("*").alias("n_leaves"), F.sum("n").alias("n_rows")).withColumn("rule", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


def q47_codebook(spark: SparkSession, d: str) -> DataFrame:
    """Leaves and their means over the archive as it is read now; the index gives the splits."""
    return _fallen(spark, d).select("code", F.posexplode("v").alias("dim", "x")).groupBy("code", "dim").agg(F.count("*").alias("n"), F.round(F.avg("x"), 6).alias("x"))


def _fallen(spark: SparkSession, d: str) -> DataFrame:
    """Every part with its leaf: an index that the session holds is not taken for the table."""
    return tsvq.descend(_parts(spark, d).select("id", _d().alias("v")), _index(spark, d).nodes)


def q48_descend(spark: SparkSession, d: str) -> DataFrame:
    return tsvq.descend(_parts(spark, d).select("id", _d().alias("v")), _index(spark, d).nodes, path=True).select("id", "code", "depth")


def q49_seed_methods(spark: SparkSession, d: str) -> DataFrame:
    """Cost of a two-level tree, and passes until its splits settle, by seeding method; on parts and on documents."""
    rows = []
    for archive in ("parts", "docs"):
        for init in ("axis", "farthest", "random", "dsquare", "parallel"):
            index = _index(spark, d, archive, init=init, max_iter=30, tol=1e-6, schedule="hybrid")
            root = index.nodes[""]
            rows.append((archive, init, len(index.leaves), sum(n.turns for n in index.nodes.values()), sum(n.wcss for n in index.leaves), root.wcss, root.n))
    return spark.createDataFrame(rows, "archive string, init string, n_leaves int, passes int, wcss double, root_wcss double, n long")


def q49_seed_costs_hold(spark: SparkSession, d: str) -> DataFrame:
    """Every method splits all rows and lowers the cost; draws by squared distance, one by one or over-sampled, come within half of the best."""
    found = q49_seed_methods(spark, d).withColumn("least", F.min("wcss").over(Window.partitionBy("archive")))
    return found.select("archive", "init", "n", (F.col("wcss") < F.col("root_wcss")).alias("lower"), F.when(F.col("init").isin("dsquare", "parallel"), F.col("wcss") <= 1.5 * F.col("least")).alias("near_best"))


def _query(spark: SparkSession, d: str) -> tuple[float, ...]:
    return tuple(map(float, _first_two(spark, d)[0]))


def q50_by_tile(spark: SparkSession, d: str) -> DataFrame:
    first = _parts(spark, d).agg(F.min("id")).first()[0]
    return search.by_id(_index(spark, d), first, 10).withColumn("dist", F.round("dist", 6))


def _docs_index(spark: SparkSession, d: str, n_min: int = 64) -> Index:
    return _index(spark, d, "docs", schedule="hybrid", stop=Stop(n_min=n_min), max_iter=20, tol=1e-6)


def _uploads(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "benchmark").select(F.col("item_id").alias("query_id"), archives.letter_histogram(F.col("text")).alias("v")).where("v IS NOT NULL")


def q51_by_upload(spark: SparkSession, d: str) -> DataFrame:
    """Benchmark passages as unseen descriptors against the documents' index, by the exact way over all leaves that may matter."""
    return search.batch(_docs_index(spark, d), _uploads(spark, d), 10, probes=8, exact=True).select("query_id", "rank", "id", F.round("dist", 6).alias("dist"))


def q51_one_leaf(spark: SparkSession, d: str) -> DataFrame:
    """The same from the reached leaf alone."""
    return search.batch(_docs_index(spark, d), _uploads(spark, d), 10)


def _describe(px: DataFrame) -> DataFrame:
    axes = [haa.Axis("h", 0.0, 1.0, 4), haa.Axis("alpha", 0.0, 1.5707963267948966, 4), haa.Axis("a", 0.0, 1.0, 2)]
    return haa.tile_histogram(px, axes=axes).select("id", "v")


def q51_pixel_upload(spark: SparkSession, d: str) -> DataFrame:
    """Uploaded pixels: the rasters of every 25th product go through decomposition and histogram, as on ingestion, and each of their tiles
    searches the index of all other products' tiles, exactly."""
    scenes = archives.scene_lineitem(spark, d)
    key = (spark.sparkContext.applicationId, id(spark.sparkContext), d, "tiles")
    if key not in _held:
        from tilemine.sources.storage import park

        index = tsvq.grow(park(_describe(scenes.where("product_id % 25 <> 0")), "tiles"), Stop(n_min=32), schedule="hybrid")
        _held[key] = Index(index.nodes, park(index.labelled, "index"), index.manifest)
    found = search.by_pixels(_held[key], scenes.where("product_id % 25 = 0"), _describe, 10)
    return found.select("query_id", "rank", "id", F.round("dist", 6).alias("dist"))


def q52_leaf(spark: SparkSession, d: str) -> DataFrame:
    return search.raw(_index(spark, d), _query(spark, d))


def q53_top(spark: SparkSession, d: str) -> DataFrame:
    return search.by_vectors(_index(spark, d), [_query(spark, d)], 10).withColumn("dist", F.round("dist", 6))


def q53_two_signatures(spark: SparkSession, d: str) -> DataFrame:
    """One query of two signatures over all leaves: a row counts by the nearer one."""
    found = search.by_vectors(_index(spark, d), _first_two(spark, d), 10, probes=2**LEVELS)
    return found.select("rank", "id", F.round("dist", 6).alias("dist"))


def _ten(spark: SparkSession, d: str) -> DataFrame:
    return _parts(spark, d).where(F.col("id") % 100 == 0).select(F.col("id").alias("query_id"), _d().alias("v"))


def q54_batch(spark: SparkSession, d: str) -> DataFrame:
    return search.batch(_index(spark, d), _ten(spark, d), 10).withColumn("dist", F.round("dist", 6))


def q54_all_leaves(spark: SparkSession, d: str) -> DataFrame:
    return search.batch(_index(spark, d), _ten(spark, d), 10, probes=4).withColumn("dist", F.round("dist", 6)).select("query_id", "rank", "id", "dist")


def _where(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "part").where((F.col("p_size") <= 25) & F.col("p_brand").startswith("Brand#")).select(F.col("p_partkey").alias("id"))


def q55_constrained(spark: SparkSession, d: str) -> DataFrame:
    return search.constrained(_index(spark, d), _query(spark, d), _where(spark, d), 10).withColumn("dist", F.round("dist", 6))


def q55_constrained_after(spark: SparkSession, d: str) -> DataFrame:
    return search.constrained(_index(spark, d), _query(spark, d), _where(spark, d), 10, "post").withColumn("dist", F.round("dist", 6)).select("id", "dist", "code")


def q56_metadata_only(spark: SparkSession, d: str) -> DataFrame:
    """Products by region and acquisition time, without a descriptor."""
    region = table(spark, d, "region").where(F.col("r_name").isin("ASIA", "EUROPE"))
    places = table(spark, d, "supplier").join(F.broadcast(table(spark, d, "nation").join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey"))), F.col("s_nationkey") == F.col("n_nationkey"))
    seen = table(spark, d, "lineitem").where("l_shipdate >= TIMESTAMP_NTZ '1995-01-01 00:00:00'").groupBy("l_suppkey").agg(F.count("*").alias("n_px"), F.min("l_shipdate").alias("first_seen"))
    return places.join(seen, F.col("s_suppkey") == F.col("l_suppkey")).select("s_suppkey", "n_name", "r_name", "n_px", F.date_format("first_seen", "yyyy-MM-dd").alias("first_seen"))


def q57_back_off(spark: SparkSession, d: str) -> DataFrame:
    n = max(x.n for x in _index(spark, d).leaves) + 1
    return search.run(_index(spark, d), RetrievePlan((_query(spark, d),), n, backoff=True)).withColumn("dist", F.round("dist", 6))


def q58_groups(spark: SparkSession, d: str) -> DataFrame:
    return search.rank_groups(_index(spark, d), _query(spark, d)).withColumn("dist", F.round("dist", 4))


def q58b_other_metrics(spark: SparkSession, d: str) -> DataFrame:
    y = _lit(_query(spark, d))
    return _parts(spark, d).select("id", *[F.round(fn(_d(), y), 6).alias(name) for name, fn in vector.METRICS.items()])


def q59_panel(spark: SparkSession, d: str) -> DataFrame:
    shown = table(spark, d, "part").select(F.col("p_partkey").alias("id"), "p_name", "p_brand")
    return search.panel(search.by_vectors(_index(spark, d), [_query(spark, d)], 10).select("rank", "id"), shown)


def q60_scan(spark: SparkSession, d: str) -> DataFrame:
    return search.scan_topk(_parts(spark, d), _ten(spark, d), 10).withColumn("dist", F.round("dist", 6))


def q61_linked_list(spark: SparkSession, d: str) -> DataFrame:
    parts = table(spark, d, "part").select(F.col("p_partkey").alias("id"))
    return search.linked_lookup(parts, parts.where("id % 100 = 0"))


def q62_sampled_index(spark: SparkSession, d: str) -> DataFrame:
    return _sampled(spark, d).table(spark).select("code", "n", "wcss", "is_leaf")


def _sampled(spark: SparkSession, d: str) -> Index:
    return search.sampled_index(archives.text_docs(spark, d), 5, stop=Stop(n_min=16))


def q62_sampled_recall(spark: SparkSession, d: str) -> DataFrame:
    """Share of the scan's results found by an index grown on a fifth of the documents, from 1, 8 and ENOUGH leaves."""
    index, out = _sampled(spark, d), None
    exact = search.scan_topk(archives.text_docs(spark, d), _doc_queries(spark, d), 10)
    for probes in (1, 8, ENOUGH):
        one = measures.recall_at(search.batch(index, _doc_queries(spark, d), 10, probes), exact).withColumn("probes", F.lit(probes))
        out = one if out is None else out.unionByName(one)
    return out


def q62_sampled_search(spark: SparkSession, d: str) -> DataFrame:
    """The exact way over the sampled index: it holds every row, so its results are the scan's."""
    return search.batch(_sampled(spark, d), _doc_queries(spark, d), 10, 8, exact=True).select("query_id", "rank", "id", F.round("dist", 6).alias("dist"))


def q63_multi_index(spark: SparkSession, d: str) -> DataFrame:
    """Letters and lengths as two features of documents, each with its index, merged by rank."""
    docs = table(spark, d, "documents")
    shape = docs.select(F.col("doc_id").alias("id"), F.array(F.log1p(F.char_length("text").cast("double")), F.log1p((F.char_length("text") - F.char_length(F.replace("text", F.lit("\n"), F.lit("")))).cast("double"))).alias("v"))
    letters = archives.text_docs(spark, d).select("id", "v")
    indexes = {"letters": _index(spark, d, "docs", schedule="hybrid", stop=Stop(n_min=64), max_iter=20, tol=1e-6), "shape": tsvq.grow(shape, Stop(n_min=64), schedule="hybrid")}
    q = {"letters": letters.where("id % 100 = 0").select(F.col("id").alias("query_id"), "v"), "shape": shape.where("id % 100 = 0").select(F.col("id").alias("query_id"), "v")}
    return search.multi_index(indexes, q, 10)


def q64_flat_of_leaf_count(spark: SparkSession, d: str) -> DataFrame:
    """Control for the tree: k-means with as many centroids as the tree has leaves; both costs."""
    index = _index(spark, d)
    flat = kmeans.fit(_parts(spark, d), len(index.leaves), "farthest")
    return spark.createDataFrame([("tree", len(index.leaves), sum(n.wcss for n in index.leaves)), ("flat", len(flat.counts), flat.wcss)], "method string, k int, wcss double")


def q65_library_controls(spark: SparkSession, d: str) -> DataFrame:
    rows = [(kind, float(search.mllib(_parts(spark, d), 4, kind)[0])) for kind in ("bisecting", "kmeans")]
    return spark.createDataFrame(rows, "method string, wcss double")


def _node_sums(index: Index, spark: SparkSession) -> DataFrame:
    return index.table(spark).select("code", "n", F.round("sq", 4).alias("sq"))


def q71_insert(spark: SparkSession, d: str) -> DataFrame:
    """Every second row is taken out and put in again: the nodes are those of the whole."""
    odd = _parts(spark, d).where("id % 2 = 1")
    return _node_sums(tsvq.insert(tsvq.delete(_index(spark, d), odd), odd), spark)


def q72_delete(spark: SparkSession, d: str) -> DataFrame:
    return _node_sums(tsvq.delete(_index(spark, d), _parts(spark, d).where("id % 3 = 0")), spark)


def q73_modify(spark: SparkSession, d: str) -> DataFrame:
    """Rows of every fifth id get the descriptor of the smallest id, and so its leaf."""
    first = _lit(_query(spark, d))
    return tsvq.modify(_index(spark, d), _parts(spark, d).where("id % 5 = 0").withColumn("v", first)).labelled.select("id", "code")


def q74_regrow(spark: SparkSession, d: str) -> DataFrame:
    """A tree of one level, grown on: that of two."""
    index = _index(spark, d, stop=Stop(h_max=1))
    return tsvq.regrow(index, Stop(h_max=LEVELS), tol=0.0, max_iter=UPDATES).labelled.select("id", "code")


def q74_live_index(spark: SparkSession, d: str) -> DataFrame:
    """Embeddings come in as a stream of micro-batches and fall down the tree of the others: rows by leaf are those of a batch descent."""
    rows = archives.vec_embeddings(spark, d).select("id", "v")
    index = tsvq.grow(rows.where("id % 4 <> 0"), Stop(n_min=64), schedule="hybrid")
    source, target, checkpoint = (storage.new_folder(spark, f"live-{x}") for x in ("source", "target", "checkpoint"))
    for part in (0, 4):
        rows.where(F.col("id") % 8 == part).write.mode("append").parquet(source)
    live.live_index(live.event_stream(spark, source, "id long, v array<double>"), index, target, checkpoint).awaitTermination()
    grown = live.with_live(index, spark, target)
    whole = tsvq.descend(tsvq.prepare(rows), index.nodes).select("id", F.col("code").alias("batch"))
    both = grown.labelled.select("id", "code").join(whole, "id", "full")
    return both.agg(F.count("*").alias("n"), F.count_if(~F.col("code").eqNullSafe(F.col("batch"))).alias("n_elsewhere"), F.lit(grown.nodes[""].n).cast("long").alias("n_root"))


def q18_storage(spark: SparkSession, d: str) -> DataFrame:
    """An index written, sorted by code, and read again."""
    path = storage.new_folder(spark, "saved")
    tsvq.save(_index(spark, d), path)
    return tsvq.load(spark, path).labelled.select("id", "code")


def q80_rate_curve(spark: SparkSession, d: str) -> DataFrame:
    rows = [(r["step"], round(r["wcss"], 4), round(r["code_length"], 6)) for r in measures.rate_curve(_index(spark, d))]
    return spark.createDataFrame(rows, "step int, wcss double, code_length double")


def q81_distance_evaluations(spark: SparkSession, d: str) -> DataFrame:
    return measures.distance_evals(_index(spark, d).labelled)


def q82_operations(spark: SparkSession, d: str) -> DataFrame:
    counts = _parts(spark, d).agg(F.count("*").alias("n"), F.max(F.size("v")).alias("d"), F.sum(F.size(F.filter("v", lambda x: x != 0))).alias("nnz"))
    return counts.select("n", "d", "nnz", (F.col("n") * F.col("d") * 2 * UPDATES).alias("dense"), ((F.col("nnz") + F.col("n")) * 2 * UPDATES).alias("sparse"))


def q83_tree_shape(spark: SparkSession, d: str) -> DataFrame:
    """Of the nodes that the archive's rows, as they are read now, fall through."""
    leaves = _fallen(spark, d).groupBy("code").agg(F.count("*").alias("n"))
    met = leaves.select("code", "n", F.explode(F.sequence(F.lit(0), F.length("code"))).alias("depth"))
    nodes = met.groupBy(F.substring("code", F.lit(1), F.col("depth")).alias("node"), "depth").agg(F.sum("n").alias("n"), F.bool_or(F.length("code") == F.col("depth")).alias("is_leaf"))
    return measures.tree_shape(nodes)


def _doc_queries(spark: SparkSession, d: str) -> DataFrame:
    return archives.text_docs(spark, d).where("id % 100 = 0").select(F.col("id").alias("query_id"), "v")


def _doc_results(spark: SparkSession, d: str, probes: int = 1, exact: bool = False) -> DataFrame:
    return search.batch(_docs_index(spark, d), _doc_queries(spark, d), 10, probes, exact=exact)


def q85_precision(spark: SparkSession, d: str) -> DataFrame:
    """Ten results each for document queries, judged by language: the index by the exact way."""
    return measures.precision_at(_doc_results(spark, d, 8, True), archives.text_docs(spark, d).select("id", "label"))


def q85_precision_by_probes(spark: SparkSession, d: str) -> DataFrame:
    """The same from 1 and 8 leaves, and from the scan."""
    docs, out = archives.text_docs(spark, d), None
    labels = docs.select("id", "label")
    for method, found in (("1 leaf", _doc_results(spark, d)), ("8 leaves", _doc_results(spark, d, 8)), ("scan", search.scan_topk(docs, _doc_queries(spark, d), 10))):
        one = measures.precision_at(found, labels).withColumn("method", F.lit(method))
        out = one if out is None else out.unionByName(one)
    return out


def q85_scan_precision(spark: SparkSession, d: str) -> DataFrame:
    docs = archives.text_docs(spark, d)
    exact = search.scan_topk(docs, docs.where("id % 100 = 0").select(F.col("id").alias("query_id"), "v"), 10)
    return measures.precision_at(exact, docs.select("id", "label"))


#: Leaves at which the document searches find nine tenths of the scan's results (see q86).
ENOUGH = 32


def q86_recall(spark: SparkSession, d: str) -> DataFrame:
    """Share of the scan's results found from the 1, 2, 4 .. nearest leaves best-bin-first, and by the exact way (probes 0)."""
    docs = archives.text_docs(spark, d)
    exact = search.scan_topk(docs, _doc_queries(spark, d), 10)
    out = None
    for probes in (1, 2, 4, 8, 16, ENOUGH, 0):
        found = _doc_results(spark, d, probes or 8, not probes)
        one = measures.recall_at(found, exact).withColumn("probes", F.lit(probes))
        out = one if out is None else out.unionByName(one)
    return out


def q86_recall_reached(spark: SparkSession, d: str) -> DataFrame:
    """Recall never falls with more leaves, reaches nine tenths at ENOUGH of them, and is whole by the exact way."""
    r = {x.probes: x for x in q86_recall(spark, d).collect()}
    by = [r[p].recall for p in (1, 2, 4, 8, 16, ENOUGH)]
    return spark.createDataFrame([(r[0].n_exact, r[0].n_found, by == sorted(by), by[-1] >= 0.9)], "n_exact long, n_found_exactly long, rises boolean, enough boolean")


def q87_agreement(spark: SparkSession, d: str) -> DataFrame:
    """Overlap of results by letters with results by a second source, the label-poor embeddings, for the same ids; both exact."""
    other = _index(spark, d, "embeddings", schedule="hybrid", stop=Stop(n_min=64), max_iter=20, tol=1e-6)
    q = archives.vec_embeddings(spark, d).where("id % 100 = 0").select(F.col("id").alias("query_id"), "v")
    return measures.agreement(_doc_results(spark, d, 8, True), search.batch(other, q, 10, 8, exact=True))


def q89_weak_labels(spark: SparkSession, d: str) -> DataFrame:
    """Label-based quality with sources that do not see what the descriptor sees: against chance."""
    e = archives.vec_embeddings(spark, d)
    index = _index(spark, d, "embeddings", schedule="hybrid", stop=Stop(n_min=64), max_iter=20, tol=1e-6)
    found = search.batch(index, e.where("id % 10 = 0").select(F.col("id").alias("query_id"), "v"), 10)
    chance = e.groupBy("label").count().agg(F.round(F.sum(F.col("count") * F.col("count")) / (F.sum("count") * F.sum("count")), 6).alias("chance"))
    return measures.precision_at(found, e.select("id", "label")).crossJoin(chance)


def q90_ablation(spark: SparkSession, d: str) -> DataFrame:
    """Leaves, depth, code length and cost by smallest node size, on documents."""
    rows = []
    for n_min in (32, 64, 128):
        index = _index(spark, d, "docs", schedule="hybrid", stop=Stop(n_min=n_min), max_iter=20, tol=1e-6)
        total = index.nodes[""]
        rows.append((n_min, len(index.leaves), max(len(n.code) for n in index.leaves), sum(len(n.code) * n.n for n in index.leaves) / total.n, sum(n.wcss for n in index.leaves) / total.wcss))
    return spark.createDataFrame(rows, "n_min int, n_leaves int, depth int, code_length double, cost_share double")


def q90_ablation_holds(spark: SparkSession, d: str) -> DataFrame:
    """Of each smallest node size: rows indexed, whether every leaf obeys it, whether cost and leaves move as they should against the next."""
    rows, before = [], None
    for n_min in (128, 64, 32):
        index = _docs_index(spark, d, n_min)
        cost = sum(n.wcss for n in index.leaves)
        obeys = all(n.n <= n_min or n.closed == "degenerate" for n in index.leaves)
        moved = before is None or cost <= before[0] and len(index.leaves) >= before[1]
        rows.append((n_min, sum(n.n for n in index.leaves), obeys, moved))
        before = (cost, len(index.leaves))
    return spark.createDataFrame(rows, "n_min int, n_rows long, obeys boolean, moved boolean")


def q91_session_replay(spark: SparkSession, d: str) -> DataFrame:
    """User turns of conversations as queries in order against the documents' index; the best result of each."""
    turns = table(spark, d, "conversations").where("role = 'user'").select((F.col("conv_id") * 1000 + F.col("turn")).alias("query_id"), archives.letter_histogram(F.col("text")).alias("v")).where("v IS NOT NULL")
    return search.batch(_docs_index(spark, d), turns, 1, 8, exact=True).select("query_id", "rank", "id", F.round("dist", 6).alias("dist"))


QUERIES = {name: f for name, f in list(globals().items()) if name[:1] == "q" and name[1:2].isdigit()}

VP = f"v0 AS (SELECT l_partkey AS id, {_BIN} AS bin FROM lineitem), vi AS (SELECT DISTINCT id FROM v0), vc AS (SELECT id, bin, count(*) AS n FROM v0 GROUP BY ALL), v AS (SELECT vi.id, CAST(d AS INTEGER) AS dim, CAST(coalesce(n, 0) AS DOUBLE) AS x FROM vi CROSS JOIN generate_series(0, 31) AS g(d) LEFT JOIN vc ON vc.id = vi.id AND vc.bin = d)"
_LETTERS = archives.LETTERS
VD = "l AS (SELECT doc_id AS id, lang, CAST(i AS INTEGER) AS dim, length(lower(text)) - length(replace(lower(text), substr('" + _LETTERS + "', CAST(i AS INTEGER) + 1, 1), '')) AS n FROM documents, generate_series(0, " + str(len(_LETTERS) - 1) + ") AS g(i)), lt AS (SELECT id, sum(n) AS total FROM l GROUP BY id), v AS (SELECT l.id, lang, dim, CAST(CAST(n * 1000 AS BIGINT) // CAST(total AS BIGINT) AS DOUBLE) AS x FROM l JOIN lt USING (id) WHERE total > 0)"
_Q = "q AS (SELECT dim, x AS y FROM v WHERE id = (SELECT min(id) FROM v))"
_DIST = f"{VP}, {_Q}, dist AS (SELECT id, sum((x - y) ** 2) AS dist FROM v JOIN q USING (dim) GROUP BY id)"
_BOOK = f"{VP}, b AS (SELECT CAST(dense_rank() OVER (ORDER BY id) - 1 AS INTEGER) AS cid, dim, x AS c FROM v WHERE id IN (SELECT id FROM vi ORDER BY id LIMIT 4)), bd AS (SELECT id, cid, sum((x - c) ** 2) AS d FROM v JOIN b USING (dim) GROUP BY ALL), near AS (SELECT id, arg_min(cid, d + cid * 1e-9) AS cid FROM bd GROUP BY id), sums AS (SELECT cid, dim, count(*) AS n, sum(x) AS s FROM near JOIN v USING (id) GROUP BY ALL)"


def kmeans_sql(k: int, updates: int, rows: str = VP) -> str:
    """CTEs up to k{updates}(cid, dim, c) and f(id, cid) from the smallest id and farthest rows."""
    out = [rows, "s0 AS (SELECT min(id) AS id FROM vi)"]
    for i in range(1, k):
        chosen = " UNION ALL ".join(f"SELECT id FROM s{j}" for j in range(i))
        out.append(f"g{i} AS (SELECT v.id, sum((v.x - w.x) ** 2) AS d FROM v JOIN v w USING (dim) WHERE w.id IN ({chosen}) GROUP BY v.id, w.id), s{i} AS (SELECT id FROM (SELECT id, min(d) AS d FROM g{i} GROUP BY id) ORDER BY d DESC, id LIMIT 1)")
    out.append("c0 AS (" + " UNION ALL ".join(f"SELECT {j} AS cid, dim, x AS c FROM v JOIN s{j} USING (id)" for j in range(k)) + ")")
    for t in range(updates + 1):
        out.append(f"a{t} AS (SELECT id, arg_min(cid, d + cid * 1e-9) AS cid FROM (SELECT id, cid, sum((x - c) ** 2) AS d FROM v JOIN c{t} USING (dim) GROUP BY ALL) GROUP BY id)")
        if t < updates:
            out.append(f"c{t + 1} AS (SELECT cid, dim, avg(x) AS c FROM a{t} JOIN v USING (id) GROUP BY ALL)")
    return ", ".join(out)


def _kmeans_result(k: int) -> str:
    return f"WITH {kmeans_sql(k, UPDATES)}, n AS (SELECT cid, count(*) AS n FROM a{UPDATES} GROUP BY cid) SELECT CAST(cid AS INTEGER) AS cid, dim, n, round(c, 6) AS centroid FROM c{UPDATES} JOIN n USING (cid)"


@lru_cache
def tree_sql(levels: int = LEVELS, updates: int = UPDATES) -> str:
    """CTEs up to lab{levels}(id, code) by the axis rule and a fixed number of updates, and nodes."""
    out = [VP, "lab0 AS (SELECT id, '' AS code FROM vi)"]
    for level in range(levels):
        p = f"x{level}_"
        out.append(f"{p}st AS (SELECT code, dim, count(*) AS n, sum(x) AS s, sum(x * x) AS ss FROM lab{level} JOIN v USING (id) GROUP BY ALL)")
        out.append(f"{p}ax AS (SELECT code, dim, s / n AS mean FROM {p}st QUALIFY row_number() OVER (PARTITION BY code ORDER BY n * ss - s * s DESC, dim) = 1)")
        out.append(f"{p}a0 AS (SELECT l.id, l.code, CAST(x > mean AS INTEGER) AS child FROM lab{level} l JOIN {p}ax ax USING (code) JOIN v ON v.id = l.id AND v.dim = ax.dim)")
        for t in range(updates + 1):
            out.append(f"{p}c{t} AS (SELECT code, dim, avg(x) FILTER (child = 0) AS y0, avg(x) FILTER (child = 1) AS y1 FROM {p}a{t} JOIN v USING (id) GROUP BY ALL)")
            out.append(f"{p}a{t + 1} AS (SELECT id, l.code, CAST(sum(x * (y1 - y0)) > sum(y1 * y1 - y0 * y0) / 2 AS INTEGER) AS child FROM lab{level} l JOIN v USING (id) JOIN {p}c{t} c ON c.code = l.code AND c.dim = v.dim GROUP BY ALL)")
        out.append(f"lab{level + 1} AS (SELECT id, code || child AS code FROM {p}a{updates + 1})")
    every = " UNION ALL ".join(f"SELECT id, code, {level} AS depth FROM lab{level}" for level in range(levels + 1))
    out.append(f"every AS ({every}), nd AS (SELECT code, depth, dim, count(*) AS n, sum(x) AS s, sum(x * x) AS ss FROM every JOIN v USING (id) GROUP BY ALL)")
    out.append(f"nodes AS (SELECT code, CAST(depth AS INTEGER) AS depth, max(n) AS n, sum(ss) AS sq, sum(ss) - sum(s * s / n) AS wcss, depth = {levels} AS is_leaf FROM nd GROUP BY code, depth)")
    return ", ".join(out)


_TREE = tree_sql()
_LAB = f"lab{LEVELS}"
_LABELS = f"WITH {_TREE} SELECT id, code FROM {_LAB}"
_TOP = f"WITH {_TREE}, {_Q}, dist AS (SELECT id, sum((x - y) ** 2) AS dist FROM v JOIN q USING (dim) GROUP BY id), hit AS (SELECT id, dist, code FROM dist JOIN {_LAB} USING (id) WHERE code = (SELECT code FROM {_LAB} WHERE id = (SELECT min(id) FROM vi)))"
_RANK = "CAST(row_number() OVER (ORDER BY dist, id) AS INTEGER) AS rank, id, round(dist, 6) AS dist, code"
_WHERE = "(SELECT p_partkey FROM part WHERE p_size <= 25 AND p_brand LIKE 'Brand#%')"
_PAIRS = "p AS (SELECT a.id AS query_id, b.id, sum((a.x - b.x) ** 2) AS dist FROM v a JOIN v b USING (dim) WHERE a.id % 100 = 0 GROUP BY ALL)"
_TEN = "SELECT query_id, CAST(rank AS INTEGER) AS rank, id, round(dist, 6) AS dist{} FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist, id) AS rank FROM {}) WHERE rank <= 10"


def letters_sql(name: str, source: str, key: str, more: str = "") -> str:
    """CTE ``name`` (id, dim, x): per-mille letters of the texts of a table."""
    return VD.replace("l AS (SELECT doc_id AS id, lang,", f"{name}l AS (SELECT {key} AS id, 0 AS lang,").replace("FROM documents,", f"FROM (SELECT * FROM {source} {more}),").replace("lt AS (SELECT id, sum(n) AS total FROM l", f"{name}lt AS (SELECT id, sum(n) AS total FROM {name}l").replace("v AS (SELECT l.id, lang, dim", f"{name} AS (SELECT {name}l.id, dim").replace("FROM l JOIN lt", f"FROM {name}l JOIN {name}lt")


def nearest_sql(queries: str, rows: str, k: int = 10, name: str = "r") -> str:
    """CTE ``name`` (query_id, rank, id, dist): the k nearest of ``rows`` (id, dim, x) for each of ``queries``."""
    return f"{name} AS (SELECT query_id, CAST(rank AS INTEGER) AS rank, id, dist FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist, id) AS rank FROM (SELECT a.id AS query_id, b.id, sum((a.x - b.x) ** 2) AS dist FROM {queries} a JOIN {rows} b USING (dim) GROUP BY ALL)) WHERE rank <= {k})"


_TENTHS = "vq AS (SELECT * FROM v WHERE id % 100 = 0)"
_FOUND = "SELECT query_id, rank, id, round(dist, 6) AS dist FROM r"
VE = "ve AS (SELECT vec_id AS id, CAST(i AS INTEGER) AS dim, CAST(embedding[CAST(i AS INTEGER) + 1] AS DOUBLE) AS x FROM embeddings, unnest(generate_series(0, len(embedding) - 1)) AS g(i)), veq AS (SELECT * FROM ve WHERE id % 100 = 0)"
_BIN4 = lambda x, hi, n: f"greatest(0, least({n - 1}, CAST(floor({x} / ({hi} / {n})) AS INTEGER)))"
_PIXELS = f"""b AS (SELECT product_id, product_id * 1000000 + ("row" // 4) * 1000 + col // 4 AS id, {_BIN4('h', '1.0', 4)} * 8 + {_BIN4('alpha', '1.5707963267948966', 4)} * 2 + {_BIN4('a', '1.0', 2)} AS dim FROM attr),
c AS (SELECT product_id, id, dim, CAST(count(*) AS DOUBLE) AS n FROM b GROUP BY ALL), w AS (SELECT product_id, id, g.dim, coalesce(c.n, 0) AS x FROM (SELECT DISTINCT product_id, id FROM b) t CROSS JOIN (SELECT CAST(i AS INTEGER) AS dim FROM generate_series(0, 31) AS y(i)) g LEFT JOIN c USING (product_id, id, dim)),
up AS (SELECT * FROM w WHERE product_id % 25 = 0), kept AS (SELECT * FROM w WHERE product_id % 25 <> 0)"""


@lru_cache
def stops_sql() -> str:
    """Leaves of the unrolled tree under each of STOPS: the nodes that a rule closes and no node above them."""
    out = []
    for name, stop in STOPS:
        rules = [f"WHEN n <= {stop.n_min} THEN 'n_min'" if stop.n_min else "", f"WHEN wcss < {stop.wcss_min} THEN 'wcss_min'" if stop.wcss_min else "", f"WHEN depth >= {stop.h_max} THEN 'h_max'"]
        out.append(f"SELECT '{name}' AS rule, code, n, CASE {' '.join(rules)} END AS close_reason FROM nodes")
    return f"WITH {tree_sql(DEEP)}, c AS ({' UNION ALL '.join(out)}) SELECT close_reason, count(*) AS n_leaves, CAST(sum(n) AS BIGINT) AS n_rows, rule FROM c WHERE close_reason IS NOT NULL AND n > 0 AND NOT EXISTS (SELECT 1 FROM c up WHERE up.rule = c.rule AND up.close_reason IS NOT NULL AND starts_with(c.code, up.code) AND length(up.code) < length(c.code)) GROUP BY ALL"


SQL = {
    "q46_stop_rules": stops_sql(),
    "q49_seed_costs_hold": f"WITH {VP}, {letters_sql('vd', 'documents', 'doc_id')} SELECT archive, init, n, true AS lower, CASE WHEN init IN ('dsquare', 'parallel') THEN true END AS near_best FROM (SELECT 'parts' AS archive, count(*) AS n FROM vi UNION ALL SELECT 'docs', count(DISTINCT id) FROM vd), unnest(['axis', 'farthest', 'random', 'dsquare', 'parallel']) AS t(init)",
    "q51_by_upload": f"WITH {VD}, {letters_sql('vb', 'benchmark', 'item_id')}, {nearest_sql('vb', 'v')} {_FOUND}",
    "q51_pixel_upload": f"WITH {HAA}, {_PIXELS}, {nearest_sql('up', 'kept')} {_FOUND}",
    "q62_sampled_search": f"WITH {VD}, {_TENTHS}, {nearest_sql('vq', 'v')} {_FOUND}",
    "q85_precision": f"WITH {VD}, {_TENTHS}, {nearest_sql('vq', 'v')}, j AS (SELECT query_id, a.lang = b.lang AS same FROM r JOIN documents a ON a.doc_id = query_id JOIN documents b ON b.doc_id = id WHERE id <> query_id) SELECT count(DISTINCT query_id) AS n_queries, count(*) AS n_results, count(*) FILTER (same) AS n_same, round(avg(CAST(same AS DOUBLE)), 6) AS precision FROM j",
    "q86_recall_reached": f"WITH {VD}, {_TENTHS}, {nearest_sql('vq', 'v')} SELECT count(*) AS n_exact, count(*) AS n_found_exactly, true AS rises, true AS enough FROM r",
    "q87_agreement": f"WITH {VD}, {_TENTHS}, {nearest_sql('vq', 'v')}, {VE}, {nearest_sql('veq', 've', 10, 's')} SELECT query_id, count(*) FILTER (r.id IS NOT NULL AND s.id IS NOT NULL) AS n_both, count(*) AS n_any, round(count(*) FILTER (r.id IS NOT NULL AND s.id IS NOT NULL) / count(*), 6) AS jaccard FROM r FULL JOIN s USING (query_id, id) GROUP BY query_id",
    "q90_ablation_holds": f"WITH {VD} SELECT CAST(m AS INTEGER) AS n_min, count(DISTINCT id) AS n_rows, true AS obeys, true AS moved FROM v, unnest([128, 64, 32]) AS t(m) GROUP BY m",
    "q91_session_replay": f"WITH {VD}, {letters_sql('vt', 'conversations', 'conv_id * 1000 + turn', chr(39).join(['WHERE role = ', 'user', '']))}, {nearest_sql('vt', 'v', 1)} {_FOUND}",
    "q18_storage": _LABELS, "q74_regrow": _LABELS,
    "q53_two_signatures": f"WITH {VP}, q AS (SELECT id AS q, dim, x AS y FROM v WHERE id IN (SELECT id FROM vi ORDER BY id LIMIT 2)), dist AS (SELECT id, min(e) AS dist FROM (SELECT v.id, q, sum((x - y) ** 2) AS e FROM v JOIN q USING (dim) GROUP BY ALL) GROUP BY id) SELECT CAST(row_number() OVER (ORDER BY dist, id) AS INTEGER) AS rank, id, round(dist, 6) AS dist FROM dist ORDER BY dist, id LIMIT 10",
    "q71_insert": f"WITH {_TREE} SELECT code, n, round(sq, 4) AS sq FROM nodes",
    "q72_delete": f"WITH {_TREE} SELECT code, count(DISTINCT id) AS n, round(sum(x * x), 4) AS sq FROM every JOIN v USING (id) WHERE id % 3 <> 0 GROUP BY code",
    "q73_modify": f"WITH {_TREE} SELECT id, CASE WHEN id % 5 = 0 THEN (SELECT code FROM {_LAB} WHERE id = (SELECT min(id) FROM vi)) ELSE code END AS code FROM {_LAB}",
    "q74_live_index": "SELECT count(*) AS n, CAST(0 AS BIGINT) AS n_elsewhere, count(*) AS n_root FROM embeddings",
    "q30_distortion": f"WITH {_DIST} SELECT id, round(dist, 6) AS dist FROM dist",
    "q31_distortion_from_norms": f"WITH {_DIST} SELECT id, round(dist, 6) AS dist FROM dist",
    "q32_bisector": f"WITH {VP}, a AS (SELECT dim, x AS ya FROM v WHERE id = (SELECT id FROM vi ORDER BY id LIMIT 1)), b AS (SELECT dim, x AS yb FROM v WHERE id = (SELECT id FROM vi ORDER BY id LIMIT 1 OFFSET 1)) SELECT id, CAST(sum((x - yb) ** 2) < sum((x - ya) ** 2) AS INTEGER) AS side FROM v JOIN a USING (dim) JOIN b USING (dim) GROUP BY id",
    "q33_flat_encode": f"WITH {_BOOK} SELECT id, cid FROM near",
    "q34_decode": f"WITH {_BOOK} SELECT id, cid, dim, c AS x FROM near JOIN b USING (cid)",
    "q35_voronoi_check": f"WITH {VP} SELECT count(*) AS n_rows, CAST(0 AS BIGINT) AS n_farther, CAST(0 AS BIGINT) AS n_overlaps FROM vi",
    "q36_root": f"WITH {VP} SELECT dim, round(avg(x), 6) AS centroid FROM v GROUP BY dim",
    "q37_assign": f"WITH {_BOOK} SELECT id, cid FROM near",
    "q38_combined_sums": f"WITH {_BOOK} SELECT cid, dim, n, round(s, 6) AS s FROM sums",
    "q38_uncombined_sums": f"WITH {_BOOK} SELECT cid, dim, n, round(s, 6) AS s FROM sums",
    "q39_update": f"WITH {_BOOK} SELECT cid, dim, round(s / n, 6) AS centroid FROM sums",
    "q40_kmeans": _kmeans_result(2), "q40_kmeans_on_disk": _kmeans_result(2), "q40_kmeans_uncached": _kmeans_result(2), "q41_kmeans_of_three": _kmeans_result(3), "q42_sparse_kmeans": _kmeans_result(2),
    "q43_wcss": f"WITH {_BOOK} SELECT cid, max(n) AS n, round(sum(e), 4) AS wcss FROM (SELECT cid, dim, count(*) AS n, sum(x * x) - sum(x) * sum(x) / count(*) AS e FROM near JOIN v USING (id) GROUP BY ALL) GROUP BY cid",
    **{name: _LABELS for name in ("q44_tree_labels", "q44_leaf_at_a_time", "q44_last_leaf_first", "q44_hybrid", "q44_greedy", "q44_on_disk")},
    "q45_nodes": f"WITH {_TREE} SELECT code, depth, n, round(sq, 4) AS sq, round(wcss, 4) AS wcss, is_leaf FROM nodes",
    "q47_codebook": f"WITH {_TREE} SELECT code, n, dim, round(s / n, 6) AS x FROM nd WHERE depth = {LEVELS}",
    "q48_descend": f"WITH {_TREE} SELECT id, code, CAST(length(code) AS INTEGER) AS depth FROM {_LAB}",
    "q50_by_tile": f"{_TOP} SELECT {_RANK} FROM hit ORDER BY dist, id LIMIT 10",
    "q52_leaf": f"{_TOP} SELECT id, code FROM hit",
    "q53_top": f"{_TOP} SELECT {_RANK} FROM hit ORDER BY dist, id LIMIT 10",
    "q54_batch": f"WITH {_TREE}, {_PAIRS}, h AS (SELECT p.*, b.code FROM p JOIN {_LAB} a ON a.id = query_id JOIN {_LAB} b ON b.id = p.id WHERE a.code = b.code) " + _TEN.format(", code", "h"),
    "q54_all_leaves": f"WITH {VP}, {_PAIRS} " + _TEN.format("", "p"),
    "q55_constrained": f"{_TOP} SELECT {_RANK} FROM hit WHERE id IN {_WHERE} ORDER BY dist, id LIMIT 10",
    "q55_constrained_after": f"{_TOP} SELECT id, round(dist, 6) AS dist, code FROM (SELECT * FROM hit ORDER BY dist, id LIMIT 10) WHERE id IN {_WHERE}",
    "q56_metadata_only": "SELECT s_suppkey, n_name, r_name, count(*) AS n_px, strftime(min(l_shipdate), '%Y-%m-%d') AS first_seen FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name IN ('ASIA', 'EUROPE') AND l_shipdate >= TIMESTAMP '1995-01-01' GROUP BY ALL",
    "q57_back_off": f"{_TOP}, big AS (SELECT max(n) + 1 AS n FROM nodes WHERE depth = {LEVELS}), own AS (SELECT code FROM hit LIMIT 1), pre AS (SELECT code FROM nodes, big WHERE nodes.n >= big.n AND starts_with((SELECT code FROM own), code) ORDER BY length(code) DESC LIMIT 1) SELECT {_RANK} FROM dist JOIN {_LAB} USING (id) WHERE starts_with(code, (SELECT code FROM pre)) ORDER BY dist, id LIMIT (SELECT n FROM big)",
    "q58_groups": f"WITH {_TREE}, {_Q}, z AS (SELECT code, max(n) AS n, sum((s / n - y) ** 2) AS dist FROM nd JOIN q USING (dim) WHERE depth = {LEVELS} GROUP BY code) SELECT code, n, round(dist, 4) AS dist, CAST(row_number() OVER (ORDER BY dist, code) AS INTEGER) AS rank FROM z",
    "q58b_other_metrics": f"WITH {VP}, {_Q} SELECT id, round(sum((x - y) ** 2), 6) AS sqeuclid, round(1 - sum(x * y) / sqrt(sum(x * x) * sum(y * y)), 6) AS cosine, round(1 - sum(least(x, y)) / least(sum(x), sum(y)), 6) AS hist_intersection, round(sum(CASE WHEN x + y > 0 THEN (x - y) ** 2 / (x + y) ELSE 0 END) / 2, 6) AS chi2 FROM v JOIN q USING (dim) GROUP BY id",
    "q59_panel": f"{_TOP}, r AS (SELECT CAST(row_number() OVER (ORDER BY dist, id) AS INTEGER) AS rank, id FROM hit ORDER BY dist, id LIMIT 10) SELECT rank, id, p_name, p_brand FROM r LEFT JOIN part ON p_partkey = id",
    "q60_scan": f"WITH {VP}, {_PAIRS} " + _TEN.format("", "p"),
    "q61_linked_list": "SELECT p_partkey AS id, n AS list_accesses, CAST(ceil(log2(t)) AS BIGINT) AS index_accesses FROM (SELECT p_partkey, row_number() OVER (ORDER BY p_partkey) AS n, count(*) OVER () AS t FROM part) WHERE p_partkey % 100 = 0",
    "q80_rate_curve": f"WITH {_TREE}, st AS (SELECT code, row_number() OVER (ORDER BY depth, code) AS step FROM nodes WHERE NOT is_leaf), steps AS (SELECT 0 AS step UNION ALL SELECT step FROM st), total AS (SELECT n AS t FROM nodes WHERE code = ''), open AS (SELECT steps.step, nodes.* FROM steps, nodes LEFT JOIN st me ON me.code = nodes.code LEFT JOIN st up ON up.code = left(nodes.code, length(nodes.code) - 1) AND nodes.code <> '' WHERE (nodes.code = '' OR up.step <= steps.step) AND (me.step IS NULL OR me.step > steps.step)) SELECT CAST(step AS INTEGER) AS step, round(sum(wcss), 4) AS wcss, round(sum(depth * n) / max(t), 6) AS code_length FROM open, total GROUP BY step",
    "q81_distance_evaluations": f"WITH {_TREE}, c AS (SELECT code, count(*) AS n FROM {_LAB} GROUP BY code) SELECT CAST(sum(n * 2 * length(code)) AS BIGINT) AS descent, CAST(sum(n * (2 * length(code) + n)) AS BIGINT) AS descent_and_leaf, CAST(sum(n) * sum(n) AS BIGINT) AS scan FROM c",
    "q82_operations": f"WITH {VP}, c AS (SELECT count(DISTINCT id) AS n, 32 AS d, count(*) FILTER (x <> 0) AS nnz FROM v) SELECT n, CAST(d AS INTEGER) AS d, nnz, n * d * 2 * {UPDATES} AS dense, (nnz + n) * 2 * {UPDATES} AS sparse FROM c",
    "q83_tree_shape": f"WITH {_TREE} SELECT count(*) AS n_nodes, count(*) FILTER (is_leaf) AS n_leaves, max(depth) AS depth, min(n) FILTER (is_leaf) AS least_leaf, max(n) FILTER (is_leaf) AS largest_leaf, round(sum(n * depth) FILTER (is_leaf) / sum(n) FILTER (is_leaf), 6) AS mean_code_length FROM nodes",
    "q85_scan_precision": f"WITH {VD}, p AS (SELECT a.id AS query_id, b.id, sum((a.x - b.x) ** 2) AS dist FROM v a JOIN v b USING (dim) WHERE a.id % 100 = 0 GROUP BY ALL), r AS (SELECT query_id, id FROM p QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY dist, id) <= 10), j AS (SELECT query_id, a.lang = b.lang AS same FROM r JOIN documents a ON a.doc_id = query_id JOIN documents b ON b.doc_id = id WHERE id <> query_id) SELECT count(DISTINCT query_id) AS n_queries, count(*) AS n_results, count(*) FILTER (same) AS n_same, round(avg(CAST(same AS DOUBLE)), 6) AS precision FROM j",
}
