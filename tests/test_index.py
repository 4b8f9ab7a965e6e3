import numpy as np
import pytest
from pyspark.sql import functions as F

from tilemine.functions import vector
from tilemine.operators import kmeans, measures, search, tsvq
from tilemine.operators.tsvq import Stop
from tilemine.plans.retrieve import RetrievePlan
from tilemine.sources import archives, storage

INITS = ("axis", "farthest", "random", "dsquare", "parallel")


def points(spark, values):
    return spark.createDataFrame([(i, [float(x) for x in (v if isinstance(v, (list, tuple)) else [v])]) for i, v in enumerate(values)], "id long, v array<double>")


@pytest.fixture(scope="module")
def cloud(spark):
    r = np.random.default_rng(2)
    x = np.concatenate([r.normal(c, 0.6, (60, 3)) for c in ((0, 0, 0), (5, 5, 0), (0, 6, 6), (9, 0, 3))]).round(3)
    return points(spark, [list(v) for v in x]).repartition(3).cache()


def codes(index):
    return {r.id: r.code for r in index.labelled.select("id", "code").collect()}


def test_one_dimension_by_hand(spark):
    df = points(spark, [1, 2, 10, 11])
    model = kmeans.fit(df, 2)
    assert sorted(model.centroids[:, 0]) == [1.5, 10.5] and model.wcss == 1.0
    index = tsvq.grow(df, Stop(h_max=2, n_min=1))
    assert codes(index) == {0: "00", 1: "01", 2: "10", 3: "11"} and abs(index.nodes[""].wcss - 82) < 1e-9
    assert all(n.wcss == 0 for n in index.leaves)
    index = tsvq.grow(df, Stop(n_min=2))
    assert {n.code: n.closed for n in index.leaves} == {"0": "n_min", "1": "n_min"}


def test_equal_points_and_ties(spark):
    index = tsvq.grow(points(spark, [5, 5, 5]), Stop())
    assert [(n.code, n.closed) for n in index.leaves] == [("", "degenerate")]
    assert [n.closed for n in tsvq.grow(points(spark, [5, 5, 5]), Stop(wcss_min=0.1)).leaves] == ["wcss_min"]
    tie = spark.createDataFrame([([1.0], [2.0], 2.0)], "x array<double>, w array<double>, b double")
    assert tie.select(vector.side(F.col("x"), F.col("w"), F.col("b"))).first()[0] == 0
    assert tsvq.grow(points(spark, []), Stop()).nodes == {}


@pytest.mark.parametrize("init", INITS)
@pytest.mark.parametrize("other", [{"schedule": "leaf"}, {"schedule": "leaf", "order": "lifo"}, {"schedule": "hybrid", "local_rows": 130}, {"schedule": "hybrid", "local_rows": 1000}, {"materialise": "dfs"}, {"combine": False}])
def test_schedules_give_the_same_tree(cloud, init, other):
    if init != "axis" and other.get("schedule") != "hybrid":
        pytest.skip("covered by the axis rule")
    stop = Stop(n_min=20, h_max=3)
    a, b = tsvq.grow(cloud, stop, init, seed=3), tsvq.grow(cloud, stop, init, seed=3, **other)
    assert codes(a) == codes(b)
    assert {c: (n.n, n.closed) for c, n in a.nodes.items()} == {c: (n.n, n.closed) for c, n in b.nodes.items()}


@pytest.mark.parametrize("init", INITS)
def test_rows_sit_at_the_nearer_sibling(cloud, init):
    index = tsvq.grow(cloud, Stop(n_min=20, h_max=3), init, max_iter=50, tol=0.0)
    x = {r.id: np.array(r.v) for r in cloud.collect()}
    for i, code in codes(index).items():
        for d in range(len(code)):
            y = [index.nodes[code[:d] + b].centroid for b in "01"]
            dist = [((x[i] - c) ** 2).sum() for c in y]
            assert dist[int(code[d])] <= dist[1 - int(code[d])] + 1e-9
    assert codes(index) == {r.id: r.code for r in tsvq.descend(tsvq.prepare(cloud), index.nodes).collect()}


def test_greedy_lowers_cost_and_stops_at_max_leaves(cloud):
    index = tsvq.grow(cloud, Stop(), schedule="greedy", max_leaves=4)
    assert len(index.leaves) == 4 and sum(n.wcss for n in index.leaves) < 0.1 * index.nodes[""].wcss


def test_rate_curve_is_monotone(cloud):
    curve = measures.rate_curve(tsvq.grow(cloud, Stop(n_min=10), schedule="hybrid"))
    assert all(a["wcss"] >= b["wcss"] and a["code_length"] < b["code_length"] for a, b in zip(curve, curve[1:]))


def test_dense_sparse_memory_disk_agree(cloud):
    sparse = cloud.withColumn("idx", F.sequence(F.lit(0), F.lit(2))).withColumn("val", F.col("v"))
    a = kmeans.fit(cloud, 3, max_iter=6)
    for b in (kmeans.fit(sparse, 3, max_iter=6, layout="sparse"), kmeans.fit(cloud, 3, max_iter=6, materialise="dfs"), kmeans.fit(cloud, 3, max_iter=6, materialise="none"), kmeans.fit(cloud, 3, max_iter=6, combine=False)):
        assert np.allclose(a.centroids, b.centroids) and a.counts == b.counts and abs(a.wcss - b.wcss) < 1e-6


def test_kmeans_improves_until_it_stops(cloud):
    model = kmeans.fit(cloud, 4, "dsquare", tol=0.0, max_iter=50, seed=1)
    assert model.moves[-1] == 0 and model.iterations < 50 and sum(model.counts) == 240
    total = measures.wcss(kmeans.assign(cloud, model.centroids), "cid").agg(F.sum("wcss")).first()[0]
    assert abs(total - model.wcss) < 1e-6


def test_search_with_one_leaf_or_all_leaves_is_the_scan(cloud):
    q = cloud.where("id % 30 = 0").select(F.col("id").alias("query_id"), "v")
    exact = sorted(map(tuple, search.scan_topk(cloud, q, 7).collect()))
    blocks = sorted(map(tuple, search.scan_topk(cloud, q, 7, block=3).collect()))
    assert [r[:3] for r in exact] == [r[:3] for r in blocks]
    single = tsvq.grow(cloud, Stop(h_max=0))
    got = search.batch(single, q, 7).select("query_id", "rank", "id").collect()
    assert sorted(map(tuple, got)) == [r[:3] for r in exact]
    index = tsvq.grow(cloud, Stop(n_min=20), schedule="hybrid")
    every = search.batch(index, q, 7, probes=len(index.leaves))
    assert sorted(tuple(r)[:3] for r in every.collect()) == [r[:3] for r in exact]
    recalls = [measures.recall_at(search.batch(index, q, 7, probes=p), search.scan_topk(cloud, q, 7), 7).first().recall for p in (1, 2, 4)]
    assert recalls == sorted(recalls) and measures.recall_at(every, search.scan_topk(cloud, q, 7), 7).first().recall == 1.0


def test_constraints_before_and_after(cloud):
    index = tsvq.grow(cloud, Stop(n_min=20), schedule="hybrid")
    v = search.vector_of(index, 7)
    ids = cloud.where("id % 2 = 1").select("id")
    pre = {r.id for r in search.constrained(index, v, ids, 1000).collect()}
    post = {r.id for r in search.constrained(index, v, ids, 1000, "post").collect()}
    assert pre == post and all(i % 2 for i in pre)
    plan = RetrievePlan((v,), 5, where=F.col("id") % 2 == 1)
    assert all(r.id % 2 for r in search.run(index, plan).collect())


def test_back_off_and_several_signatures(cloud):
    index = tsvq.grow(cloud, Stop(n_min=20), schedule="hybrid")
    v, w = search.vector_of(index, 7), search.vector_of(index, 200)
    assert search.by_vectors(index, [v], 100, backoff=True).count() == 100
    ids = {r.id for r in search.by_vectors(index, [v, w], 10_000).collect()}
    assert ids == {r.id for x in (v, w) for r in search.raw(index, x).collect()}
    assert search.by_id(index, 7, 1).first().id == 7
    with pytest.raises(KeyError):
        search.by_id(index, 10**6)


def test_maintenance(cloud, spark):
    stop = Stop(n_min=20)
    some, rest = cloud.where("id % 3 <> 0"), cloud.where("id % 3 = 0")
    index = tsvq.grow(some, stop, schedule="hybrid")
    more = tsvq.insert(index, rest)
    assert codes(more) == {r.id: r.code for r in tsvq.descend(tsvq.prepare(cloud), index.nodes).collect()}
    assert more.nodes[""].n == 240 and sum(n.n for n in more.leaves) == 240
    assert abs(more.nodes[""].wcss - tsvq.grow(cloud, Stop(h_max=0)).nodes[""].wcss) < 1e-6
    back = tsvq.delete(more, rest.select("id"))
    assert codes(back) == codes(index) and {c: n.n for c, n in back.nodes.items()} == {c: n.n for c, n in index.nodes.items()}
    moved = tsvq.modify(more, cloud.where("id = 4").select("id", F.array(*map(F.lit, (9.0, 0.0, 3.0))).alias("v")))
    assert moved.nodes[""].n == 240 and codes(moved)[4] == tsvq.descend_one(np.array([9.0, 0, 3]), index.nodes)
    grown = tsvq.regrow(more, stop, schedule="hybrid")
    assert all(n.closed for n in grown.leaves) and sum(n.n for n in grown.leaves) == 240 and max(n.n for n in grown.leaves) <= 20


def test_saved_index_is_the_same(cloud, spark, tmp_path):
    index = tsvq.grow(cloud, Stop(n_min=20), schedule="hybrid")
    tsvq.save(index, f"file://{tmp_path}/i")
    again = tsvq.load(spark, f"file://{tmp_path}/i")
    assert codes(again) == codes(index) and again.manifest["init"] == "axis"
    facts = measures.plan_facts(search.leaf(again, "0"))
    assert facts["EqualTo"] >= 1
    assert measures.plan_facts(again.labelled.where(F.col("code").startswith("0")))["StringStartsWith"] >= 1
    assert storage.size_of(spark, f"file://{tmp_path}/i") > 0


def test_plans(cloud):
    index = tsvq.grow(cloud, Stop(n_min=20), schedule="hybrid")
    q = cloud.limit(3).select(F.col("id").alias("query_id"), "v")
    assert measures.plan_facts(search.batch(index, q, 5))["WindowGroupLimit"] >= 1
    assert "TakeOrderedAndProject" in index.labelled.orderBy("id").limit(3)._jdf.queryExecution().executedPlan().toString()


def test_sampled_and_multi_index(cloud):
    index = search.sampled_index(cloud, 2, stop=Stop(n_min=10))
    assert index.nodes[""].n == 240
    q = cloud.where("id % 60 = 0").select(F.col("id").alias("query_id"), "v")
    merged = search.multi_index({"a": index, "b": tsvq.grow(cloud, Stop(n_min=20), schedule="hybrid")}, {"a": q, "b": q}, 5)
    assert merged.where("rank = 1 AND id = query_id").count() == 4


def test_documents_find_their_language(spark, sf):
    docs = archives.text_docs(spark, sf)
    index = tsvq.grow(docs, Stop(n_min=32), schedule="hybrid")
    q = docs.where("id % 20 = 0").select(F.col("id").alias("query_id"), "v")
    assert measures.precision_at(search.batch(index, q, 10), docs.select("id", "label")).first().precision >= 0.9


def test_bad_vectors_are_refused(spark):
    with pytest.raises(ValueError):
        storage.check_vectors(points(spark, [[1, 2], [1]]))
    assert storage.check_vectors(points(spark, [[1, 2], [3, 4]])) == 2


def test_leaves_come_best_bin_first_with_true_bounds(cloud):
    index = tsvq.grow(cloud, Stop(n_min=8))
    splits = {c: n.split for c, n in index.nodes.items() if n.split is not None}
    rows = [(r.code, np.array(r.v)) for r in index.labelled.collect()]
    x = np.array([2.5, 3.1, 0.4])
    found = tsvq.near_leaves(x, splits)
    assert sorted(c for c, _ in found) == sorted(n.code for n in index.leaves) and found[0][0] == tsvq.descend_one(x, index.nodes)
    bounds = [b for _, b in found]
    assert bounds == sorted(bounds) and bounds[0] == 0
    for code, bound in found:
        assert all(((x - v) ** 2).sum() >= bound - 1e-9 for c, v in rows if c == code)
    assert [c for c, _ in tsvq.near_leaves(x, splits, 3)] == [c for c, _ in found[:3]]
    assert [c for c, _ in tsvq.near_leaves(x, splits, radius=bounds[4])] == [c for c, b in found if b <= bounds[4]]


def test_exact_search_is_the_scan_and_reads_fewer_leaves(cloud):
    index = tsvq.grow(cloud, Stop(n_min=8))
    q = cloud.where("id % 20 = 0").select(F.col("id").alias("query_id"), "v")
    rows = lambda df: sorted((r.query_id, r["rank"], r.id, round(r.dist, 9)) for r in df.collect())
    scan = search.scan_topk(cloud, q, 5)
    assert rows(search.batch(index, q, 5, 1, exact=True)) == rows(scan) == rows(search.batch(index, q, 5, 3, exact=True))
    assert rows(search.batch(index, q, 300, 1, exact=True)) == rows(search.scan_topk(cloud, q, 300))
    recall = [measures.recall_at(search.batch(index, q, 5, m), scan, 5).first().recall for m in (1, 2, 4, 99)]
    assert recall == sorted(recall) and recall[-1] == 1
    reach = q.withColumn("radius", F.lit(0.5))
    assert tsvq.probe(reach, index.nodes).count() < q.count() * len(index.leaves) / 2
    with pytest.raises(ValueError):
        search.batch(index, q, 5, metric="cosine", exact=True)


@pytest.mark.parametrize("metric", sorted(vector.METRICS))
def test_scan_metrics_are_those_of_the_expressions(spark, metric):
    df = points(spark, [[i % 5 + 1, i % 3, (i * i) % 7] for i in range(40)])
    q = df.where("id < 3").select(F.col("id").alias("query_id"), "v")
    pairs = df.crossJoin(q.select("query_id", F.col("v").alias("qv"))).select("query_id", "id", vector.METRICS[metric](F.col("v"), F.col("qv")).alias("dist"))
    want = {(r.query_id, r.id): r.dist for r in pairs.collect()}
    got = search.scan_topk(df, q, 40, metric, block=2).collect()
    assert len(got) == 120 and all(abs(r.dist - want[r.query_id, r.id]) < 1e-9 for r in got)


def test_growing_keeps_one_copy_and_narrow_numbers(spark):
    df = spark.createDataFrame([(i, [i % 50, i % 7]) for i in range(400)], "id long, v array<int>")
    held = tsvq.Held(df, "memory")
    assert held.mine and dict(held.under.rows.dtypes)["v"] == "array<int>"
    held.under.rows.unpersist()
    cached = df.persist()
    assert not tsvq.Held(cached, "memory").mine
    many = {h: tsvq.grow(cached, Stop(n_min=4), materialise=h) for h in ("memory", "none", "dfs")}
    assert max(len(n.code) for n in many["memory"].leaves) > tsvq.REFRESH
    assert codes(many["memory"]) == codes(many["none"]) == codes(many["dfs"])
    assert {c: n.n for c, n in many["memory"].nodes.items()} == {c: n.n for c, n in many["dfs"].nodes.items()}
    cached.unpersist()


def test_regrowing_all_leaves_at_once_is_growing_on(cloud):
    index = tsvq.grow(cloud, Stop(h_max=2))
    whole = tsvq.grow(cloud, Stop(n_min=20, h_max=6))
    again = tsvq.regrow(index, Stop(n_min=20, h_max=6))
    assert codes(again) == codes(whole) and {c: n.n for c, n in again.nodes.items()} == {c: n.n for c, n in whole.nodes.items()}
    one = tsvq.regrow(index, Stop(n_min=20, h_max=6), [index.leaves[0].code])
    assert {n.code for n in index.leaves[1:]} <= {n.code for n in one.leaves} and sum(n.n for n in one.leaves) == cloud.count()
    assert all(n.closed != "kept" for n in one.leaves)


def test_over_sampling_draws_many_rows_a_round_and_reduces_by_weight(cloud):
    from tilemine.operators import passes, seeds

    rows = tsvq.prepare(cloud)
    first = {"": np.array(cloud.first().v)}
    drawn = []

    def draw(chosen, codes):
        drawn.append(passes.draw(rows, chosen, codes))
        return drawn[-1]

    found = seeds.oversampled(first, lambda now: passes.costs(rows, now), draw, 4, 1)
    assert len(drawn) == seeds.ROUNDS and max(len(d[""]) for d in drawn) > 1
    cost, n = passes.costs(rows, found)[""]
    assert n.sum() == cloud.count() and len(found[""]) == 4
    assert cost < 2 * kmeans.fit(cloud, 4, "farthest").wcss
    points_, weights = np.array([[0.0], [1.0], [10.0]]), np.array([5.0, 5.0, 1.0])
    assert sorted(c[0] for c in seeds.weighted_reduction(points_, weights, 2, "", 0)) == [0.5, 10.0]


def test_sample_of_the_sampled_index_is_bounded_and_the_same(cloud):
    a, b = (search.sampled_index(cloud, 2, stop=Stop(n_min=8), max_rows=60) for _ in range(2))
    assert codes(a) == codes(b) and sum(n.n for n in a.leaves) == cloud.count()
