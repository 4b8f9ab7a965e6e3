"""Searches at size: no row for each pair, no sample on the driver; brute force on ties and odd shapes."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import DataFrame, functions as F

import __spark_entry__ as E

from tilemine.operators import search, tsvq
from tilemine.operators.tsvq import Stop


def rows_of(spark, n=600):
    r = np.random.default_rng(5)
    return spark.createDataFrame([(i, [int(x) for x in v]) for i, v in enumerate(r.integers(0, 6, (n, 5)))], "id long, v array<int>").repartition(3)


def brute(df, k, every):
    rows = sorted((r.id, np.array(r.v)) for r in df.collect())
    return sorted((q, n + 1, i, float(d)) for q, y in rows if q % every == 0 for n, (d, i) in enumerate(sorted((((x - y) ** 2).sum(), i) for i, x in rows)[:k]))


def test_no_row_is_made_for_each_pair_and_ties_go_by_id(spark):
    df = rows_of(spark)
    index = tsvq.grow(df, Stop(n_min=8), schedule="hybrid")
    q = df.where("id % 20 = 0").select(F.col("id").alias("query_id"), "v")
    for block in (7, 20_000):
        got = search.batch(index, q, 9, 2, exact=True, block=block)
        assert sorted((r.query_id, r["rank"], r.id, r.dist) for r in got.collect()) == brute(df, 9, 20)
    assert "Join" not in got._jdf.queryExecution().executedPlan().toString()
    assert search.batch(index, q.where("query_id < 0"), 9, exact=True).count() == 0


def test_nearest_keeps_the_same_rows_in_small_steps():
    r = np.random.default_rng(7)
    x, y, ids = r.normal(size=(300, 4)), r.normal(size=(11, 4)), r.permutation(300)
    x[:50] = x[50]  # copies
    near = search.Nearest(y, 6)
    near.PAIRS = 40
    for at in np.array_split(np.arange(300), 9):
        near.add(x[at], ids[at], np.arange(11))
    got = sorted(zip(*(c.tolist() for c in near.found()[:3])))
    want = sorted((q, int(i), float(d)) for q in range(11) for d, i in sorted(zip(((x - y[q]) ** 2).sum(1), ids))[:6])
    assert got == want


def test_sampled_tree_grows_in_a_task(spark, monkeypatch):
    def refused(self):
        raise AssertionError("the sample reached the driver")

    monkeypatch.setattr(DataFrame, "toPandas", refused)
    df = rows_of(spark)
    index = search.sampled_index(df, 2, stop=Stop(n_min=8))
    assert index.nodes[""].n == 600 and index.labelled.count() == 600
    q = df.where("id % 20 = 0").select(F.col("id").alias("query_id"), "v")
    assert sorted((r.query_id, r["rank"], r.id, r.dist) for r in search.batch(index, q, 9, 2, exact=True).collect()) == brute(df, 9, 20)


def test_two_dearest_orders_of_repeated_customers(spark, sf, tmp_path):
    con = duckdb.connect()
    con.execute(f"CREATE TABLE customer AS SELECT t.* FROM '{sf}/customer.parquet' t, range(3)")
    con.execute(f"CREATE TABLE orders AS SELECT * REPLACE (CASE WHEN o_orderkey % 7 = 0 THEN NULL ELSE o_totalprice END AS o_totalprice, CASE WHEN o_orderkey % 11 = 0 THEN NULL ELSE o_orderkey END AS o_orderkey) FROM '{sf}/orders.parquet'")
    for name in ("customer", "orders"):
        con.execute(f"COPY {name} TO '{tmp_path}/{name}.parquet'")
    got = [(r.c_custkey, r.o_orderkey) for r in E.queries()["q119_lateral"](spark, str(tmp_path)).collect()]
    assert sorted(got, key=repr) == sorted(con.execute(E.oracle_sql()["q119_lateral"]).fetchall(), key=repr) != []


@pytest.mark.parametrize("name", ["q47_codebook", "q83_tree_shape"])
def test_codebook_and_shape_read_the_table_when_the_index_is_held(spark, sf, name):
    E.queries()["q45_nodes"](spark, sf).collect()
    assert any("lineitem" in f for f in E.queries()[name](spark, sf).inputFiles())


@pytest.mark.parametrize("name", ["q54_batch", "q54_all_leaves"])
def test_batches_of_parts_join_no_pairs(spark, sf, name):
    assert "Join" not in E.queries()[name](spark, sf)._jdf.queryExecution().executedPlan().toString()


def test_few_pairs_are_ranked_once_limits_are_known(monkeypatch):
    r = np.random.default_rng(11)
    x, y = r.integers(0, 9, (6000, 8)).astype(float), r.integers(0, 9, (40, 8)).astype(float)
    partition, ranked = np.partition, []
    monkeypatch.setattr(np, "partition", lambda d, *a, **k: ranked.append(np.size(d)) or partition(d, *a, **k))
    near = search.Nearest(y, 5)
    for part in np.array_split(np.argsort(x[:, 0], kind="stable"), 3):  # as leaves: a stretch of one is far from some queries
        near.add(x[part], part, np.arange(40))
    assert sum(ranked) < len(x) * len(y) / 3
    got = sorted(zip(*(c.tolist() for c in near.found()[:3])))
    assert got == sorted((q, int(i), float(d)) for q in range(40) for d, i in sorted(zip(((x - y[q]) ** 2).sum(1), range(6000)))[:5])


def cached_parts(df):
    held = df.select("*").persist()
    held.count()
    n = held.rdd.getNumPartitions()
    held.unpersist()
    return n


def test_parts_grow_in_as_many_tasks_as_their_size_asks_for(spark, sf, monkeypatch):
    from tilemine.plans import queries_index

    seen, grow = [], tsvq.grow
    monkeypatch.setattr(tsvq, "grow", lambda df, **how: seen.append(cached_parts(df)) or grow(df.coalesce(1), **how))
    monkeypatch.setattr(queries_index, "_held", {})
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "40")
    try:
        queries_index._index(spark, sf)
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    assert seen[0] <= 8


def test_draws_by_squared_distance_end_near_the_best_for_every_seed(spark):
    from tilemine.sources import archives

    rows = archives.text_docs(spark, "/root/testdata/sf0.01").select("id", "v").toArrow().sort_by("id")
    ids, x = rows["id"].to_numpy(), np.array(rows["v"].to_pylist(), float)
    cost = [sum(n.wcss for n in tsvq.grow_local(ids, x, "", Stop(h_max=2), init, 1e-6, 30, seed)[0] if n.split is None) for init in ("dsquare", "parallel") for seed in range(4)]
    assert max(cost) <= 1.5 * min(cost)


@pytest.mark.parametrize("init", ["dsquare", "parallel"])
def test_seeds_of_passes_are_those_of_one_task(spark, init):
    df = rows_of(spark)
    level, local = (tsvq.grow(df, Stop(h_max=2), init=init, schedule=s) for s in ("level", "hybrid"))
    assert sorted(map(tuple, level.labelled.select("id", "code").collect())) == sorted(map(tuple, local.labelled.select("id", "code").collect()))
    equal = spark.createDataFrame([(i, [1, 2]) for i in range(9)] + [(9, [3, 2])], "id long, v array<int>")
    assert [len(tsvq.grow(equal, Stop(h_max=2), init=init, schedule=s).leaves) for s in ("level", "hybrid")] == [2, 2]
