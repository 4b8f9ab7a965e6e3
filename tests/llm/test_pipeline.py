import os

import duckdb
import pytest

import __spark_entry__ as E
import corpus_pipeline as C
from tilemine.llm import common, decontaminate as D, lines as L, pieces as P, quality as Q, simhash as S


def test_stages_keep_columns_and_run(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert [n for n, _ in C.STAGES] == ["quality_rules", "line_dedup", "simhash_near_dedup", "decontamination", "sentencepiece"]
    for name, stage in C.STAGES[:-1]:
        assert stage(spark, docs.limit(20), sf).columns == docs.columns, name
    assert C.run(spark, sf).columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "ids"]


def test_run_is_the_stages_one_after_another(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    good = docs.join(Q.assess(docs).where("kept").select("doc_id"), "doc_id").cache()
    rows = {r.doc_id: r for r in good.collect()}
    from test_long_lines import brute_long

    gone = brute_long([(i, r.text) for i, r in rows.items()], L.WINDOW, L.LONG_WORDS)
    texts = {}
    for i, r in rows.items():
        parts = r.text.split("\n")
        left = [x for p, x in enumerate(parts) if p not in gone[i]]
        if not gone[i] or any(x.strip() for x in left):
            texts[i] = "\n".join(left)
    from test_simhash import brute, classes

    fps = [(i, brute(t)) for i, t in sorted(texts.items())]
    kept = {i for (i, _), c in zip(fps, classes(fps)) if i == c}
    frame = spark.createDataFrame([(i, texts[i]) for i in kept], "doc_id long, text string")
    want = P.digests(D.clean(frame, spark.read.parquet(f"{sf}/benchmark.parquet")), with_ids=True)
    assert sorted(map(tuple, C.run(spark, sf).collect())) == sorted(map(tuple, want.collect()))


def edge_tables(spark, folder, rows):
    names = "k t row body text_ __k __text ids runs".split()
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or ""), *names) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{c}` string" for c in names))
    docs.write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([("b", " ".join(f"item{i}" for i in range(30))), (None, None)], "item_id string, text string").write.parquet(f"{folder}/benchmark.parquet")
    return docs


def test_edges_pass_all_stages(spark, tmp_path):
    """Nulls, empty and very long texts, repeated rows and ids, extra columns: each stage keeps the columns, and clean rows arrive."""
    words = [" ".join(f"w{n}x{i}" for i in range(40)) for n in range(4)]
    long = " ".join(f"long{i}" for i in range(60_000))
    rows = [(None, None), (1, ""), (2, words[0]), (3, words[0]), (4, words[1]), (4, words[2]), (5, long), (None, words[3]), (6, " ".join(f"item{i}" for i in range(30)))]
    docs = edge_tables(spark, tmp_path, rows)
    at = docs
    for _, stage in C.STAGES[:-1]:
        at = C.park_only(spark, lambda at=at, stage=stage: stage(spark, at, str(tmp_path)), "edges")
        assert at.columns == docs.columns
    assert sorted((str(r.doc_id), r.text[:4]) for r in at.collect()) == [("2", "w0x0"), ("4", "w1x0"), ("4", "w2x0"), ("5", "long"), ("None", "w3x0")]
    out = C.run(spark, str(tmp_path)).collect()
    assert len(out) == 5 and all(len(r.ids) == r.n_tokens for r in out)
    assert sorted(P.decoded(C.run(spark, str(tmp_path))).select("text").toPandas()["text"]) == sorted([words[0], words[1], words[2], words[3], long])


def test_hot_keys_meet_a_broadcast_table(spark):
    rows = spark.createDataFrame([(k, i) for k, n in (("hot", 900), ("warm", 90), ("a", 6), ("b", 4)) for i in range(n)], "fp string, i int")
    keyed = common.park(rows.groupBy("fp").count().withColumnRenamed("count", "n").where("fp <> 'b'"), "keyed")
    joined = common.hot_join(rows, keyed, ["fp"], 1000, most=20)
    assert joined.groupBy("fp").count().orderBy("fp").collect() == rows.where("fp <> 'b'").groupBy("fp").count().orderBy("fp").collect()
    assert "BroadcastHashJoin" in joined._jdf.queryExecution().executedPlan().toString()
    assert common.hot_join(rows.limit(0), keyed, ["fp"], 0).count() == 0


def test_parked_tables_go_but_the_last(spark):
    folder = common.shared_folder(spark).removeprefix("file://")
    before = set(os.listdir(folder))
    out = common.park_only(spark, lambda: common.park_only(spark, lambda: common.park(spark.range(3).toDF("a"), "x"), "y").join(common.park(spark.range(9).toDF("a"), "z"), "a"), "kept")
    assert [n.rpartition("-")[0] for n in set(os.listdir(folder)) - before] == ["kept"] and out.count() == 3
    with pytest.raises(ZeroDivisionError):
        common.park_only(spark, lambda: (common.park(spark.range(3).toDF("a"), "lost"), 1 // 0)[0], "never")
    assert not [n for n in os.listdir(folder) if n.startswith("lost")]


def test_empty_table_passes_all_stages(spark, tmp_path):
    edge_tables(spark, tmp_path, [])
    assert C.run(spark, str(tmp_path)).count() == 0


def test_a_run_leaves_its_stages_only(spark, sf):
    folder = common.shared_folder(spark).removeprefix("file://")
    before = set(os.listdir(folder))
    C.run(spark, sf).count()
    assert sorted(n.rpartition("-")[0] for n in set(os.listdir(folder)) - before) == sorted(f"pipeline-{n}" for n, _ in C.STAGES)


@pytest.mark.parametrize("name", sorted(n for n in E.oracle_sql() if n.startswith("op")))
def test_queries_against_sql(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "pages", "benchmark"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    got = E.queries()[name](spark, sf)
    names = sorted(got.columns)
    want = con.execute(E.oracle_sql()[name])
    columns = [c[0] for c in want.description]
    assert sorted(columns) == names
    rows = sorted(tuple(r[columns.index(n)] for n in names) for r in want.fetchall()) if name != "op5_warc_normaliser" else sorted((tuple(r[columns.index(n)] for n in names) for r in want.fetchall()), key=str)
    mine = [tuple(r[n] for n in names) for r in got.collect()]
    assert sorted(mine, key=str) == sorted(rows, key=str)


@pytest.mark.parametrize("n", range(1, 11))
def test_every_operator_has_its_query(n):
    assert sum(name.startswith(f"op{n}_") for name in E.queries()) == 1


def test_simhash_query(spark, sf):
    assert S.op3_simhash_near_dedup(spark, sf).count() == 200
