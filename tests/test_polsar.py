import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from tilemine.functions import polsar
from tilemine.operators import haa, tiling
from tilemine.sources import archives


def frame(spark, matrices):
    rows = []
    for i, t in enumerate(matrices):
        rows.append((1, i, 0, *[float(t[k, k].real) for k in range(3)], *[float(x) for a, b in ((0, 1), (0, 2), (1, 2)) for x in (t[a, b].real, t[a, b].imag)]))
    return spark.createDataFrame(rows, "product_id long, row int, col int, " + ", ".join(f"{c} double" for c in ["t11", "t22", "t33", "t12r", "t12i", "t13r", "t13i", "t23r", "t23i"]))


def random_coherence(n, looks=5, dim=3, seed=0):
    r = np.random.default_rng(seed)
    k = r.standard_normal((n, looks, dim)) + 1j * r.standard_normal((n, looks, dim))
    return np.einsum("nli,nlj->nij", k, k.conj()) / looks


def test_closed_form_equals_numpy(spark):
    t = random_coherence(300)
    want = polsar.angles_of(t)
    got = {r.row: r for r in haa.decompose(frame(spark, t)).collect()}
    for i in range(300):
        for n in ("l1", "l2", "l3", "h", "alpha", "a"):
            assert abs(got[i][n] - want[n][i]) < 1e-9, n
        assert abs(got[i].p1 + got[i].p2 + got[i].p3 - 1) < 1e-12
        assert 0 <= got[i].h <= 1 + 1e-12 and 0 <= got[i].a <= 1 and 0 <= got[i].alpha <= math.pi / 2


@pytest.mark.parametrize("diagonal,h,alpha,a", [((1, 0, 0), 0, 0, 0), ((0, 1, 0), 0, math.pi / 2, 0), ((0.5, 0.25, 0.25), 0.946395, math.pi / 4, 0), ((3 / 6, 2 / 6, 1 / 6), 0.920620, math.pi / 4, 1 / 3), ((1 / 3, 1 / 3, 1 / 3), 1, math.pi / 3, 0)])
def test_hand_checked_mechanisms(diagonal, h, alpha, a):
    out = polsar.angles_of(np.diag(diagonal).astype(complex)[None])
    assert abs(out["h"][0] - h) < 1e-6 and abs(out["alpha"][0] - alpha) < 1e-6 and abs(out["a"][0] - a) < 1e-6


def test_four_components_are_bounded_by_one():
    out = polsar.angles_of(random_coherence(50, 9, 4))
    assert ((out["h"] > 0) & (out["h"] <= 1)).all()
    assert abs(polsar.angles_of(np.eye(4, dtype=complex)[None])["h"][0] - 1) < 1e-12


def test_products_give_the_same_coherence(spark, sf):
    px = polsar.reciprocal(archives.scene_lineitem(spark, sf))
    a = polsar.coherence(px)
    b = polsar.coherence_from_products(polsar.cross_products(px))
    both = a.join(b.select("product_id", "row", "col", *[F.col(c).alias(f"{c}_") for c in polsar.T_COLUMNS]), ["product_id", "row", "col"])
    worst = both.agg(F.max(F.greatest(*[F.abs(F.col(c) - F.col(f"{c}_")) for c in polsar.T_COLUMNS])).alias("w")).first().w
    assert worst < 1e-12


def test_degenerate_rows_take_the_fallback(spark):
    t = [np.diag((0.5, 0.25, 0.25)).astype(complex), np.zeros((3, 3), complex), *random_coherence(3)]
    rows = {r.row: r for r in haa.decompose(frame(spark, t)).collect()}
    assert rows[0].degenerate and rows[0].alpha is None and not rows[1].valid and not rows[2].degenerate
    px = spark.createDataFrame([(1, 0, c, 1.0, 0.0, 0.0, 0.0, 0.0, 0.0, 1.0, 0.0) for c in range(2)] + [(1, 2, c, *[0.0] * 8) for c in range(2)], "product_id long, row int, col int, hh_re double, hh_im double, hv_re double, hv_im double, vh_re double, vh_im double, vv_re double, vv_im double")
    out = haa.haa(px).collect()
    assert [(r.row, round(r.h, 6), round(r.alpha, 6), r.a, r.mech) for r in out] == [(0, 0, 0, 0, "surface")]
    assert [(r.n_cells, r.n_invalid) for r in haa.invalid(px).collect()] == [(2, 1)]


def test_boxcar_equals_a_plain_loop(spark):
    r = np.random.default_rng(3)
    rows = [(1, i, j, *map(float, r.random(9))) for i in range(6) for j in range(7) if (i, j) != (2, 3)]
    df = spark.createDataFrame(rows, "product_id long, row int, col int, " + ", ".join(f"{c} double" for c in polsar.T_COLUMNS))
    got = {(x.row, x.col): (x.t11, x.n_look) for x in haa.multilook(df, (3, 3), "boxcar").collect()}
    held = {(x[1], x[2]): x[3] for x in rows}
    for (i, j), (mean, n) in got.items():
        near = [held[a, b] for a in range(i - 1, i + 2) for b in range(j - 1, j + 2) if (a, b) in held]
        assert n == len(near) and abs(mean - sum(near) / n) < 1e-12


def test_tiling_counts(spark):
    px = spark.range(32 * 19).select(F.lit(1).cast("long").alias("product_id"), (F.col("id") / 19).cast("int").alias("row"), (F.col("id") % 19).cast("int").alias("col"))
    assert tiling.tiles(tiling.cut(px, 8)).count() == 12
    assert tiling.tiles(tiling.cut(px, 8, edge="drop")).count() == 8
    assert tiling.tiles(tiling.cut(px, 8, edge="pad")).where("n_px = 64").count() == 12
    square = px.where("row < 16 AND col < 16")
    overlapping = tiling.cut(square, 8, 4)
    full = tiling.tiles(overlapping).where("n_px = 64")
    assert full.count() == 9 and overlapping.where("row = 8 AND col = 8 AND tr < 3 AND tc < 3").count() == 4
    for side, overlap in ((6, 0), (8, 8), (8, -1)):
        with pytest.raises(ValueError):
            tiling.cut(px, side, overlap)


def test_histograms_agree_and_clamp(spark):
    df = spark.createDataFrame([(1, -5.0), (1, 0.0), (1, 0.99), (1, 1.0), (1, 7.0), (2, 0.5)], "tile_id long, x double")
    axis = [haa.Axis("x", 0.0, 1.0, 2)]
    assert {r.tile_id: r.v for r in haa.joint(df, ["tile_id"], axis).collect()} == {1: [2, 3], 2: [0, 1]}
    assert {r.tile_id: r.v for r in haa.joint(df, ["tile_id"], axis, "frequency").collect()} == {1: [0.4, 0.6], 2: [0.0, 1.0]}
    assert {r.tile_id: (r.idx, r.val) for r in haa.joint(df, ["tile_id"], axis, layout="sparse").collect()} == {1: ([0, 1], [2, 3]), 2: ([1], [1])}


def test_pixel_plan_stays_in_the_engine(spark, sf):
    t = haa.decompose(haa.multilook(polsar.coherence(archives.scene_lineitem(spark, sf))))
    plan = t._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and plan.count("HashAggregate") == 2


def test_mean_angles_and_target_equal_numpy(spark, sf):
    from tilemine.sources import archives

    t = haa.multilook(polsar.coherence(polsar.reciprocal(archives.scene_lineitem(spark, sf))), (2, 2))
    native = polsar.eigenvector_angles(haa.decompose(t)).where("valid AND turned").withColumns(polsar.mean_target())
    other = {(r.product_id, r.row, r.col): r for r in polsar.angles(t).collect()}
    rows = native.collect()
    assert len(rows) > 100
    for r in rows:
        o = other[r.product_id, r.row, r.col]
        assert all(abs(r[a] - o[a]) < 1e-5 for a in ("alpha", "beta", "delta", "gamma"))
        u = np.array([r[f"u{i}_re"] + 1j * r[f"u{i}_im"] for i in (1, 2, 3)])
        assert abs((np.abs(u) ** 2).sum() - 1) < 1e-9 and abs(np.arccos(abs(u[0])) - r.alpha) < 1e-7
