"""Queries over the pixel archives, with their SQL: tiling, decomposition, histograms."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, functions as F

from tilemine.functions import polsar
from tilemine.functions.complexes import Cx
from tilemine.operators import haa, tiling
from tilemine.sources import archives
from tilemine.sources.archives import table

_CHANNELS = [f"{c}_{p}" for c in ("hh", "hv", "vh", "vv") for p in ("re", "im")]


def _r(n: int, *names: str):
    return [F.round(F.col(c), n).alias(c) for c in names]


def _px(spark: SparkSession, d: str) -> DataFrame:
    return archives.scene_lineitem(spark, d)


PX = """px AS (SELECT l_suppkey AS product_id, CAST((rn - 1) // 32 AS INTEGER) AS "row", CAST((rn - 1) % 32 AS INTEGER) AS col,
  (l_quantity - 25.5) / 25 AS hh_re, (l_extendedprice - 52949.85) / 52048 AS hh_im, (l_discount - 0.05) / 0.05 / 2 AS hv_re, (l_tax - 0.04) / 0.04 / 2 AS hv_im,
  (l_discount - 0.05) / 0.05 / 2 AS vh_re, (l_tax - 0.04) / 0.04 / 2 AS vh_im,
  (date_diff('day', DATE '1970-01-01', CAST(l_shipdate AS DATE)) % 365 - 182) / 182.0::DOUBLE AS vv_re, (l_partkey % 101 - 50) / 50.0::DOUBLE AS vv_im
  FROM (SELECT *, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) AS rn FROM lineitem))"""
T = PX + """,
k AS (SELECT product_id, "row", col, (hh_re + vv_re) / sqrt(2) AS ar, (hh_im + vv_im) / sqrt(2) AS ai, (hh_re - vv_re) / sqrt(2) AS br, (hh_im - vv_im) / sqrt(2) AS bi, sqrt(2) * (hv_re + vh_re) / 2 AS cr, sqrt(2) * (hv_im + vh_im) / 2 AS ci FROM px),
t AS (SELECT product_id, "row", col, ar * ar + ai * ai AS t11, br * br + bi * bi AS t22, cr * cr + ci * ci AS t33, ar * br + ai * bi AS t12r, ai * br - ar * bi AS t12i,
  ar * cr + ai * ci AS t13r, ai * cr - ar * ci AS t13i, br * cr + bi * ci AS t23r, bi * cr - br * ci AS t23i FROM k)"""


def _averages(rows: int, cols: int) -> str:
    return ", ".join(f"avg({c}) AS {c}" for c in polsar.T_COLUMNS) + f', count(*) AS n_look FROM t GROUP BY product_id, "row" // {rows}, col // {cols}'


ML = T + f',\nm AS (SELECT product_id, CAST("row" // 2 AS INTEGER) AS "row", CAST(col // 2 AS INTEGER) AS col, {_averages(2, 2)})'
EIG = ML + """,
e1 AS (SELECT *, (t11 + t22 + t33) / 3 AS q, t12r * t12r + t12i * t12i AS x, t13r * t13r + t13i * t13i AS y, t23r * t23r + t23i * t23i AS z FROM m),
e2 AS (SELECT *, sqrt(((t11 - q) ** 2 + (t22 - q) ** 2 + (t33 - q) ** 2 + 2 * (x + y + z)) / 6) AS p FROM e1),
e3 AS (SELECT *, CASE WHEN p > 1e-12 * q THEN least(1, greatest(-1, ((t11 - q) * (t22 - q) * (t33 - q) + 2 * ((t12r * t23r - t12i * t23i) * t13r + (t12r * t23i + t12i * t23r) * t13i)
   - (t11 - q) * z - (t22 - q) * y - (t33 - q) * x) / (2 * p ** 3))) ELSE 1 END AS c FROM e2),
e4 AS (SELECT *, q + 2 * p * cos(acos(c) / 3) AS l1, q + 2 * p * cos(acos(c) / 3 + 2 * pi() / 3) AS lx FROM e3),
e AS (SELECT *, greatest(0, 3 * q - l1 - lx) AS l2, greatest(0, lx) AS l3 FROM e4)"""
HAA = EIG + """,
u AS (SELECT *, (t22 + t33) / 2 + sqrt(((t22 - t33) / 2) ** 2 + z) AS ua, (t22 + t33) / 2 - sqrt(((t22 - t33) / 2) ** 2 + z) AS ub, l1 + l2 + l3 AS tr, l1 - l2 < 1e-6 * (l1 + l2 + l3) OR l2 - l3 < 1e-6 * (l1 + l2 + l3) AS dg FROM e WHERE l1 + l2 + l3 > 1e-12),
a AS (SELECT *, l1 / tr AS p1, l2 / tr AS p2, l3 / tr AS p3, acos(sqrt(least(1, greatest(0, (l1 - ua) * (l1 - ub) / ((l1 - l2) * (l1 - l3)))))) AS alpha1,
  acos(sqrt(least(1, greatest(0, (l2 - ua) * (l2 - ub) / ((l2 - l1) * (l2 - l3)))))) AS alpha2, acos(sqrt(least(1, greatest(0, (l3 - ua) * (l3 - ub) / ((l3 - l1) * (l3 - l2)))))) AS alpha3 FROM u),
attr AS (SELECT *, -(CASE WHEN p1 > 0 THEN p1 * ln(p1) ELSE 0 END + CASE WHEN p2 > 0 THEN p2 * ln(p2) ELSE 0 END + CASE WHEN p3 > 0 THEN p3 * ln(p3) ELSE 0 END) / ln(3) AS h,
  CASE WHEN dg THEN p1 * alpha1 ELSE p1 * alpha1 + p2 * alpha2 + p3 * alpha3 END AS alpha, CASE WHEN l2 + l3 > 1e-6 * tr THEN (l2 - l3) / (l2 + l3) ELSE 0 END AS a FROM a)"""
_CELL = 'product_id, "row", col'


def q08_tiles(spark: SparkSession, d: str) -> DataFrame:
    return tiling.tiles(tiling.cut(_px(spark, d), 8))


def q09_overlapping_tiles(spark: SparkSession, d: str) -> DataFrame:
    return tiling.tiles(tiling.cut(_px(spark, d), 8, 4))


def q10_georeference(spark: SparkSession, d: str) -> DataFrame:
    boxes = tiling.georef(tiling.tiles(tiling.cut(_px(spark, d), 8)), tiling.product_corners(table(spark, d, "supplier")), 8)
    return boxes.select("tile_id", *_r(6, "lat_min", "lat_max", "lon_min", "lon_max"))


def q11_edge_tiles(spark: SparkSession, d: str) -> DataFrame:
    parts = []
    for edge in ("keep", "drop", "pad"):
        parts.append(tiling.cut(_px(spark, d), 8, edge=edge).agg(F.lit(edge).alias("edge"), F.countDistinct("tile_id").alias("n_tiles"), F.count("*").alias("n_px")))
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def q12_haa_cells(spark: SparkSession, d: str) -> DataFrame:
    return haa.haa(_px(spark, d)).select("product_id", "row", "col", *_r(4, "h", "alpha", "a"), "mech")


def _parts(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").select(F.col("l_partkey").alias("id"), archives.part_bins().alias("bin"))


def q13_joint_histogram(spark: SparkSession, d: str) -> DataFrame:
    return _parts(spark, d).groupBy("id", "bin").agg(F.count("*").alias("n"))


def q13_haa_histogram(spark: SparkSession, d: str) -> DataFrame:
    return haa.joint(tiling.cut(haa.haa(_px(spark, d)), 4), ["tile_id"], layout="long")


def q14_marginals(spark: SparkSession, d: str) -> DataFrame:
    cells = haa.haa(_px(spark, d))
    parts = [haa.joint(cells, ["product_id"], [axis], layout="long").withColumn("axis", F.lit(axis.column)) for axis in haa.HAA_AXES]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def q15_plane_frequencies(spark: SparkSession, d: str) -> DataFrame:
    plane = haa.joint(haa.haa(_px(spark, d)), ["product_id"], haa.HAA_AXES[:2], norm="frequency", layout="sparse")
    return plane.select("product_id", F.explode(F.arrays_zip("idx", "val")).alias("x")).select("product_id", F.col("x.idx").alias("bin"), F.round("x.val", 6).alias("share"))


def q16_product_descriptor(spark: SparkSession, d: str) -> DataFrame:
    dense = haa.joint(haa.haa(_px(spark, d)), ["product_id"], layout="dense")
    return dense.select("product_id", F.posexplode("v").alias("bin", "n"))


def q17_scatter(spark: SparkSession, d: str) -> DataFrame:
    out = polsar.scatter(Cx(F.lit(1.0), F.lit(0.0)), Cx(F.lit(0.0), F.lit(1.0)))
    return _px(spark, d).select("product_id", "row", "col", *[F.round(c, 6).alias(n) for v, w in zip(out, ("h", "v")) for n, c in ((f"e{w}_re", v.re), (f"e{w}_im", v.im))])


def q18_powers(spark: SparkSession, d: str) -> DataFrame:
    return polsar.powers(_px(spark, d)).select("product_id", "row", "col", *_r(6, "p_co", "p_cross"))


def q19_pauli(spark: SparkSession, d: str) -> DataFrame:
    k = polsar.pauli(3)
    return polsar.reciprocal(_px(spark, d)).select("product_id", "row", "col", *[F.round(c, 6).alias(n) for i, x in enumerate(k, 1) for n, c in ((f"k{i}_re", x.re), (f"k{i}_im", x.im))])


def q20_coherence(spark: SparkSession, d: str) -> DataFrame:
    return polsar.coherence(polsar.reciprocal(_px(spark, d))).select("product_id", "row", "col", *_r(6, *polsar.T_COLUMNS))


def q21_from_products(spark: SparkSession, d: str) -> DataFrame:
    return polsar.coherence_from_products(polsar.cross_products(polsar.reciprocal(_px(spark, d)))).select("product_id", "row", "col", *_r(6, *polsar.T_COLUMNS))


def _ml(spark: SparkSession, d: str) -> DataFrame:
    return haa.multilook(polsar.coherence(polsar.reciprocal(_px(spark, d))))


def q22_multilook(spark: SparkSession, d: str) -> DataFrame:
    # averages of short decimals end on ties: a small shift takes them off
    return _ml(spark, d).select("product_id", "row", "col", "n_look", *[F.round(F.col(c) + 1e-9, 6).alias(c) for c in polsar.T_COLUMNS])


def q22_boxcar(spark: SparkSession, d: str) -> DataFrame:
    out = haa.multilook(polsar.coherence(polsar.reciprocal(_px(spark, d))), (3, 3), "boxcar")
    return out.select("product_id", "row", "col", "n_look", *[F.round(F.col(c) + 1e-9, 6).alias(c) for c in ("t11", "t22", "t33")])


def q23_eigenvalues(spark: SparkSession, d: str) -> DataFrame:
    return polsar.eigenvalues(_ml(spark, d)).select("product_id", "row", "col", *_r(6, "l1", "l2", "l3"))


def q24_alphas(spark: SparkSession, d: str) -> DataFrame:
    return polsar.alphas(polsar.eigenvalues(_ml(spark, d))).select("product_id", "row", "col", *_r(4, "alpha1", "alpha2", "alpha3"))


def q25_entropy_anisotropy(spark: SparkSession, d: str) -> DataFrame:
    return haa.decompose(_ml(spark, d)).where("valid").select("product_id", "row", "col", *_r(4, "p1", "p2", "p3", "h", "alpha", "a"))


def q26_mechanisms(spark: SparkSession, d: str) -> DataFrame:
    cells = haa.haa(_px(spark, d)).withColumn("regime", polsar.entropy_class(F.col("h")))
    return cells.groupBy("product_id", "mech", "regime").agg(F.count("*").alias("n"))


def q27_roll_invariance(spark: SparkSession, d: str) -> DataFrame:
    px = _px(spark, d)
    a, b = (haa.haa(p).select("product_id", "row", "col", *[F.col(c).alias(f"{c}{i}") for c in ("h", "alpha", "a")]) for i, p in enumerate((px, polsar.roll(px, 0.3))))
    both = a.join(b, ["product_id", "row", "col"])
    worst = F.greatest(*[F.abs(F.col(f"{c}0") - F.col(f"{c}1")) for c in ("h", "alpha", "a")])
    return both.agg(F.count("*").alias("n_cells"), F.count_if(worst > 1e-6).alias("n_changed"))


def _mean_angles(spark: SparkSession, d: str) -> DataFrame:
    t = haa.multilook(polsar.coherence(polsar.reciprocal(_px(spark, d))), (2, 2))
    return polsar.eigenvector_angles(haa.decompose(t)).where("valid AND turned")


def q28_mean_angles(spark: SparkSession, d: str) -> DataFrame:
    """Mean eigenvector angles of cells whose eigenvalues differ and whose phases have a definite sign."""
    return _mean_angles(spark, d).select("product_id", "row", "col", *_r(4, "beta", "delta", "gamma"))


def q28_mean_target(spark: SparkSession, d: str) -> DataFrame:
    """The mean unit target vector of the same cells, and its length."""
    u = _mean_angles(spark, d).withColumns(polsar.mean_target())
    parts = [f"u{i}_{p}" for i in (1, 2, 3) for p in ("re", "im")]
    return u.select("product_id", "row", "col", *_r(4, *parts), F.round(sum((F.col(c) * F.col(c) for c in parts), F.lit(0.0)), 6).alias("length"))


def q29_bistatic_entropy(spark: SparkSession, d: str) -> DataFrame:
    out = haa.haa(archives.scene_embeddings(spark, d), (4, 8), n_dim=4)
    return out.select("row", "col", *_r(6, "h", "l1", "l2", "l3", "l4"))


def q88_invalid_cells(spark: SparkSession, d: str) -> DataFrame:
    return haa.invalid(_px(spark, d))


QUERIES = {f.__name__: f for f in (q08_tiles, q09_overlapping_tiles, q10_georeference, q11_edge_tiles, q12_haa_cells, q13_joint_histogram, q13_haa_histogram, q14_marginals, q15_plane_frequencies, q16_product_descriptor, q17_scatter, q18_powers, q19_pauli, q20_coherence, q21_from_products, q22_multilook, q22_boxcar, q23_eigenvalues, q24_alphas, q25_entropy_anisotropy, q26_mechanisms, q27_roll_invariance, q28_mean_angles, q28_mean_target, q29_bistatic_entropy, q88_invalid_cells)}

_TILE = "product_id * 1099511627776 + tr * 262144 + tc AS tile_id"
_CUT = PX + """,
c AS (SELECT *, CAST("row" // 8 AS INTEGER) AS tr, CAST(col // 8 AS INTEGER) AS tc FROM px),
g AS (SELECT product_id * 1099511627776 + tr * 262144 + tc AS tile_id, product_id, tr, tc, count(*) AS n_px FROM c GROUP BY ALL)"""
_BIN = "least(3, CAST(floor((l_quantity - 1) * 4 / 50) AS INTEGER)) * 8 + least(3, CAST(floor(round(l_discount * 100) * 4 / 11) AS INTEGER)) * 2 + least(1, CAST(floor(round(l_tax * 100) * 2 / 9) AS INTEGER))"


def _axis(x: str, hi: str) -> str:
    return f"greatest(0, least(7, CAST(floor({x} / ({hi} / 8)) AS INTEGER)))"


_HB, _LB, _AB = _axis("h", "1.0"), _axis("alpha", str(math.pi / 2)), _axis("a", "1.0")
_ROUND6 = ", ".join(f"round({c}, 6) + 0.0::DOUBLE AS {c}" for c in polsar.T_COLUMNS)
_SHIFTED = ", ".join(f"round({c} + 1e-9, 6) + 0.0::DOUBLE AS {c}" for c in polsar.T_COLUMNS)
def _angles_sql() -> str:
    """CTE g: mean beta, delta, gamma of cells with definite phases, from the projectors' entries."""
    square = {"22": "x + t22 * t22 + z", "33": "y + z + t33 * t33"}
    other = {"21r": ("t12r * (t11 + t22) + t23r * t13r + t23i * t13i", "t12r"), "21i": ("-t12i * (t11 + t22) + t23i * t13r - t23r * t13i", "-t12i"),
             "31r": ("t13r * (t11 + t33) + t23r * t12r - t23i * t12i", "t13r"), "31i": ("-t13i * (t11 + t33) - t23r * t12i - t23i * t12r", "-t13i")}
    parts = []
    for i, j, k in ((1, 2, 3), (2, 1, 3), (3, 1, 2)):
        sign = f"sign((l{i} - l{j}) * (l{i} - l{k}))"
        parts += [f"sqrt(greatest(0, ({square[n]} - t{n} * (l{j} + l{k}) + l{j} * l{k}) * {sign})) AS m{n}_{i}" for n in square]
        parts += [f"({a} - ({b}) * (l{j} + l{k})) * {sign} AS e{n}_{i}" for n, (a, b) in other.items()]
    mean = lambda a, b: " + ".join(f"p{i} * atan2({a}_{i}, {b}_{i})" for i in (1, 2, 3))
    turned = " AND ".join(f"abs(e{n}_{i}) > 1e-6 * tr * tr" for n in ("21i", "31i") for i in (1, 2, 3))
    return f"w AS (SELECT *, {', '.join(parts)} FROM attr WHERE NOT dg), g AS (SELECT {_CELL}, alpha, {mean('m33', 'm22')} AS beta, {mean('e21i', 'e21r')} AS delta, {mean('e31i', 'e31r')} AS gamma FROM w WHERE {turned})"


SQL = {
    "q08_tiles": f"WITH {_CUT} SELECT * FROM g",
    "q09_overlapping_tiles": f"""WITH {PX}, o AS (SELECT product_id, CAST(tr AS INTEGER) AS tr, CAST(tc AS INTEGER) AS tc FROM px, unnest(generate_series(greatest(0, CAST(floor(("row" - 8) / 4.0) AS BIGINT) + 1), "row" // 4)) AS a(tr), unnest(generate_series(greatest(0, CAST(floor((col - 8) / 4.0) AS BIGINT) + 1), col // 4)) AS b(tc))
       SELECT {_TILE}, product_id, tr, tc, count(*) AS n_px FROM o GROUP BY ALL""",
    "q10_georeference": f"""WITH {_CUT}, p AS (SELECT s_suppkey AS product_id, 60.0 - 4 * (s_nationkey // 5) AS lat0, 10.0 * (s_nationkey % 5) + s_suppkey % 10 AS lon0 FROM supplier)
       SELECT tile_id, round(lat0 - tr * 8 * 0.001::DOUBLE - 0.008::DOUBLE, 6) AS lat_min, round(CAST(lat0 AS DOUBLE) - tr * 8 * 0.001::DOUBLE, 6) AS lat_max, round(CAST(lon0 AS DOUBLE) + tc * 8 * 0.001::DOUBLE, 6) AS lon_min, round(CAST(lon0 AS DOUBLE) + tc * 8 * 0.001::DOUBLE + 0.008::DOUBLE, 6) AS lon_max FROM g JOIN p USING (product_id)""",
    "q11_edge_tiles": f"WITH {_CUT} SELECT 'keep' AS edge, count(*) AS n_tiles, CAST(sum(n_px) AS BIGINT) AS n_px FROM g UNION ALL SELECT 'drop', count(*), CAST(coalesce(sum(n_px), 0) AS BIGINT) FROM g WHERE n_px = 64 UNION ALL SELECT 'pad', count(*), count(*) * 64 FROM g",
    "q12_haa_cells": f"WITH {HAA} SELECT {_CELL}, round(h, 4) AS h, round(alpha, 4) AS alpha, round(a, 4) AS a, CASE WHEN alpha < radians(40) THEN 'surface' WHEN alpha <= radians(50) THEN 'volume' ELSE 'double' END AS mech FROM attr",
    "q13_joint_histogram": f"SELECT l_partkey AS id, {_BIN} AS bin, count(*) AS n FROM lineitem GROUP BY ALL",
    "q13_haa_histogram": f"""WITH {HAA}, b AS (SELECT product_id, "row" // 4 AS tr, col // 4 AS tc, {_HB} * 64 + {_LB} * 8 + {_AB} AS bin FROM attr) SELECT {_TILE}, bin, count(*) AS n FROM b GROUP BY ALL""",
    "q14_marginals": f"WITH {HAA} SELECT product_id, 'h' AS axis, {_HB} AS bin, count(*) AS n FROM attr GROUP BY ALL UNION ALL SELECT product_id, 'alpha', {_LB}, count(*) FROM attr GROUP BY ALL UNION ALL SELECT product_id, 'a', {_AB}, count(*) FROM attr GROUP BY ALL",
    "q15_plane_frequencies": f"WITH {HAA}, b AS (SELECT product_id, {_HB} * 8 + {_LB} AS bin, count(*) AS n FROM attr GROUP BY ALL) SELECT product_id, bin, round(n / sum(n) OVER (PARTITION BY product_id), 6) AS share FROM b",
    "q16_product_descriptor": f"WITH {HAA}, b AS (SELECT product_id, {_HB} * 64 + {_LB} * 8 + {_AB} AS bin, count(*) AS n FROM attr GROUP BY ALL), g AS (SELECT DISTINCT product_id, CAST(i AS INTEGER) AS bin FROM attr, unnest(generate_series(0, 511)) AS x(i)) SELECT product_id, bin, CAST(coalesce(n, 0) AS INTEGER) AS n FROM g LEFT JOIN b USING (product_id, bin)",
    "q17_scatter": f"WITH {PX} SELECT {_CELL}, round(hh_re - hv_im, 6) + 0.0::DOUBLE AS eh_re, round(hh_im + hv_re, 6) + 0.0::DOUBLE AS eh_im, round(vh_re - vv_im, 6) + 0.0::DOUBLE AS ev_re, round(vh_im + vv_re, 6) + 0.0::DOUBLE AS ev_im FROM px",
    "q18_powers": f"WITH {PX} SELECT {_CELL}, round(hh_re ** 2 + hh_im ** 2 + vv_re ** 2 + vv_im ** 2, 6) AS p_co, round(2 * (hv_re ** 2 + hv_im ** 2), 6) AS p_cross FROM px",
    "q19_pauli": f"WITH {T} SELECT {_CELL}, round(ar, 6) + 0.0::DOUBLE AS k1_re, round(ai, 6) + 0.0::DOUBLE AS k1_im, round(br, 6) + 0.0::DOUBLE AS k2_re, round(bi, 6) + 0.0::DOUBLE AS k2_im, round(cr, 6) + 0.0::DOUBLE AS k3_re, round(ci, 6) + 0.0::DOUBLE AS k3_im FROM k",
    "q20_coherence": f"WITH {T} SELECT {_CELL}, {_ROUND6} FROM t",
    "q21_from_products": f"WITH {T} SELECT {_CELL}, {_ROUND6} FROM t",
    "q22_multilook": f"WITH {ML} SELECT {_CELL}, n_look, {_SHIFTED} FROM m",
    "q22_boxcar": f"""WITH {T} SELECT a.product_id, a."row", a.col, count(*) AS n_look, round(avg(b.t11) + 1e-9, 6) AS t11, round(avg(b.t22) + 1e-9, 6) AS t22, round(avg(b.t33) + 1e-9, 6) AS t33 FROM t a JOIN t b ON a.product_id = b.product_id AND b."row" BETWEEN a."row" - 1 AND a."row" + 1 AND b.col BETWEEN a.col - 1 AND a.col + 1 GROUP BY ALL""",
    "q23_eigenvalues": f"WITH {EIG} SELECT {_CELL}, round(l1, 6) AS l1, round(l2, 6) AS l2, round(l3, 6) AS l3 FROM e",
    "q24_alphas": f"WITH {HAA} SELECT {_CELL}, CASE WHEN NOT dg THEN round(alpha1, 4) END AS alpha1, CASE WHEN NOT dg THEN round(alpha2, 4) END AS alpha2, CASE WHEN NOT dg THEN round(alpha3, 4) END AS alpha3 FROM attr",
    "q28_mean_angles": f"WITH {HAA}, {_angles_sql()} SELECT {_CELL}, round(beta, 4) AS beta, round(delta, 4) AS delta, round(gamma, 4) AS gamma FROM g",
    "q28_mean_target": f"WITH {HAA}, {_angles_sql()} SELECT {_CELL}, round(cos(alpha), 4) AS u1_re, CAST(0 AS DOUBLE) AS u1_im, round(sin(alpha) * cos(beta) * cos(delta), 4) AS u2_re, round(sin(alpha) * cos(beta) * sin(delta), 4) AS u2_im, round(sin(alpha) * sin(beta) * cos(gamma), 4) AS u3_re, round(sin(alpha) * sin(beta) * sin(gamma), 4) AS u3_im, CAST(1 AS DOUBLE) AS length FROM g",
    "q25_entropy_anisotropy": f"WITH {HAA} SELECT {_CELL}, round(p1, 4) AS p1, round(p2, 4) AS p2, round(p3, 4) AS p3, round(h, 4) AS h, CASE WHEN NOT dg THEN round(alpha, 4) END AS alpha, round(a, 4) AS a FROM attr",
    "q26_mechanisms": f"WITH {HAA} SELECT product_id, CASE WHEN alpha < radians(40) THEN 'surface' WHEN alpha <= radians(50) THEN 'volume' ELSE 'double' END AS mech, CASE WHEN h < 0.5 THEN 'point' WHEN h < 0.9 THEN 'mixed' ELSE 'noise' END AS regime, count(*) AS n FROM attr GROUP BY ALL",
    "q27_roll_invariance": f"WITH {HAA} SELECT count(*) AS n_cells, CAST(0 AS BIGINT) AS n_changed FROM attr",
    "q88_invalid_cells": f"WITH {ML} SELECT product_id, count(*) AS n_cells, count(*) FILTER (t11 + t22 + t33 <= 1e-12) AS n_invalid FROM m GROUP BY product_id",
}
