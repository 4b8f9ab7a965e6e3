"""Entropy, mean alpha and anisotropy of tiles: multilook averages, decomposition, joint histograms."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, functions as F

from tilemine.functions import polsar


def multilook(t: DataFrame, looks: tuple[int, int] = (2, 2), mode: str = "block", by: tuple[str, ...] = ()) -> DataFrame:
    """Averages of coherence entries.  ``block``: one result for each cell of looks rows by looks columns (partial
    aggregates, one shuffle of sums).  ``boxcar``: one for each pixel over a centred window.  Looks of 1 by 1 change nothing.  ``by``: columns that cells must not mix."""
    names = [c for c in t.columns if c[0] == "t" and c[1:2].isdigit()]
    if looks == (1, 1):
        return t.withColumn("n_look", F.lit(1).cast("long"))
    lr, lc = looks
    if mode == "block":
        keys = [F.col("product_id"), F.floor(F.col("row") / lr).cast("int").alias("row"), F.floor(F.col("col") / lc).cast("int").alias("col"), *map(F.col, by)]
        return t.groupBy(*keys).agg(*[F.avg(n).alias(n) for n in names], F.count("*").alias("n_look"))
    # each pixel goes to the windows it lies in, along columns and then, as sums, along rows: looks rows + looks columns copies
    # instead of their product; ragged edges and gaps are counted right, and a window stays where its centre is a pixel
    side = lambda n: F.explode(F.sequence(F.lit(-(n // 2)), F.lit((n - 1) // 2)))
    rest = [F.col("product_id"), *map(F.col, by)]
    sums = [F.sum(n).alias(n) for n in names]
    wide = t.withColumn("d", side(lc)).groupBy(*rest, "row", (F.col("col") + F.col("d")).alias("col")).agg(*sums, F.count("*").alias("n_look"), F.max(F.col("d") == 0).alias("own"))
    whole = wide.withColumn("d", side(lr)).groupBy(*rest, (F.col("row") + F.col("d")).alias("row"), "col").agg(*sums, F.sum("n_look").alias("n_look"), F.max((F.col("d") == 0) & F.col("own")).alias("own"))
    return whole.where("own").select("product_id", "row", "col", *by, *[(F.col(n) / F.col("n_look")).alias(n) for n in names], "n_look")


def decompose(t: DataFrame) -> DataFrame:
    """l1..l3, p1..p3, alpha1..alpha3, h, alpha, a, valid, degenerate of three-component coherence rows."""
    out = polsar.pseudo_probabilities(polsar.alphas(polsar.eigenvalues(t)))
    least = polsar.GAP * (F.col("l1") + F.col("l2") + F.col("l3"))
    return polsar.barrier(polsar.barrier(out).withColumns({"h": polsar.entropy([F.col("p1"), F.col("p2"), F.col("p3")]), "alpha": polsar.mean_alpha(), "a": polsar.anisotropy(F.col("l2"), F.col("l3"), least)}))


def haa(px: DataFrame, looks: tuple[int, int] = (2, 2), mode: str = "block", n_dim: int = 3, source: str = "channels") -> DataFrame:
    """(product_id, row, col, l1.., h, alpha, a, mech, n_look) for valid cells.  Rows with coinciding eigenvalues,
    and all rows of four-component data, take the numpy way."""
    if source == "products":
        t = polsar.coherence_from_products(px)
    else:
        t = polsar.coherence(polsar.reciprocal(px) if n_dim == 3 else px, n_dim)
    t = multilook(t, looks, mode)
    names = ["product_id", "row", "col", "n_look", "l1", "l2", "l3", "h", "alpha", "a"]
    if n_dim == 4:
        out = polsar.angles(t, 4, ("product_id", "row", "col", "n_look")).where(sum(F.col(f"l{i}") for i in range(1, 5)) > polsar.EPS)
        out = out.select(*names, "l4")
    else:
        closed = decompose(t)
        plain = closed.where("valid AND NOT degenerate").select(*names)
        rare = polsar.angles(closed.where("valid AND degenerate").select("product_id", "row", "col", "n_look", *polsar.T_COLUMNS), 3, ("product_id", "row", "col", "n_look"))
        out = plain.unionByName(rare.select(*names))
    return out.withColumn("mech", polsar.mechanism(F.col("alpha")))


def invalid(px: DataFrame, looks: tuple[int, int] = (2, 2)) -> DataFrame:
    """Cells without power for each product."""
    t = multilook(polsar.coherence(polsar.reciprocal(px)), looks)
    trace = F.col("t11") + F.col("t22") + F.col("t33")
    return t.groupBy("product_id").agg(F.count("*").alias("n_cells"), F.count_if(trace <= polsar.EPS).alias("n_invalid"))


@dataclass(frozen=True)
class Axis:
    """Equal bins of [lo, hi]; values outside go to the border bins."""

    column: str
    lo: float
    hi: float
    bins: int

    def index(self) -> Column:
        place = F.floor((F.col(self.column) - self.lo) / ((self.hi - self.lo) / self.bins))
        return F.greatest(F.lit(0), F.least(F.lit(self.bins - 1), place)).cast("int")


HAA_AXES = [Axis("h", 0.0, 1.0, 8), Axis("alpha", 0.0, 1.5707963267948966, 8), Axis("a", 0.0, 1.0, 8)]


def joint(df: DataFrame, by: list[str], axes: list[Axis] = HAA_AXES, norm: str = "count", layout: str = "dense") -> DataFrame:
    """Joint histogram over ``axes`` for each group: (by.., v) dense, (by.., idx, val) sparse, or (by.., bin, n) long.
    First counts by (group, bin), then gathers a group's bins, of which there are a fixed number."""
    place: Column = F.lit(0)
    for axis in axes:
        place = place * axis.bins + axis.index()
    size = 1
    for axis in axes:
        size *= axis.bins
    counts = df.select(*by, place.alias("bin")).groupBy(*by, "bin").agg(F.count("*").alias("n"))
    if layout == "long":
        return counts
    pairs = counts.groupBy(*by).agg(F.array_sort(F.collect_list(F.struct("bin", "n"))).alias("pairs"), F.sum("n").alias("total"))
    value = (lambda n: n / F.col("total")) if norm == "frequency" else (lambda n: n.cast("int"))
    if layout == "sparse":
        return pairs.select(*by, F.transform("pairs", lambda x: x["bin"]).alias("idx"), F.transform("pairs", lambda x: value(x["n"])).alias("val"))
    filled = F.map_from_entries("pairs")
    return pairs.withColumn("m", filled).select(*by, F.transform(F.sequence(F.lit(0), F.lit(size - 1)), lambda i: F.coalesce(value(F.element_at("m", i)), F.lit(0.0) if norm == "frequency" else F.lit(0))).alias("v"))


def tile_histogram(px: DataFrame, side: int = 8, looks: tuple[int, int] = (2, 2), axes: list[Axis] | None = None) -> DataFrame:
    """(id, product_id, v) from pixels: decomposition, then a joint histogram of each tile of side x side pixels; the id is product,
    tile row and tile column in steps of a thousand tiles an axis."""
    cells = haa(px, looks)
    tr, tc = F.floor(F.col("row") * looks[0] / side), F.floor(F.col("col") * looks[1] / side)
    placed = cells.withColumn("id", (F.col("product_id") * 1_000_000 + tr * 1000 + tc).cast("long"))
    return joint(placed, ["id", "product_id"], axes or HAA_AXES)
