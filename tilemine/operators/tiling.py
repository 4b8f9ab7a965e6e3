"""Cutting rasters into square tiles of a power-of-two side, with ids, overlap and geographic boxes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F


def tile_id(product: Column, tr: Column, tc: Column) -> Column:
    """product, tile row and tile column packed in one long (22 and 18 bits for the tile's place)."""
    return F.shiftleft(product.cast("long"), 40).bitwiseOR(F.shiftleft(tr.cast("long"), 18)).bitwiseOR(tc.cast("long"))


def cut(px: DataFrame, side: int, overlap: int = 0, edge: str = "keep") -> DataFrame:
    """Pixels with tr, tc, tile_id; a pixel of overlapping tiles has a row for each.  Narrow, except that ``drop`` counts
    the pixels of each tile to leave out incomplete ones."""
    if side < 1 or side & (side - 1) or not 0 <= overlap < side:
        raise ValueError("side must be a power of two, overlap from 0 to side - 1")
    step = side - overlap
    if overlap:
        def firsts(name: str) -> Column:
            last = F.floor(F.col(name) / step)
            first = F.greatest(F.lit(0), F.floor((F.col(name) - side) / step) + 1)
            return F.explode(F.sequence(first.cast("int"), last.cast("int")))

        out = px.withColumn("tr", firsts("row")).withColumn("tc", firsts("col"))
    else:
        out = px.withColumns({"tr": F.floor(F.col("row") / side).cast("int"), "tc": F.floor(F.col("col") / side).cast("int")})
    out = out.withColumn("tile_id", tile_id(F.col("product_id"), F.col("tr"), F.col("tc")))
    if edge == "drop":
        full = out.groupBy("tile_id").count().where(F.col("count") == side * side).select("tile_id")
        out = out.join(full, "tile_id", "left_semi")
    elif edge == "pad":  # the place of every pixel of a tile, without values where the raster has none
        grid = out.select("product_id", "tr", "tc", "tile_id").distinct().withColumn("dr", F.explode(F.sequence(F.lit(0), F.lit(side - 1)))).withColumn("dc", F.explode(F.sequence(F.lit(0), F.lit(side - 1))))
        grid = grid.withColumns({"row": (F.col("tr") * step + F.col("dr")).cast("int"), "col": (F.col("tc") * step + F.col("dc")).cast("int")}).drop("dr", "dc")
        out = grid.join(out.drop("product_id", "tr", "tc"), ["tile_id", "row", "col"], "left")
    return out


def tiles(pixels: DataFrame) -> DataFrame:
    return pixels.groupBy("tile_id", "product_id", "tr", "tc").agg(F.count("*").alias("n_px"))


def georef(tile_rows: DataFrame, products: DataFrame, side: int, step: float = 0.001, overlap: int = 0) -> DataFrame:
    """Boxes on an equiangular grid from each product's north-west corner (product_id, lat0, lon0)."""
    stride = side - overlap
    out = tile_rows.join(products.select("product_id", "lat0", "lon0"), "product_id")
    top, left = F.col("lat0") - F.col("tr") * stride * step, F.col("lon0") + F.col("tc") * stride * step
    return out.select("tile_id", "product_id", "tr", "tc", (top - side * step).alias("lat_min"), top.alias("lat_max"), left.alias("lon_min"), (left + side * step).alias("lon_max"))


def product_corners(supplier: DataFrame) -> DataFrame:
    """Invented corners: nations on a grid, suppliers beside each other."""
    return supplier.select(F.col("s_suppkey").alias("product_id"), (60.0 - 4 * F.floor(F.col("s_nationkey") / 5)).alias("lat0"), (10.0 * (F.col("s_nationkey") % 5) + F.col("s_suppkey") % 10).alias("lon0"))
