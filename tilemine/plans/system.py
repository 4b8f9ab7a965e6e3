"""The three phases in one place: ingest pixels into descriptors, build the index, search it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from tilemine.operators import haa, search, tiling, tsvq
from tilemine.sources import archives

SMALL_AXES = [haa.Axis("h", 0.0, 1.0, 4), haa.Axis("alpha", 0.0, 1.5707963267948966, 4), haa.Axis("a", 0.0, 1.0, 2)]


def ingest(px: DataFrame, side: int = 8, looks: tuple[int, int] = (2, 2), axes: list[haa.Axis] = SMALL_AXES) -> DataFrame:
    """(id, v): the joint histogram of each tile's multilook cells.  Cells are named by their own row and column, so a tile of ``side`` pixels has side / looks cells."""
    cells = haa.haa(px, looks)
    cut = tiling.cut(cells, max(1, side // looks[0]))
    return haa.joint(cut, ["tile_id"], axes).select(F.col("tile_id").alias("id"), "v")


def build(vectors: DataFrame, n_min: int = 32, h_max: int = 8, **settings) -> tsvq.Index:
    return tsvq.grow(vectors, tsvq.Stop(n_min=n_min, h_max=h_max), **settings)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pixels to tiles to index; ten tiles as queries, ten results each."""
    vectors = ingest(archives.scene_lineitem(spark, sf_dir))
    index = build(vectors, h_max=4, n_min=8)
    queries = index.labelled.orderBy("id").limit(10).select(F.col("id").alias("query_id"), "v")
    return search.batch(index, queries, 10)
