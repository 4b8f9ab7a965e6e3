"""Stand-in archives over the given tables: pixel rasters and descriptor sets."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F, types as T

from tilemine.sources.storage import table

WIDTH = 32
LETTERS = "abcdefghijklmnopqrstuvwxyzäöüßéèêçñáíóú"
_LINE = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]


def scene_lineitem(spark: SparkSession, sf_dir: str, bistatic: bool = False, width: int = WIDTH) -> DataFrame:
    """A raster for each supplier, pixels in the order of all columns; one shuffle, by product."""
    order = Window.partitionBy("l_suppkey").orderBy(*_LINE)
    line = table(spark, sf_dir, "lineitem").withColumn("rn", F.row_number().over(order) - 1)
    disc, tax = (F.col("l_discount") - 0.05) / 0.05 / 2, (F.col("l_tax") - 0.04) / 0.04 / 2
    days = F.unix_date(F.to_date("l_shipdate"))
    return line.select(
        F.col("l_suppkey").alias("product_id"), F.floor(F.col("rn") / width).cast("int").alias("row"), (F.col("rn") % width).cast("int").alias("col"),
        ((F.col("l_quantity") - 25.5) / 25).alias("hh_re"), ((F.col("l_extendedprice") - 52949.85) / 52048).alias("hh_im"),
        disc.alias("hv_re"), tax.alias("hv_im"), (tax if bistatic else disc).alias("vh_re"), (disc if bistatic else tax).alias("vh_im"),
        ((days % 365 - 182) / 182).alias("vv_re"), ((F.col("l_partkey") % 101 - 50) / 50).alias("vv_im"),
    )


def scene_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One raster row for each vector: 8 pixels of 8 consecutive floats; not reciprocal, no shuffle."""
    names = [f"{c}_{p}" for c in ("hh", "hv", "vh", "vv") for p in ("re", "im")]
    pixel = F.explode(F.transform(F.sequence(F.lit(0), F.lit(7)), lambda c: F.struct(c.alias("col"), *[F.get("embedding", c * 8 + i).cast("double").alias(n) for i, n in enumerate(names)])))
    return table(spark, sf_dir, "embeddings").select(F.lit(0).cast("long").alias("product_id"), F.col("vec_id").alias("row"), pixel.alias("x")).select("product_id", "row", "x.*")


def vec_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("v"), F.col("label").cast("string").alias("label"))


def letter_counts(texts: pd.Series) -> pd.Series:
    """Per-mille counts of the letters of each text, None for one without any; one pass over the code points."""
    place = np.full(512, len(LETTERS))
    place[[ord(c) for c in LETTERS]] = np.arange(len(LETTERS))
    out = []
    for text in texts:
        code = np.frombuffer((text or "").lower().encode("utf-32-le", "surrogatepass"), np.uint32)
        n = np.bincount(place[np.minimum(code, 511)], minlength=len(LETTERS) + 1)[: len(LETTERS)]
        total = n.sum()
        out.append((n * 1000 // total).astype(np.int32) if total else None)
    return pd.Series(out, dtype=object)


def letter_histogram(text: Column) -> Column:
    """``letter_counts`` of a text column, in Arrow batches: as column functions it would take a pass over the text for each letter."""
    return F.pandas_udf(letter_counts, T.ArrayType(T.IntegerType()))(text)


def pair_counts(texts: pd.Series) -> pd.Series:
    """Counts of neighbouring letters of each text in ten-thousandths, a bin a pair; None for one without any."""
    side = len(LETTERS)
    place = np.full(512, side)
    place[[ord(c) for c in LETTERS]] = np.arange(side)
    out = []
    for text in texts:
        code = np.frombuffer((text or "").lower().encode("utf-32-le", "surrogatepass"), np.uint32)
        at = place[np.minimum(code, 511)]
        both = (at[:-1] < side) & (at[1:] < side)
        n = np.bincount((at[:-1] * side + at[1:])[both], minlength=side * side)
        total = n.sum()
        out.append((n * 10000 // total).astype(np.int32) if total else None)
    return pd.Series(out, dtype=object)


def vec_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Long descriptors: a joint histogram of neighbouring letters for each document, about 6 kB each; narrow."""
    pairs = F.pandas_udf(pair_counts, T.ArrayType(T.IntegerType()))
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), pairs("text").alias("v"), F.col("lang").alias("label"))
    return docs.where(F.col("v").isNotNull())


def text_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), letter_histogram(F.col("text")).alias("v"), F.col("lang").alias("label"))
    return docs.where(F.col("v").isNotNull())


def part_bins() -> Column:
    """Joint bin of quantity (4), discount (4) and tax (2) on whole numbers."""
    q = F.least(F.lit(3), F.floor((F.col("l_quantity") - 1) * 4 / 50)).cast("int")
    d = F.least(F.lit(3), F.floor(F.round(F.col("l_discount") * 100) * 4 / 11)).cast("int")
    t = F.least(F.lit(1), F.floor(F.round(F.col("l_tax") * 100) * 2 / 9)).cast("int")
    return q * 8 + d * 2 + t


def vec_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A tile for each part: counts of its line items' bins; two aggregates, the second on the first one's key."""
    line = table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("id"), part_bins().alias("bin"))
    counts = line.groupBy("id").pivot("bin", list(range(32))).count().na.fill(0)
    return counts.select("id", F.array(*[F.col(f"`{i}`").cast("int") for i in range(32)]).alias("v"), F.lit(None).cast("string").alias("label"))
