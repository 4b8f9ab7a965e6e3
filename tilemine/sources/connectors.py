"""Python data sources: pixel rasters by tile range, a stream of the task queue; readers of foreign files."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

_PX = [f"{c}_{p}" for c in ("hh", "hv", "vh", "vv") for p in ("re", "im")]
_PX_SCHEMA = "product_id long, row int, col int, " + ", ".join(f"{n} double" for n in _PX)


class _Rows(InputPartition):
    def __init__(self, product: int, first: int, last: int):
        super().__init__((product, first, last))
        self.product, self.first, self.last = product, first, last


class RasterSource(DataSource):
    """format 'polraster': speckle rasters made from a seed.  Options: products, rows, cols, rows_per_task, seed.
    A partition is a range of raster rows, so a product of any size is read by many tasks."""

    @classmethod
    def name(cls) -> str:
        return "polraster"

    def schema(self) -> str:
        return _PX_SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _RasterReader({k: int(self.options.get(k, v)) for k, v in (("products", 1), ("rows", 32), ("cols", 32), ("rows_per_task", 16), ("seed", 0))})


class _RasterReader(DataSourceReader):
    def __init__(self, options: dict[str, int]):
        self.o = options

    def partitions(self) -> list[InputPartition]:
        o = self.o
        return [_Rows(p, r, min(r + o["rows_per_task"], o["rows"])) for p in range(o["products"]) for r in range(0, o["rows"], o["rows_per_task"])]

    def read(self, part: _Rows) -> Iterator[pa.RecordBatch]:
        for row in range(part.first, part.last):
            random = np.random.default_rng([self.o["seed"], part.product, row])
            values = random.standard_normal((self.o["cols"], 8))
            n = self.o["cols"]
            yield pa.RecordBatch.from_arrays([pa.array(np.full(n, part.product)), pa.array(np.full(n, row, np.int32)), pa.array(np.arange(n, dtype=np.int32)), *(pa.array(values[:, i]) for i in range(8))], names=["product_id", "row", "col", *_PX])


class QueueSource(DataSource):
    """format 'taskqueue': a stream of invented tasks, ``per_batch`` each trigger up to ``total``."""

    @classmethod
    def name(cls) -> str:
        return "taskqueue"

    def schema(self) -> str:
        return "task_id long, service_s double"

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return _QueueReader(int(self.options.get("per_batch", 10)), int(self.options.get("total", 30)))


class _QueueReader(SimpleDataSourceStreamReader):
    def __init__(self, per_batch: int, total: int):
        self.per_batch, self.total = per_batch, total

    def initialOffset(self) -> dict:
        return {"next": 0}

    def read(self, start: dict):
        stop = min(start["next"] + self.per_batch, self.total)
        return iter([(i, float(i * 37 % 100 * 10)) for i in range(start["next"], stop)]), {"next": stop}

    def readBetweenOffsets(self, start: dict, end: dict):
        return iter([(i, float(i * 37 % 100 * 10)) for i in range(start["next"], end["next"])])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(RasterSource)
    spark.dataSource.register(QueueSource)


def read_foreign(spark: SparkSession, path: str, kind: str, schema: str | None = None) -> DataFrame:
    """csv, json, orc, text or binaryFile by one call."""
    reader = spark.read.format(kind)
    if kind == "csv":
        reader = reader.option("header", True).option("timestampFormat", "yyyy-MM-dd HH:mm:ss")
    return (reader.schema(schema) if schema else reader).load(path)


def rasters_of_files(spark: SparkSession, path: str, width: int, part_bytes: int = 16 << 20) -> DataFrame:
    """Raw little-endian double files, eight values a pixel, as pixels; the file name's digits are the product.  A file of any size is
    read in stretches of about ``part_bytes`` of whole raster rows, each by one task at a time; no cell holds a file."""
    step = max(1, part_bytes // (64 * width)) * 64 * width
    files = spark.read.format("binaryFile").load(path).where("length > 0").select("path", "length")  # contents stay unread
    parts = files.select(F.regexp_extract("path", r"(\d+)[^/]*$", 1).cast("long").alias("product_id"), "path", "length", F.explode(F.expr(f"sequence(0L, length - 1, {step}L)")).alias("offset"))
    dealt = parts.repartition(max(spark.sparkContext.defaultParallelism, 1), "path", "offset")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for product, name, length, offset in zip(*(c.to_pylist() for c in batch.columns)):
                store, at = fs.FileSystem.from_uri(re.sub(r"^file:/+", "file:///", name))
                with store.open_input_file(at) as raw:
                    values = np.frombuffer(raw.read_at(min(step, length - offset), offset), "<f8").reshape(-1, 8)
                place = offset // 64 + np.arange(len(values))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(values), product)), pa.array((place // width).astype(np.int32)), pa.array((place % width).astype(np.int32)), *(pa.array(values[:, j].copy()) for j in range(8))], names=["product_id", "row", "col", *_PX])

    return dealt.mapInArrow(run, _PX_SCHEMA)
