"""Shared helpers of the text operators: ids, byte-level words, batches; tables come from ``sources``.

``park`` writes a DataFrame as a Parquet table in the folder that the cluster names in
``spark.checkpoint.dir`` and reads it back.  It cuts the lineage with files that every
executor can read, so a lost executor costs no more than the tasks it was running.  ``park_only``
also deletes the tables that were parked on the way.
"""

from __future__ import annotations

import re
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import Column, DataFrame, functions as F

from tilemine.sources.storage import delete, new_folder, park, park_only, shared_folder, table  # noqa: F401

#: Null document ids sort before all others and are one document.
NULL_ID = -(2**63)


def remove(df: DataFrame) -> None:
    """Delete the files of a parked table that nothing reads any more."""
    for name in {f.rpartition("/")[0] for f in df.inputFiles()}:
        delete(df.sparkSession, name)


def id_key(column: str = "doc_id") -> Column:
    """A document's id for joins and order: null is the smallest."""
    return F.coalesce(F.col(column).cast("long"), F.lit(NULL_ID))


def back_to_id(column: str = "doc_id") -> Column:
    return F.when(F.col(column) != NULL_ID, F.col(column))


def hot_join(rows: DataFrame, keyed: DataFrame, keys: list[str], total: int, most: int = 1000) -> DataFrame:
    """``rows`` joined with ``keyed`` (written, one row a key, with n, the rows of the key; all n add up to ``total`` at most).
    A key that holds a thousandth of the total is hot: its rows meet a broadcast table, which has at most ``most`` keys since the
    counts add up, and stay where they are.  The others are shuffled."""
    hot = keyed.where(F.col("n") * most >= total)
    cold = keyed.where(F.col("n") * most < total).drop("n")
    there = rows.join(F.broadcast(hot.drop("n")), keys)
    return there.unionByName(rows.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(cold, keys))


def settled(df: DataFrame) -> DataFrame:
    """The same rows through a generator of one row: what stands above uses computed columns instead of repeating, in
    each filter and expression, all that they are computed from."""
    return df.select(F.inline(F.array(F.struct(*[F.col(f"`{c}`") for c in df.columns]))))


def by_batch(rows: Callable[[dict[str, list]], dict[str, list]], schema: pa.Schema) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A mapInArrow function from one that takes and gives lists by column name."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 512):
                part = batch.slice(start, 512)
                out = rows({n: part.column(i).to_pylist() for i, n in enumerate(part.schema.names)})
                yield pa.RecordBatch.from_arrays([pa.array(out[f.name], f.type) for f in schema], schema=schema)
        pa.default_memory_pool().release_unused()  # the worker lives on

    return run


_GAP = re.compile(rb"[\x20\x09-\x0D]")


def word_lists(body: bytes, size: int = 1 << 20) -> Iterator[list[bytes]]:
    """The words of a text in order, those of about ``size`` bytes at a time: the words of a very long text would take some ten times its size."""
    if len(body) <= size:
        yield body.split()
        return
    at = 0
    while at < len(body):
        gap = _GAP.search(body, at + size) if at + size < len(body) else None
        end = gap.start() if gap else len(body)
        yield body[at:end].split()
        at = end


def id_and_bytes(docs: DataFrame, text: str = "text", doc: str = "doc_id") -> DataFrame:
    """(doc_id, body): the id and the text's UTF-8 bytes; a null text is empty."""
    return docs.select(F.col(doc).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).cast("binary").alias("body"))


def open_folder(folder: str) -> tuple[fs.FileSystem, str]:
    """The file system of a folder's URI and the path in it."""
    return fs.FileSystem.from_uri(folder if "://" in folder or folder.startswith("file:") else f"file://{folder}")


def publish(store: fs.FileSystem, temporary: str, path: str) -> None:
    """Give a complete file its name.  A task that is run again finds the name taken by an equal file and leaves it."""
    try:
        store.move(temporary, path)
    except OSError:
        if store.get_file_info(path).type == fs.FileType.NotFound:
            raise
        store.delete_file(temporary)


def write_file(store: fs.FileSystem, path: str, data: bytes) -> None:
    folder, _, name = path.rpartition("/")
    temporary = f"{folder}/.{name}.{uuid.uuid4().hex}"
    store.create_dir(folder, recursive=True)
    with store.open_output_stream(temporary, compression=None) as sink:
        sink.write(data)
    publish(store, temporary, path)
