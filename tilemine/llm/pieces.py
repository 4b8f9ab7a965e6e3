"""SentencePiece encoding and decoding by a table of distinct chunks.

A chunk is a run of whitespace markers with the word after it.  If no piece of the model has
a marker behind another character (checked when a model is loaded), no merge crosses a chunk's
start, so a text's ids are its chunks' ids in turn.  Each Python worker keeps a table of the distinct
chunks that its tasks have met: a chunk is segmented once, by the library, and its ids are joined back to
every position that holds it.  The table is emptied when it holds ``table_chars`` characters,
which costs time but no results, so memory is bounded.  A chunk of over ``long_chunk`` characters
is segmented where it stands and never stored.

``encoded_by_join`` is the same with one table for the whole corpus and a Spark join by position; it shuffles more than the text itself (figures
in the README), which is why ``digests`` and the query keep a table in each worker.  A model whose pieces cross markers is refused, as is one that trims or rewrites text.

Edge cases: null and empty texts have no ids and decode to the empty string; a very long text is held whole, its chunks one by one; repeated rows give
repeated results; an empty table gives none; other columns are ignored.
"""

from __future__ import annotations

import functools
import hashlib
import itertools
import re
from collections.abc import Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame, SparkSession, functions as F

from tilemine.llm.common import by_batch, id_and_bytes, park, table

MODEL = "piece_bpe_32k.model"
_MARK = "▁"
#: Spaces and literal markers are the same to the model.
_CHUNK = re.compile(f"[ {_MARK}]+[^ {_MARK}]*|[^ {_MARK}]+")


@functools.lru_cache(maxsize=4)
def load(model: str = MODEL) -> sentencepiece.SentencePieceProcessor:
    """The model, if its ids are those of its chunks."""
    sp = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(model))
    crossing = [p for p in map(sp.id_to_piece, range(sp.get_piece_size())) if _MARK in p.lstrip(_MARK)]
    probe = "  ﬁ x\n\t ÅÅ "
    if crossing or sp.normalize(probe) != _MARK + probe.replace(" ", _MARK):
        raise ValueError(f"{model}: pieces cross whitespace markers or the model rewrites text")
    return sp


class Chunks:
    """Distinct chunk -> (ids, ids as text)."""

    def __init__(self, sp: sentencepiece.SentencePieceProcessor, table_chars: int = 4_000_000, long_chunk: int = 2000):
        self.sp, self.limit, self.long_chunk = sp, table_chars, long_chunk
        self.known: dict[str, tuple[list[int], str]] = {}
        self.held = 0
        self.mark_alone = sp.encode("a ")[len(sp.encode("a")) :]

    def _segment(self, chunk: str) -> tuple[list[int], str]:
        """``chunk`` is encoded as it stands in the middle of a text: a leading marker is given, the dummy one replaces it."""
        ids = self.sp.encode(chunk[1:]) if len(chunk) > 1 else self.mark_alone
        return ids, ",".join(map(str, ids))

    def blocks(self, text: str, most: int = 100_000) -> Iterator[tuple[list[int], list[str]]]:
        """Ids of a text, and the ids of each chunk as text, for ``most`` chunks at a time."""
        known = self.known
        found = (m.group() for m in _CHUNK.finditer(" " + text)) if text else iter(())
        while some := list(itertools.islice(found, most)):
            ids, shown = [], []
            for chunk in some:
                got = known.get(chunk)
                if got is None:
                    got = self._segment(chunk)
                    if len(chunk) <= self.long_chunk:
                        if self.held > self.limit:
                            known.clear()
                            self.held = 0
                        known[chunk] = got
                        self.held += len(chunk) + 40
                ids += got[0]
                shown.append(got[1])
            yield ids, shown


@functools.lru_cache(maxsize=1)
def worker_chunks(model: str) -> Chunks:
    """One table for all tasks that a Python worker runs."""
    return Chunks(load(model))


def decode(sp: sentencepiece.SentencePieceProcessor, ids: list[int]) -> str:
    return sp.decode(ids) if ids else ""


def digests(docs: DataFrame, model: str = MODEL, with_ids: bool = False) -> DataFrame:
    """Per row: number of ids, SHA-256 of the comma-joined ids and of the decoded text, and the ids themselves if wanted."""
    fields = [("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())]
    schema = pa.schema(fields + [("ids", pa.list_(pa.int32()))] * with_ids)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sp, chunks = load(model), worker_chunks(model)

        def rows(x: dict[str, list]) -> dict[str, list]:
            out: dict[str, list] = {"doc_id": x["doc_id"], "n_tokens": [], "ids_sha256": [], "decoded_sha256": [], "ids": []}
            for body in x["body"]:
                flat, sha = [], hashlib.sha256()
                for ids, shown in chunks.blocks(body.decode()):
                    sha.update((("," if flat else "") + ",".join(shown)).encode())
                    flat += ids
                out["n_tokens"].append(len(flat))
                out["ids_sha256"].append(sha.hexdigest())
                out["decoded_sha256"].append(hashlib.sha256(decode(sp, flat).encode()).hexdigest())
                if with_ids:
                    out["ids"].append(np.array(flat, np.int32))
            return out

        yield from by_batch(rows, schema)(batches)

    return id_and_bytes(docs).mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids)


def encoded(docs: DataFrame, model: str = MODEL) -> DataFrame:
    """(doc_id, ids): the ids themselves, one row per row of ``docs``."""
    return digests(docs, model, with_ids=True).select("doc_id", "ids")


def distinct_chunks(docs: DataFrame) -> DataFrame:
    """(row, doc_id, chunk, places): a row for each distinct chunk of a row of ``docs``, with the places that hold it."""
    schema = pa.schema([("row", pa.int64()), ("doc_id", pa.int64()), ("chunk", pa.string()), ("places", pa.list_(pa.int32()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                text = batch.column(2)[i].as_py().decode()
                places: dict[str, list[int]] = {}
                for at, chunk in enumerate(_CHUNK.findall(" " + text) if text else []):
                    places.setdefault(chunk, []).append(at)
                n = max(len(places), 1)  # a row without chunks keeps its place in the result
                yield pa.RecordBatch.from_arrays([pa.array([batch.column(0)[i].as_py()] * n, pa.int64()), pa.array([batch.column(1)[i].as_py()] * n, pa.int64()), pa.array(list(places) or [None], pa.string()), pa.array(list(places.values()) or [None], pa.list_(pa.int32()))], schema=schema)

    numbered = id_and_bytes(docs).select(F.monotonically_increasing_id().alias("row"), "doc_id", "body")
    return numbered.mapInArrow(run, "row long, doc_id long, chunk string, places array<int>")


def encoded_by_join(docs: DataFrame, model: str = MODEL) -> DataFrame:
    """(doc_id, ids) by one table for all documents: every distinct chunk of the corpus is segmented once, and its ids are joined back to
    the places that hold it.  A row for each distinct chunk of a document is shuffled twice (see the README for what that costs), so ``digests``
    keeps a table in each worker instead."""
    found = park(distinct_chunks(docs), "chunks")
    schema = pa.schema([("chunk", pa.string()), ("ids", pa.list_(pa.int32()))])

    def segment(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        chunks = worker_chunks(model)
        yield from by_batch(lambda x: {"chunk": x["chunk"], "ids": [chunks._segment(c)[0] for c in x["chunk"]]}, schema)(batches)

    segments = park(found.where("chunk IS NOT NULL").select("chunk").distinct().mapInArrow(segment, "chunk string, ids array<int>"), "segments")
    placed = found.join(segments, "chunk", "left").select("row", "doc_id", F.explode_outer("places").alias("at"), "ids")
    ordered = placed.groupBy("row", "doc_id").agg(F.array_sort(F.collect_list(F.when(F.col("at").isNotNull(), F.struct("at", "ids")))).alias("x"))
    return ordered.select("doc_id", F.flatten(F.transform("x", lambda x: x["ids"])).alias("ids"))


def decoded(tokens: DataFrame, model: str = MODEL) -> DataFrame:
    """(doc_id, text) from (doc_id, ids); null ids decode to the empty string."""
    schema = pa.schema([("doc_id", pa.int64()), ("text", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sp = load(model)
        yield from by_batch(lambda x: {"doc_id": x["doc_id"], "text": [decode(sp, i or []) for i in x["ids"]]}, schema)(batches)

    return tokens.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def op7_sentencepiece_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digests(table(spark, sf_dir, "documents"))
