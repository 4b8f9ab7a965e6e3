"""WARC archives of pages, and a normaliser of monolithic gzip archives.

``write_monolithic`` writes one archive for each task (a further one after ``most_bytes``), as a single gzip stream over all records
(which readers cannot seek in).  ``normalise`` inflates each such file once, as a stream, writes every record as
its own gzip member and a sidecar index of offsets, a task for each part, and ``read_back`` opens records through that
index, a task for each stretch of an archive.  A payload of ``least`` bytes or more that equals that of a smaller page_id becomes a revisit record.

Files go to the shared folder under temporary names and are renamed when complete, so a task that
is run again after an executor was lost replaces or repeats a whole file, never a part of one.
Memory: one record at a time.

Edge cases: a null html is the empty payload; null page ids sort first; rows that repeat the smallest
page_id of a payload are all responses; a very long page is one record, held whole; a null url gives a record without target; an empty table gives no archive;
other columns are ignored.
"""

from __future__ import annotations

import gzip
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, functions as F

from tilemine.llm.common import NULL_ID, delete, id_key, open_folder, park, park_only, publish, shared_folder, table

LEAST = 100
#: Bytes of records after which a new archive is begun, and of members that a task reads back.
MOST_BYTES, TASK_BYTES = 1 << 30, 64 << 20
_DATE = "2024-01-01T00:00:00Z"
_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def typed(pages: DataFrame, page: str = "page_id", url: str = "url", html: str = "html", least: int = LEAST) -> DataFrame:
    """(k, url, payload, digest, first): first is the page that a revisit refers to, else null."""
    rows = pages.select(id_key(page).alias("k"), F.col(url).cast("string").alias("url"), F.coalesce(F.col(html), F.lit("")).cast("binary").alias("payload")).withColumn("digest", F.sha2("payload", 256))
    firsts = rows.where(F.octet_length("payload") >= least).groupBy("digest").agg(F.min("k").alias("first"), F.max("k").alias("last")).where("first <> last").select("digest", "first")
    firsts = park(firsts, "warc-firsts")
    return rows.join(firsts, "digest", "left").select("k", "url", "payload", "digest", F.when(F.col("first") < F.col("k"), F.col("first")).alias("first"))


def _record_id(k: int) -> str:
    return f"<urn:page:{'null' if k == NULL_ID else k}>"


def _page_of(record_id: str) -> int | None:
    name = record_id.strip("<>").rpartition(":")[2]
    return None if name == "null" else int(name)


def record(k: int, url: str | None, payload: bytes, digest: str, first: int | None) -> bytes:
    """One WARC/1.1 record.  A revisit holds the HTTP head alone, with the full payload's length and digest."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    head = [f"WARC-Type: {'response' if first is None else 'revisit'}", f"WARC-Record-ID: {_record_id(k)}", f"WARC-Date: {_DATE}", f"WARC-Payload-Digest: sha256:{digest}", "Content-Type: application/http; msgtype=response"]
    if url is not None:
        head.append("WARC-Target-URI: " + re.sub(r"[\r\n]+", " ", url))
    if first is not None:
        head += [f"WARC-Profile: {_PROFILE}", f"WARC-Refers-To: {_record_id(first)}"]
    block = http if first is not None else http + payload
    return ("WARC/1.1\r\n" + "\r\n".join([*head, f"Content-Length: {len(block)}"]) + "\r\n\r\n").encode() + block + b"\r\n\r\n"


def parse(data: bytes) -> tuple[dict[str, str], dict[str, str], bytes]:
    """Record headers, HTTP headers (names in lower case) and payload of one whole record."""

    def fields(head: bytes) -> dict[str, str]:
        return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in head.decode().split("\r\n")[1:])}

    head, _, rest = data.partition(b"\r\n\r\n")
    outer = fields(head)
    http, _, payload = rest[: int(outer["content-length"])].partition(b"\r\n\r\n")
    return outer, fields(http), payload


def archive_name(part: int, roll: int) -> str:
    return f"part-of-{part:06d}-{roll:03d}.warc.gz"


def write_monolithic(rows: DataFrame, folder: str, level: int = 4, most_bytes: int = MOST_BYTES) -> DataFrame:
    """Write ``rows`` as of ``typed``: for each task an archive, and a further one whenever ``most_bytes`` of records are
    reached.  Returns (part, archive, n_records)."""
    schema = pa.schema([("part", pa.int64()), ("archive", pa.string()), ("n_records", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, path = open_folder(folder)
        part, roll, n, held, raw, sink, temporary = TaskContext.get().partitionId(), 0, 0, 0, None, None, ""

        def close() -> pa.RecordBatch:
            raw.write(sink.flush())
            raw.close()
            publish(store, temporary, f"{path}/{archive_name(part, roll)}")
            return pa.RecordBatch.from_arrays([pa.array([part], pa.int64()), pa.array([archive_name(part, roll)]), pa.array([n], pa.int64())], schema=schema)

        for batch in batches:
            for i in range(batch.num_rows):
                if raw is None:
                    store.create_dir(path, recursive=True)
                    temporary = f"{path}/.{archive_name(part, roll)}.{uuid.uuid4().hex}"
                    raw = store.open_output_stream(temporary, compression=None)
                    sink = zlib.compressobj(level, zlib.DEFLATED, 31)
                k, url, payload, digest, first = (batch.column(j)[i].as_py() for j in range(5))
                data = record(k, url, payload, digest, first)
                raw.write(sink.compress(data))
                n, held = n + 1, held + len(data)
                if held >= most_bytes:
                    yield close()
                    roll, n, held, raw = roll + 1, 0, 0, None
        if raw is not None:
            yield close()

    return rows.select("k", "url", "payload", "digest", "first").mapInArrow(run, "part long, archive string, n_records long")


def records(chunks: Iterator[bytes]) -> Iterator[bytes]:
    """Whole records, each with its closing line ends, from a gzip stream of one or more members."""
    inflate, held, need = zlib.decompressobj(31), bytearray(), None
    for chunk in chunks:
        while chunk:
            held += inflate.decompress(chunk)
            chunk = inflate.unused_data
            if inflate.eof:
                inflate = zlib.decompressobj(31)
            at = 0
            while True:
                if need is None:
                    head = held.find(b"\r\n\r\n", at)
                    if head < 0:
                        break
                    size = re.search(rb"\r\nContent-Length:[ \t]*(\d+)", held[at : head + 2], re.I)
                    if not held.startswith(b"WARC/", at) or size is None:
                        raise ValueError("not a WARC record")
                    need = head + 4 - at + int(size[1]) + 4
                if len(held) - at < need:
                    break
                yield bytes(held[at : at + need])
                at, need = at + need, None
            del held[:at]
    if held:
        raise ValueError("the archive ends inside a record")


def normalise(archives: DataFrame, source: str, target: str, level: int = 4) -> DataFrame:
    """Rewrite each archive of (part, archive) with a member for each record and a sidecar index, a task for each part.
    Returns the index rows: (archive, offset, length, record_id, record_type)."""
    schema = pa.schema([("archive", pa.string()), ("offset", pa.int64()), ("length", pa.int64()), ("record_id", pa.string()), ("record_type", pa.string())])

    def one(name: str) -> Iterator[pa.RecordBatch]:
        store, path = open_folder(source)
        _, out = open_folder(target)
        store.create_dir(out, recursive=True)
        mark = uuid.uuid4().hex
        with store.open_input_stream(f"{path}/{name}", compression=None) as raw, store.open_output_stream(f"{out}/.{name}.{mark}", compression=None) as sink, store.open_output_stream(f"{out}/.{name}.idx.{mark}", compression=None) as index:
            offset, rows = 0, []
            for data in records(iter(lambda: raw.read(1 << 20), b"")):
                head = data[: data.find(b"\r\n\r\n")].decode()
                kind, rid = re.search(r"\r\nWARC-Type: *(\S+)", head)[1], re.search(r"\r\nWARC-Record-ID: *(\S+)", head)[1]
                member = gzip.compress(data, level, mtime=0)
                sink.write(member)
                index.write(f"{offset} {len(member)} {kind} {rid}\n".encode())
                rows.append((name, offset, len(member), rid, kind))
                offset += len(member)
                if len(rows) == 4096:
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows)], schema=schema)
                    rows = []
        publish(store, f"{out}/.{name}.{mark}", f"{out}/{name}")
        publish(store, f"{out}/.{name}.idx.{mark}", f"{out}/{name}.idx")
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows)], schema=schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, path = open_folder(source)
        for batch in batches:
            for part in batch.column(0).to_pylist():
                for roll in range(rolls):
                    if store.get_file_info(f"{path}/{archive_name(part, roll)}").type != fs.FileType.NotFound:
                        yield from one(archive_name(part, roll))

    # the names follow from the numbers: a range has one number a task, which a shuffle of a few rows would not keep
    known = archives.groupBy("part").count().agg(F.max("part").alias("last"), F.max("count").alias("rolls")).first()
    rolls = known["rolls"] or 0
    parts = archives.sparkSession.range(0, 0 if known["last"] is None else known["last"] + 1, 1, max(1, (known["last"] or 0) + 1))
    return parts.mapInArrow(run, "archive string, offset long, length long, record_id string, record_type string")


def read_back(index: DataFrame, folder: str) -> DataFrame:
    """(page_id, payload_bytes, payload_digest, record_type, refers_to), each record opened by its offset.  A response's
    figures come from its payload, which must agree with its header; a revisit's from its headers."""
    schema = pa.schema([("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, path = open_folder(folder)
        name, raw = None, None
        for batch in batches:
            out = []
            for archive, offset, length in zip(*(batch.column(i).to_pylist() for i in range(3))):
                if archive != name:
                    name, raw = archive, store.open_input_file(f"{path}/{archive}")
                outer, http, payload = parse(gzip.decompress(raw.read_at(length, offset)))
                kind, digest = outer["warc-type"], outer["warc-payload-digest"].partition(":")[2]
                size = int(http["content-length"])
                if kind == "response" and (hashlib.sha256(payload).hexdigest() != digest or len(payload) != size):
                    raise ValueError(f"{archive} at {offset}: the payload does not agree with its header")
                out.append((_page_of(outer["warc-record-id"]), size, digest, kind, _page_of(outer["warc-refers-to"]) if kind == "revisit" else None))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out), schema)], schema=schema)

    return index.select("archive", "offset", "length").mapInArrow(run, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")


def spread(index: DataFrame, task_bytes: int = TASK_BYTES) -> DataFrame:
    """The index rows dealt to tasks by stretches of their archives, in order of offset: as many tasks as the session has
    cores at least, and one for each ``task_bytes``."""
    total = index.agg(F.sum("length")).first()[0] or 0
    n = max(index.sparkSession.sparkContext.defaultParallelism, total // task_bytes + 1)
    return index.repartition(n, "archive", F.floor(F.col("offset") / (total // (4 * n) + 1))).sortWithinPartitions("archive", "offset")


def round_trip(pages: DataFrame, folder: str | None = None, least: int = LEAST, most_bytes: int = MOST_BYTES) -> DataFrame:
    """Write, normalise and read back.  Archives and sidecars stay in ``folder``/normalised; the monolithic ones go."""
    spark = pages.sparkSession
    keep, folder = folder is not None, folder or f"{shared_folder(spark)}/warc-{uuid.uuid4().hex}"
    archives = park_only(spark, lambda: write_monolithic(typed(pages, least=least), f"{folder}/monolithic", most_bytes=most_bytes), "warc-archives")
    index = park(normalise(archives, f"{folder}/monolithic", f"{folder}/normalised"), "warc-index")
    if not keep:
        delete(spark, f"{folder}/monolithic")
    return read_back(spread(index), f"{folder}/normalised")


def op5_warc_normaliser(spark: SparkSession, sf_dir: str) -> DataFrame:
    return round_trip(table(spark, sf_dir, "pages"))


SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
q AS (SELECT page_id, octet_length(encode(h)) AS n, sha256(h) AS d, min(page_id) OVER (PARTITION BY sha256(h)) AS f FROM p)
SELECT page_id, CAST(n AS BIGINT) AS payload_bytes, d AS payload_digest, CASE WHEN n >= 100 AND f < page_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN n >= 100 AND f < page_id THEN f END AS refers_to FROM q
"""
