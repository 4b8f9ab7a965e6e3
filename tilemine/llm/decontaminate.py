"""Benchmark decontamination with a generalised suffix automaton of the test items.

The items' normalised words make automata; a document's words are streamed through
them and the longest match that ends at each word is tracked.  A match of ``window`` words,
or of a whole shorter item, marks its words.

The items are dealt to blocks of about ``block_words`` words (an item is never cut).  Tasks build a block's automaton each and write
it as flat numpy arrays, some 80 bytes a word, into the shared folder.  Nothing of it passes the driver, and documents
are not shuffled: a task reads the blocks, holds the only one, or goes through many in turn, each read once
for every ``slice_bytes`` of text, so memory is bounded by one block and one slice whatever the size of the benchmark.

Results in edge cases: a null or wordless text has no words and no hits; an item without
words never occurs; repeated item ids count once if any of their texts occurs; a null item id is an item of its own, counted and
left out of the digest; a very long text is one slice; repeated
document rows each give a row; no items, no hits; an empty table gives an empty result; other columns are ignored by ``hits`` and kept by ``clean``, whatever their names.
"""

from __future__ import annotations

import hashlib
import io
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, functions as F

from tilemine.llm.common import id_and_bytes, new_folder, open_folder, table, write_file

#: A-Z become a-z; every ASCII byte that is no letter or digit separates words.
_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c > 127 else 32 for c in range(256))
_WORD = re.compile(rb"[0-9A-Za-z\x80-\xff]+")
BLOCK_WORDS = 100_000
#: Text that passes all blocks together.
SLICE_BYTES = 8 << 20


def words(body: bytes) -> list[bytes]:
    return body.translate(_FOLD).split()


class Builder:
    """Builds a suffix automaton over the word ids of several items, without matches across items."""

    def __init__(self, items: list[tuple[str | None, list[bytes]]], window: int):
        self.window, self.names = window, sorted({name for name, _ in items}, key=lambda x: (x is not None, x or ""))
        place = {name: i for i, name in enumerate(self.names)}
        self.ids: dict[bytes, int] = {}
        self.next: list[dict[int, int]] = [{}]
        self.link, self.length = [-1], [0]
        self.texts = [(place[name], [self.ids.setdefault(w, len(self.ids)) for w in ws]) for name, ws in items if ws]
        for _, sequence in self.texts:
            last = 0
            for symbol in sequence:
                last = self._extend(last, symbol)

    def _extend(self, last: int, symbol: int) -> int:
        """Append a symbol after state ``last``; an existing transition is reused or split."""
        if symbol in self.next[last]:
            there = self.next[last][symbol]
            return there if self.length[there] == self.length[last] + 1 else self._split(last, there, symbol)
        new = self._state({}, 0, self.length[last] + 1)
        while last >= 0 and symbol not in self.next[last]:
            self.next[last][symbol] = new
            last = self.link[last]
        if last >= 0:
            there = self.next[last][symbol]
            self.link[new] = there if self.length[there] == self.length[last] + 1 else self._split(last, there, symbol)
        return new

    def _split(self, state: int, there: int, symbol: int) -> int:
        clone = self._state(dict(self.next[there]), self.link[there], self.length[state] + 1)
        self.link[there] = clone
        while state >= 0 and self.next[state].get(symbol) == there:
            self.next[state][symbol] = clone
            state = self.link[state]
        return clone

    def _state(self, moves: dict[int, int], link: int, length: int) -> int:
        self.next.append(moves)
        self.link.append(link)
        self.length.append(length)
        return len(self.next) - 1

    def arrays(self) -> dict[str, np.ndarray]:
        """The automaton as flat arrays: transitions sorted by (state, symbol), suffix links, lengths, the items whose
        windows end in a state, the short items that do, word pairs, words and names."""
        n, size, window = len(self.next), len(self.ids) + 1, self.window
        within: list[set[int]] = [set() for _ in range(n)]
        whole: list[set[tuple[int, int]]] = [set() for _ in range(n)]
        for item, sequence in self.texts:
            state = 0
            for symbol in sequence:
                state = self.next[state][symbol]
                up = state
                while up > 0 and self.length[up] >= window and item not in within[up]:
                    within[up].add(item)
                    up = self.link[up]
            if len(sequence) < window:
                whole[state].add((len(sequence), item))
        short: list[tuple[tuple[int, int], ...]] = [()] * n
        for state in sorted(range(1, n), key=self.length.__getitem__):
            short[state] = (*short[self.link[state]], *sorted(whole[state]))
        moves = sorted((state * size + symbol, there) for state, to in enumerate(self.next) for symbol, there in to.items())
        flat = lambda rows: np.array([x for row in rows for x in row], np.int64)
        ends = lambda rows: np.cumsum([0, *map(len, rows)])
        return {
            "keys": np.array([k for k, _ in moves], np.int64), "to": np.array([t for _, t in moves], np.int32), "link": np.array(self.link, np.int32), "length": np.array(self.length, np.int32),
            "long_ends": ends(within), "long": flat(map(sorted, within)), "short_ends": ends(short), "short": flat(short).reshape(-1, 2),
            "pairs": np.unique(np.array([a * size + b for _, s in self.texts for a, b in zip(s, s[1:])], np.int64)),
            "words": np.frombuffer(b" ".join(self.ids), np.uint8), "names": np.frombuffer("\0".join(f"={x}" if x is not None else "-" for x in self.names).encode(), np.uint8),
            "head": np.array([window, min([window, *(len(s) for _, s in self.texts if len(s) < window)]) if self.texts else 0], np.int64),
        }


class Automaton:
    """Scans documents by the arrays of a built automaton."""

    def __init__(self, arrays: dict[str, np.ndarray]):
        self.__dict__.update(arrays)
        self.window, self.least = arrays["head"].tolist()
        self.ids = {w: i for i, w in enumerate(arrays["words"].tobytes().split())}
        self.names = [x[1:] if x.startswith("=") else None for x in arrays["names"].tobytes().decode().split("\0")]

    @classmethod
    def of(cls, items: list[tuple[str | None, list[bytes]]], window: int) -> Automaton:
        return cls(Builder(items, window).arrays())

    def pack(self) -> bytes:
        return pack({k: v for k, v in self.__dict__.items() if isinstance(v, np.ndarray)})

    def _step(self, state: int, symbol: int) -> int:
        """The state after ``symbol``, -1 if there is none."""
        key = state * (len(self.ids) + 1) + symbol
        at = int(self.keys.searchsorted(key))
        return int(self.to[at]) if at < len(self.keys) and self.keys[at] == key else -1

    def scan(self, ws: list[bytes], hit: np.ndarray) -> set[str | None]:
        """Mark the words of ``ws`` inside matches in ``hit``; the items that occur."""
        if not self.least or len(ws) < self.least:
            return set()
        get = self.ids.get
        known = np.fromiter((get(w, -1) for w in ws), np.int64, len(ws))
        found: set[int] = set()
        for start, stop in self._runs(known):
            self._stream(known[start:stop].tolist(), start, hit, found)
        return {self.names[i] for i in found}

    def _runs(self, known: np.ndarray) -> Iterator[tuple[int, int]]:
        """Stretches in which each two neighbours are neighbours in an item too; a match lies within one."""
        if self.least < 2:
            ok = known >= 0
            edge = np.flatnonzero(np.diff(np.concatenate(([False], ok, [False])).astype(np.int8)))
            yield from zip(edge[::2].tolist(), edge[1::2].tolist())
            return
        pair = known[:-1] * (len(self.ids) + 1) + known[1:]
        at = np.searchsorted(self.pairs, pair)
        at[at == len(self.pairs)] = 0
        ok = (known[:-1] >= 0) & (known[1:] >= 0) & (self.pairs[at] == pair) if len(self.pairs) else np.zeros(len(pair), bool)
        edge = np.flatnonzero(np.diff(np.concatenate(([False], ok, [False])).astype(np.int8)))
        for start, stop in zip(edge[::2].tolist(), edge[1::2].tolist()):
            if stop + 1 - start >= self.least:
                yield start, stop + 1

    def _stream(self, symbols: list[int], offset: int, hit: np.ndarray, found: set[int]) -> None:
        state = length = 0
        for i, symbol in enumerate(symbols, offset):
            while (there := self._step(state, symbol)) < 0 and state:
                state = int(self.link[state])
                length = int(self.length[state])
            if there < 0:
                continue
            state, length = there, length + 1
            if length >= self.window:
                while self.length[self.link[state]] >= self.window:
                    state = int(self.link[state])
                length = min(length, int(self.length[state]))
                hit[i - self.window + 1 : i + 1] = True
                found.update(self.long[self.long_ends[state] : self.long_ends[state + 1]].tolist())
            for size, item in self.short[self.short_ends[state] : self.short_ends[state + 1]].tolist():
                if size <= length:
                    hit[i - size + 1 : i + 1] = True
                    found.add(item)


def pack(arrays: dict[str, np.ndarray]) -> bytes:
    out = io.BytesIO()
    np.savez(out, **arrays)
    return out.getvalue()


def unpack(data: bytes) -> Automaton:
    with np.load(io.BytesIO(data)) as held:
        return Automaton({name: held[name] for name in held.files})


def build(benchmark: DataFrame, window: int, block_words: int = BLOCK_WORDS, item: str = "item_id", text: str = "text") -> tuple[str, list[tuple[str, int]]]:
    """Write an automaton for each block of items.  Returns their folder and (file, bytes) of each."""
    spark = benchmark.sparkSession
    folder = new_folder(spark, "automata")
    items = benchmark.select(F.col(item).cast("string").alias("name"), F.coalesce(F.col(text), F.lit("")).alias("body"))
    size = items.agg(F.sum(F.regexp_count("body", F.lit(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")))).first()[0] or 0
    n = size // block_words + 1
    dealt = items.withColumn("block", F.pmod(F.xxhash64("name", "body"), F.lit(n))).repartition(n, "block").sortWithinPartitions("block")
    schema = pa.schema([("file", pa.string()), ("bytes", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, path = open_folder(folder)

        def close(block: int, held: list) -> pa.RecordBatch:
            data, file = pack(Builder(held, window).arrays()), f"block-{block:06d}.npz"
            write_file(store, f"{path}/{file}", data)
            return pa.RecordBatch.from_arrays([pa.array([file]), pa.array([len(data)], pa.int64())], schema=schema)

        now, held = None, []
        for batch in batches:
            for name, body, block in zip(*(batch.column(i).to_pylist() for i in range(3))):
                if now not in (None, block):
                    yield close(now, held)
                    held = []
                now = block
                held.append((name, words(body.encode())))
        if held:
            yield close(now, held)

    # sums and names only: one row for each block of words
    return folder, sorted((r.file, r.bytes) for r in dealt.mapInArrow(run, "file string, bytes long").collect())


class Scanner:
    """Goes through texts block by block; a single block is held."""

    def __init__(self, folder: str, files: list[str]):
        self.files = files
        self.store, self.path = open_folder(folder)
        self.only = self._open(files[0]) if len(files) == 1 else None

    def _open(self, file: str) -> Automaton:
        with self.store.open_input_stream(f"{self.path}/{file}", compression=None) as raw:
            return unpack(raw.read())

    def __call__(self, bodies: list[bytes]) -> list[tuple[int, np.ndarray, set[str | None]]]:
        """(words, hit, items) of each text."""
        split = [words(b) for b in bodies]
        hits = [np.zeros(len(ws), bool) for ws in split]
        items: list[set[str | None]] = [set() for _ in split]
        for file in self.files:
            automaton = self.only or self._open(file)
            for ws, hit, found in zip(split, hits, items):
                found |= automaton.scan(ws, hit)
        return [(len(ws), hit, found) for ws, hit, found in zip(split, hits, items)]


def slices(sizes: list[int], most: int) -> Iterator[tuple[int, int]]:
    """Stretches of texts of at most ``most`` bytes, or of one text."""
    start = held = 0
    for i, size in enumerate(sizes):
        if i > start and held + size > most:
            yield start, i
            start, held = i, 0
        held += size
    if start < len(sizes):
        yield start, len(sizes)


def hits(docs: DataFrame, benchmark: DataFrame, window: int = 13, coverage: tuple[int, int] = (1, 20), block_words: int = BLOCK_WORDS) -> DataFrame:
    """Per document: words, words inside item windows, items found and the verdict (hit words >= coverage of all)."""
    (folder, files), (part, of) = build(benchmark, window, block_words), coverage
    files = [file for file, _ in files]
    schema = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_hit", pa.int64()), ("n_items", pa.int64()), ("items_sha256", pa.string()), ("contaminated", pa.bool_()), ("items", pa.list_(pa.string()))])

    def rows(ids: list, out: list) -> dict[str, list]:
        n_hit = [int(hit.sum()) for _, hit, _ in out]
        return {
            "doc_id": ids, "n_words": [n for n, _, _ in out], "n_hit": n_hit, "n_items": [len(f) for _, _, f in out],
            "items_sha256": [hashlib.sha256(",".join(sorted(f - {None})).encode()).hexdigest() for _, _, f in out],
            "contaminated": [h > 0 and of * h >= part * n for h, (n, _, _) in zip(n_hit, out)], "items": [sorted(f, key=lambda x: (x is not None, x or "")) for _, _, f in out],
        }

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scan = Scanner(folder, files)
        for batch in batches:
            bodies = batch.column(1)
            for start, stop in slices(pc.binary_length(bodies).to_pylist(), SLICE_BYTES):
                out = rows(batch.column(0)[start:stop].to_pylist(), scan(bodies[start:stop].to_pylist()))
                yield pa.RecordBatch.from_arrays([pa.array(out[f.name], f.type) for f in schema], schema=schema)

    return id_and_bytes(docs).mapInArrow(run, "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, items array<string>")


def clean(docs: DataFrame, benchmark: DataFrame, window: int = 13, coverage: tuple[int, int] = (1, 20), block_words: int = BLOCK_WORDS) -> DataFrame:
    """The rows of ``docs`` that stay: contaminated ones go, other matches are cut out of ``text`` with the white
    space after them.  Rows without a match keep their text byte for byte; ``n_chars``, if there, follows the text."""
    (folder, files), (part, of) = build(benchmark, window, block_words), coverage
    files = [file for file, _ in files]
    names = docs.columns
    columns = [F.col(f"`{c}`") for c in names]
    at = names.index("text")

    def cut(body: bytes, hit: np.ndarray) -> str:
        spans, kept, last = [m.span() for m in _WORD.finditer(body)], [], 0
        edge = np.flatnonzero(np.diff(np.concatenate(([False], hit, [False])).astype(np.int8))).tolist()
        for start, stop in zip(edge[::2], edge[1::2]):
            kept.append(body[last : spans[start][0]])
            last = spans[stop][0] if stop < len(spans) else len(body)
        return b"".join([*kept, body[last:]]).decode()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scan = Scanner(folder, files)
        for whole in batches:
            for start, stop in slices(pc.fill_null(pc.binary_length(whole.column(at)), 0).to_pylist(), SLICE_BYTES):
                batch = whole.slice(start, stop - start)
                texts = batch.column(at).to_pylist()
                bodies = [(t or "").encode() for t in texts]
                keep, new = [], []
                for text, body, (n, hit, _) in zip(texts, bodies, scan(bodies)):
                    h = int(hit.sum())
                    keep.append(not (h and of * h >= part * n))
                    new.append(text if not h else cut(body, hit) if keep[-1] else text)
                arrays = [pa.array(new, batch.schema.field(i).type) if i == at else batch.column(i) for i in range(len(names))]
                yield pa.RecordBatch.from_arrays(arrays, schema=batch.schema).filter(pa.array(keep, pa.bool_()))

    out = docs.select(*columns).mapInArrow(run, docs.schema)
    return out.withColumn("n_chars", F.when(F.col("text").isNotNull(), F.char_length("text").cast("long"))) if "n_chars" in names else out


def op2_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hits(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).drop("items")


SQL = r"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda w: w <> '') AS w FROM documents),
b AS (SELECT item_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda w: w <> '') AS w FROM benchmark),
bw AS (SELECT DISTINCT item_id, least(13, len(w)) AS n, array_to_string(list_slice(w, i, i + least(13, len(w)) - 1), ' ') AS s
       FROM b, unnest(generate_series(1, greatest(len(w) - 12, 1))) AS g(i) WHERE len(w) > 0),
sizes AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT doc_id, i, n, array_to_string(list_slice(w, i, i + n - 1), ' ') AS s FROM d, sizes, unnest(generate_series(1, len(w) - n + 1)) AS g(i) WHERE len(w) >= n),
m AS (SELECT dw.doc_id, dw.i, dw.n, bw.item_id FROM dw JOIN bw USING (n, s)),
h AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(generate_series(i, i + n - 1)) AS p FROM (SELECT DISTINCT doc_id, i, n FROM m)) GROUP BY doc_id),
t AS (SELECT doc_id, count(*) AS n_items, string_agg(x, ',' ORDER BY x) AS items FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS x FROM m) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN h USING (doc_id) LEFT JOIN t USING (doc_id)
"""
