"""Exact token counts of huge texts by overlap resynchronisation.

A text of up to ``chunk`` characters is encoded whole.  A longer one is encoded in chunks that
overlap.  Two neighbouring encodings are spliced at a boundary that is stable: both encodings have
a token boundary there by their offsets and agree on all tokens between the overlap's first and last such place, and the place is proven to be one that no rule of the tokenizer reaches
across, namely a white-space character between two others (normalisation is local to such a
place, the word pattern never matches white space, and no special string contains it).  If the overlap
holds no such place, or the two encodings differ between the places found, the overlap is
doubled, up to the whole text.  Only the tokens before the splice of the left chunk and after it of
the right chunk count.

A text of up to ``chunk`` characters is one chunk: such texts go to the library in batches.

Edge cases: null and empty texts have no tokens; a very long text is
held as a whole and encoded by chunks; a text without stable places is encoded whole in the end; repeated rows give repeated results; an empty table gives none; other columns are ignored.
"""

from __future__ import annotations

import functools
import json
import os
import re
from collections.abc import Iterator

import public_tokenizers
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from tilemine.llm.common import by_batch, id_and_bytes, table

FILE = "word_bpe_49k.json"
#: Characters of a chunk, and of what neighbouring chunks share.
CHUNK, OVERLAP = 16_000, 400
#: White space between two characters that neither are white space nor combine with what stands before them.
_STABLE = re.compile(r"(?<=[A-Za-z0-9.,;:!?])[ \n\t](?=[A-Za-z0-9])")
#: What the normaliser would do more to than turn capitals into small letters: combining marks and all beyond them, a letter whose small form is two characters, special strings.
_NOT_PLAIN = re.compile("[\u0130\u0300-\U0010ffff]|<\\|")
_COLLAPSE = {"type": "Replace", "pattern": {"Regex": "\\s+"}, "content": " "}


@functools.lru_cache(maxsize=4)
def load(file: str = FILE):
    """The tokenizer, read once by each Python worker."""
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer, normalizers

    path = public_tokenizers.path(file)
    spec = json.load(open(path))
    pattern = json.dumps(spec.get("pre_tokenizer"))
    if '"behavior": "Removed"' not in pattern or any(re.search(r"\s", t["content"]) or t["lstrip"] or t["rstrip"] for t in spec["added_tokens"]):
        raise ValueError(f"{file}: white space isn't a proven boundary of this tokenizer")
    tokenizer = Tokenizer.from_file(path)
    # collapsing white space changes no token, since the word pattern never matches any: a fifth of the time is saved
    parts = spec["normalizer"].get("normalizers", []) if spec.get("normalizer") else []
    if parts and all(p["type"] in ("NFC", "Lowercase") or p == _COLLAPSE for p in parts):
        tokenizer.normalizer = normalizers.Sequence([getattr(normalizers, p["type"])() for p in parts if p != _COLLAPSE])
    return tokenizer


@functools.lru_cache(maxsize=4)
def load_plain(file: str = FILE):
    """The tokenizer without its normaliser, for small letters below the combining marks, which NFC leaves alone; None if its normaliser is another."""
    from tokenizers import Tokenizer, normalizers

    spec = json.load(open(public_tokenizers.path(file)))
    kinds = [p["type"] for p in (spec["normalizer"] or {}).get("normalizers", [])]
    if sorted(kinds) != ["Lowercase", "NFC", "Replace"] or any("<|" not in t["content"] or t["normalized"] for t in spec["added_tokens"]):
        return None
    tokenizer = Tokenizer.from_str(load(file).to_str())
    tokenizer.normalizer = normalizers.Sequence([])
    return tokenizer


class Counter:
    def __init__(self, tokenizer, chunk: int = CHUNK, overlap: int = OVERLAP, plain=None):
        self.tokenizer, self.chunk, self.overlap, self.plain = tokenizer, chunk, overlap, plain
        self.widened = self.spliced = 0

    def count_all(self, texts: list[str]) -> list[int]:
        """Texts of one chunk go to the library in batches of bounded size."""
        out, size = [0] * len(texts), 0
        batches: tuple[list, list] = ([], [])
        for i, text in enumerate(texts):
            if len(text) > self.chunk:
                out[i] = self.count_long(text)
                continue
            plain = self.plain is not None and not _NOT_PLAIN.search(text)
            batches[plain].append((i, text.lower() if plain else text))
            size += len(text)
            if size > 200_000:
                self._flush(batches, out)
                size = 0
        self._flush(batches, out)
        return out

    def _flush(self, batches: tuple[list, list], out: list[int]) -> None:
        for tokenizer, batch in zip((self.tokenizer, self.plain), batches):
            if batch:
                for (i, _), x in zip(batch, tokenizer.encode_batch_fast([t for _, t in batch], add_special_tokens=False)):
                    out[i] = len(x)
                batch.clear()

    def _encode(self, text: str):
        if self.plain is not None and not _NOT_PLAIN.search(text):
            return self.plain.encode(text.lower(), add_special_tokens=False)
        return self.tokenizer.encode(text, add_special_tokens=False)

    def count_long(self, text: str) -> int:
        """Left to right; ``left`` is the encoding from ``begin``, whose tokens from the word behind ``start`` on are not yet counted."""
        total, begin, start, overlap = 0, 0, -1, self.overlap
        end = min(self.chunk, len(text))
        left, first = self._encode(text[:end]), 0
        while end < len(text):
            right_from = max(start, end - overlap, 0)
            right_to = min(len(text), right_from + self.chunk + overlap)
            right = self._encode(text[right_from:right_to])
            splice = self._splice(text, left, begin, right, right_from, end)
            if splice is None:
                self.widened += 1
                if right_from == max(start, 0):  # the overlap is all that is left of this chunk: encode it with more text
                    begin, end = right_from, min(len(text), right_from + 2 * (end - right_from))
                    left = self._encode(text[begin:end])
                    first = left.char_to_token(start + 1 - begin) if start >= 0 else 0
                else:
                    overlap *= 2
                continue
            self.spliced += 1
            place, at_left, at_right = splice
            total += at_left - first
            start, begin, left, end, overlap, first = place, right_from, right, right_to, self.overlap, at_right
        return total + len(left) - first

    @staticmethod
    def _splice(text: str, left, begin: int, right, right_from: int, end: int) -> tuple[int, int, int] | None:
        """The middle one of the stable places, with the token behind it in both encodings, if both cut the text alike between
        the first and the last."""
        places = [m.start() for m in _STABLE.finditer(text, right_from, end)]
        if len(places) < 2:
            return None
        a, b, middle = places[0], places[-1], places[len(places) // 2]
        in_left, in_right = ([e.char_to_token(p + 1 - at) for p in (a, middle, b)] for e, at in ((left, begin), (right, right_from)))
        if None in in_left or None in in_right or in_left[2] - in_left[0] != in_right[2] - in_right[0]:
            return None
        if left.ids[in_left[0] : in_left[2]] != right.ids[in_right[0] : in_right[2]]:
            return None
        for i, j in zip(range(in_left[0], in_left[2]), range(in_right[0], in_right[2])):
            one, two = left.token_to_chars(i), right.token_to_chars(j)
            if (one[0] + begin, one[1] + begin) != (two[0] + right_from, two[1] + right_from) or one[0] + begin < middle < one[1] + begin:
                return None
        return middle, in_left[1], in_right[1]


def counts(docs: DataFrame, limit: int = 2048, file: str = FILE, chunk: int = CHUNK, overlap: int = OVERLAP) -> DataFrame:
    """Per row: UTF-8 bytes, tokens, and whether there are more tokens than ``limit``."""
    schema = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_tokens", pa.int64()), ("over_limit", pa.bool_())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = Counter(load(file), chunk, overlap, load_plain(file))

        def rows(x: dict[str, list]) -> dict[str, list]:
            n = counter.count_all([b.decode() for b in x["body"]])
            return {"doc_id": x["doc_id"], "n_bytes": list(map(len, x["body"])), "n_tokens": n, "over_limit": [k > limit for k in n]}

        yield from by_batch(rows, schema)(batches)

    return id_and_bytes(docs).mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return counts(table(spark, sf_dir, "documents"))
