"""Language identification: averaged hashed subword embeddings and a linear softmax.

A text's vector is the mean of the embeddings of its words' subwords (the word itself and its
character n-grams, hashed to ``buckets``); a softmax over languages follows.  Both layers are
trained by stochastic gradient descent in numpy on the driver, on a sample of about
``sample_rows`` labelled documents and at most about ``sample_bytes`` (whole texts, cut into pieces of different lengths so that short
texts are learned too).  A part of the sample is kept out of the descent to fit the temperature that
calibrates the scores and the score below which a prediction is rejected: the limit that rejects ``REJECTED_RIGHT`` of the right ones.

To predict, embeddings and softmax are multiplied out once: each bucket has a row of class scores, a word's scores
are kept in a table that is emptied at ``most_words``, and the text's are their mean.  One pass, no shuffle.

Edge cases: texts that are null or have no letter are ``und`` with score 0, as is every text if no
labelled row was given; of languages with equal scores the first by name is taken; a very long text is scored in pieces of
50,000 words; an empty table gives an empty result; rows with null labels are never learned from; repeated rows give repeated results; null ids are
held out of nothing (crc32 of null counts as 0); other columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from tilemine.llm.common import id_and_bytes, table

UNKNOWN = "und"
SAMPLE_ROWS = 3000
#: Expected bytes of the sample's texts.
SAMPLE_BYTES = 32 << 20
#: The share of right predictions on the kept-out part that the fitted limit may reject.
REJECTED_RIGHT = 0.01
BUCKETS = 1 << 16
_WORD = re.compile(r"[^\W\d_]+")


def subwords(word: str, buckets: int = BUCKETS) -> list[int]:
    marked = f"<{word}>".encode() if word.isascii() else f"<{word}>"
    n = len(marked)
    parts = [marked[i : i + k] for k in (2, 3, 4) for i in range(n - k + 1)] + [marked]
    crc = zlib.crc32
    return [crc(p if type(p) is bytes else p.encode()) % buckets for p in parts]


@dataclass
class Model:
    languages: list[str]
    scores: np.ndarray  # bucket x language, logits already divided by the temperature
    bias: np.ndarray
    reject_below: float


def _features(words: list[str], buckets: int, known: dict[str, list[int]]) -> tuple[np.ndarray, np.ndarray]:
    out: list[int] = []
    for w in words:
        got = known.get(w)
        if got is None:
            got = known[w] = subwords(w, buckets)
        out += got
    index, n = np.unique(np.array(out, np.int64), return_counts=True)
    return index, (n / n.sum()).astype(np.float32)


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def train(rows: list[tuple[str, str]], buckets: int = BUCKETS, width: int = 16, epochs: int = 5, rate: float = 0.5, seed: int = 7) -> Model:
    """Fit on (text, language) rows."""
    languages = sorted({label for _, label in rows})
    random = np.random.default_rng(seed)
    known: dict[str, list[int]] = {}
    fit, held = [], []
    for i, (text, label) in enumerate(rows):
        words, at = _WORD.findall(text.lower()), 0
        y = languages.index(label)
        while at < len(words):
            size = int(random.choice((2, 5, 12, 40, 150)))
            (held if i % 5 == 4 else fit).append((*_features(words[at : at + size], buckets, known), y))
            at += size
            if at > 400:  # long texts give one last piece
                (held if i % 5 == 4 else fit).extend([(*_features(words[at:], buckets, known), y)] if at < len(words) else [])
                break
    if not fit or not languages:
        return Model([], np.zeros((buckets, 0), np.float32), np.zeros(0, np.float32), 1.0)
    embed = (random.standard_normal((buckets, width)) * 0.1).astype(np.float32)
    out, bias = np.zeros((width, len(languages)), np.float32), np.zeros(len(languages), np.float32)
    steps, step = epochs * len(fit), 0
    for _ in range(epochs):
        for i in random.permutation(len(fit)):
            index, weight, y = fit[i]
            x = weight @ embed[index]
            error = _softmax(x @ out + bias)
            error[y] -= 1
            lr = rate * (1 - step / steps)
            back = out @ error
            out -= lr * np.outer(x, error)
            bias -= lr * 0.1 * error
            embed[index] -= lr * np.outer(weight, back) * 10
            step += 1
    z = np.array([weight @ embed[index] @ out + bias for index, weight, _ in held or fit])
    y = np.array([y for *_, y in held or fit])
    losses = {t: -np.log(_softmax(z / t)[np.arange(len(y)), y] + 1e-9).mean() for t in np.geomspace(0.25, 8, 41)}
    t = min(losses, key=losses.get)
    p = _softmax(z / t)
    right = p[np.arange(len(y)), y] == p.max(1)
    reject = float(np.quantile(p.max(1)[right], REJECTED_RIGHT)) if right.any() else 1.0
    return Model(languages, (embed @ out / t).astype(np.float32), (bias / t).astype(np.float32), reject)


class Predictor:
    def __init__(self, model: Model, most_words: int = 200_000):
        self.model, self.most = model, most_words
        self.place: dict[str, int] = {}
        self.sums = np.zeros((most_words, len(model.languages)), np.float32)
        self.counts = np.zeros(most_words, np.float32)

    def _add(self, word: str) -> int:
        if len(self.place) == self.most:
            raise MemoryError
        i = self.place[word] = len(self.place)
        index = subwords(word, len(self.model.scores))
        self.sums[i], self.counts[i] = self.model.scores[index].sum(0), len(index)
        return i

    def __call__(self, text: str | None, reject_below: float = 0.0) -> tuple[str, float]:
        words = _WORD.findall(text.lower()) if text else []
        if not words or not self.model.languages:
            return UNKNOWN, 0.0
        total, n = np.zeros(len(self.model.languages)), 0.0
        for at in range(0, len(words), 50_000):  # a piece has fewer distinct words than the table has places
            part = words[at : at + 50_000]
            if len(self.place) + len(part) > self.most:
                self.place.clear()
            get = self.place.get
            index = np.fromiter((i if (i := get(w)) is not None else self._add(w) for w in part), np.int64, len(part))
            total += self.sums[index].sum(0)
            n += self.counts[index].sum()
        p = _softmax(total / n + self.model.bias)
        best = int(p.argmax())
        return (self.model.languages[best], float(p[best])) if p[best] >= reject_below else (UNKNOWN, float(p[best]))


def remainder(doc: str = "doc_id"):
    return F.pmod(F.coalesce(F.crc32(F.col(doc).cast("string")), F.lit(0)), F.lit(3))


def learn(docs: DataFrame, sample_rows: int = SAMPLE_ROWS, sample_bytes: int = SAMPLE_BYTES) -> Model:
    """Train on a sample of the labelled rows that are not held out: those whose id and text have a hash below a limit that lets
    about ``sample_rows`` rows and ``sample_bytes`` of text pass (both are counted first).  Equal rows are one.  Only these reach the driver."""
    rows = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (remainder() != 1))
    n = rows.agg(F.count(F.lit(1)).alias("rows"), F.sum(F.octet_length("text")).alias("bytes")).first()
    share = min(1.0, sample_rows / max(n.rows, 1), sample_bytes / max(n.bytes or 0, 1))
    some = rows.where(F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 30)) < int(share * (1 << 30))).select("text", "lang", "doc_id").distinct().collect()
    return train([(r.text, r.lang) for r in sorted(some, key=lambda r: (r.doc_id is not None, r.doc_id, r.text, r.lang))])


def identify(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, held_out, lang_pred, score, rejected) per row; ``rejected`` says that the score lies below the model's fitted
    limit, so that the prediction is not to be trusted: a user who wants only trusted ones takes the others as unknown."""
    schema = pa.schema([("doc_id", pa.int64()), ("lang_pred", pa.string()), ("score", pa.float64()), ("rejected", pa.bool_())])
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        predict = Predictor(sent.value)
        for batch in batches:
            found = [predict(batch.column(1)[i].as_py().decode()) for i in range(batch.num_rows)]
            scores = [b for _, b in found]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([a for a, _ in found], pa.string()), pa.array(scores, pa.float64()), pa.array([b < sent.value.reject_below for b in scores], pa.bool_())], schema=schema)

    out = id_and_bytes(docs).mapInArrow(run, "doc_id long, lang_pred string, score double, rejected boolean")
    return out.select("doc_id", (remainder() == 1).alias("held_out"), "lang_pred", "score", "rejected")


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return identify(docs, learn(docs))
