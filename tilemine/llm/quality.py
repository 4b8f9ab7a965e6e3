"""Quality rules as a short-circuit cascade.

A text is kept if no rule rejects it.  Each rule names what it needs of the text: words, lines, letters, repeated
windows.  What a rule asks for first is computed then, once for each text, so a rule's cost is that of the figures it
needs.  A sample, chosen by a hash of the text over all files, is measured on the executors: seconds and rejections of each rule,
each on fresh texts.  Rules run by rejections per second, and a text that one rule rejects never meets the others,
nor are the figures computed that only those need.  Only the sums, two numbers a rule, reach the driver.  The sample sets the order and
nothing else: a conjunction is the same in any order, so verdicts are exact and equal in every run.

``keep_good`` (the pipeline) computes what the cascade asks for; ``assess`` (op8) has to report all base figures of each
text, so there the cascade saves only what no base figure needs.

The rule on insults (English words alone) is the only one on wording: a text with two or more of ``INSULTS`` that are at least one word in
two hundred goes.

Edge cases: a null or wordless text has no words and fails the base rule; a very long text is judged whole, in memory of some
50 bytes a word; equal texts have equal verdicts, and a share equal to its limit passes (but for the insults' share, which is reached at one in two hundred);
repeated rows give repeated results; an empty table gives none; other columns are ignored by ``assess`` and kept by ``keep_good``, whatever their names.
"""

from __future__ import annotations

import re
import time
from collections.abc import Callable, Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from tilemine.llm.common import by_batch, id_and_bytes, table, word_lists

_SYMBOLS = b"#*$%&|<>"
_SPACE = bytes([32, 9, 10, 11, 12, 13])
#: Continuation bytes of UTF-8: not counted as code points.
_TAIL = bytes(range(0x80, 0xC0))
#: Expected rows of the sample that orders the rules.
SAMPLE_ROWS = 400
_HAS_LETTER = re.compile(rb"[A-Za-z\x80-\xff]")
_BULLET = re.compile(rb"[ \t]*(?:[*-]|\xe2\x80\xa2)")
_ELLIPSIS = re.compile(rb"(?:\.\.\.|\xe2\x80\xa6)[ \t\r]*\Z")
#: A-Z become a-z, every other ASCII byte that is no letter becomes a space.
_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if 97 <= c <= 122 or c > 127 else 32 for c in range(256))
#: English insults.
INSULTS = frozenset(
    word.encode()
    for word in "asshole assholes bastard bastards bitch bitches clown clowns cunt cunts disgusting dumbass dumbasses fool fools idiot idiotic idiots imbecile imbeciles loser losers moron moronic morons pathetic "
    "retard retarded retards scum scumbag scumbags slut sluts stupid trash vermin whore whores worthless".split()
)


def repeated_words(code: np.ndarray, distinct: int, window: int = 5) -> int:
    """Words covered by windows that occur twice or more in a text, given as the numbers of its words."""
    if len(code) - window + 1 < 2 or distinct == len(code):
        return 0
    # exact names of longer and longer windows: a pair of names is renumbered before it can overflow
    name, size = code, 1
    for step in (1, 2, 4):
        if size + step > window:
            break
        name = np.unique(name[:-step] * (int(name.max()) + 1) + name[step:], return_inverse=True)[1]
        size += step
    while size < window:
        name = np.unique(name[:-1] * distinct + code[size : size + len(name) - 1], return_inverse=True)[1]
        size += 1
    twice = np.bincount(name)[name] > 1
    edge = np.zeros(len(code) + 1, np.int64)
    np.add.at(edge, np.flatnonzero(twice), 1)
    np.add.at(edge, np.flatnonzero(twice) + window, -1)
    return int((np.cumsum(edge[:-1]) > 0).sum())


class Text:
    """A text's figures, each computed when it is first asked for."""

    def __init__(self, body: bytes):
        self.body = body

    @cached_property
    def coded(self) -> tuple[np.ndarray, dict[bytes, int]]:
        """The text's words as numbers, and the number of each distinct word."""
        ids: dict[bytes, int] = {}
        parts = [np.fromiter([ids.setdefault(w, len(ids)) for w in ws], np.int64, len(ws)) for ws in word_lists(self.body)]
        return (parts[0] if len(parts) == 1 else np.concatenate(parts) if parts else np.zeros(0, np.int64)), ids

    @cached_property
    def lines(self) -> list[bytes]:
        return [x for x in self.body.split(b"\n") if x and x.strip()]

    @cached_property
    def n_words(self) -> int:
        return len(self.coded[0])

    @cached_property
    def word_chars(self) -> int:
        return len(self.body.translate(None, _SPACE + _TAIL))

    @cached_property
    def n_symbols(self) -> int:
        return len(self.body) - len(self.body.translate(None, _SYMBOLS))

    @cached_property
    def n_dup_lines(self) -> int:
        return len(self.lines) - len(set(self.lines))

    @cached_property
    def n_repeat_words(self) -> int:
        return repeated_words(self.coded[0], len(self.coded[1]))

    @cached_property
    def n_letter_words(self) -> int:
        code, ids = self.coded
        letters = np.fromiter((_HAS_LETTER.search(w) is not None for w in ids), bool, len(ids))
        return int(np.bincount(code, minlength=len(ids))[letters].sum())


FIGURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def _insulting(x: Text) -> bool:
    n = sum(sum(map(INSULTS.__contains__, ws)) for ws in word_lists(x.body.translate(_FOLD)))
    return n >= 2 and 200 * n >= x.n_words


#: The base rules of the contract, and the others: name -> true if the text is to go.  Limits are whole numbers so that SQL agrees.
BASE: dict[str, Callable[[Text], bool]] = {
    "few_words": lambda x: x.n_words < 10,
    "repeated_windows": lambda x: 100 * x.n_repeat_words > 20 * x.n_words,
}
RULES: dict[str, Callable[[Text], bool]] = {
    "words_too_short_or_long": lambda x: not 2 * x.n_words <= x.word_chars <= 14 * x.n_words,
    "symbols": lambda x: 10 * x.n_symbols > 3 * x.n_words,
    "repeated_lines": lambda x: 2 * x.n_dup_lines > x.body.count(b"\n") + 1,
    "few_letter_words": lambda x: 2 * x.n_letter_words < x.n_words,
    "shouting": lambda x: 10 * x.body.count(b"!!") > 3 * x.n_words,
    "bullets": lambda x: 10 * sum(1 for line in x.lines if _BULLET.match(line)) > 9 * len(x.lines),
    "ellipses": lambda x: 10 * sum(1 for line in x.lines if _ELLIPSIS.search(line)) > 3 * len(x.lines),
    "placeholder": lambda x: b"lorem ipsum" in x.body.lower(),
    "insults": _insulting,
}


def base_failed(x: Text) -> bool:
    return any(rule(x) for rule in BASE.values())


def measure(bodies: list[bytes], rules: dict[str, Callable[[Text], bool]]) -> dict[str, tuple[float, int]]:
    """Seconds and rejections of each rule, each on fresh texts."""
    found = {}
    for name, rule in rules.items():
        began = time.perf_counter()
        rejected = sum(rule(Text(b)) for b in bodies)
        found[name] = (time.perf_counter() - began, rejected)
    return found


def rank(measured: dict[str, tuple[float, int]]) -> list[str]:
    """Rule names by rejections per second, most first; a rule that rejects nothing counts as one hundredth of a rejection."""
    return sorted(measured, key=lambda name: (-(measured[name][1] + 0.01) / (measured[name][0] + 1e-9), name))


def sample(docs: DataFrame, rows: int) -> DataFrame:
    """(body): about ``rows`` texts, chosen by a hash of text and id that is below a share of its range."""
    share = min(1.0, rows / max(docs.count(), 1))
    chosen = F.pmod(F.xxhash64(F.lit("quality"), F.col("doc_id"), F.col("text")), F.lit(1 << 30)) < int(share * (1 << 30))
    return docs.where(chosen).select(F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("body"))


def order(docs: DataFrame, rules: dict[str, Callable[[Text], bool]], rows: int = SAMPLE_ROWS) -> list[str]:
    """Rule names in cascade order; measured in tasks, of which only sums come back."""
    schema = pa.schema([("rule", pa.string()), ("seconds", pa.float64()), ("rejected", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                found = measure(batch.column(0).to_pylist(), rules)
                yield pa.RecordBatch.from_arrays([pa.array(list(found)), pa.array([s for s, _ in found.values()]), pa.array([n for _, n in found.values()])], schema=schema)

    sums = sample(docs, rows).mapInArrow(run, "rule string, seconds double, rejected long").groupBy("rule").agg(F.sum("seconds").alias("s"), F.sum("rejected").alias("n")).collect()
    return rank(dict.fromkeys(rules, (0.0, 0)) | {r.rule: (r.s, r.n) for r in sums})


def first_against(x: Text, turn: list[str], rules: dict[str, Callable[[Text], bool]]) -> str | None:
    """The first rule in turn that rejects the text; the rest isn't asked."""
    return next((name for name in turn if rules[name](x)), None)


def assess(docs: DataFrame, rules: dict[str, Callable[[Text], bool]] = RULES, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """Per row: the base figures, base_failed, kept and the first rule (in cascade order) that rejects it."""
    turn = order(docs, rules, sample_rows)
    schema = pa.schema([("doc_id", pa.int64()), *((n, pa.int64()) for n in FIGURES), ("base_failed", pa.bool_()), ("kept", pa.bool_()), ("rule", pa.string())])

    def rows(x: dict[str, list]) -> dict[str, list]:
        out: dict[str, list] = {n: [] for n in schema.names}
        out["doc_id"] = x["doc_id"]
        for body in x["body"]:
            found = Text(body)
            failed = base_failed(found)
            rule = "base" if failed else first_against(found, turn, rules)
            for n in FIGURES:
                out[n].append(getattr(found, n))
            out["base_failed"].append(failed)
            out["kept"].append(rule is None)
            out["rule"].append(rule)
        return out

    return id_and_bytes(docs).mapInArrow(by_batch(rows, schema), "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, rule string")


def keep_good(docs: DataFrame, rules: dict[str, Callable[[Text], bool]] | None = None, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """The rows of ``docs`` that every rule lets pass, columns as they are; no shuffle.  The base rules are part of the cascade."""
    rules = BASE | RULES if rules is None else rules
    turn = order(docs, rules, sample_rows)
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = [first_against(Text((batch.column(at)[i].as_py() or "").encode()), turn, rules) is None for i in range(batch.num_rows)]
            yield batch.filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assess(table(spark, sf_dir, "documents")).drop("rule")


SQL = r"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda w: w <> '') AS w FROM documents),
l AS (SELECT doc_id, list_filter(string_split(text, chr(10)), lambda x: regexp_replace(x, '[\x20\x09-\x0D]+', '', 'g') <> '') AS l FROM d),
g AS (SELECT doc_id, i, array_to_string(list_slice(w, i, i + 4), ' ') AS s FROM d, unnest(generate_series(1, len(w) - 4)) AS t(i)),
r AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(generate_series(i, i + 4)) AS p FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, s) AS c FROM g) WHERE c > 1) GROUP BY doc_id),
i AS (SELECT doc_id, small, len(list_filter(regexp_split_to_array(small, '[\x00-\x60\x7B-\x7F]+'), lambda x: list_contains([INSULTS], x))) AS n_insults
      FROM (SELECT doc_id, translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS small FROM d)),
f AS (SELECT d.doc_id, text, w, l, small, n_insults, CAST(len(w) AS BIGINT) AS n_words, CAST(length(array_to_string(w, '')) AS BIGINT) AS word_chars,
      CAST(length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines, CAST(coalesce(r.n, 0) AS BIGINT) AS n_repeat_words
      FROM d JOIN l USING (doc_id) JOIN i USING (doc_id) LEFT JOIN r USING (doc_id)),
b AS (SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM f)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND word_chars BETWEEN 2 * n_words AND 14 * n_words AND 10 * n_symbols <= 3 * n_words
       AND 2 * n_dup_lines <= len(string_split(text, chr(10))) AND 2 * len(list_filter(w, lambda x: regexp_matches(x, '[A-Za-z]|[^\x00-\x7F]'))) >= n_words
       AND 10 * ((length(text) - length(replace(text, '!!', ''))) // 2) <= 3 * n_words
       AND 10 * len(list_filter(l, lambda x: regexp_matches(x, '^[ \t]*([*-]|•)'))) <= 9 * len(l) AND 10 * len(list_filter(l, lambda x: regexp_matches(x, '(\.\.\.|…)[ \t\r]*$'))) <= 3 * len(l)
       AND NOT contains(small, 'lorem ipsum') AND NOT (n_insults >= 2 AND 200 * n_insults >= n_words) AS kept
FROM b
""".replace("INSULTS", ", ".join(f"'{x.decode()}'" for x in sorted(INSULTS)))
