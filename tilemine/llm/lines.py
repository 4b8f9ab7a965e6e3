"""Line dedup by winnowing, with DataFrame functions only.

Lines that hold more than white space are hashed.  Each window of ``window`` consecutive lines selects its smallest
hash (the leftmost of equal ones) as fingerprint, so any run of ``window`` lines that occurs twice shares a
fingerprint at the same offset: that is the guarantee of winnowing.  A window also carries the hash of its lines
(a second, independent hash function), which is the context of its fingerprint.

1. Fingerprints whose line is selected at one position alone match nothing and go.
2. Positions of shared fingerprints are joined: each with the smallest document that has the same fingerprint in the
   same context, by a grouped minimum and a join back.  A fingerprint that stands in a third of all rows is so never
   paired with all of its own positions.
3. A match is extended from its position to the left and to the right as far as its windows match.
4. A run is deleted where a smaller doc_id, or the same row further up, holds it.  Runs that overlap or touch are
   deleted whole, so the result is that of comparing all runs of at least ``window`` lines.

Lines count as equal by two independent 64-bit hashes; no text is compared.  With ``long_words`` a run of fewer than
``window`` lines is compared as well if it holds at least so many words, so that a repeated passage of whole lines is found by what
it holds and not only by its number of lines; ``op1_line_dedup``, its SQL and the pipeline do so with ``LONG_WORDS``.

Groups are never gathered: fingerprints and windows are counted with partial aggregates and joined back from written
tables.  Rows of hot ones (a thousandth of all windows or more, so a thousand at most) meet them by broadcast and are not shuffled.  Texts are read twice, once for
their windows and once to delete, and shuffled once, to meet what was found in them.

Edge cases: a null or empty text has no lines; lines of white space alone are never matched and stay; a document
with fewer than ``window`` lines that count loses none unless they hold ``long_words``; rows that repeat a doc_id are none earlier than the
other, and what is found in a row is deleted in it alone (and in rows of the same id and text); null ids sort first;
of repeated runs in one row the first stays (equal hashes: the leftmost); a very long text is one row, whose arrays of line hashes and windows (some 40 bytes
a counted line) must fit a task; an empty table gives an empty result; other columns are
kept by ``deduplicate``, whatever their names, and ignored by ``report``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from tilemine.llm.common import back_to_id, hot_join, id_key, park, park_only, settled, table

WINDOW = 3
#: The fewest words that make a shorter run worth comparing: documents with fewer go by the quality rules anyway.
LONG_WORDS = 10
#: Seeds the second hash of a line.
_CONTEXT = 7


def _lines(text: str = "text") -> Column:
    return F.split(F.coalesce(F.col(text), F.lit("")), "\n", -1)


def _counted(lines: Column) -> Column:
    """Places of the lines that hold more than white space."""
    return F.filter(F.sequence(F.lit(0), F.size(lines) - 1), lambda i: F.get(lines, i).rlike(r"[^\x20\x09-\x0D]"))


def _text_key(text: str = "text") -> Column:
    """What tells rows of one id apart."""
    return F.xxhash64(F.col(text))


def windows(docs: DataFrame, window: int = WINDOW, long_words: int | None = None) -> DataFrame:
    """(k, t, start, n, fp, at, key, again) per window: its row's id and text key, its start among the counted lines, its
    lines, its fingerprint with its position, the hash of its lines and whether an earlier window of the row has the same lines."""
    base = docs.select(id_key().alias("k"), _text_key().alias("t"), _lines().alias("lines"))
    counted = F.filter("lines", lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    least = window if long_words is None else 1
    names = ["k", "t", "h", "g"] if long_words is None else ["k", "t", "h", "g", "words"]
    words = F.transform(counted, lambda x: F.regexp_count(x, F.lit(r"[^\x20\x09-\x0D]+")))
    base = base.select("k", "t", F.transform(counted, lambda x: F.xxhash64(x)).alias("h"), F.transform(counted, lambda x: F.xxhash64(F.lit(_CONTEXT), x)).alias("g"), words.alias("words")).select(*names).where(F.size("h") >= least)

    def cuts(n: int) -> Column:
        return F.transform(F.sequence(F.lit(0), F.size("h") - n), lambda s: F.struct(s.alias("start"), F.lit(n).alias("n"), F.slice("h", s + 1, n).alias("part"), F.slice("g", s + 1, n).alias("context")))

    def shorter(n: int) -> Column:
        held = F.filter(cuts(n), lambda x: F.aggregate(F.slice("words", x["start"] + 1, n), F.lit(0), lambda a, b: a + b) >= long_words)
        return F.when(F.size("h") >= n, held).otherwise(F.slice(cuts(1), 1, 0))

    if long_words is None:
        cut = cuts(window)
    else:
        cut = F.concat(*[shorter(n) for n in range(1, window)], F.when(F.size("h") >= window, cuts(window)).otherwise(F.slice(cuts(1), 1, 0)))
    base = base.select("k", "t", cut.alias("cut"))
    named = F.transform("cut", lambda x: F.struct(F.xxhash64(x["context"]).alias("key"), F.array_min(x["part"]).alias("fp"), x["start"].alias("start"), x["n"].alias("n"), (x["start"] + F.array_position(x["part"], F.array_min(x["part"])) - 1).alias("at")))
    base = base.select("k", "t", F.array_sort(named).alias("w"))
    rows = base.select("k", "t", F.explode(F.transform("w", lambda x, i: F.struct(x["start"].alias("start"), x["n"].alias("n"), x["fp"].alias("fp"), x["at"].alias("at"), x["key"].alias("key"), ((i > 0) & (F.get("w", i - 1)["key"] == x["key"]) & (F.get("w", i - 1)["fp"] == x["fp"])).alias("again")))).alias("x"))
    return rows.select("k", "t", "x.*")


def repeated(docs: DataFrame, window: int = WINDOW, long_words: int | None = None) -> DataFrame:
    """(k, t, runs): per id and text the matched runs that occur earlier, each as its first counted line and the one behind its last."""
    found = park(windows(docs, window, long_words), "line-windows")
    # a position is selected by neighbouring windows; its first one counts it
    shared = found.groupBy("fp").agg(F.min("at").alias("a"), F.max("at").alias("b"), F.min("k").alias("c"), F.max("k").alias("d"), F.min("t").alias("e"), F.max("t").alias("f"), F.count(F.lit(1)).alias("n")).where("a <> b OR c <> d OR e <> f").select("fp", "n")
    shared, total = park(shared, "line-fingerprints"), found.count()
    near = park(hot_join(found.withColumnRenamed("n", "lines"), shared, ["fp"], total), "line-positions")
    earliest = near.groupBy("fp", "key").agg(F.min("k").alias("first"), F.max("k").alias("last"), F.count(F.lit(1)).alias("n")).where("first <> last").select("fp", "key", "first", "n")
    earliest = park(earliest, "line-earliest")
    across = hot_join(near.where("NOT again"), earliest, ["fp", "key"], total).where("k > first").withColumnRenamed("lines", "n")
    near = near.withColumnRenamed("lines", "n")
    names = ["k", "t", "at", "start", "n"]
    matched = across.select(*names).unionByName(near.where("again").select(*names)).repartition("k", "t")
    # all windows of a position hold it, so their union has no gap: the match reaches from the first start to the last end
    reach = matched.groupBy("k", "t", "at").agg(F.min("start").alias("from"), F.max(F.col("start") + F.col("n")).alias("to"))
    return reach.groupBy("k", "t").agg(F.collect_list(F.struct("from", "to")).alias("runs"))


def _marked(docs: DataFrame, window: int, long_words: int | None) -> DataFrame:
    """(row, k, text, lines, gone, places): each input row as one struct, its lines, the places of those to delete (null if
    there are none) and of those that stay."""
    found = park_only(docs.sparkSession, lambda: repeated(docs, window, long_words), "line-runs")
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    rows = rows.select("row", id_key("row.doc_id").alias("k"), F.col("row.text").alias("text"), _text_key("row.text").alias("t"))
    both = rows.join(found, ["k", "t"], "left").withColumn("lines", _lines())
    counted = F.when(F.col("runs").isNotNull(), _counted(F.col("lines")))
    within = F.array_distinct(F.flatten(F.transform("runs", lambda x: F.sequence(x["from"], x["to"] - 1))))
    both = settled(both.withColumn("counted", counted).withColumn("within", within))
    both = settled(both.withColumn("gone", F.when(F.col("runs").isNotNull(), F.transform("within", lambda i: F.get("counted", i)))))
    every = F.sequence(F.lit(0), F.size("lines") - 1)
    return settled(both.select("row", "k", "text", "lines", "gone", F.when(F.col("gone").isNull(), every).otherwise(F.array_except(every, "gone")).alias("places")))


def _kept_text() -> Column:
    return F.array_join(F.transform("places", lambda i: F.get("lines", i)), "\n")


def deduplicate(docs: DataFrame, window: int = WINDOW, long_words: int | None = None) -> DataFrame:
    """The rows with repeated lines deleted from ``text``; a row that loses its last counted line goes.  Rows without
    repeated lines stay as they are; ``n_chars``, if there, follows the text."""
    both = _marked(docs, window, long_words)
    clean = F.col("gone").isNull()
    both = settled(both.select("row", "gone", F.when(clean, F.col("text")).otherwise(_kept_text()).alias("left"))).where(clean | F.col("left").rlike(r"[^\x20\x09-\x0D]"))
    n = F.when(clean, F.col("row.n_chars")).otherwise(F.char_length("left").cast("long")) if "n_chars" in docs.columns else None
    return both.select(*[F.col("left").alias(c) if c == "text" else n.alias(c) if c == "n_chars" else F.col(f"row.`{c}`").alias(c) for c in docs.columns])


def report(docs: DataFrame, window: int = WINDOW, long_words: int | None = None) -> DataFrame:
    """Per row: lines, deleted lines and the SHA-256 of the remaining lines joined by line ends."""
    both = _marked(docs.select("doc_id", "text"), window, long_words)
    n = F.when(F.coalesce(F.length("text"), F.lit(0)) == 0, F.lit(0)).otherwise(F.size("lines")).cast("long")
    whole = F.when(F.col("gone").isNull(), F.coalesce("text", F.lit(""))).otherwise(_kept_text())
    return both.select(back_to_id("k").alias("doc_id"), n.alias("n_lines"), F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("n_removed"), F.sha2(whole, 256).alias("kept_sha256"))


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Runs of three lines, and shorter ones of LONG_WORDS words or more."""
    return report(table(spark, sf_dir, "documents"), long_words=LONG_WORDS)


def removed_sql(source: str, window: int = WINDOW, long_words: int = LONG_WORDS) -> str:
    """DuckDB: common table expressions up to gone(doc_id, p), the deleted lines (from 1), by comparing all runs of ``window`` lines and all shorter ones of enough words."""
    return rf"""
l AS (SELECT doc_id, coalesce(text, '') AS text, string_split(coalesce(text, ''), chr(10)) AS l FROM {source}),
c AS (SELECT doc_id, l, list_filter(generate_series(1, len(l)), lambda i: regexp_matches(l[i], '[^\x20\x09-\x0D]')) AS c FROM l),
a AS (SELECT doc_id, i, n, c, list_transform(generate_series(i, i + n - 1), lambda j: l[c[j]]) AS x FROM c, unnest(generate_series(1, len(c))) AS g(i), generate_series(1, {window}) AS h(n) WHERE i + n - 1 <= len(c)),
w AS (SELECT doc_id, i, n, c, to_json(x) AS s FROM a WHERE n = {window} OR len(list_filter(regexp_split_to_array(array_to_string(x, chr(10)), '[\x20\x09-\x0D]+'), lambda y: y <> '')) >= {long_words}),
f AS (SELECT doc_id, i, n, c, row_number() OVER (PARTITION BY s ORDER BY doc_id, i) AS m FROM w),
gone AS (SELECT DISTINCT doc_id, unnest(list_transform(generate_series(i, i + n - 1), lambda j: c[j])) AS p FROM f WHERE m > 1)"""


SQL = f"""
WITH {removed_sql("documents")},
g AS (SELECT doc_id, list(p) AS a FROM gone GROUP BY doc_id)
SELECT l.doc_id, CAST(CASE WHEN text = '' THEN 0 ELSE len(l) END AS BIGINT) AS n_lines, CAST(coalesce(len(a), 0) AS BIGINT) AS n_removed,
       sha256(array_to_string(list_transform(list_filter(generate_series(1, len(l)), lambda i: NOT coalesce(list_contains(a, i), false)), lambda i: l[i]), chr(10))) AS kept_sha256
FROM l LEFT JOIN g USING (doc_id)
"""
