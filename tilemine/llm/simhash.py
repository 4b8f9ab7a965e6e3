"""SimHash near-duplicates with a hierarchical index in Gray order.

1. Fingerprints: one pass, no shuffle.  Equal fingerprints become one node.
2. Upper nodes: the 64 bits are cut into blocks, more than ``radius`` of them.  Two fingerprints that differ in ``radius`` bits agree in all
   but ``radius`` blocks at least, so for each choice of that many blocks the codes are put in an order in which those blocks lead: codes that
   agree in them lie together and are one upper node, whose mask is the blocks and whose pattern is their bits.  A query enters the one
   upper node of each order that it differs from in no masked bit; all others are pruned as whole groups.  The number of
   blocks is chosen by the number of fingerprints (``block_count``): 4 orders of 16-bit nodes, 10 of 25-bit ones for tens of
   millions, 20 of 32-bit ones for billions.  The result is the same for each.  Upper nodes of more than ``most`` fingerprints are cut into
   chunks, and the pairs of chunks become groups, so no link is lost.
3. Lower nodes: each task sorts the fingerprints of its groups by Gray rank, so that neighbours share long
   bit patterns.  Runs of neighbours become nodes, runs of nodes become the nodes above; a node holds
   the bits that all below it share (mask and pattern, without those its parent holds).  A query
   walks down, adds up the differing masked bits and leaves a whole group out at ``radius + 1``.
4. Links found in a task are reduced to a spanning forest there, so that a group of g copies gives
   g - 1 links and never all pairs; connected components are found by alternating star joins.

Ranges of the Gray order alone, without step 2, would have to take copies of a fingerprint into 16, 52 and 128 ranges of 4,096 among 2^16,
2^18 and 2^20 random fingerprints (counted by the index's own pruning; it grows with the cube of the logarithm), against 4 here.

Edge cases: a null or wordless text has fingerprint zero, which links like any other; repeated rows
give repeated result rows; rows that repeat an id share its smallest component; null ids sort first; a very long text is hashed in
stretches of a million bytes; equal distances need no order, as every link counts; an empty table gives an empty result; other
columns are ignored.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, functions as F

from tilemine.llm.common import NULL_ID, back_to_id, by_batch, id_and_bytes, park, remove, table, word_lists

_WEIGHT = np.uint64(1) << np.arange(64, dtype=np.uint64)


def fingerprint(body: bytes, shingle: int = 3, seed: int = 42) -> int:
    """The 64-bit SimHash of the lower-cased words' shingles, repeats included."""
    digest, counts, total, held = xxhash.xxh64_intdigest, np.zeros(64, np.int64), 0, []
    for some in word_lists(body.lower()):
        ws = held + some
        n = len(ws) - shingle + 1
        if n > 0:
            joined = b" ".join(ws)
            stop = np.cumsum(np.fromiter(map(len, ws), np.int64, len(ws)) + 1) - 1
            start = np.concatenate(([0], stop[:-1] + 1))
            for at in range(0, n, 65536):
                a, b = start[at : min(at + 65536, n)].tolist(), stop[at + shingle - 1 : min(at + 65536, n) + shingle - 1].tolist()
                h = np.array([digest(joined[i:j], seed) for i, j in zip(a, b)], np.uint64)
                counts += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
            total += n
        held = ws[max(0, len(ws) - shingle + 1) :]  # the next stretch's first shingles begin here
    if not total:
        return digest(b" ".join(held), seed) if held else 0
    return int(_WEIGHT[2 * counts > total].sum(dtype=np.uint64))


def fingerprints(docs: DataFrame, shingle: int = 3) -> DataFrame:
    """(doc_id, fp) per row; fp is the fingerprint's bits as a signed long, a null id the smallest long."""
    schema = pa.schema([("doc_id", pa.int64()), ("fp", pa.int64())])

    def rows(x: dict[str, list]) -> dict[str, list]:
        fps = np.array([fingerprint(b, shingle) for b in x["body"]], np.uint64).view(np.int64)
        return {"doc_id": [NULL_ID if i is None else i for i in x["doc_id"]], "fp": fps.tolist()}

    return id_and_bytes(docs).mapInArrow(by_batch(rows, schema), "doc_id long, fp long")


def gray_rank(codes: np.ndarray) -> np.ndarray:
    """Place of each code word in the reflected Gray sequence."""
    rank = codes.copy()
    for shift in (1, 2, 4, 8, 16, 32):
        rank ^= rank >> np.uint64(shift)
    return rank


class GrayIndex:
    """Levels of nodes over code words sorted by (group, Gray rank); ``fan`` children to a node."""

    def __init__(self, codes: np.ndarray, group: np.ndarray, fan: int = 8):
        order = np.lexsort((gray_rank(codes), group))
        self.order, self.codes, self.fan = order, codes[order], fan
        self.levels: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []
        first = np.flatnonzero(np.concatenate(([True], group[order][1:] != group[order][:-1])))
        self.roots, sizes = first, np.diff(np.concatenate((first, [len(codes)])))
        mask, pattern = np.full(len(codes), ~np.uint64(0)), self.codes
        counts = sizes
        while True:  # a node's children are consecutive and of one group
            parents = -(-counts // fan)
            group_of = np.repeat(np.arange(len(counts)), parents)
            nth = np.arange(parents.sum()) - np.repeat(np.cumsum(parents) - parents, parents)
            begin = np.repeat(np.cumsum(counts) - counts, parents) + nth * fan
            end = np.minimum(begin + fan, np.cumsum(counts)[group_of])
            all_and = np.bitwise_and.reduceat(pattern, begin)
            all_or = np.bitwise_or.reduceat(pattern, begin)
            shared = np.bitwise_and.reduceat(mask, begin) & ~(all_and ^ all_or)
            self.levels.append((mask & ~np.repeat(shared, end - begin), pattern, begin, end))
            mask, pattern, counts = shared, all_and & shared, parents
            if counts.max(initial=1) == 1:
                break
        self.top = (mask, pattern)

    def near(self, radius: int, chunk: int = 1 << 20) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Pairs (i, j), i < j in index order, of one group within ``radius``.  Queries go in blocks of bounded work."""
        root_of = np.repeat(np.arange(len(self.roots)), np.diff(np.concatenate((self.roots, [len(self.codes)]))))
        stack = [(len(self.levels), np.arange(a, min(a + chunk, len(self.codes))), root_of[a : a + chunk], None) for a in range(0, len(self.codes), chunk)]
        while stack:
            level, query, node, spent = stack.pop()
            if spent is None:
                mask, pattern = self.top
                spent = np.bitwise_count((self.codes[query] ^ pattern[node]) & mask[node]).astype(np.int16)
                alive = spent <= radius
                query, node, spent = query[alive], node[alive], spent[alive]
            if not level:
                yes = node > query
                yield query[yes], node[yes]
                continue
            mask, pattern, begin, end = self.levels[level - 1]
            width = end[node] - begin[node]
            if width.sum() > 4 * chunk and len(query) > 1:
                half = len(query) // 2
                stack += [(level, query[:half], node[:half], spent[:half]), (level, query[half:], node[half:], spent[half:])]
                continue
            child = np.repeat(begin[node], width) + np.arange(width.sum()) - np.repeat(np.cumsum(width) - width, width)
            query, spent = np.repeat(query, width), np.repeat(spent, width)
            spent = spent + np.bitwise_count((self.codes[query] ^ pattern[child]) & mask[child]).astype(np.int16)
            alive = spent <= radius
            stack.append((level - 1, query[alive], child[alive], spent[alive]))


def forest(n: int, pairs: Iterator[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """The smallest member of each of n nodes' components."""
    root = np.arange(n)
    for a, b in pairs:
        while len(a):
            ra, rb = root[a], root[b]
            open_ = ra != rb
            a, b, ra, rb = a[open_], b[open_], ra[open_], rb[open_]
            np.minimum.at(root, np.maximum(ra, rb), np.minimum(ra, rb))
            while (root != root[root]).any():
                root = root[root]
    return root


def block_count(n: int, radius: int, dear: float = 100.0) -> int:
    """The number of blocks with the least work a fingerprint: copies for its orders, and ``dear`` comparisons inside a group count as a copy."""
    work = {b: math.comb(b, radius) * (1 + n / 2.0 ** (64 * (b - radius) / b) / dear) for b in range(radius + 1, radius + 5)}
    return min(work, key=work.get)


def masks(blocks: int, radius: int) -> list[int]:
    """The leading bits of each order: every choice of ``blocks - radius`` of the blocks, as signed numbers."""
    edges = [round(64 * i / blocks) for i in range(blocks + 1)]
    bits = [(1 << b) - (1 << a) for a, b in zip(edges, edges[1:])]
    chosen = [sum(c) for c in itertools.combinations(bits, blocks - radius)]
    return [m - (m >> 63 << 64) for m in chosen]


def links(nodes: DataFrame, radius: int = 3, most: int = 4000, task_rows: int = 250_000, blocks: int | None = None) -> DataFrame:
    """(u, v) links of distinct fingerprints (column fp) that connect all within ``radius`` bits, not all pairs."""
    blocks = blocks or block_count(nodes.count(), radius)
    keys = F.array(*[F.struct(F.lit(i).alias("block"), F.col("fp").bitwiseAND(F.lit(m)).alias("value")) for i, m in enumerate(masks(blocks, radius))])
    routed = nodes.select("fp", F.explode(keys).alias("k")).select("fp", "k.block", "k.value")
    sizes = routed.groupBy("block", "value").count().where(F.col("count") > 1)
    sizes = park(sizes, "simhash-groups")
    placed = routed.join(sizes, ["block", "value"])
    cuts = F.ceil(F.col("count") / (most / 2)).cast("int")
    mine = F.pmod(F.xxhash64("fp"), cuts).cast("int")
    whole = placed.where(F.col("count") <= most).withColumn("part", F.lit(0))
    cut = placed.where(F.col("count") > most).withColumn("cuts", cuts).withColumn("mine", mine)
    other = F.explode(F.sequence(F.lit(0), F.col("cuts") - 1)).alias("other")
    cut = cut.select("fp", "block", "value", "count", "cuts", "mine", other).withColumn("part", F.least("mine", "other") * F.col("cuts") + F.greatest("mine", "other"))
    rows = whole.select("fp", "block", "value", "part").unionByName(cut.select("fp", "block", "value", "part"))
    tasks = sizes.agg(F.sum(F.when(F.col("count") <= most, F.col("count")).otherwise(F.col("count") * F.ceil(F.col("count") / (most / 2))))).first()[0] or 0
    tasks = max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), tasks // task_rows + 1)
    dealt = rows.repartition(tasks, "block", "value", "part").sortWithinPartitions("block", "value", "part")
    schema = pa.schema([("u", pa.int64()), ("v", pa.int64())])

    def solve(held: list[pa.RecordBatch]) -> pa.RecordBatch | None:
        t = pa.Table.from_batches(held)
        fp = t["fp"].to_numpy().view(np.uint64)
        key = [t[c].to_numpy() for c in ("block", "value", "part")]
        new = np.zeros(len(fp), bool)
        for k in key:
            new[1:] |= k[1:] != k[:-1]
        index = GrayIndex(fp, np.cumsum(new))
        root = forest(len(fp), index.near(radius))
        own = np.flatnonzero(root != np.arange(len(fp)))
        codes = index.codes.view(np.int64)
        return pa.RecordBatch.from_arrays([pa.array(codes[own]), pa.array(codes[root[own]])], schema=schema) if len(own) else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Whole groups are gathered until there are enough rows, then solved; a group is at most ``most`` rows, or 2 chunks."""
        held: list[pa.RecordBatch] = []
        for batch in batches:
            if sum(b.num_rows for b in held) >= 100_000 and batch.num_rows:
                # close before the group that the last held row belongs to, which may go on here
                t = pa.Table.from_batches(held).combine_chunks().to_batches()[0]
                key = [t.column(t.schema.get_field_index(c)).to_numpy() for c in ("block", "value", "part")]
                same = np.logical_and.reduce([k == k[-1] for k in key])
                cut_at = int(np.argmax(same))
                if cut_at:
                    if (out := solve([t.slice(0, cut_at)])) is not None:
                        yield out
                    held = [t.slice(cut_at)]
            held.append(batch)
        if held and sum(b.num_rows for b in held) and (out := solve(held)) is not None:
            yield out

    return dealt.mapInArrow(run, "u long, v long")


def components(edges: DataFrame) -> DataFrame:
    """(node, root): the smallest node reachable, for every node with an edge.  Alternates the large-star and
    small-star operations until every edge points at its root; the edges live in written tables."""
    edges = park(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "stars")
    while True:  # each round shortens every path to its root, so a component of n nodes takes some log n rounds
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = park(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")), "stars-least")
        large = park(both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct(), "stars-large")
        least2 = park(large.groupBy("u").agg(F.min("v").alias("m")), "stars-least")
        small = large.join(least2, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").unionByName(least2.select("u", F.col("m").alias("v"))).distinct()
        small = park(small, "stars")
        # at rest: no node is both a child and a root, and no child has two roots
        roots, children = small.select(F.col("v").alias("u")).distinct(), small.groupBy("u").count()
        settled = children.where("count > 1").isEmpty() and children.join(roots, "u", "left_semi").isEmpty()
        for used in (edges, least, large, least2):
            remove(used)
        edges = small
        if settled:
            return edges.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())


def near_duplicates(docs: DataFrame, radius: int = 3, shingle: int = 3, most: int = 4000) -> DataFrame:
    """(doc_id, fingerprint, component_id) per row of ``docs``; component_id is the smallest id reachable by links."""
    fps = park(fingerprints(docs, shingle), "simhash")
    nodes = park(fps.groupBy("fp").agg(F.min("doc_id").alias("least")), "simhash-nodes")
    rooted = park(components(links(nodes.select("fp"), radius, most)), "simhash-roots")
    own = nodes.join(rooted, nodes.fp == rooted.node, "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    own = park(own, "simhash-own")
    merged = park(own.groupBy("root").agg(F.min("least").alias("component_id")), "simhash-least")
    known = park(own.join(merged, "root").select("fp", "component_id"), "simhash-known")
    hexed = F.lower(F.lpad(F.hex("fp"), 16, "0"))
    return fps.join(known, "fp").select(back_to_id().alias("doc_id"), hexed.alias("fingerprint"), back_to_id("component_id").alias("component_id"))


def keep_one(docs: DataFrame, radius: int = 3, shingle: int = 3) -> DataFrame:
    """The rows of ``docs`` whose id is the smallest of its component.  Rows that repeat an id all go or stay."""
    if not docs.columns:
        return docs
    found = near_duplicates(docs, radius, shingle)
    first = park(found.where(F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias("kept_id")).distinct(), "simhash-kept")
    # a merge join at every size: whether the ids would fit a broadcast depends on the corpus
    return docs.join(first.hint("merge"), docs["doc_id"].eqNullSafe(first["kept_id"]), "left_semi")


def op3_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
