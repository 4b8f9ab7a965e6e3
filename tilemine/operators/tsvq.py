"""Growing a binary tree of two-way splits: the index.

The rows stay where they are; a row's node is its ``code``, a string of child bits.  Each pass handles all
open nodes of the schedule's front: sums under the splits sent to the tasks come back merged, new
bisectors go out.  Schedules: ``level`` (the whole front), ``leaf`` (one node at a time), ``greedy`` (the
leaf whose split lowers the cost most, up to ``max_leaves``), ``hybrid`` (levels until a node has at
most ``local_rows`` rows, then one shuffle by code and the rest of its subtree in one task).
"""

from __future__ import annotations

import heapq
import json
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession, functions as F, types as T

from tilemine.operators import seeds
from tilemine.operators.passes import Split, Under, assign, by_code, nearest, relabel, sums, vectors
from tilemine.sources.storage import park, write

NODE_SCHEMA = "code string, depth int, n long, ssum array<double>, sq double, centroid array<double>, wcss double, is_leaf boolean, close_reason string, split_w array<double>, split_b double"


@dataclass(frozen=True)
class Stop:
    """Any of these closes a node; none at all leaves equal rows as the only stop."""

    n_min: int | None = None
    wcss_min: float | None = None
    h_max: int | None = None
    min_child: int | None = None

    def reason(self, depth: int, n: int, wcss: float) -> str | None:
        if self.n_min is not None and n <= self.n_min:
            return "n_min"
        if self.wcss_min is not None and wcss < self.wcss_min:
            return "wcss_min"
        if self.h_max is not None and depth >= self.h_max:
            return "h_max"
        return None


@dataclass
class Node:
    code: str
    n: int
    s: np.ndarray
    sq: float
    ss: np.ndarray
    closed: str | None = None
    split: Split | None = None
    turns: int = 0  # passes until its split settled

    @property
    def centroid(self) -> np.ndarray:
        return self.s / max(self.n, 1)

    @property
    def wcss(self) -> float:
        return max(0.0, float(self.sq - self.s @ self.s / max(self.n, 1)))


@dataclass
class Index:
    """nodes by code (on the driver: a node has d numbers; deep trees are written by ``save``), labelled rows, settings."""

    nodes: dict[str, Node]
    labelled: DataFrame
    manifest: dict = field(default_factory=dict)

    @property
    def leaves(self) -> list[Node]:
        return [n for n in self.nodes.values() if n.split is None]

    def table(self, spark: SparkSession) -> DataFrame:
        rows = [(n.code, len(n.code), n.n, n.s.tolist(), n.sq, n.centroid.tolist(), n.wcss, n.split is None, n.closed, None if n.split is None else n.split[0].tolist(), None if n.split is None else n.split[1]) for n in sorted(self.nodes.values(), key=lambda n: n.code)]
        return spark.createDataFrame(rows, NODE_SCHEMA)


def prepare(df: DataFrame) -> DataFrame:
    """(id, code, v, ..): descriptors as doubles, all in the root."""
    rest = [c for c in df.columns if c not in ("id", "v", "code")]
    return df.select(F.col("id").cast("long").alias("id"), F.lit("").alias("code"), F.transform("v", lambda x: x.cast("double")).alias("v"), *rest)


def _node(code: str, part: dict) -> Node:
    return Node(code, part["n"], part["s"], part["sq"], part["ss"])


def _split_nodes(labelled: Under, nodes: list[Node], init: str, tol: float, max_iter: int, seed: int, combine: bool, log: list) -> dict[str, tuple[Split, list[dict], int]]:
    """Two-means of every node of ``nodes`` at once; nodes that settle leave the job."""
    stats = {n.code: {"n": n.n, "s": n.s, "ss": n.ss} for n in nodes}
    open_ = seeds.first_splits(labelled, stats, init, seed)
    done: dict[str, tuple[Split, list[dict], int]] = {}
    before: dict[str, list[np.ndarray]] = {}
    reseeded: set[str] = set()
    for turn in range(max_iter + 2):
        if not open_:
            break
        parts = sums(labelled.only(list(open_)) if len(open_) <= 64 else labelled, open_, combine)
        log.append({"nodes": len(open_), "rows": sum(stats[c]["n"] for c in open_)})
        empty = {c for c in open_ if seeds.centroids_of(parts, c) is None}
        again = seeds.farthest_split(labelled, {c: stats[c]["s"] / stats[c]["n"] for c in empty - reseeded})
        reseeded |= empty
        new: dict[str, Split] = dict(again)
        for code, split in open_.items():
            if code in empty:
                continue
            now = seeds.centroids_of(parts, code)
            move = max(np.abs(a - b).max() for a, b in zip(now, before[code])) if code in before else np.inf
            last = turn > max_iter or code in before and move <= tol
            before[code] = now
            if last:
                done[code] = (split, [parts[code, 0], parts[code, 1]], turn + 1)
            else:
                new[code] = seeds.bisector(*now)
        open_ = new
    return done


#: Element types of descriptors that are kept as they are; kernels turn them into doubles.
_NUMBERS = {f"array<{t}>" for t in ("tinyint", "smallint", "int", "bigint", "float", "double")}
#: Levels after which written codes are renewed, in memory mode.
REFRESH = 6


def _compact(df: DataFrame) -> DataFrame:
    """As prepare, but numbers stay as narrow as they are."""
    return prepare(df) if dict(df.dtypes)["v"] not in _NUMBERS else df.select(F.col("id").cast("long").alias("id"), F.lit("").alias("code"), "v", *[c for c in df.columns if c not in ("id", "v", "code")])


class Held:
    """The rows of a growing tree.  ``memory``: one cached copy as narrow as the input (none if the caller has cached it), codes followed down the
    splits found since, renewed every REFRESH levels; ``dfs``: written and read again at every level; ``none``: read from the source each time."""

    def __init__(self, df: DataFrame, materialise: str, written: bool = False):
        self.how, self.mine = materialise, False
        level = df.storageLevel
        rows = df if written else _compact(df)
        if materialise == "dfs":
            rows = park(prepare(df) if not written else df, "labelled")
        elif materialise == "memory" and not (level.useMemory or level.useDisk):
            rows, self.mine = rows.persist(StorageLevel.MEMORY_AND_DISK), True
        self.under, self.levels = Under(rows), 0

    def _renew(self) -> None:
        """Write the codes out; the copy before goes when the new one is there."""
        old, rows = self.under.rows, relabel(self.under).persist(StorageLevel.MEMORY_AND_DISK)
        rows.count()
        if self.mine:
            old.unpersist()
        self.under, self.mine, self.levels = Under(rows), True, 0

    def add(self, splits: dict[str, Split]) -> None:
        if self.how == "dfs":
            self.under = Under(park(relabel(self.under, splits), "labelled"))
            return
        self.under = Under(self.under.rows, self.under.splits | splits)
        self.levels += 1
        if self.how == "memory" and self.levels >= REFRESH:
            self._renew()

    def finish(self) -> DataFrame:
        """(id, code, v, ..) with codes written out and v as doubles; kept in memory in memory mode."""
        if self.how == "memory":
            self._renew()
            return self.under.rows
        return relabel(self.under)


def grow(df: DataFrame, stop: Stop, init: str = "axis", tol: float = 1e-6, max_iter: int = 20, schedule: str = "level", local_rows: int = 100_000, seed: int = 0, combine: bool = True, materialise: str = "memory", max_leaves: int | None = None, order: str = "fifo", most_open: int = 1024, start: dict[str, Node] | None = None) -> Index:
    """Grow the tree over (id, v, ..).  ``max_iter`` counts centroid updates of a split.  ``most_open`` bounds the nodes of one pass, and so
    what is sent to tasks and collected: nodes x 2 x d numbers.  ``start``: nodes to go on from; ``df`` then has their codes."""
    held = Held(df, materialise, written=start is not None)
    log: list[dict] = []
    if start is None:
        found = sums(held.under)
        if not found:
            return Index({}, held.finish(), {"stop": vars(stop), "passes": log})
        nodes = {"": _node("", found["", 0])}
    else:
        nodes = dict(start)
    pending: dict[str, tuple[Split, list[dict], int]] = {}
    rows: DataFrame | None = None

    def front() -> list[Node]:
        out = []
        for n in nodes.values():
            if n.split is None and n.closed is None:
                n.closed = stop.reason(len(n.code), n.n, n.wcss)
                if n.closed is None:
                    out.append(n)
        return out

    while True:
        open_ = front()
        if schedule == "hybrid" and open_:
            small = [n for n in open_ if n.n <= local_rows]
            if len(small) == len(open_):
                rows = _finish_locally(held.finish(), nodes, small, stop, init, tol, max_iter, seed)
                break
            open_ = [n for n in open_ if n.n > local_rows]
        if not open_:
            break
        if schedule == "leaf":
            open_ = [open_[0] if order == "fifo" else open_[-1]]
        if schedule == "greedy":
            if max_leaves is not None and sum(n.split is None for n in nodes.values()) >= max_leaves:
                for n in open_:
                    n.closed = "max_leaves"
                break
            todo = [n for n in open_ if n.code not in pending]
            pending |= _split_nodes(held.under, todo, init, tol, max_iter, seed, combine, log) if todo else {}
            for n in todo:
                if n.code not in pending:
                    n.closed = "degenerate"
            able = [n for n in open_ if n.code in pending]
            if not able:
                continue
            best = max(able, key=lambda n: (n.wcss - sum(_node("", p).wcss for p in pending[n.code][1]), [-ord(c) for c in n.code]))
            done, open_ = {best.code: pending.pop(best.code)}, [best]
        else:
            open_ = open_[:most_open]
            done = _split_nodes(held.under, open_, init, tol, max_iter, seed, combine, log)
        splits = {}
        for n in open_:
            if n.code not in done or stop.min_child and min(p["n"] for p in done[n.code][1]) < stop.min_child:
                n.closed = "degenerate" if n.code not in done else "min_child"
                continue
            n.split, parts, n.turns = done[n.code]
            splits[n.code] = n.split
            for bit, part in enumerate(parts):
                nodes[f"{n.code}{bit}"] = _node(f"{n.code}{bit}", part)
        if splits:
            held.add(splits)
    return Index(nodes, held.finish() if rows is None else rows, {"stop": vars(stop), "init": init, "seed": seed, "schedule": schedule, "passes": log})


def grow_local(ids: np.ndarray, x: np.ndarray, code: str, stop: Stop, init: str, tol: float, max_iter: int, seed: int) -> tuple[list[Node], np.ndarray]:
    """The subtree below ``code`` over a matrix: the same rules as the distributed passes."""
    codes = np.full(len(x), code, object)
    out: list[Node] = []
    todo = [(code, np.arange(len(x)))]
    while todo:
        name, at = todo.pop()
        own = x[at]
        node = Node(name, len(at), own.sum(0), float((own * own).sum()), (own * own).sum(0))
        out.append(node)
        node.closed = stop.reason(len(name), node.n, node.wcss)
        if node.closed:
            continue
        split = _local_first(ids[at], own, name, node, init, seed)
        before, final, reseeded = None, None, False
        for turn in range(max_iter + 2):
            if split is None:
                break
            child = assign(own, split)
            if child.all() or not child.any():
                d = ((own - node.centroid) ** 2).sum(1)
                split = None if reseeded or not d.max() > 0 else seeds.bisector(node.centroid, own[np.lexsort((ids[at], -d))[0]])
                reseeded = True
                continue
            ones = child.astype(float)
            now = [side @ own / side.sum() for side in (1 - ones, ones)]  # products, as picking each side's rows copies them
            move = max(np.abs(a - b).max() for a, b in zip(now, before)) if before else np.inf
            if turn > max_iter or before and move <= tol:
                final, node.turns = (split, child), turn + 1
                break
            before, split = now, seeds.bisector(*now)
        if final is None:
            node.closed = "degenerate"
            continue
        child = final[1]
        if stop.min_child and min((child == 0).sum(), (child == 1).sum()) < stop.min_child:
            node.closed = "min_child"
            continue
        node.split = final[0]
        for bit in (1, 0):
            part = at[child == bit]
            codes[part] = f"{name}{bit}"
            todo.append((f"{name}{bit}", part))
    return out, codes


def _local_first(ids: np.ndarray, x: np.ndarray, code: str, node: Node, init: str, seed: int) -> Split | None:
    if (node.n * node.ss - node.s**2).max(initial=0) <= 1e-9 * max(1.0, node.ss.max(initial=0)):
        return None
    if init == "axis":
        return seeds.axis_split(node.n, node.s, node.ss)

    def pick(score: np.ndarray) -> np.ndarray:
        return x[np.lexsort((ids, score))[0]]

    if init == "farthest":
        a = pick(ids.astype(float))
        b = pick(-((x - a) ** 2).sum(1))
    elif init == "random":
        first, second = np.lexsort((ids, seeds.uniform(code, ids, seed)))[:2]
        a, b = x[first], x[second]
    else:
        order = np.argsort(ids, kind="stable")

        def cost_of(now: dict) -> dict:
            near, d = nearest(x, np.array(now[code]))
            return {code: (float(np.bincount(near, d).sum()), np.bincount(near, minlength=len(now[code])))}

        def bests_of(score, _) -> dict:
            return {(code, trial): (int(ids[i]), x[i], s[i]) for trial, s in enumerate(score(code, ids, x)) for i in [np.lexsort((ids, s))[0]]}

        def draw_of(chosen, _) -> dict:
            return {code: [(int(ids[i]), x[i]) for i in order[chosen(code, ids[order], x[order])]]}

        found = seeds.looking_ahead({code}, init, seed, lambda _: {code: pick(seeds.uniform(code, ids, seed))}, bests_of, cost_of, draw_of)[code]
        a, b = found if len(found) > 1 else (found[0], found[0])
        if not (a != b).any():
            b = pick(-((x - a) ** 2).sum(1))
    return seeds.bisector(a, b) if (a != b).any() else None


def _finish_locally(rows: DataFrame, nodes: dict[str, Node], small: list[Node], stop: Stop, init: str, tol: float, max_iter: int, seed: int) -> DataFrame:
    """One shuffle by code; each group (at most local_rows rows) grows in one task, closed leaves pass by unmoved."""
    names = [c for c in rows.columns if c != "code"]
    codes = [n.code for n in small]
    still, moving = rows.where(~F.col("code").isin(*codes)), rows.where(F.col("code").isin(*codes))
    kinds = dict(rows.dtypes)
    node_type = "struct<code:string,n:bigint,s:array<double>,sq:double,ss:array<double>,closed:string,w:array<double>,b:double,turns:int>"
    schema = T.StructType.fromDDL(", ".join([*(f"`{c}` {kinds[c]}" for c in names), "code string", f"node {node_type}"]))
    arrow_node = pa.struct([("code", pa.string()), ("n", pa.int64()), ("s", pa.list_(pa.float64())), ("sq", pa.float64()), ("ss", pa.list_(pa.float64())), ("closed", pa.string()), ("w", pa.list_(pa.float64())), ("b", pa.float64()), ("turns", pa.int32())])

    def run(group: pa.Table) -> pa.Table:
        ids, x = group["id"].to_numpy(), vectors(group["v"])
        code = group["code"][0].as_py()
        order = np.argsort(ids, kind="stable")
        made, labels = grow_local(ids[order], x[order], code, stop, init, tol, max_iter, seed)
        back = np.empty(len(ids), object)
        back[order] = labels
        n = len(made)
        told = [{"code": m.code, "n": m.n, "s": m.s.tolist(), "sq": m.sq, "ss": m.ss.tolist(), "closed": m.closed, "w": None if m.split is None else m.split[0].tolist(), "b": None if m.split is None else m.split[1], "turns": m.turns} for m in made]
        columns = [pa.concat_arrays([group[c].combine_chunks() if group[c].num_chunks != 1 else group[c].chunk(0), pa.nulls(n, group.schema.field(c).type)]) for c in names]
        return pa.Table.from_arrays([*columns, pa.array([*back.tolist(), *[None] * n], pa.string()), pa.array([*[None] * len(ids), *told], arrow_node)], names=[*names, "code", "node"])

    done = park(moving.groupBy("code").applyInArrow(run, schema), "subtrees")
    for batch in done.where("node IS NOT NULL").select("node.*").toArrow().to_batches():  # as Arrow: a node has 3 x d numbers, which rows would hold as objects
        get = dict(zip(batch.schema.names, batch.columns))
        plain = zip(*(get[c].to_pylist() for c in ("code", "n", "sq", "closed", "b", "turns")))
        for i, (code, n, sq, closed, b, turns) in enumerate(plain):
            s, ss, w = (get[c][i].values for c in ("s", "ss", "w"))
            nodes[code] = Node(code, n, np.array(s), sq, np.array(ss), closed, None if w is None else (np.array(w), b), turns)
    return still.select(*rows.columns).unionByName(done.where("node IS NULL").select(*rows.columns))


def descend(df: DataFrame, nodes: dict[str, Node], path: bool = False) -> DataFrame:
    """Adds ``code``: the leaf that each vector falls into, choosing the nearer child at every branch.  The tree's splits are sent to the tasks; with
    ``path``, also ``depth``."""
    out = relabel(df.drop("code").withColumn("code", F.lit("")), {c: n.split for c, n in nodes.items() if n.split is not None})
    return out.withColumn("depth", F.length("code")) if path else out


def near_leaves(x: np.ndarray, splits: dict[str, Split], probes: int | None = None, radius: float = np.inf) -> list[tuple[str, float]]:
    """Leaves best-bin-first: (code, bound), bound being the least squared distance that a point of the leaf's region can have by
    any one of the bisectors between; the first ``probes`` of them, or all with a bound of at most ``radius``.  A branch that is not
    entered costs one heap entry, so m leaves cost m paths."""
    heap, out = [(0.0, "")], []
    while heap and (probes is None or len(out) < probes):
        bound, code = heapq.heappop(heap)
        if bound > radius:
            break
        while (split := splits.get(code)) is not None:
            margin = float(x @ split[0]) - split[1]
            near = int(margin > 0)
            norm = float(split[0] @ split[0])
            heapq.heappush(heap, (max(bound, margin * margin / norm if norm else 0.0), f"{code}{1 - near}"))
            code = f"{code}{near}"
        out.append((code, bound))
    return out


def reached(codes: set[str], splits: dict[str, Split], y: np.ndarray, radius: np.ndarray) -> Iterator[tuple[str, np.ndarray]]:
    """Those of the leaves ``codes`` that may hold a point within some query's squared ``radius``, with the places of these queries: bounds as
    in ``near_leaves``, for all queries at once, down the common paths."""
    wanted = {c[:i] for c in codes for i in range(len(c) + 1)}
    todo = [("", np.arange(len(y)), np.zeros(len(y)))]
    while todo:
        code, who, bound = todo.pop()
        split = splits.get(code)
        if split is None:
            yield code, who
            continue
        margin = (y[who] if 4 * len(who) < len(y) else y) @ split[0] - split[1]
        margin = margin if len(margin) == len(who) else margin[who]
        norm = float(split[0] @ split[0])
        beyond = np.maximum(bound, margin * margin / norm) if norm else bound
        for bit in (1, 0):
            if f"{code}{bit}" in wanted:
                own = np.where((margin > 0) == bit, bound, beyond)
                near = own <= radius[who]
                if near.any():
                    todo.append((f"{code}{bit}", who[near], own[near]))


def probe(queries: DataFrame, nodes: dict[str, Node], probes: int | None = None) -> DataFrame:
    """(query_id, v, code, bound), a row for each of a query's nearest ``probes`` leaves, or, without a number, for each leaf that may
    hold a point within the squared distance in its column ``radius``."""
    splits = {c: n.split for c, n in nodes.items() if n.split is not None}
    sent = queries.sparkSession.sparkContext.broadcast(splits)
    rows = queries.select("query_id", "v", *(["radius"] if probes is None else []))
    kind = dict(queries.dtypes)["query_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = vectors(batch.column(1))
            limits = batch.column(2).to_numpy(zero_copy_only=False) if probes is None else np.full(len(x), np.inf)
            for begin in range(0, len(x), 256):  # a query may meet many leaves
                part = range(begin, min(begin + 256, len(x)))
                found = [(i, *leaf) for i in part for leaf in near_leaves(x[i], sent.value, probes, limits[i])]
                at = pa.array([i for i, _, _ in found], pa.int32())
                yield pa.RecordBatch.from_arrays([batch.column(0).take(at), batch.column(1).take(at), pa.array([c for _, c, _ in found], pa.string()), pa.array([b for *_, b in found], pa.float64())], names=["query_id", "v", "code", "bound"])

    return rows.mapInArrow(run, f"query_id {kind}, v {dict(queries.dtypes)['v']}, code string, bound double")


def descend_one(v: np.ndarray, nodes: dict[str, Node]) -> str:
    code = ""
    while nodes[code].split is not None:
        code += str(int(np.dot(v, nodes[code].split[0]) > nodes[code].split[1]))
    return code


def codebook(index: Index, spark: SparkSession) -> DataFrame:
    """Leaf codes and centroids: the entries of the index."""
    return index.table(spark).where("is_leaf").select("code", "centroid", "n", "wcss")


def save(index: Index, path: str) -> None:
    """nodes, rows sorted by code (so a leaf is a few row groups of one file) and the settings."""
    spark = index.labelled.sparkSession
    index.table(spark).write.mode("overwrite").parquet(f"{path}/nodes")
    write(index.labelled, f"{path}/rows", sort_by=["code", "id"])
    spark.createDataFrame([(json.dumps(index.manifest),)], "manifest string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")


def load(spark: SparkSession, path: str) -> Index:
    nodes = {}
    for r in spark.read.parquet(f"{path}/nodes").collect():
        nodes[r.code] = Node(r.code, r.n, np.array(r.ssum), r.sq, np.zeros(len(r.ssum)), r.close_reason, None if r.split_w is None else (np.array(r.split_w), r.split_b))
    return Index(nodes, spark.read.parquet(f"{path}/rows"), json.loads(spark.read.text(f"{path}/manifest").first()[0]))


def _restat(index: Index, rows: DataFrame, sign: int) -> dict[str, Node]:
    """Node statistics after adding (sign 1) or removing (-1) rows: sums by leaf, carried up the path."""
    nodes = {c: Node(n.code, n.n, n.s.copy(), n.sq, n.ss.copy(), n.closed, n.split) for c, n in index.nodes.items()}
    for (code, _), part in sums(rows).items():
        for depth in range(len(code) + 1):
            n = nodes[code[:depth]]
            n.n, n.s, n.sq, n.ss = n.n + sign * part["n"], n.s + sign * part["s"], n.sq + sign * part["sq"], n.ss + sign * part["ss"]
    return nodes


def insert(index: Index, df: DataFrame) -> Index:
    """New rows fall into leaves; the tree stays."""
    new = descend(prepare(df), index.nodes).select(*index.labelled.columns)
    new = park(new, "inserted")
    return Index(_restat(index, new, 1), index.labelled.unionByName(new), index.manifest)


def delete(index: Index, ids: DataFrame) -> Index:
    gone = index.labelled.join(ids.select("id").distinct(), "id", "left_semi").select(*index.labelled.columns)
    return Index(_restat(index, gone, -1), index.labelled.join(ids.select("id").distinct(), "id", "left_anti").select(*index.labelled.columns), index.manifest)


def modify(index: Index, df: DataFrame) -> Index:
    """Replace descriptors by id."""
    return insert(delete(index, df), df)


def regrow(index: Index, stop: Stop, codes: list[str] | None = None, **settings) -> Index:
    """Grow further below leaves that no longer meet a stop rule, or below those named: one front over all of them, in the passes of ``grow``."""
    codes = codes or [n.code for n in index.leaves if stop.reason(len(n.code), n.n, n.wcss) is None and n.closed != "degenerate"]
    now = sums(index.labelled.where(F.col("code").isin(*codes))) if codes else {}
    reopened = {c: _node(c, now[c, 0]) for c in codes if (c, 0) in now}
    kept = {c: n.closed for c, n in index.nodes.items() if n.split is None and c not in reopened}
    start = {c: Node(n.code, n.n, n.s, n.sq, n.ss, "kept" if c in kept else n.closed, n.split) for c, n in index.nodes.items()} | reopened
    grown = grow(index.labelled, stop, start=start, **settings)
    for c, closed in kept.items():
        grown.nodes[c].closed = closed
    return Index(grown.nodes, grown.labelled, index.manifest)


__all__ = ["Index", "Node", "Stop", "by_code", "codebook", "delete", "descend", "descend_one", "grow", "grow_local", "insert", "load", "modify", "near_leaves", "prepare", "probe", "reached", "regrow", "save"]
