"""Scaling and cost-benefit experiments: the index on 1, 2, 4 .. cores and on profiles of worker types, then fits.

python experiments.py [tables [runs]] prints one JSON line: medians of RUNS runs, linear fit with and without the points that the Bonferroni
test flags, speed-up, cost trade-off against the smallest configuration, transfer times by cores; the same index on two cores with
so little memory that cached blocks are evicted; worker types; and a deep tree over 12,950 descriptors from memory and from disk.
Each run is one process and one machine, so a core stands for a node; all have 6 GB but for the starved one and the types.
"""

from __future__ import annotations

import json
import os
import shutil
import subprocess
import sys
import tempfile
import time

HERE = os.path.dirname(os.path.abspath(__file__))
RUNS = 3
#: Heap of the run in which the descriptors do not fit, MB.
STARVED = 1000
#: Tiles of the published archive.
TILES = 12_950
#: Profiles that mirror the ratios of the worker types: cores and driver memory in MB.
PROFILES = {"m1.small": (1, 1200), "m1.medium": (1, 2000), "m1.large": (2, 3000), "m1.xlarge": (4, 5000), "c1.medium": (2, 1200), "c1.xlarge": (8, 2800)}


def prepare(d: str, out: str) -> dict:
    """The descriptors that all runs index, written once."""
    sys.path.insert(0, HERE)
    from bench import session
    from tilemine.sources import archives

    spark = session(os.cpu_count() or 1)
    archives.vec_pairs(spark, d).repartition(48).write.mode("overwrite").parquet(out)
    made = spark.read.parquet(out)
    made.orderBy("id").limit(TILES).repartition(16).write.mode("overwrite").parquet(f"{out}-tiles")
    said = {"descriptors": made.count(), "dimensions": len(made.first().v)}
    spark.stop()
    return said


def one(pairs: str, cores: int) -> dict:
    """In a process of its own: seconds to load the descriptors into memory, to index and to copy them, and the median latency of a query."""
    sys.path.insert(0, HERE)
    from bench import session
    from tilemine.operators import measures, search, tsvq
    from tilemine.operators.tsvq import Stop
    from tilemine.sources import storage

    spark = session(cores)
    began = time.perf_counter()
    docs = spark.read.parquet(pairs).persist()
    docs.count()
    loaded = time.perf_counter() - began
    began = time.perf_counter()
    index = tsvq.grow(docs, Stop(n_min=500, h_max=2), max_iter=5)
    took = time.perf_counter() - began
    blocks = [(x.memSize(), x.diskSize()) for x in spark._jsc.sc().getRDDStorageInfo()]
    queries = [r.v for r in docs.where("id % 1000 = 0").orderBy("id").limit(10).collect()]
    held = tsvq.Index(index.nodes, storage.park(index.labelled.repartitionByRange("code").sortWithinPartitions("code"), "searched"), {})
    search.by_vectors(held, [queries[0]], 10).collect()
    each = sorted(measures.timed(lambda v=v: search.by_vectors(held, [v], 10).collect(), 1)["median"] for v in queries)
    target = f"{pairs}-copy"
    moved = storage.stage_in(spark, pairs, target)["seconds"]
    spark.stop()
    shutil.rmtree(target, ignore_errors=True)
    return {"load_s": round(loaded, 3), "index_s": round(took, 3), "query_s": round(each[len(each) // 2], 3), "query_worst_s": round(each[-1], 3), "transfer_s": round(moved, 3), "cached_mb": sum(m for m, _ in blocks) >> 20, "evicted_mb": sum(d for _, d in blocks) >> 20}


def tree(tiles: str, materialise: str) -> dict:
    """In a process of its own: seconds to grow a tree down to nodes of 1,000 over the tiles, its passes and levels."""
    sys.path.insert(0, HERE)
    from bench import session
    from tilemine.operators import tsvq
    from tilemine.operators.tsvq import Stop

    spark = session(min(3, os.cpu_count() or 1))
    docs = spark.read.parquet(tiles)
    docs.count()
    began = time.perf_counter()
    index = tsvq.grow(docs, Stop(n_min=1000), max_iter=10, materialise=materialise)
    took = time.perf_counter() - began
    spark.stop()
    return {"index_s": round(took, 3), "passes": len(index.manifest["passes"]), "leaves": len(index.leaves), "levels": max(len(n.code) for n in index.leaves)}


def child(memory_mb: int, *args: str) -> dict:
    said = subprocess.run([sys.executable, os.path.abspath(__file__), *args], env=os.environ | {"BENCH_MEMORY": f"{memory_mb}m"}, capture_output=True, text=True)
    found = json.loads(said.stdout.strip().splitlines()[-1]) if said.returncode == 0 else {"failed": said.stderr[-300:]}
    print(*args, f"{memory_mb} MB", found, file=sys.stderr, flush=True)
    return found


def judge(by_cores: dict, by_type: dict) -> dict:
    """Fits, outliers, speed-up and cost trade-off of the measured runs."""
    sys.path.insert(0, HERE)
    from bench import session
    from tilemine.operators import measures
    from tilemine.operators.ingest import TYPES

    spark, schema = session(2), "config string, nodes int, minutes double, rate double"
    said: dict = {}
    for what in ("load_s", "index_s"):
        runs = spark.createDataFrame([(f"n{c}", c, x[what] / 60, 0.1) for c, x in by_cores.items() if what in x], schema)
        flagged = [r.config for r in measures.bonferroni_outliers(runs).collect() if r.outlier]
        refit = measures.fit(runs.where(~runs["config"].isin(flagged))).first().asDict() if flagged else None
        said[what] = {"fit": measures.fit(runs).first().asDict(), "outliers": flagged, "refit_without_them": refit, "speedup": [r.asDict() for r in measures.speedup(runs).collect()]}
        said[what]["tradeoff_cores"] = {r.config: r.tradeoff for r in measures.tradeoff(measures.relative(runs, f"n{min(by_cores)}")).collect()}
    rates = {t[0]: t[6] for t in TYPES}
    types = [(n, 3, x["index_s"] / 60, rates[n]) for n, x in by_type.items() if "index_s" in x]
    if any(t[0] == "m1.small" for t in types):
        said["tradeoff_types"] = {r.config: r.tradeoff for r in measures.tradeoff(measures.relative(spark.createDataFrame(types, schema), "m1.small")).collect()}
    spark.stop()
    return said


def median(found: list[dict]) -> dict:
    """Medians of the runs that ended; how many failed."""
    good = [x for x in found if "failed" not in x]
    out = {k: sorted(x[k] for x in good)[len(good) // 2] for k in (good[0] if good else {})}
    return out | ({"failed_runs": len(found) - len(good)} if len(good) < len(found) else {})


def main(args: list[str]) -> None:
    d = args[0] if args else "/root/testdata/sf0.1"
    runs = int(args[1]) if len(args) > 1 else RUNS
    top = os.cpu_count() or 1
    with tempfile.TemporaryDirectory(prefix="experiments-") as folder:  # one machine
        pairs = f"{folder}/pairs"
        made = child(6000, "--prepare", d, pairs)
        trees = {m: child(6000, "--tree", f"{pairs}-tiles", m) for m in ("memory", "dfs", "none")}
        by_cores = {c: median([child(6000, "--one", pairs, str(c)) for _ in range(runs)]) for c in (8, 6, 4, 3, 2, 1) if c <= top}
        starved = child(STARVED, "--one", pairs, "2")
        by_type = {name: child(m, "--one", pairs, str(min(c, top))) for name, (c, m) in PROFILES.items()}
        with_starved = by_cores | ({2: starved} if "index_s" in starved else {})
        print(json.dumps(made | {"trees": trees, "by_cores": by_cores, "starved": starved, "by_type": by_type, "with_starved": judge(with_starved, {})} | judge(by_cores, by_type)))


if __name__ == "__main__":
    if sys.argv[1:2] == ["--one"]:
        print(json.dumps(one(sys.argv[2], int(sys.argv[3]))))
    elif sys.argv[1:2] == ["--tree"]:
        print(json.dumps(tree(sys.argv[2], sys.argv[3])))
    elif sys.argv[1:2] == ["--prepare"]:
        print(json.dumps(prepare(*sys.argv[2:4])))
    else:
        main(sys.argv[1:])
