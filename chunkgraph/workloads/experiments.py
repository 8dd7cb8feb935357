"""The experiments as runs over the given tables: each returns rows of plain values, times in seconds.

    python -m chunkgraph.workloads.experiments /root/testdata/sf0.01 [name ...]

Cores are those of the session: `CORES=1` and `CORES=8` before the command give the two ends of the scaling table.

Absolute times say little at these sizes, where a round of Spark jobs outweighs its data; what is read off is how a figure
moves with its parameter and which side of a comparison does less work.
"""

from __future__ import annotations

import os
import random
import statistics
import sys
import threading
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import algorithms, baselines, sets
from ..operators.graph import Graph, two_hop, two_hop_work
from ..plans import cost
from ..plans.scratch import scratch_dir, settle
from ..sources.graphs import edges, pairs, rmat, sample_updates, symmetrised
from ..sources.store import VersionStore

GRAPHS = ("ps", "cs", "op", "cp", "ev", "web")
#: Local queries of a batch.
LOCAL = 2048


def timed(f, runs: int = 1) -> float:
    """Median seconds of running f to the end; a frame that it returns is computed whole."""
    out = []
    for _ in range(runs):
        began = time.time()
        result = f()
        if isinstance(result, DataFrame):
            result.write.format("noop").mode("overwrite").save()
        out.append(time.time() - began)
    return round(statistics.median(out), 3)


def _source(e: DataFrame) -> int:
    return e.agg(F.min("src")).first()[0]


def input_statistics(spark: SparkSession, d: str) -> list[dict]:
    out = []
    for name in GRAPHS:
        n, m = Graph.from_edges(edges(spark, d, name)).counts().first()
        out.append({"graph": name, "n": n, "m": m, "avg_degree": round(m / n, 2)})
    return out


def memory_by_format(spark: SparkSession, d: str, sizes=(8, 16, 256)) -> list[dict]:
    """Bytes of each format; with small b where vertices have few neighbours."""
    return [{"graph": name, "b": b, **cost.memory_formats(Graph.from_edges(edges(spark, d, name), b=b).chunks).first().asDict()} for name in GRAPHS for b in sizes]


def stored_bytes(spark: SparkSession, d: str, name: str = "cs", sizes=(8, 256)) -> list[dict]:
    """Bytes that a version store's files take with each codec, beside the model's."""
    out = []
    for b in sizes:
        for codec in ("plain", "delta", "bytecode"):
            store = VersionStore(spark, scratch_dir(spark), b=b, codec=codec)
            store.publish(Graph.from_edges(edges(spark, d, name), b=b))
            folder = store._path(f"{store.path}/data")
            out.append({"b": b, "codec": codec, "file_bytes": store._fs.getContentSummary(folder).getLength(), "model_bytes": cost.memory_formats(store.graph().recoded("plain").chunks).first()["coded_bytes"]})
    return out


def chunk_size_sweep(spark: SparkSession, d: str, name: str = "cs", sizes=tuple(2**k for k in range(1, 13))) -> list[dict]:
    e, out = settle(edges(spark, d, name)), []
    s = _source(e)
    for b in sizes:
        g = Graph.from_edges(e, b=b).flat_snapshot()
        row = {"b": b, "coded_bytes": cost.memory_formats(g.chunks).first()["coded_bytes"]}
        row |= {"bfs_s": timed(lambda: algorithms.bfs(g, s)), "bc_s": timed(lambda: algorithms.bc(g, s)), "mis_s": timed(lambda: algorithms.mis(g))}  # noqa: B023
        g.release()
        out.append(row)
    return out


def _local_sources(g: Graph, count: int = LOCAL) -> DataFrame:
    """(vid): that many vertices at most, those of least hash."""
    from ..functions.hashing import wide_hash

    return g.vertices().where("deg > 0").orderBy(wide_hash(F.col("vid"), 13), "vid").select("vid").limit(count)


def analyses(spark: SparkSession, d: str, graphs=GRAPHS, local: int = LOCAL) -> list[dict]:
    """The five analyses; local ones as one job over many sources, time per source."""
    out = []
    for name in graphs:
        e = settle(edges(spark, d, name))
        g, s = Graph.from_edges(e, b=16).flat_snapshot(), _source(e)
        some = settle(_local_sources(g, local))
        count = some.count()
        row = {"graph": name, "bfs_s": timed(lambda: algorithms.bfs(g, s)), "bc_s": timed(lambda: algorithms.bc(g, s)), "mis_s": timed(lambda: algorithms.mis(g)), "sources": count}  # noqa: B023
        row["two_hop_s"] = round(timed(lambda: two_hop(g, some.select(F.col("vid").alias("src"))).groupBy("src").count()) / count, 5)  # noqa: B023
        row["local_cluster_s"] = round(timed(lambda: algorithms.local_cluster(g, some.limit(64), 1e-3)) / min(64, count), 5)  # noqa: B023
        g.release()
        out.append(row)
    return out


def scaling(spark: SparkSession, d: str, graphs=("ps", "op"), partitions=(1, 2, 4, 8)) -> list[dict]:
    """BFS and independent sets by the number of partitions, so of tasks at once; 1 is the sequential arm on any session."""
    out, before = [], spark.conf.get("spark.sql.shuffle.partitions")
    try:
        for name in graphs:
            e = settle(edges(spark, d, name))
            s = _source(e)
            for n in partitions:
                spark.conf.set("spark.sql.shuffle.partitions", n)
                g = Graph.from_edges(e.coalesce(n), b=16).flat_snapshot()
                g.chunks.count()
                out.append({"graph": name, "tasks": n, "bfs_s": timed(lambda: algorithms.bfs(g, s)), "mis_s": timed(lambda: algorithms.mis(g))})  # noqa: B023
                g.release()
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    return out


def local_queries(spark: SparkSession, d: str, name: str = "op", count: int = LOCAL, alone: int = 4) -> list[dict]:
    """Two-hop and local-cluster queries: one after another, and as one job for all; with the chunks that are opened."""
    e = settle(edges(spark, d, name))
    g = Graph.from_edges(e, b=16).flat_snapshot()
    some = settle(_local_sources(g, count))
    ids, total = [r["vid"] for r in some.limit(alone).collect()], some.count()
    one = lambda v: some.where(F.col("vid") == v)
    hop = lambda q: two_hop(g, q.select(F.col("vid").alias("src")))
    cluster = lambda q: algorithms.local_cluster(g, q, 1e-3)
    work = two_hop_work(g, one(ids[0]).select(F.col("vid").alias("src"))).first().asDict()
    out = [{"graph": name, "query": label, "sequential_s": round(sum(timed(lambda: f(one(v))) for v in ids) / len(ids), 4), "together_s": round(timed(lambda: f(q)) / n, 5), "queries": n} for label, f, q, n in (("two_hop", hop, some, total), ("local_cluster", cluster, some.limit(64), min(64, total)))]  # noqa: B023
    g.release()
    return [*out, {"graph": name, "query": "one two_hop", **work}]


def flat_snapshot_ablation(spark: SparkSession, d: str, graphs=GRAPHS) -> list[dict]:
    """BFS on chunks that each round reads anew and on a flat snapshot; what building it takes, and its share of both."""
    out = []
    for name in graphs:
        e = edges(spark, d, name)
        g, s = Graph.from_edges(settle(e), b=16).settled(), _source(e)
        flat = g.flat_snapshot()
        build = timed(lambda: flat.chunks.count())  # noqa: B023
        with_ = timed(lambda: algorithms.bfs(flat, s))  # noqa: B023
        flat.release()
        without = timed(lambda: algorithms.bfs(g, s))  # noqa: B023
        out.append({"graph": name, "without_s": without, "build_s": build, "with_s": with_, "build_share": round(build / (build + with_), 3), "speed_up": round(without / (build + with_), 3)})
    return out


def direction_ablation(spark: SparkSession, d: str, name: str = "cp") -> list[dict]:
    """Edges that BFS examines, sparse only and with the switch (a dense round looks at unvisited vertices only)."""
    g = Graph.from_edges(settle(edges(spark, d, name)), b=16).flat_snapshot()
    out = []
    for mode in ("sparse", "dense", "auto"):
        trace: list = []
        seconds = timed(lambda: algorithms.bfs(g, 0, mode, trace=trace))  # noqa: B023
        out.append({"mode": mode, "bfs_s": seconds, "rounds": len(trace), "dense_rounds": sum(t[1] == "dense" for t in trace), "frontier_edges_sparse": sum(t[3] for t in trace if t[1] == "sparse")})
    return out


def batch_throughput(spark: SparkSession, d: str, name: str = "ps", sizes=(10, 100, 1000, 10_000, 100_000, 1_000_000), runs: int = 3) -> list[dict]:
    """Directed edges a second of inserting and deleting a batch of draws; sorting and combining included."""
    base, out = Graph.from_edges(edges(spark, d, name), b=16).settled(), []
    for k in sizes:
        batch = settle(rmat(spark, 12, k).select("src", "dst"))
        insert = timed(lambda: base.insert_edges(batch).chunks, runs)  # noqa: B023
        grown = base.insert_edges(batch).settled()
        delete = timed(lambda: grown.delete_edges(batch).chunks, runs)  # noqa: B023
        touched = baselines.path_copy(base.chunks, batch.select(F.col("src").alias("owner"), F.col("dst").alias("elem")), 16).first()
        out.append({"batch": k, "insert_per_s": round(k / insert), "delete_per_s": round(k / delete), "chunks": touched["chunks"], "touched": touched["touched"]})
    return out


def concurrent_updates(spark: SparkSession, d: str, name: str = "cs", batches: int = 4) -> list[dict]:
    """A writer that applies the 90/10 stream in batches while BFS queries run on pinned versions; then queries alone."""
    ab = settle(pairs(spark, d, name).where("a <> b").distinct())
    s = settle(sample_updates(ab))
    store = VersionStore(spark, scratch_dir(spark), b=16)
    store.publish(Graph.from_edges(symmetrised(ab.join(s.where("op = 'I'"), ["a", "b"], "left_anti")), b=16))
    both = settle(s.select(F.col("spot").alias("seq"), "op", F.col("a").alias("src"), F.col("b").alias("dst")).unionByName(s.select(F.col("spot").alias("seq"), "op", F.col("b").alias("src"), F.col("a").alias("dst"))))
    total, took, during, done = both.count(), [], {"bfs": [], "local_cluster": []}, threading.Event()
    r, ids = random.Random(17), [x["vid"] for x in _local_sources(store.graph(), 64).collect()]

    def query(kind):
        """From a random source, on a version that stays pinned meanwhile."""
        held, v = store.acquire(), r.choice(ids)
        try:
            g = store.graph(held.version)
            return timed(lambda: algorithms.bfs(g, v) if kind == "bfs" else algorithms.local_cluster(g, g.vertices().where(F.col("vid") == v).select("vid"), 1e-3))
        finally:
            store.release(held)

    def read():
        while not done.is_set():
            for kind, seen in during.items():
                seen.append(query(kind))

    reader = threading.Thread(target=read)
    reader.start()
    for k in range(batches):
        began = time.time()
        store.apply(both.where(F.col("seq") % batches == k), batch_id=k)
        took.append(time.time() - began)
    done.set()
    reader.join()
    row = {"directed_updates": total, "updates_per_s": round(total / sum(took)), "visible_after_s": round(statistics.mean(took), 3)}
    for kind, seen in during.items():
        row |= {f"{kind}_during_s": round(statistics.median(seen), 3), f"{kind}_alone_s": round(statistics.median(query(kind) for _ in range(3)), 3)}
    return [row]


def against_streaming_baselines(spark: SparkSession, d: str, sizes=(10, 1000, 100_000), snapshots=(1, 4, 16)) -> list[dict]:
    """Blocked lists and chained snapshots against chunks: updates on a near-empty graph (median of three batches), memory,
    BFS and betweenness without a switch of direction; what a reader walks in chained snapshots."""
    out = []
    for k in sizes:
        batch = settle(rmat(spark, 12, k).select("src", "dst"))
        first = settle(rmat(spark, 12, 64, seed=99).select("src", "dst").distinct())
        blocked, chunked = baselines.BlockedListGraph.from_edges(first), Graph.from_edges(first, b=16)
        scanned = baselines.BlockedListGraph.from_edges(edges(spark, d, "ps")).insert_cost(batch).first()
        times = {"blocked_s": timed(lambda: blocked.insert(batch).blocks, 3), "chunked_s": timed(lambda: chunked.insert_edges(batch).chunks, 3)}  # noqa: B023
        out.append({"batch": k, **times, "slots_scanned_on_ps": scanned["slots_scanned"]})
    e = settle(edges(spark, d, "ps"))
    n, s = e.select("src").distinct().count(), _source(e)
    b1, ours, chains = baselines.BlockedListGraph.from_edges(e), Graph.from_edges(e, b=256), {}
    for count in snapshots:
        g = baselines.MultiSnapshotGraph(n)
        for k in range(count):
            g = g.ingest(e.where((F.col("src") * 7 + F.col("dst")) % count == k))
        chains[count] = g
        out.append({"snapshots": count, "fragments_per_vertex": round(g.fragmentation().agg(F.avg("fragments")).first()[0], 2), "array_entries": count * g.n})
    most = chains[max(snapshots)]
    memory = {"chunked": cost.memory_formats(ours.chunks).first()["coded_bytes"], "blocked": b1.memory(n).first()["bytes"], "chained": most.memory().first()["bytes"]}
    for label, g, mode in (("chunked", ours, "auto"), ("chunked, no switch", ours, "sparse"), ("blocked", b1.view(), "sparse"), ("chained", most.view(), "sparse")):
        flat = g.flat_snapshot()
        flat.chunks.count()
        out.append({"layout": label, "bytes": memory[label.split(",")[0]], "bfs_s": timed(lambda: algorithms.bfs(flat, s, mode)), "bc_s": timed(lambda: algorithms.bc(flat, s, mode))})  # noqa: B023
        flat.release()
    return out + [{"ratios": "bytes", **cost.ratios({"blocked": memory["chunked"], "chained": memory["chunked"]}, memory)}]


def against_static_baselines(spark: SparkSession, d: str, name: str = "ps") -> list[dict]:
    """Chunks against static layouts: BFS, betweenness and independent sets; coded rows are decoded by every traversal."""
    e = settle(edges(spark, d, name))
    s, out = _source(e), []
    layouts = (
        ("chunked", Graph.from_edges(e, b=256), "auto"), ("chunked, coded", Graph.from_edges(e, b=256, codec="bytecode"), "auto"), ("plain", baselines.plain_graph(e), "auto"),
        ("static rows, coded", baselines.static_graph(e, "bytecode"), "auto"), ("static rows", baselines.static_graph(e), "auto"), ("static rows, no switch", baselines.static_graph(e), "sparse"),
    )
    for label, g, mode in layouts:
        g = g.settled()
        out.append({"layout": label, "rows": g.chunks.count(), "bfs_s": timed(lambda: algorithms.bfs(g, s, mode), 3), "bc_s": timed(lambda: algorithms.bc(g, s, mode)), "mis_s": timed(lambda: algorithms.mis(g))})  # noqa: B023
    return out


def index_updates(spark: SparkSession, d: str) -> list[dict]:
    """An inverted index by chunks: sizes before and after documents are added in batches."""
    from .set_checks import postings

    p = settle(postings(spark, d).select("owner", "elem"))
    index, out = sets.build(p.where("elem % 4 <> 0"), 16), []
    for k in (1, 2):
        index = settle(sets.union(index, p.where(f"elem % 4 = 0 AND elem % 8 = {4 * (k - 1)}"), 16))
        out.append({"batch": k, "lists": index.select("owner").distinct().count(), "entries": index.agg(F.sum(sets.weight())).first()[0]})
    return out


EXPERIMENTS = {
    f.__name__: f
    for f in (
        input_statistics, memory_by_format, stored_bytes, chunk_size_sweep, analyses, scaling, local_queries, flat_snapshot_ablation, direction_ablation,
        batch_throughput, concurrent_updates, against_streaming_baselines, against_static_baselines, index_updates,
    )
}
#: Arguments for a quick run of each.
SMALL = {
    "chunk_size_sweep": {"sizes": (4, 64)}, "analyses": {"graphs": ("tree",), "local": 16}, "scaling": {"graphs": ("tree",), "partitions": (1, 2)}, "local_queries": {"name": "tree", "count": 8, "alone": 1},
    "flat_snapshot_ablation": {"graphs": ("tree",)}, "direction_ablation": {"name": "tree"}, "batch_throughput": {"sizes": (10, 1000), "runs": 1}, "concurrent_updates": {"name": "tree", "batches": 2},
    "against_streaming_baselines": {"sizes": (10,), "snapshots": (1, 3)}, "against_static_baselines": {"name": "tree"}, "stored_bytes": {"name": "tree", "sizes": (8,)},
}


def main(arguments: list[str]) -> None:
    spark = SparkSession.builder.master(f"local[{os.environ.get('CORES', '8')}]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "6g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.sql.warehouse.dir", "/tmp/chunkgraph_experiments").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name in arguments[1:] or EXPERIMENTS:
        print(f"# {name}", flush=True)
        for row in EXPERIMENTS[name](spark, arguments[0]):
            print(row, flush=True)


if __name__ == "__main__":
    main(sys.argv[1:])
