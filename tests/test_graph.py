import random
import threading

import pytest
from pyspark.sql import functions as F

from chunkgraph.operators import algorithms, baselines, walks
from chunkgraph.operators import graph as graph_module
from chunkgraph.operators.graph import Graph, VertexSubset, edge_map, two_hop
from chunkgraph.plans import cost
from chunkgraph.plans.scratch import scratch_dir, settle
from chunkgraph.sources.graphs import rmat
from chunkgraph.sources.store import VersionStore, WriterConflict
from chunkgraph.workloads.queries import oracle_sql, queries

from .compare import assert_same, connection
from .conftest import DATA


def both_ways(pairs):
    return sorted({(a, b) for a, b in pairs} | {(b, a) for a, b in pairs})


def graph(spark, pairs, b=4):
    return Graph.from_edges(spark.createDataFrame(both_ways(pairs), "src long, dst long"), b=b)


def random_pairs(seed, n=40, m=70):
    r = random.Random(seed)
    return {(a, b) for a, b in ((r.randrange(n), r.randrange(n)) for _ in range(m)) if a != b}


def plain_bfs(pairs, source):
    near = {}
    for a, b in both_ways(pairs):
        near.setdefault(a, set()).add(b)
    level, front = {source: 0}, [source]
    parent = {source: None}
    while front:
        new = {}
        for u in front:
            for v in near.get(u, ()):
                if v not in level:
                    new[v] = min(new.get(v, u), u)
        for v, u in new.items():
            level[v], parent[v] = level[front[0]] + 1, u
        front = sorted(new)
    return {v: (level[v], parent[v]) for v in level}


@pytest.mark.parametrize("mode", ["sparse", "dense", "auto"])
def test_bfs_in_every_mode(spark, mode):
    pairs = random_pairs(1) | {(100, 101)}
    g = graph(spark, pairs)
    got = {r["vid"]: (r["level"], r["parent"]) for r in algorithms.bfs(g, 3, mode).collect()}
    assert got == plain_bfs(pairs, 3)


def test_bfs_query_goes_as_deep_as_its_sql(spark, tmp_path):
    """A path of orders and parts that is longer than the SQL's recursion."""
    duck = connection(DATA)
    duck.execute(f"COPY (SELECT * REPLACE (k AS l_orderkey, k + j AS l_partkey) FROM (SELECT * FROM lineitem LIMIT 1), range(9) a(k), range(2) b(j)) TO '{tmp_path}/lineitem.parquet' (FORMAT parquet)")
    duck.execute(f"CREATE OR REPLACE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet'")
    df = queries()["bfs_op"](spark, str(tmp_path))
    assert_same(df, duck, oracle_sql()["bfs_op"])
    assert df.agg(F.max("level")).first()[0] == 8
    pairs = {(k, k + 1) for k in range(6)}
    assert rows(algorithms.bfs(graph(spark, pairs), 0, depth=3), "vid", "level") == [(k, k) for k in range(4)]
    assert algorithms.bfs(graph(spark, pairs), 0).count() == 7


def test_layouts_agree(spark):
    pairs = random_pairs(2)
    want = plain_bfs(pairs, 0)
    edges = spark.createDataFrame(both_ways(pairs), "src long, dst long")
    for g in (Graph.from_edges(edges, b=1), Graph.from_edges(edges, b=256), baselines.static_graph(edges), Graph.from_edges(edges).flat_snapshot()):
        assert {r["vid"]: (r["level"], r["parent"]) for r in algorithms.bfs(g, 0).collect()} == want


def test_betweenness_by_hand(spark):
    """A triangle with a tail: 0-1, 0-2, 1-2, 2-3, 3-4."""
    got = {r["vid"]: (r["level"], r["sigma"], r["delta"]) for r in algorithms.bc(graph(spark, {(0, 1), (0, 2), (1, 2), (2, 3), (3, 4)}), 0).collect()}
    assert got == {0: (0, 1.0, 0.0), 1: (1, 1.0, 0.0), 2: (1, 1.0, 2.0), 3: (2, 1.0, 1.0), 4: (3, 1.0, 0.0)}


def test_independent_set_is_greedy(spark):
    from chunkgraph.functions.hashing import portable_hash_int

    pairs = random_pairs(3)
    near = {}
    for a, b in both_ways(pairs):
        near.setdefault(a, set()).add(b)
    chosen = set()
    for v in sorted(near, key=lambda v: (portable_hash_int(v, 3), v)):
        if not near[v] & chosen:
            chosen.add(v)
    g = graph(spark, pairs)
    found = algorithms.mis(g, 3)
    assert {r["vid"] for r in found.where("in_mis").collect()} == chosen
    assert tuple(algorithms.mis_violations(g, found).first()) == (0, 0)


def test_local_cluster_finds_a_clique(spark):
    clique = lambda s: {(s + i, s + j) for i in range(6) for j in range(i)}
    g = graph(spark, clique(0) | clique(10) | {(0, 10)})
    seeds = spark.createDataFrame([(3,)], "vid long")
    got = algorithms.local_cluster(g, seeds, 1e-4, 10).collect()
    assert {r["vid"] for r in got} == set(range(6)) and abs(got[0]["conductance"] - 1 / 31) < 1e-9


def test_local_cluster_in_groups_cuts_as_all_edges_do(spark, monkeypatch):
    g = graph(spark, random_pairs(7, 60, 150) | {(3, 3)})
    seeds = g.vertices().where("vid % 5 = 0").select("vid")
    degrees = algorithms._degrees(g)
    ranked = algorithms._ranked(algorithms.walk(g, seeds, 1e-3, 4), degrees)
    got, plain = (rows(algorithms._prefixes(g, ranked, degrees, d), "seed", "rank", "vid", "conductance") for d in (algorithms._downhill(g, degrees), None))
    assert got == plain and got
    whole = rows(algorithms.local_cluster(g, seeds, 1e-3, 4), "seed", "vid", "conductance")
    monkeypatch.setattr(algorithms, "SEEDS_TOGETHER", 3)
    assert rows(algorithms.local_cluster(g, seeds, 1e-3, 4), "seed", "vid", "conductance") == whole


def walked_by_hand(near, seed, eps, steps):
    state = {seed: 1.0}
    for _ in range(steps):
        active, after = {v: p for v, p in state.items() if near.get(v) and p >= eps * len(near[v])}, {}
        if not active:
            break
        for v, p in active.items():
            after[v] = after.get(v, 0.0) + p / 2
            for x in near[v]:
                after[x] = after.get(x, 0.0) + p / (2 * len(near[v]))
        state = after
    return state


@pytest.mark.parametrize("directed, eps, steps", [(False, 1e-3, 10), (False, 0.02, 6), (False, 0.2, 3), (True, 1e-3, 6), (False, 0.0, 2), (False, 1e-3, 0)])
def test_walks_in_batches_are_those_by_hand(spark, monkeypatch, directed, eps, steps):
    pairs, near = random_pairs(5, 60, 130) | {(1, 1), (-7, 3), (-7, 1 << 40)}, {}
    both = pairs if directed else both_ways(pairs)
    for a, b in both:
        near.setdefault(a, set()).add(b)
    g = Graph.from_edges(spark.createDataFrame(sorted(both), "src long, dst long"), directed=directed, b=4)
    ids = [*range(0, 60, 4), -7, 1 << 40, 999]
    monkeypatch.setattr(walks, "BATCH_SEEDS", 4)
    got = {}
    for r in algorithms.walk(g, spark.createDataFrame([(x,) for x in ids], "vid long"), eps, steps).collect():
        got.setdefault(r["seed"], {})[r["vid"]] = r["p"]
    assert got == {x: pytest.approx(walked_by_hand(near, x, eps, steps), abs=1e-14) for x in ids}


@pytest.mark.parametrize("eps", [1e-3, 0.3])
def test_clusters_of_arrays_cut_as_frames_do(spark, eps):
    g = graph(spark, random_pairs(9, 50, 140) | {(3, 3), (7, 7)})
    degrees, seeds = settle(algorithms._degrees(g)), g.vertices().where("vid % 4 = 0").select("vid")
    near = settle(algorithms._near(g, degrees, eps))
    lists = lambda df: {r[0]: sorted(r[1]) for r in df.collect()}
    assert lists(near.where(F.size("to") > 0).select("vid", "to")) == lists(algorithms._downhill(g, degrees))
    want = algorithms._best(algorithms.sweep(g, algorithms.walk(g, seeds, eps, 5)))
    got, want = ({(r["seed"], r["vid"]): r["conductance"] for r in df.collect()} for df in (algorithms.local_cluster(g, seeds, eps, 5), want))
    assert got == pytest.approx(want, abs=1e-12) and got


def test_a_walk_that_has_its_lists_needs_no_more_rounds(spark):
    g = graph(spark, {(i, j) for i in range(6) for j in range(i)})
    degrees = algorithms._degrees(g)
    near = algorithms._near(g, degrees, 1e-4).select("vid", "near")
    rounds = walks.walked(spark.createDataFrame([(3,), (999,)], "vid long"), degrees, near, 2, 1e-4, 10)
    assert len(rounds) == 3 and walks.ended(rounds, 10).count() == 2


def test_settled_plans_leave_no_shuffle_files(spark):
    files = lambda: sum(f.getName().startswith("shuffle_") for f in spark._jvm.scala.jdk.javaapi.CollectionConverters.asJava(spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()))
    before, kept = files(), spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled")
    df = settle(spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count())
    assert files() <= before and df.count() == 7
    assert spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled") == kept


def test_two_hop(spark):
    g = graph(spark, {(i, i + 1) for i in range(6)})
    s = spark.createDataFrame([(2,)], "src long")
    assert {r["vid"] for r in two_hop(g, s).collect()} == {0, 1, 2, 3, 4}
    assert {r["vid"] for r in two_hop(g, s, exact=True).collect()} == {0, 4}


@pytest.mark.parametrize("exact", [False, True])
def test_two_hop_in_slices_shuffles_no_pairs(spark, monkeypatch, exact):
    pairs = random_pairs(11, 50, 120) | {(-7, 3), (-7, 1 << 40)}
    g, near = graph(spark, pairs), {}
    for a, b in both_ways(pairs):
        near.setdefault(a, set()).add(b)
    s = [*range(0, 50, 3), -7, 1 << 40, 999]
    monkeypatch.setattr(graph_module, "CELL_ELEMENTS", 50)
    df = two_hop(g, spark.createDataFrame([(x,) for x in s], "src long"), exact)
    want = set()
    for x in s:
        one = near.get(x, set())
        two = set().union(*(near[y] for y in one))
        want |= {(x, v) for v in (two - one - {x} if exact else two | one | {x})}
    assert sorted((r["src"], r["vid"]) for r in df.collect()) == sorted(want)
    assert "Aggregate" not in df._jdf.queryExecution().executedPlan().toString().split("Exchange")[0]


def test_edge_map_modes(spark):
    g = graph(spark, random_pairs(5))
    front = spark.createDataFrame([(v,) for v in range(8)], "vid long")
    rows = [{tuple(r) for r in edge_map(g, front, lambda t: t.where("dst > 10"), m).select("dst", "src").collect()} for m in ("sparse", "dense")]
    assert rows[0] == rows[1] and rows[0]


def test_ids_at_the_ends_of_bitmaps(spark):
    ids = [-98304, -32769, -32768, -1, 0, 1, 32767, 32768, 65535, 65536, 1 << 40]
    subset = VertexSubset(spark.createDataFrame([(x,) for x in ids], "vid long"))
    dense = subset.to_dense()
    assert {(r["bucket"], r["n"]) for r in dense.select("bucket", F.call_function("bitmap_count", "bits").alias("n")).collect()} == {(1 + k, sum(x // 32768 == k for x in ids)) for k in {x // 32768 for x in ids}}
    assert rows(VertexSubset.from_dense(dense).frame, "vid") == [(x,) for x in ids]
    g = graph(spark, {(a, b) for a in ids for b in ids if a < b})
    assert rows(edge_map(g, subset.frame.where("vid <> 0"), mode="dense"), "dst", "src") == rows(edge_map(g, subset.frame.where("vid <> 0"), mode="sparse"), "dst", "src")


def test_insert_vertices_query_with_ids_that_are_there(spark, tmp_path):
    """The SQL lists an inserted id with degree 0, whether it was a vertex or not."""
    duck = connection(DATA)
    duck.execute(f"COPY (SELECT * REPLACE (500000 + k AS l_partkey) FROM (SELECT * FROM lineitem LIMIT 3), range(2) a(k)) TO '{tmp_path}/lineitem.parquet' (FORMAT parquet)")
    duck.execute(f"CREATE OR REPLACE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet'")
    assert_same(queries()["insert_vertices"](spark, str(tmp_path)), duck, oracle_sql()["insert_vertices"])
    g = graph(spark, {(1, 2)})
    assert rows(g.insert_vertices(spark.range(2, 4).withColumnRenamed("id", "vid")).vertices(), "vid", "deg") == [(1, 1), (2, 1), (3, 0)]


def test_updates(spark):
    edges = both_ways(random_pairs(6))
    g = Graph.from_edges(spark.createDataFrame(edges, "src long, dst long"), b=4)
    batch = [(1, "I", 1, 39), (2, "D", 1, 39), (3, "I", 2, 38), (4, "I", 2, 38), (5, "D", *edges[0]), (6, "I", *edges[0]), (7, "D", *edges[5]), (8, "D", 999, 1000)]
    got = {tuple(r) for r in g.apply(spark.createDataFrame(batch, "seq long, op string, src long, dst long")).edges().collect()}
    assert got == (set(edges) | {(2, 38)}) - {edges[5], (1, 39)}
    new = spark.createDataFrame([(500, 501), (501, 500)], "src long, dst long")
    back = g.insert_edges(new).delete_edges(new)
    layout = lambda x: sorted(map(tuple, x.chunks.select("owner", "head", "elems").collect()), key=repr)
    assert layout(back) == layout(g) and {r["vid"] for r in back.isolated.collect()} == {500, 501}


def test_empty_and_single(spark):
    g = Graph.from_edges(spark.createDataFrame([], "src long, dst long"), vertices=spark.createDataFrame([(7,)], "vid long"))
    assert tuple(g.counts().first()) == (1, 0)
    assert [(r["vid"], r["in_mis"]) for r in algorithms.mis(g).collect()] == [(7, True)]
    assert [tuple(r) for r in algorithms.bfs(g, 7).collect()] == [(7, 0, None)]


def test_store(spark):
    edges = both_ways(random_pairs(7))
    store = VersionStore(spark, scratch_dir(spark), b=4, buckets=8)
    store.publish(Graph.from_edges(spark.createDataFrame(edges, "src long, dst long"), b=4))
    held = store.acquire()
    for k in range(3):
        store.apply(spark.createDataFrame([(1, "I", 200 + k, 1), (2, "D", *edges[k])], "seq long, op string, src long, dst long"), batch_id=k)
    assert store.apply(spark.createDataFrame([(1, "I", 202, 1)], "seq long, op string, src long, dst long"), batch_id=2) == 3
    assert {tuple(r) for r in store.graph(held.version).edges().collect()} == set(edges)
    assert {tuple(r) for r in store.graph().edges().collect()} == (set(edges) | {(200, 1), (201, 1), (202, 1)}) - set(edges[:3])
    first, last = ({f["path"] for f in store.manifest(v)["files"]} for v in (0, 1))
    assert first & last  # untouched buckets are shared
    store.gc()
    assert {tuple(r) for r in store.graph(held.version).edges().collect()} == set(edges)
    assert store.release(held)
    store.gc()
    assert store.versions() == [3]


def test_two_writers_cannot_both_publish(spark):
    store = VersionStore(spark, scratch_dir(spark), b=4)
    store.publish(Graph.from_edges(spark.createDataFrame([(1, 2), (2, 1)], "src long, dst long"), b=4))
    parent, lost = store.manifest(), []

    def write(k):
        try:
            store._write(store.graph(0), parent, None, k, parent["buckets"])
        except WriterConflict:
            lost.append(k)

    threads = [threading.Thread(target=write, args=(k,)) for k in range(2)]
    [t.start() for t in threads]
    [t.join() for t in threads]
    assert len(lost) == 1 and store.versions() == [0, 1]


def test_baselines_hold_the_same_edges(spark):
    edges = both_ways(random_pairs(8, 20, 120))
    df = spark.createDataFrame(edges, "src long, dst long")
    b1 = baselines.BlockedListGraph.from_edges(df, block=4)
    new = spark.createDataFrame([(0, 77), (0, 78)], "src long, dst long")
    assert {tuple(r) for r in b1.insert(new).edges().collect()} == set(edges) | {(0, 77), (0, 78)}
    assert {tuple(r) for r in b1.insert(new).delete(new).edges().collect()} == set(edges)
    b2 = baselines.MultiSnapshotGraph(100).ingest(df).ingest(new)
    assert {tuple(r) for r in b2.edges().collect()} == set(edges) | {(0, 77), (0, 78)}
    assert {r["src"]: r["fragments"] for r in b2.fragmentation().collect()}[0] == 2
    chunked, btree = (min(x[3] for x in baselines.copy_costs(10**6) if x[0] == k) for k in ("chunked", "b_tree"))
    assert chunked < btree * 2 + 700


def test_published_memory_model(spark):
    got = {r["graph"]: (r["flat_gib"], r["plain_gib"]) for r in cost.published_memory(spark).collect()}
    for name, flat, plain in (("G1", 0.0722, 2.77), ("G3", 0.620, 73.5), ("G6", 53.1, 6889)):
        assert abs(got[name][0] / flat - 1) < 0.01 and abs(got[name][1] / plain - 1) < 0.01
    assert cost.ratios({"a": 2.0}, {"a": 4.0, "b": 1.0}) == {"a": 2.0, "average": 2.0}


def test_coding_saves_and_larger_chunks_save_more(spark):
    r = rmat(spark, 8, 6000)
    edges = r.select("src", "dst").where("src <> dst").distinct()
    size = [cost.memory_formats(Graph.from_edges(edges, b=b).chunks).first() for b in (2, 8, 64)]
    assert all(x["coded_bytes"] < x["chunked_bytes"] < x["plain_bytes"] for x in size)
    assert size[0]["coded_bytes"] > size[1]["coded_bytes"] > size[2]["coded_bytes"]


def test_posting_index(spark):
    from chunkgraph.operators.postings import PostingIndex

    texts = {k: f"{'red ' * (k % 2)}{'blue ' * (k % 3 > 0)}w{k}" for k in range(60)} | {60: None, 61: ""}
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    index = PostingIndex.build(df.where("doc_id < 30")).add_docs(df.where("doc_id >= 30"))
    red, blue = ({k for k, t in texts.items() if t and c in t} for c in ("red", "blue"))
    ids = lambda f: {r["doc_id"] for r in f.collect()}
    assert ids(index.and_("red", "blue")) == red & blue and ids(index.or_("red", "blue")) == red | blue and ids(index.minus("red", "blue")) == red - blue
    assert ids(index.remove_docs(df.where("doc_id < 10")).and_("red", "red")) == {k for k in red if k >= 10}


def directed(spark, pairs, **options):
    return Graph.from_edges(spark.createDataFrame(sorted(pairs), "src long, dst long"), directed=True, b=2, **options)


def rows(df, *columns):
    return sorted(map(tuple, df.select(*columns).collect()))


def test_directed_graphs(spark):
    edges = {(1, 2), (2, 3), (3, 1), (3, 4), (4, 3), (4, 9)}
    g = directed(spark, edges)
    assert rows(g.vertices(), "vid", "deg") == [(1, 1), (2, 1), (3, 2), (4, 2), (9, 0)]  # a sink is a vertex
    left = g.delete_vertices(spark.createDataFrame([(3,)], "vid long"))
    assert rows(left.edges(), "src", "dst") == [(1, 2), (4, 9)]
    assert rows(left.transposed().edges(), "src", "dst") == [(2, 1), (9, 4)]
    assert rows(left.vertices(), "vid") == [(1,), (2,), (4,), (9,)]
    got = {r["vid"]: r["level"] for r in algorithms.bfs(g, 1).collect()}
    assert got == {1: 0, 2: 1, 3: 2, 4: 3, 9: 4}
    long = directed(spark, {(k, k + 1) for k in range(25)} | {(25, 0)})
    assert {r["vid"]: r["level"] for r in algorithms.bfs(long, 0, "dense").collect()} == {k: k for k in range(26)}
    half = Graph.from_edges(spark.createDataFrame([(0, 1), (1, 2), (2, 0), (3, 0)], "src long, dst long"))
    with pytest.raises(ValueError):
        algorithms.bfs(half, 0)


def test_null_ends_are_no_edges(spark):
    df = spark.createDataFrame([(1, 2), (2, 1), (None, 1), (1, None), (None, None)], "src long, dst long")
    g = Graph.from_edges(df, vertices=spark.createDataFrame([(None,), (5,)], "vid long"))
    assert tuple(g.counts().first()) == (3, 2)
    assert tuple(g.insert_edges(df).counts().first()) == (3, 2) and tuple(g.delete_edges(df).counts().first()) == (3, 0)


@pytest.mark.parametrize("codec", ["plain", "delta", "bytecode"])
def test_store_keeps_all_of_a_graph(spark, codec):
    edges = {(1, 2), (2, 3), (3, 1), (3, 4), (-7, 2**40)}
    store = VersionStore(spark, scratch_dir(spark), b=2, buckets=4, codec=codec)
    store.publish(directed(spark, edges, vertices=spark.createDataFrame([(50,), (1,)], "vid long")))
    front = spark.createDataFrame([(1,), (-7,)], "vid long")
    for mode in ("sparse", "dense"):
        assert rows(edge_map(store.graph(), front, mode=mode), "dst", "src") == [(2, 1), (2**40, -7)]
    assert store.graph().codec == codec and rows(store.graph().vertices(), "vid") == [(-7,), (1,), (2,), (3,), (4,), (50,), (2**40,)]
    store.apply(spark.createDataFrame([(1, "D", 1, 2), (2, "D", 3, 4), (3, "I", 50, 1)], "seq long, op string, src long, dst long"), batch_id=5)
    assert rows(store.graph().edges(), "src", "dst") == sorted((edges | {(50, 1)}) - {(1, 2), (3, 4)})
    assert rows(store.graph().transposed().edges(), "src", "dst") == sorted((b, a) for a, b in (edges | {(50, 1)}) - {(1, 2), (3, 4)})
    assert rows(store.history(), "version", "n", "m") == [(0, 7, 5), (1, 7, 4)]
    near = store.graph(owners=spark.createDataFrame([(2,)], "owner long"))
    assert (2, 3) in rows(near.edges(), "src", "dst")


def test_weights_in_the_store(spark):
    df = spark.createDataFrame([(1, 2, 1.0), (1, 2, 2.0), (2, 5, 4.0)], "src long, dst long, weight double")
    store = VersionStore(spark, scratch_dir(spark), b=2, buckets=2)
    store.publish(Graph.from_edges(df, directed=True, b=2, weight="weight", combine="sum"))
    store.apply(spark.createDataFrame([(1, "I", 1, 2, 9.0), (2, "I", 1, 2, 5.0), (3, "D", 2, 5, 0.0)], "seq long, op string, src long, dst long, weight double"))
    assert rows(store.graph().edges(), "src", "dst", "weight") == [(1, 2, 5.0)] and store.graph().total_weight().first()[0] == 5.0


def test_readers_during_writes_see_whole_versions(spark):
    """Every batch moves the only edge of a star's centre: a reader that pins a version sees one edge, both ways, never two
    or none. A single copy that is overwritten in place (deletions first, then insertions) shows its readers states between."""
    store, seen, stop = VersionStore(spark, scratch_dir(spark), b=2, buckets=2), [], threading.Event()
    both = lambda v: [(0, v), (v, 0)]
    store.publish(Graph.from_edges(spark.createDataFrame(both(1), "src long, dst long"), b=2))

    def read():
        while not stop.is_set():
            held = store.acquire()
            seen.append((held.version, rows(store.graph(held.version).edges(), "src", "dst")))
            store.release(held)

    reader = threading.Thread(target=read)
    reader.start()
    for v in (2, 3, 4):
        batch = [(1, "D", *e) for e in both(v - 1)] + [(2, "I", *e) for e in both(v)]
        store.apply(spark.createDataFrame(batch, "seq long, op string, src long, dst long"), batch_id=v)
        store.gc()
    stop.set()
    reader.join()
    assert seen and all(edges == sorted(both(version + 1)) for version, edges in seen)
    path, between = scratch_dir(spark), []
    spark.createDataFrame(both(1), "src long, dst long").write.parquet(path)
    for step in ([], both(2)):  # the mutable copy: what was deleted is gone before the new edges are there
        spark.createDataFrame(step, "src long, dst long").write.mode("overwrite").parquet(path)
        between.append(rows(spark.read.schema("src long, dst long").parquet(path), "src", "dst"))
    assert between == [[], both(2)]


def test_codecs_give_the_same_chunks(spark):
    edges = both_ways(random_pairs(9)) + [(-3, -40), (-40, -3), (-3, 2**50), (2**50, -3)]
    df = spark.createDataFrame(edges, "src long, dst long")
    plain = Graph.from_edges(df, b=4)
    layout = lambda g: sorted(map(tuple, g.chunks.select("owner", "head", "lo", "hi", "cnt", "elems").collect()), key=repr)
    for codec in ("delta", "bytecode"):
        g = Graph.from_edges(df, b=4, codec=codec)
        assert g.codec == codec and layout(g.recoded("plain")) == layout(plain)
        new = spark.createDataFrame([(0, 500), (500, 0)], "src long, dst long")
        assert layout(g.insert_edges(new).delete_edges(new).recoded("plain")) == layout(plain)


def test_several_queries_on_one_snapshot(spark):
    """Queries that start from the same flat snapshot while another thread's query runs on it too."""
    pairs = random_pairs(12)
    g, got = graph(spark, pairs).flat_snapshot(), {}

    def run(v):
        got[v] = {r["vid"]: (r["level"], r["parent"]) for r in algorithms.bfs(g, v).collect()}

    threads = [threading.Thread(target=run, args=(v,)) for v in (0, 1, 2)]
    [t.start() for t in threads]
    [t.join() for t in threads]
    assert all(got[v] == plain_bfs(pairs, v) for v in (0, 1, 2))
    g.release()


@pytest.mark.parametrize("name", ["input_statistics", "memory_by_format", "chunk_size_sweep", "analyses", "scaling", "flat_snapshot_ablation", "direction_ablation", "batch_throughput", "concurrent_updates", "against_streaming_baselines", "against_static_baselines", "local_queries", "index_updates"])
def test_experiments_run(spark, name):
    from chunkgraph.workloads import experiments

    assert experiments.EXPERIMENTS[name](spark, DATA, **experiments.SMALL.get(name, {}))
