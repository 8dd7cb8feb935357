"""Analyses on a graph: BFS, single-source betweenness, maximal independent set, local clustering, batches of local queries.

All run on `edge_map`, so on any layout that a Graph can hold: chunked, plain, coded, flat, or the rows of a baseline.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.codec import opened
from ..functions.hashing import portable_hash
from ..plans.scratch import forget, settle
from . import sets, walks
from .graph import DENSE_SHARE, Graph, bucket_of, choose_mode, edge_map, out_pairs

#: Levels of a directed graph's BFS that are read one by one before they are written together.
LEVELS_TOGETHER = 8
#: Seeds of local clustering that are walked from together; their walks' states are on disk at once.
SEEDS_TOGETHER = 1 << 16


def _degrees(g: Graph) -> DataFrame:
    return g.chunks.groupBy(F.col("owner").alias("vid")).agg(F.sum(sets.weight()).cast("long").alias("deg"))


class _Search:
    """Levels of a breadth-first search. A round is one job that writes the new frontier, with each vertex's degree, and one
    that reads its size, edges and range of ids from what was written; these choose the next round's mode.

    In a symmetric graph a neighbour of a level is in it, in the one before or in the next, so only two levels are held
    against the targets; in a directed one all are, written together now and then.
    """

    def __init__(self, g: Graph, source: int, mode: str, share: int, values: dict | None = None, trace: list | None = None):
        self.g, self.mode, self.share, self.trace = g, mode, share, trace
        self.degrees = settle(_degrees(g))
        about = self.degrees.agg(F.coalesce(F.sum("deg"), F.lit(0)), F.count("*")).first()
        self.m, self.most = about[0], about[1] + 2
        start = g.chunks.sparkSession.range(1).select(F.lit(source).cast("long").alias("vid"), F.lit(0).alias("level"), *(v.alias(n) for n, v in (values or {}).items()))
        self.levels = [settle(start.join(self.degrees, "vid", "left").withColumn("deg", F.coalesce("deg", F.lit(0).cast("long"))))]
        self.old: DataFrame | None = None  # of a directed graph: all but the last levels
        self.recent = 1
        self._measure()

    def _measure(self) -> None:
        bucket = bucket_of("vid")
        self.size, self.out, self.buckets = self.levels[-1].agg(F.count("*"), F.coalesce(F.sum("deg"), F.lit(0)), F.count_distinct(bucket)).first()

    def _seen(self) -> DataFrame:
        if self.g.into is None:
            frames = self.levels[-2:]
        else:
            if self.recent > LEVELS_TOGETHER:
                self.old, self.recent = settle(self._all(self.levels)), 0
            frames = [*([] if self.old is None else [self.old]), *self.levels[len(self.levels) - self.recent :]]
        return self._all(frames).withColumnRenamed("vid", "dst")

    @staticmethod
    def _all(frames: list[DataFrame]) -> DataFrame:
        return reduce(DataFrame.unionByName, (f.select("vid") for f in frames))

    def step(self, update: dict, carried: tuple = ()) -> bool:
        """The next level, with the columns of the update; False when there is none."""
        level, how = len(self.levels), choose_mode(self.size, self.out, self.m, self.share) if self.mode == "auto" else self.mode
        if level > self.most:
            raise ValueError("more levels than vertices: an undirected graph without some of its reversed edges")
        if self.trace is not None:
            self.trace.append((level, how, self.size, self.out))
        seen = self._seen()
        found = edge_map(self.g, self.levels[-1].select("vid", *carried), lambda t: t.join(seen, "dst", "left_anti"), how, update, buckets=self.buckets)
        found = found.withColumnRenamed("dst", "vid").join(self.degrees, "vid", "left")
        self.levels.append(settle(found.select("vid", F.lit(level).alias("level"), *update, F.coalesce("deg", F.lit(0).cast("long")).alias("deg"))))
        self.recent += 1
        self._measure()
        if not self.size:
            forget(self.levels.pop())
        return bool(self.size)


def bfs(g: Graph, source: int, mode: str = "auto", share: int = DENSE_SHARE, trace: list | None = None, depth: int | None = None) -> DataFrame:
    """(vid, level, parent) of all vertices reached, or of those within `depth` levels; the parent is the least neighbour
    one level up. mode: sparse, dense or auto. trace gets (round, mode, frontier vertices, edges out of the frontier) for the cost tables."""
    search = _Search(g, source, mode, share, {"parent": F.lit(None).cast("long")}, trace)
    while (depth is None or len(search.levels) <= depth) and search.step({"parent": F.min("src")}):
        pass
    return reduce(DataFrame.unionByName, (f.select("vid", "level", "parent") for f in search.levels))


def bc(g: Graph, source: int, mode: str = "auto", share: int = DENSE_SHARE, trace: list | None = None) -> DataFrame:
    """(vid, level, sigma, delta) of all vertices reached: shortest paths from the source through each, and its dependency.

    Forward, a level's path counts are summed along its edges; backward, each level hands (1 + delta) / sigma to the one
    above, along the edges' other direction. Path counts are doubles; they overflow to infinity beyond about 10^308 paths.
    """
    search = _Search(g, source, mode, share, {"sigma": F.lit(1.0)}, trace)
    while search.step({"sigma": F.sum("sigma")}, ("sigma",)):
        pass
    back, levels = g.transposed(), [f.select("vid", "level", "sigma") for f in search.levels]
    done = [levels[-1].withColumn("delta", F.lit(0.0))]
    for upper in reversed(levels[:-1]):
        below = done[-1].select("vid", ((1 + F.col("delta")) / F.col("sigma")).alias("share"))
        above = upper.select(F.col("vid").alias("dst"))
        part = edge_map(back, below, lambda t: t.join(above, "dst", "left_semi"), "dense" if mode == "dense" else "sparse", {"share": F.sum("share")})  # noqa: B023
        delta = upper.join(part.withColumnRenamed("dst", "vid"), "vid", "left")
        done.append(settle(delta.select("vid", "level", "sigma", (F.col("sigma") * F.coalesce("share", F.lit(0.0))).alias("delta"))))
    out = reduce(DataFrame.unionByName, done)
    return out.withColumn("delta", F.when(F.col("vid") == source, 0.0).otherwise(F.col("delta")))


def mis(g: Graph, seed: int = 3, mode: str = "sparse") -> DataFrame:
    """(vid, in_mis): the greedy maximal independent set in order of (hash, id); isolated vertices are in. For symmetric graphs.

    A round decides every undecided vertex whose priority is least among its undecided neighbours, and their neighbours.
    """
    decided = [] if g.isolated is None else [g.isolated.select("vid", F.lit(True).alias("in_mis"))]
    open_ = settle(g.chunks.select(F.col("owner").alias("vid")).distinct().select("vid", portable_hash(F.col("vid"), seed).alias("h")))
    while open_.take(1):
        own = open_.select(F.col("vid").alias("dst"))
        among = lambda t: t.join(own, "dst", "left_semi")  # noqa: B023, E731
        least = F.min(F.when(F.col("src") != F.col("dst"), F.struct(F.col("h"), F.col("src").alias("vid"))))
        near = edge_map(g, open_, among, mode, {"least": least}).withColumnRenamed("dst", "vid")
        joins = settle(open_.join(near, "vid", "left").where(F.col("least").isNull() | (F.struct("h", "vid") < F.col("least"))).select("vid"))
        out = edge_map(g, joins, among, mode).select(F.col("dst").alias("vid"))
        now = joins.select("vid", F.lit(True).alias("in_mis")).unionByName(out.join(joins, "vid", "left_anti").select("vid", F.lit(False).alias("in_mis")))
        now, last = settle(now), open_
        decided.append(now)
        open_ = settle(last.join(now.select("vid"), "vid", "left_anti"))
        forget(last)
        forget(joins)
    if not decided:
        return open_.select("vid", F.lit(True).alias("in_mis"))
    return reduce(DataFrame.unionByName, decided)


def mis_violations(g: Graph, chosen: DataFrame) -> DataFrame:
    """One row: edges with both ends in the set, and vertices outside it without a neighbour in it."""
    edges = g.edges().where("src <> dst")
    inside = chosen.where("in_mis").select("vid")
    both = edges.join(inside.withColumnRenamed("vid", "src"), "src", "left_semi").join(inside.withColumnRenamed("vid", "dst"), "dst", "left_semi")
    covered = edges.join(inside.withColumnRenamed("vid", "dst"), "dst", "left_semi").select(F.col("src").alias("vid"))
    bare = chosen.where("NOT in_mis").select("vid").join(covered, "vid", "left_anti")
    return both.agg(F.count("*").alias("edges_inside")).join(bare.agg(F.count("*").alias("uncovered")), how="cross")  # one row each


def _near(g: Graph, degrees: DataFrame, eps: float) -> DataFrame:
    """(vid, near, to): each vertex's neighbours with their degrees, unless its own is over 1/eps (it never passes mass on);
    and its edges to ends of no smaller degree (then id), loops too: at most about the square root of twice the number of edges.

    Every vertex sends its degree to those that have it as a neighbour, so edges are shuffled once."""
    own = g.in_chunks.join(degrees.withColumnRenamed("vid", "owner"), "owner", "left").withColumn("deg", F.coalesce("deg", F.lit(0).cast("long")))
    sent = opened(own).select(F.explode(sets.all_elems()).alias("vid"), F.struct(F.col("owner").alias("dst"), F.col("deg").alias("far")).alias("x"))
    hubs = degrees.where(~(F.lit(1.0) >= eps * F.col("deg"))).withColumnRenamed("deg", "hub")
    no_less = lambda deg, x: F.struct(deg.alias("deg"), F.col("vid")) <= F.struct(x["far"].alias("deg"), x["dst"].alias("vid"))
    kept = sent.join(hubs, "vid", "left").where(F.col("hub").isNull() | no_less(F.col("hub"), F.col("x")))
    lists = kept.repartition("vid").groupBy("vid").agg(F.max("hub").alias("hub"), F.collect_list("x").alias("all"))
    deg = F.coalesce("hub", F.size("all").cast("long"))
    near = F.when(F.col("hub").isNull(), F.col("all")).otherwise(F.slice("all", 1, 0)).alias("near")
    return lists.select("vid", near, F.transform(F.filter("all", lambda x: no_less(deg, x)), lambda x: x["dst"]).alias("to"))


def walk(g: Graph, seeds: DataFrame, eps: float = 1e-6, steps: int = 10, degrees: DataFrame | None = None) -> DataFrame:
    """(seed, vid, p): truncated lazy random walks from all seeds at once. Mass below eps times the degree is dropped; a
    walk without mass above it keeps its last state."""
    degrees = settle(_degrees(g)) if degrees is None else degrees
    near, seeds = settle(_near(g, degrees, eps)), seeds.select("vid").distinct()
    rounds = walks.walked(seeds, degrees, near.select("vid", "near"), walks.batches_of(seeds.count(), eps) or 1, eps, steps)
    state = walks.ended(rounds, steps).select("seed", F.explode(F.arrays_zip("vids", "ps")).alias("x"))
    return state.select("seed", F.col("x.vids").alias("vid"), F.col("x.ps").alias("p"))


def _downhill(g: Graph, degrees: DataFrame) -> DataFrame:
    """(owner, to): each edge of a symmetric graph at its end of smaller degree (then id), loops too; one list a vertex,
    of at most about the square root of twice the number of edges."""
    far = degrees.select(F.col("vid").alias("dst"), F.col("deg").alias("far"))
    own = out_pairs(g.chunks, degrees.select("vid", "deg")).join(far, "dst")
    kept = own.where(F.struct("deg", "src") <= F.struct(F.col("far").alias("deg"), F.col("dst").alias("src")))
    return kept.groupBy(F.col("src").alias("owner")).agg(F.collect_list("dst").alias("to"))


def _ranked(state: DataFrame, degrees: DataFrame) -> DataFrame:
    by = Window.partitionBy("seed").orderBy(F.desc("score"), "vid")
    scored = state.join(degrees, "vid").withColumn("score", F.round(F.col("p") / F.col("deg"), 12))
    return scored.select("seed", "vid", "deg", F.row_number().over(by).alias("rank"))


def _prefixes(g: Graph, ranked: DataFrame, degrees: DataFrame, downhill: DataFrame | None) -> DataFrame:
    total = degrees.agg(F.sum("deg").alias("m"))
    other = ranked.select("seed", F.col("vid").alias("elem"), F.col("rank").alias("other"))
    # an edge between ranks i < j is cut by the prefixes i .. j-1; an edge out of the support by all from i on
    if downhill is None:
        leaving = out_pairs(g.chunks, ranked.select("vid", "seed", "rank")).select("seed", "rank", F.col("dst").alias("elem"))
        ends = leaving.join(other, ["seed", "elem"], "left")
        change = F.when(F.col("other").isNull() | (F.col("other") > F.col("rank")), 1).when(F.col("other") < F.col("rank"), -1).otherwise(0)
        steps, own = ends.groupBy("seed", "rank").agg(F.sum(change).alias("cut_step")), F.lit(0)
    else:
        # all edges of a vertex count as leaving, and each inside the support takes two back where its later end is: so
        # only edges inside are looked for, each from one end
        inside = ranked.withColumnRenamed("vid", "owner").join(downhill, "owner").select("seed", "rank", F.explode("to").alias("elem")).join(other, ["seed", "elem"])
        change = F.when(F.col("other") == F.col("rank"), -1).otherwise(-2)
        steps, own = inside.groupBy("seed", F.greatest("rank", "other").alias("rank")).agg(F.sum(change).alias("cut_step")), F.col("deg")
    upto = Window.partitionBy("seed").orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
    rows = ranked.join(steps, ["seed", "rank"], "left").withColumn("cut", F.sum(own + F.coalesce("cut_step", F.lit(0))).over(upto)).withColumn("vol", F.sum("deg").over(upto))
    least = F.least(F.col("vol"), F.col("m") - F.col("vol"))
    return rows.join(F.broadcast(total), how="cross").select("seed", "rank", "vid", F.when(least > 0, F.col("cut") / least).otherwise(F.lit(1.0)).alias("conductance"))


def sweep(g: Graph, state: DataFrame) -> DataFrame:
    """(seed, rank, vid, conductance): prefixes by p/deg (then id) of each seed's walk, with the conductance of each."""
    degrees = settle(_degrees(g))
    return _prefixes(g, settle(_ranked(state, degrees)), degrees, None if g.into is not None else _downhill(g, degrees))


def _best(prefixes: DataFrame) -> DataFrame:
    best = prefixes.groupBy("seed").agg(F.min(F.struct(F.round("conductance", 12).alias("c"), F.col("rank").alias("r"))).alias("best"))
    return prefixes.join(best, "seed").where(F.col("rank") <= F.col("best.r")).select("seed", "vid", F.col("best.c").alias("conductance"))


def local_cluster(g: Graph, seeds: DataFrame, eps: float = 1e-6, steps: int = 10) -> DataFrame:
    """(seed, vid, conductance): members of the first prefix of least conductance. Seeds go in groups, one after another,
    and a group leaves its members alone on disk."""
    seeds, degrees = settle(seeds.select("vid").distinct()), settle(_degrees(g))
    count = seeds.count()
    groups, done = max(1, -(-count // SEEDS_TOGETHER)), []
    near, total = settle(_near(g, degrees, eps)), degrees.agg(F.coalesce(F.sum("deg"), F.lit(0))).first()[0]
    batches = max(1, walks.batches_of(-(-count // groups), eps))
    for k in range(groups):
        some = seeds.where(F.pmod(F.xxhash64("vid"), F.lit(groups)) == k)
        rounds = walks.walked(some, degrees, near.select("vid", "near"), batches, eps, steps)
        if g.into is None:
            done.append(settle(walks.clusters(rounds, near.where(F.size("to") > 0).select("vid", "to"), total, steps)))
        else:
            state = walks.ended(rounds, steps).select("seed", F.explode(F.arrays_zip("vids", "ps")).alias("x"))
            ranked = settle(_ranked(state.select("seed", F.col("x.vids").alias("vid"), F.col("x.ps").alias("p")), degrees))
            prefixes = settle(_prefixes(g, ranked, degrees, None))
            done.append(settle(_best(prefixes)))
            forget(ranked)
            forget(prefixes)
        for f in rounds:
            forget(f)
    return reduce(DataFrame.unionByName, done)
