"""Graphs as chunked neighbour sets, vertex subsets, and the frontier interface."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.codec import codec_of, coded, opened
from ..plans.scratch import settle
from . import sets

#: How many bitmaps of a frontier (4 KiB for 32,768 ids each) are broadcast; beyond, they are joined by a shuffle.
MOST_BITMAPS = 1 << 14
#: A frontier is dense when its vertices and their edges are over this share of all edges.
DENSE_SHARE = 20
#: Blocks of two-hop sources, elements of lists that one of their tasks holds, and rows it gives at once.
TWO_HOP_BLOCKS, CELL_ELEMENTS, TWO_HOP_ROWS = 32, 1 << 23, 1 << 16


@dataclass(frozen=True)
class Graph:
    """Immutable; every update gives a new Graph that shares what it did not touch.

    chunks: see `sets` (owner = source vertex), in any codec. isolated: vertices without edges. weighted graphs have vals
    and agg. Edges with a null end are no edges. A directed graph holds its in-neighbours too; a vertex with in-edges
    alone is a vertex of degree 0.
    """

    chunks: DataFrame
    b: int = sets.DEFAULT_B
    seed: int = 0
    isolated: DataFrame | None = None
    into: DataFrame | None = None  # chunks of in-neighbours of a directed graph; None: the graph is symmetric
    flat: bool = False

    @staticmethod
    def from_edges(
        edges: DataFrame, directed: bool = False, b: int = sets.DEFAULT_B, seed: int = 0, weight: str | None = None, combine: str = "last",
        vertices: DataFrame | None = None, order: str | None = None, span: int | None = None, codec: str = "plain",
    ) -> "Graph":
        """edges: src, dst[, weight]. Undirected input is expected symmetrised (both directions present).

        order: of parallel edges, for combine last and first. span: deals a vertex's neighbours over tasks by ranges of
        ids, for graphs whose largest list is too long for one. codec: see `codec`.
        """
        more = [*([F.col(weight).alias("val")] if weight else []), *([F.col(order).alias("_order")] if order else [])]
        side = lambda x, y: sets.build(edges.select(F.col(x).alias("owner"), F.col(y).alias("elem"), *more), b, seed, combine, "_order" if order else None, span, codec)
        g = Graph(side("src", "dst"), b, seed, None, side("dst", "src") if directed else None)
        return g if vertices is None else g.insert_vertices(vertices)

    @property
    def in_chunks(self) -> DataFrame:
        return self.chunks if self.into is None else self.into

    def ends(self, among: DataFrame | None = None) -> DataFrame:
        """(vid) of all vertices that have an edge, in or out; of those among some (vid)."""
        owners = [c.select(F.col("owner").alias("vid")) for c in (self.chunks, self.into) if c is not None]
        if among is not None:
            owners = [o.join(among, "vid", "left_semi") for o in owners]
        return (owners[0] if len(owners) == 1 else owners[0].unionByName(owners[1])).distinct()

    def vertices(self) -> DataFrame:
        """vid, deg (out-degree), n_heads, prefix_cnt."""
        out = self.chunks.groupBy(F.col("owner").alias("vid")).agg(
            F.sum(sets.weight()).cast("long").alias("deg"), F.count("head").alias("n_heads"), F.sum(F.when(F.col("head").isNull(), F.col("cnt")).otherwise(0)).cast("long").alias("prefix_cnt")
        )
        zero, bare = F.lit(0).cast("long"), self.isolated
        if self.into is not None:
            sinks = self.into.select(F.col("owner").alias("vid")).distinct().join(out.select("vid"), "vid", "left_anti")
            bare = sinks if bare is None else bare.select("vid").unionByName(sinks)
        return out if bare is None else out.unionByName(bare.select("vid", zero.alias("deg"), zero.alias("n_heads"), zero.alias("prefix_cnt")))

    def vertex_chunks(self, b: int, span: int | None = None) -> DataFrame:
        """The vertex set as one chunked set (owner 0) with each vertex's degree as its value, so that a chunk's `agg` is
        the number of edges of its vertices."""
        return sets.build(self.vertices().select(F.lit(0).cast("long").alias("owner"), F.col("vid").alias("elem"), F.col("deg").alias("val")), b, self.seed, span=span)

    def counts(self) -> DataFrame:
        """One row: n (with isolated vertices), m."""
        return self.vertices().agg(F.count("*").alias("n"), F.coalesce(F.sum("deg"), F.lit(0)).alias("m"))

    def edges(self) -> DataFrame:
        out = sets.entries(self.chunks)
        return out.select(F.col("owner").alias("src"), F.col("elem").alias("dst"), *([F.col("val").alias("weight")] if "val" in out.columns else []))

    def neighbors(self, vid: int) -> DataFrame:
        return sets.entries(self.chunks.where(F.col("owner") == vid)).select(F.col("elem").alias("vid"))

    def degree(self, vid: int) -> DataFrame:
        return self.chunks.where(F.col("owner") == vid).agg(F.coalesce(F.sum(sets.weight()), F.lit(0)).cast("long").alias("deg"))

    def find_vertex(self, vid: int) -> DataFrame:
        return self.vertices().where(F.col("vid") == vid)

    def total_weight(self) -> DataFrame:
        """Sum of all weights from the chunks' stored sums."""
        return self.chunks.agg(F.sum("agg").alias("total_weight"))

    # ------------------------------------------------------------------------------------------------------- updates

    def _both(self, batch: DataFrame, columns: list, f) -> tuple[DataFrame, DataFrame | None]:
        """f(chunks, batch as owner, elem, ...) on the out- and, for a directed graph, the in-neighbours."""
        side = lambda x, y: batch.select(F.col(x).alias("owner"), F.col(y).alias("elem"), *columns)
        return f(self.chunks, side("src", "dst")), None if self.into is None else f(self.into, side("dst", "src"))

    def insert_edges(self, batch: DataFrame, combine: str = "last", order: str | None = None) -> "Graph":
        """batch: src, dst[, weight], duplicates allowed (folded by `order` for last and first); an edge that exists has
        its weight folded with the batch's."""
        has = "vals" in self.chunks.columns
        columns = [*([F.col("weight").alias("val")] if has else []), *([F.col(order).alias("_order")] if order else [])]
        chunks, into = self._both(batch, columns, lambda old, new: sets.multi_insert(old, new, self.b, self.seed, combine, "_order" if order else None))
        alone = self.isolated
        if alone is not None:
            edges = batch.where("src IS NOT NULL AND dst IS NOT NULL")
            alone = alone.join(edges.select(F.explode(F.array("src", "dst")).alias("vid")).distinct(), "vid", "left_anti")
        return replace(self, chunks=chunks, into=into, isolated=alone, flat=False)

    def delete_edges(self, batch: DataFrame) -> "Graph":
        """Vertices that lose their last edge stay, isolated."""
        chunks, into = self._both(batch, [], lambda old, new: sets.multi_delete(old, new, self.b, self.seed))
        return self._without(chunks, into, batch.select(F.explode(F.array("src", "dst")).alias("vid")).distinct())

    def _without(self, chunks: DataFrame, into: DataFrame | None, hit: DataFrame) -> "Graph":
        """With fewer edges at the vertices hit: those that have none any more are isolated."""
        out = replace(self, chunks=chunks, into=into, flat=False)
        bare = self.ends(hit).join(out.ends(hit), "vid", "left_anti")
        return replace(out, isolated=bare if self.isolated is None else self.isolated.select("vid").unionByName(bare).distinct())

    def insert_vertices(self, vids: DataFrame) -> "Graph":
        wanted = vids.select("vid").where("vid IS NOT NULL").distinct()
        new = wanted.join(self.ends(wanted), "vid", "left_anti")
        return replace(self, isolated=new if self.isolated is None else self.isolated.select("vid").unionByName(new).distinct())

    def delete_vertices(self, vids: DataFrame) -> "Graph":
        """The vertices go with all edges at either end; neighbours stay, isolated if these were their only edges. Only
        the lists of the vertices and of their neighbours are opened."""
        gone = vids.select("vid").distinct()
        owned = gone.withColumnRenamed("vid", "owner")

        def left(chunks, back):
            """chunks without the lists of the vertices, and without them in the lists of those in `back` that name them."""
            dead = out_pairs(back, gone).select(F.col("dst").alias("owner"), F.col("src").alias("elem"))
            return sets.multi_delete(chunks.join(owned, "owner", "left_anti"), dead.join(owned, "owner", "left_anti"), self.b, self.seed)

        chunks = left(self.chunks, self.in_chunks)
        into = None if self.into is None else left(self.into, self.chunks)
        near = out_pairs(self.chunks, gone).select(F.col("dst").alias("vid"))
        near = near if self.into is None else near.unionByName(out_pairs(self.into, gone).select(F.col("dst").alias("vid")))
        out = self._without(chunks, into, near.unionByName(gone).distinct())
        return replace(out, isolated=out.isolated.join(gone, "vid", "left_anti"))

    def apply(self, updates: DataFrame) -> "Graph":
        """updates: seq, op ('I' or 'D'), src, dst[, weight]; of one edge's operations the one of largest seq counts."""
        last = settle(updates.groupBy("src", "dst").agg(F.max_by(F.struct("op", *[c for c in ("weight",) if c in updates.columns]), "seq").alias("u")).select("src", "dst", "u.*"))
        return self.delete_edges(last.where("op = 'D'")).settled().insert_edges(last.where("op = 'I'")).settled()

    def settled(self) -> "Graph":
        """The same graph, written out: later plans start from files, not from all updates so far."""
        keep = lambda df: None if df is None else settle(df)
        return replace(self, chunks=settle(self.chunks), into=keep(self.into), isolated=keep(self.isolated))

    # --------------------------------------------------------------------------------------------------------- layout

    @property
    def codec(self) -> str:
        return codec_of(self.chunks)

    def recoded(self, codec: str) -> "Graph":
        change = lambda df: None if df is None else coded(opened(df), codec)
        return replace(self, chunks=change(self.chunks), into=change(self.into), flat=False)

    def flat_snapshot(self) -> "Graph":
        """The chunk rows, opened and kept in memory, for many queries; dealt by vertex and head, so that a hub's chunks are
        in all partitions."""
        kept = lambda df: opened(df).repartition("owner", "head").persist()
        return replace(self, chunks=kept(self.chunks), into=None if self.into is None else kept(self.into), flat=True)

    def transposed(self) -> "Graph":
        return self if self.into is None else replace(self, chunks=self.into, into=self.chunks)

    def release(self) -> None:
        if self.flat:
            self.chunks.unpersist()
            if self.into is not None:
                self.into.unpersist()


def bucket_of(vid: str) -> Column:
    """Bucket k holds the 32,768 ids from (k - 1) * 32,768 on, negative ones too."""
    return F.shiftright(F.col(vid).cast("long"), 15) + 1


def place_of(vid: str) -> Column:
    """An id's bit in the bitmap of its bucket."""
    return F.col(vid).bitwiseAND(F.lit(32767).cast("long"))


class VertexSubset:
    """A set of vertices: a frame of ids (sparse), or bitmaps (dense)."""

    def __init__(self, frame: DataFrame):
        self.listed = frame.select("vid").where("vid IS NOT NULL")

    @property
    def frame(self) -> DataFrame:
        """Each vertex once."""
        return self.listed.distinct()

    def size(self) -> DataFrame:
        return self.frame.agg(F.count("*").alias("size"))

    def to_dense(self) -> DataFrame:
        """(bucket, bits): one bitmap a bucket of 32,768 ids."""
        return self.listed.groupBy(bucket_of("vid").alias("bucket")).agg(F.call_function("bitmap_construct_agg", place_of("vid")).alias("bits"))

    @staticmethod
    def from_dense(bitmaps: DataFrame) -> "VertexSubset":
        """The ids of `to_dense` again."""
        place = F.explode(F.sequence(F.lit(0), F.octet_length("bits") * 8 - 1)).alias("p")
        byte = F.conv(F.hex(F.substring("bits", F.shiftright("p", 3) + 1, F.lit(1))), 16, 10).cast("int")
        set_ = bitmaps.select("bucket", "bits", place).where(F.call_function("getbit", byte, F.col("p").bitwiseAND(7)) == 1)
        return VertexSubset(set_.select(((F.col("bucket") - 1) * 32768 + F.col("p")).cast("long").alias("vid")))

    def union(self, other: "VertexSubset") -> "VertexSubset":
        return VertexSubset(self.frame.unionByName(other.frame))

    def intersect(self, other: "VertexSubset") -> "VertexSubset":
        return VertexSubset(self.frame.join(other.frame, "vid", "left_semi"))

    def minus(self, other: "VertexSubset") -> "VertexSubset":
        return VertexSubset(self.frame.join(other.frame, "vid", "left_anti"))


def _frame(subset) -> DataFrame:
    return subset.frame if isinstance(subset, VertexSubset) else subset


def vertex_filter(subset, condition: Column, about: DataFrame | None = None) -> VertexSubset:
    """The vertices of a subset that meet a condition on their columns, or on those of `about` (vid, ...)."""
    frame = _frame(subset)
    return VertexSubset((frame if about is None else frame.join(about, "vid")).where(condition))


def vertex_map(subset, **columns: Column) -> DataFrame:
    """The subset with a value computed for each vertex."""
    return _frame(subset).withColumns(columns)


def frontier_bitmaps(frontier: DataFrame) -> DataFrame:
    """(bucket, words): the bitmaps of `VertexSubset.to_dense` as 512 words of 64 bits each."""
    word = lambda k: F.conv(F.hex(F.substring("bits", k * 8 + 1, F.lit(8))), 16, -10).cast("long")
    return VertexSubset(frontier).to_dense().select("bucket", F.transform(F.sequence(F.lit(0), F.lit(511)), word).alias("words"))


def in_bitmap(words: str, vid: str) -> Column:
    """Is an id in its bucket's bitmap? Words are read from their first byte, so bytes count from the top."""
    at = place_of(vid)
    return F.call_function("getbit", F.get(words, F.shiftright(at, 6).cast("int")), at.bitwiseAND(63).bitwiseXOR(56).cast("int")) == 1


def out_pairs(chunks: DataFrame, frontier: DataFrame) -> DataFrame:
    """(src, dst, ...) of all edges that leave the frontier (vid, ...), with the frontier's other columns, once for each of
    its rows. The frontier meets the chunk table first, so only its vertices' chunks are opened."""
    extra = [c for c in frontier.columns if c != "vid"]
    met = chunks.join(frontier.withColumnRenamed("vid", "owner"), "owner", "inner" if extra else "left_semi")
    return opened(met).select(F.col("owner").alias("src"), F.explode(sets.all_elems()).alias("dst"), *extra)


def out_work(g: Graph, frontier: DataFrame) -> tuple[int, int, int]:
    """(vertices of the frontier, edges out of it, all edges)."""
    mark = frontier.select(F.col("vid").alias("owner"), F.lit(1).alias("_f")).distinct()
    row = g.chunks.join(mark, "owner", "left").agg(F.coalesce(F.sum(F.when(F.col("_f") == 1, sets.weight())), F.lit(0)).alias("out"), F.coalesce(F.sum(sets.weight()), F.lit(0)).alias("m")).first()
    return frontier.select("vid").distinct().count(), row["out"], row["m"]


def choose_mode(size: int, out_edges: int, m: int, share: int = DENSE_SHARE) -> str:
    return "dense" if size + out_edges > m / share else "sparse"


def edge_map(g: Graph, frontier, allowed=None, mode: str = "auto", update: dict[str, Column] | None = None, accept: Column | None = None, share: int = DENSE_SHARE, buckets: int | None = None) -> DataFrame:
    """Applies an update along all edges from a frontier to allowed targets: (dst, one column a name in `update`).

    frontier: a VertexSubset, or a frame (vid, ...) whose other columns the update can read. allowed(frame with dst) ->
    frame: the condition on targets, as a join or filter. update: aggregates over a target's edges, on src, dst and the
    frontier's columns; by default src, the least source. accept: a condition on the aggregates; targets where it holds
    are the new subset (`VertexSubset(out.withColumnRenamed("dst", "vid"))`).

    sparse: edges leave the frontier and are shuffled by target, after a map-side aggregate. dense: every allowed target
    looks through its own in-neighbours; without columns to carry, membership is a test against the frontier's bitmaps,
    which are broadcast, so that no edge is moved. auto chooses by the frontier's size and edges against m / share.
    All give the same rows. buckets: number of the frontier's bitmaps, if known.
    """
    frame = _frame(frontier)
    update = update or {"src": F.min("src")}
    extra = [c for c in frame.columns if c != "vid"]
    if mode == "auto":
        mode = choose_mode(*out_work(g, frame), share)
    if mode == "dense":
        targets = g.in_chunks.withColumnRenamed("owner", "dst")
        near = opened(allowed(targets) if allowed else targets).select("dst", F.explode(sets.all_elems()).alias("src"))
        if extra:
            pairs = near.join(frame.withColumnRenamed("vid", "src"), "src")
        else:
            bitmaps = frontier_bitmaps(frame)
            count = frame.agg(F.count_distinct(bucket_of("vid"))).first()[0] if buckets is None else buckets
            met = near.withColumn("bucket", bucket_of("src")).join(F.broadcast(bitmaps) if count <= MOST_BITMAPS else bitmaps, "bucket")
            pairs = met.where(in_bitmap("words", "src"))
        out = pairs.groupBy("dst").agg(*(c.alias(n) for n, c in update.items()))
    else:
        found = out_pairs(g.chunks, frame).groupBy("dst").agg(*(c.alias(n) for n, c in update.items()))
        out = allowed(found) if allowed else found
    return out if accept is None else out.where(accept)


def _two_hop_rows(slices: int, exact: bool):
    """Rows of whole cells, in each the lists first (near null), then the sources with their neighbours: (src, vid)."""
    schema = pa.schema([("src", pa.int64()), ("vid", pa.int64())])

    def reached(src, near, lists, slice_):
        own = np.array([src, *near], np.int64)
        two = [part for v in near for part in lists.get(v, ())]
        if exact:
            return np.setdiff1d(np.concatenate(two), own) if two else own[:0]
        return np.unique(np.concatenate([own[slice_of(own, slices) == slice_], *two]))

    def run(batches):
        cell, lists, src, near, out, size = None, {}, None, [], [], 0

        def flush():
            vids = np.concatenate([v for _, v in out])
            srcs = np.repeat(np.array([s for s, _ in out], np.int64), [len(v) for _, v in out])
            for k in range(0, len(vids), TWO_HOP_ROWS):
                yield pa.RecordBatch.from_arrays([pa.array(srcs[k : k + TWO_HOP_ROWS]), pa.array(vids[k : k + TWO_HOP_ROWS])], schema=schema)

        for batch in batches:
            cells, srcs, vids = (batch.column(k).to_pylist() for k in (0, 1, 2))
            elems = batch.column(3)
            values, edge = elems.values.to_numpy(zero_copy_only=False), elems.offsets.to_pylist()
            for r, (c, s, v) in enumerate(zip(cells, srcs, vids)):
                if src is not None and (c, s) != (cell, src):
                    found = reached(src, near, lists, cell % slices)
                    out.append((src, found))
                    size += len(found)
                    src, near = None, []
                    if size >= TWO_HOP_ROWS:
                        yield from flush()
                        out, size = [], 0
                if c != cell:
                    cell, lists = c, {}
                if s is None:
                    lists.setdefault(v, []).append(values[edge[r] : edge[r + 1]])
                else:
                    src = s
                    if v is not None:
                        near.append(v)
        if src is not None:
            out.append((src, reached(src, near, lists, cell % slices)))
        if out:
            yield from flush()

    return run, "src long, vid long"


def slice_of(ids: np.ndarray, slices: int) -> np.ndarray:
    return (ids ^ (ids >> 15)) % slices


def two_hop(g: Graph, sources: DataFrame, exact: bool = False) -> DataFrame:
    """sources (src) -> (src, vid): the source, its neighbours and theirs; with exact, the ring at two hops alone. Only the
    chunks of the sources and of their neighbours are opened.

    Sources are dealt to blocks and targets to slices. A cell, a block and a slice, gets the lists of its sources'
    neighbours, each once, and finds a source's targets there; so what is shuffled are lists, never the pairs found.
    """
    s = sources.select("src").where("src IS NOT NULL").distinct()
    one = settle(out_pairs(g.chunks, s.select(F.col("src").alias("vid"), F.col("src").alias("q"))).select(F.col("q").alias("src"), F.col("dst").alias("vid")).unionByName(s.withColumn("vid", F.lit(None).cast("long"))))
    block = F.pmod(F.xxhash64("src"), F.lit(TWO_HOP_BLOCKS))
    asked = one.where("vid IS NOT NULL").select(block.alias("block"), "vid").distinct()
    total = g.chunks.join(asked.select(F.col("vid").alias("owner")).distinct(), "owner", "left_semi").agg(F.coalesce(F.sum(sets.weight()), F.lit(0))).first()[0]
    slices = max(1, -(-total // CELL_ELEMENTS))
    cell, every = (F.col("block") * slices + F.col("k")).cast("int").alias("cell"), F.explode(F.sequence(F.lit(0), F.lit(slices - 1)))
    met = opened(g.chunks.join(asked.withColumnRenamed("vid", "owner"), "owner")).select("block", F.col("owner").alias("vid"), sets.all_elems().alias("elems"))
    place = lambda x: F.pmod(x.bitwiseXOR(F.shiftright(x, 15)), F.lit(slices))
    if slices == 1:
        lists = met.withColumn("k", F.lit(0))
    else:
        lists = met.withColumn("k", every).select("block", "vid", "k", F.filter("elems", lambda x: place(x) == F.col("k")).alias("elems")).where(F.size("elems") > 0)
    lists = lists.select(cell, F.lit(None).cast("long").alias("src"), "vid", "elems")
    asking = one.withColumn("block", block).withColumn("k", every).select(cell, "src", "vid", F.lit(None).cast("array<long>").alias("elems"))
    rows = lists.unionByName(asking).repartitionById(TWO_HOP_BLOCKS * slices, F.col("cell")).sortWithinPartitions("cell", F.asc_nulls_first("src"))
    return rows.mapInArrow(*_two_hop_rows(slices, exact))


def two_hop_work(g: Graph, sources: DataFrame) -> DataFrame:
    """One row: chunks of the graph, chunks that a two-hop query opens at most, edges that it reads."""
    s = sources.select("src").distinct()
    one = out_pairs(g.chunks, s.withColumnRenamed("src", "vid")).select(F.col("dst").alias("vid"))
    reached = s.withColumnRenamed("src", "vid").unionByName(one).distinct().select(F.col("vid").alias("owner"), F.lit(1).alias("_f"))
    hit = F.col("_f").isNotNull()
    return g.chunks.join(reached, "owner", "left").agg(F.count("*").alias("chunks"), F.sum(hit.cast("long")).alias("opened"), F.sum(F.when(hit, sets.weight()).otherwise(0)).cast("long").alias("edges_read"))
