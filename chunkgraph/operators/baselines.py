"""What the chunked graph is compared with: blocked lists, chained snapshots, static rows, offsets, and copy-cost models."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import sets
from .graph import Graph

BLOCK = 16
#: Bytes of a vertex entry, of an edge slot, and of a link between blocks, for the baselines' memory.
VERTEX_BYTES, SLOT_BYTES, LINK_BYTES = 8, 4, 8


def plain_graph(edges: DataFrame) -> Graph:
    """One element a node: every element is a head (b = 1)."""
    return Graph.from_edges(edges, b=1)


@dataclass
class BlockedListGraph:
    """Edges of a vertex in a chain of fixed-size blocks: rows (src, block_no, slots). An insertion reads all of them."""

    blocks: DataFrame
    block: int = BLOCK

    @staticmethod
    def from_edges(edges: DataFrame, block: int = BLOCK) -> "BlockedListGraph":
        place = F.row_number().over(Window.partitionBy("src").orderBy("dst")) - 1
        dealt = edges.select("src", "dst").distinct().withColumn("p", place)
        return BlockedListGraph(dealt.groupBy("src", F.floor(F.col("p") / block).alias("block_no")).agg(F.sort_array(F.collect_list("dst")).alias("slots")), block)

    def edges(self) -> DataFrame:
        return self.blocks.select("src", F.explode("slots").alias("dst"))

    def insert(self, batch: DataFrame) -> "BlockedListGraph":
        """All blocks of a touched vertex are rewritten: the place of a free slot is not known without the scan."""
        touched = batch.select("src").distinct()
        old = self.blocks.join(touched, "src", "left_semi")
        new = BlockedListGraph.from_edges(old.select("src", F.explode("slots").alias("dst")).unionByName(batch.select("src", "dst")), self.block)
        return BlockedListGraph(self.blocks.join(touched, "src", "left_anti").unionByName(new.blocks), self.block)

    def delete(self, batch: DataFrame) -> "BlockedListGraph":
        gone = batch.select("src", "dst").distinct()
        touched = gone.select("src").distinct()
        left = self.blocks.join(touched, "src", "left_semi").select("src", F.explode("slots").alias("dst")).join(gone, ["src", "dst"], "left_anti")
        return BlockedListGraph(self.blocks.join(touched, "src", "left_anti").unionByName(BlockedListGraph.from_edges(left, self.block).blocks), self.block)

    def view(self) -> Graph:
        """The blocks themselves as a graph: a traversal reads a vertex's whole chain, block by block."""
        return _headless(self.blocks.select(F.col("src").alias("owner"), F.col("slots").alias("elems")))

    def memory(self, n: int) -> DataFrame:
        """One row: blocks, bytes of n vertex entries and of all slots, used or free, with a link a block."""
        return self.blocks.agg(F.count("*").alias("blocks"), (F.lit(VERTEX_BYTES).cast("long") * n + F.count("*") * (self.block * SLOT_BYTES + LINK_BYTES)).alias("bytes"))

    def insert_cost(self, batch: DataFrame) -> DataFrame:
        """One row: updates, slots scanned (the whole list of each source, once an update), chain steps."""
        lists = self.blocks.groupBy("src").agg(F.sum(F.size("slots")).alias("slots"), F.count("*").alias("chain"))
        met = batch.select("src").join(lists, "src", "left")
        return met.agg(F.count("*").alias("updates"), F.coalesce(F.sum("slots"), F.lit(0)).alias("slots_scanned"), F.coalesce(F.sum("chain"), F.lit(0)).alias("chain_steps"))


@dataclass
class MultiSnapshotGraph:
    """A snapshot a batch: its edges grouped by vertex, linked to the snapshots before; nothing is ever compacted."""

    n: int
    fragments: list[DataFrame] = field(default_factory=list)

    def ingest(self, batch: DataFrame) -> "MultiSnapshotGraph":
        rows = batch.select("src", "dst").distinct().groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("dsts"))
        return MultiSnapshotGraph(self.n, [*self.fragments, rows.withColumn("snapshot", F.lit(len(self.fragments)))])

    def view(self) -> Graph:
        """The fragments themselves as a graph: a traversal reads a vertex's fragments of all snapshots. An edge that two
        batches have is read twice, which path counts must not be asked of."""
        return _headless(self.all().select(F.col("src").alias("owner"), F.col("dsts").alias("elems")))

    def memory(self) -> DataFrame:
        """One row: snapshots, bytes of their vertex arrays and edges."""
        edges = self.all().agg(F.coalesce(F.sum(F.size("dsts")), F.lit(0)).alias("m"))
        return edges.select(F.lit(len(self.fragments)).alias("snapshots"), (F.lit(len(self.fragments)).cast("long") * self.n * VERTEX_BYTES + F.col("m") * SLOT_BYTES).alias("bytes"))

    def all(self) -> DataFrame:
        out = self.fragments[0]
        for f in self.fragments[1:]:
            out = out.unionByName(f)
        return out

    def edges(self) -> DataFrame:
        return self.all().select("src", F.explode("dsts").alias("dst")).distinct()

    def fragmentation(self) -> DataFrame:
        """(src, fragments, deg): how many snapshots a reader of a vertex walks."""
        return self.all().groupBy("src").agg(F.count("*").alias("fragments"), F.sum(F.size("dsts")).alias("deg"))

    def ingest_cost(self) -> DataFrame:
        """(snapshot, array_entries, edges): each batch pays a vertex array of all n vertices besides its own edges."""
        return self.all().groupBy("snapshot").agg(F.lit(self.n).cast("long").alias("array_entries"), F.sum(F.size("dsts")).alias("edges"))


def static_rows(edges: DataFrame) -> DataFrame:
    """(owner, elems): one sorted row a vertex, rebuilt on every update; the static frameworks' layout."""
    return edges.groupBy(F.col("src").alias("owner")).agg(F.sort_array(F.collect_set("dst")).alias("elems"))


def _headless(rows: DataFrame) -> Graph:
    """Rows (owner, elems sorted), several for an owner, as chunks without heads; the same traversals run on them."""
    null = F.lit(None).cast("long")
    return Graph(rows.select("owner", null.alias("head"), F.element_at("elems", 1).alias("lo"), F.element_at("elems", -1).alias("hi"), F.size("elems").alias("cnt"), "elems"), b=1 << 30)


def static_graph(edges: DataFrame, codec: str = "plain") -> Graph:
    """Static rows as a graph: every list is one row, coded as a whole with a codec."""
    return _headless(static_rows(edges)).recoded(codec)


def offsets(edges: DataFrame) -> DataFrame:
    """(src, offset, deg) of a compressed sparse row layout over vertices in order of id; offsets by ranges of ids."""
    deg = edges.groupBy("src").agg(F.count_distinct("dst").alias("deg")).withColumn("_range", F.floor(F.col("src") / 65536))
    before = deg.groupBy("_range").agg(F.sum("deg").alias("_n"))
    carried = before.select("_range", F.coalesce(F.sum("_n").over(Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    inside = F.sum("deg").over(Window.partitionBy("_range").orderBy("src").rowsBetween(Window.unboundedPreceding, -1))
    return deg.join(carried, "_range").select("src", (F.coalesce(inside, F.lit(0)) + F.col("_before")).alias("offset"), "deg")


def copy_costs(n: int, fan_outs=(4, 16, 64, 256), chunk_sizes=(4, 16, 64, 256)) -> list[tuple[str, int, float, float]]:
    """(structure, parameter, levels copied, bytes copied) of one update under path copying of n elements.

    A B-tree copies a node of as many pointers as its fan-out on each level; a chunked tree one small node a level (36
    bytes, the middle of what a node takes) and one chunk.
    """
    import math

    out = [("b_tree", f, lv := math.ceil(math.log(n) / math.log(f)), 8.0 * f * lv) for f in fan_outs]
    return out + [("chunked", b, lv := math.ceil(math.log2(max(2, n / b))), 36.0 * lv + 4.0 * b) for b in chunk_sizes]


def path_copy(chunks: DataFrame, delta: DataFrame, b: int, seed: int = 0) -> DataFrame:
    """One row: chunks in all, chunks a batch rewrites, elements in these."""
    hit = sets.touched(chunks, delta, b, seed).withColumnRenamed("owner", "_o").withColumnRenamed("head", "_h")
    met = chunks.join(hit, (F.col("owner") == F.col("_o")) & F.col("head").eqNullSafe(F.col("_h")), "left")
    used = F.col("_o").isNotNull()
    return met.agg(F.count("*").alias("chunks"), F.sum(used.cast("long")).alias("touched"), F.sum(F.when(used, sets.weight()).otherwise(0)).cast("long").alias("elements_copied"))
