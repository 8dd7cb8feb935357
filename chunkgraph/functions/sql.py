"""The functions under SQL names."""

from __future__ import annotations

from pyspark.sql import Row, SparkSession
from pyspark.sql.functions import udtf

from .hashing import MODULUS, STEP_ONE, STEP_TWO


@udtf(returnType="vid: bigint")
class Neighbors:
    """The elements of a chunk as rows."""

    def eval(self, elems: list):
        for vid in elems or ():
            yield (vid,)


@udtf(returnType="i: bigint, src: bigint, dst: bigint")
class RmatDraws:
    """The first draws from 2^scale vertices; the same rows as the generator's."""

    def eval(self, scale: int, count: int):
        from ..sources.datasource import draws

        yield from zip(*(c.tolist() for c in draws(0, count, scale, 1)))


@udtf(returnType="i: bigint, src: bigint, dst: bigint")
class RmatDrawsOf:
    """The draws of a table's numbers (its first column), from 2^scale vertices; a task draws many at once."""

    def __init__(self):
        self.ids, self.scale = [], 0

    def eval(self, row: Row, scale: int):
        self.scale = scale
        if row[0] is not None:
            self.ids.append(row[0])
        if len(self.ids) >= 1 << 14:
            yield from self.drawn()

    def drawn(self):
        from ..sources.datasource import draws_of

        ids, self.ids = self.ids, []
        yield from zip(*(c.tolist() for c in draws_of(ids, self.scale, 1)))

    def terminate(self):
        if self.ids:
            yield from self.drawn()


def register(spark: SparkSession) -> None:
    """portable_hash(x), is_head(x, b), byte_len(x), and the table functions neighbors(elems), rmat_draws(scale, count) and
    rmat_draws_of(TABLE(...), scale)."""
    a = f"((x % {MODULUS} * {STEP_ONE[0]} + {STEP_ONE[1]}) % {MODULUS})"
    body = f"((({a} ^ shiftright({a}, 15)) % {MODULUS} * {STEP_TWO[0]} + {STEP_TWO[1]}) % {MODULUS})"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION portable_hash(x BIGINT) RETURNS BIGINT RETURN {body}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION is_head(x BIGINT, b INT) RETURNS BOOLEAN RETURN {body} % b = 0")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION byte_len(x BIGINT) RETURNS INT RETURN CAST(greatest(1, ceil(log2(x + 1) / 7)) AS INT)")
    spark.udtf.register("neighbors", Neighbors)
    spark.udtf.register("rmat_draws", RmatDraws)
    spark.udtf.register("rmat_draws_of", RmatDrawsOf)


def register_views(spark: SparkSession, g, prefix: str = "g") -> None:
    """A graph as temporary views: <prefix>_edges (src, dst[, weight]), <prefix>_chunks and <prefix>_vertices (vid, deg, ...)."""
    g.edges().createOrReplaceTempView(f"{prefix}_edges")
    g.chunks.createOrReplaceTempView(f"{prefix}_chunks")
    g.vertices().createOrReplaceTempView(f"{prefix}_vertices")

