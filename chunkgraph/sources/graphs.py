"""Graphs made from the given tables, the random update generator, and hash-ranked samples; each with its SQL.

All edge lists are symmetrised and distinct: edges(src, dst). Left sides get even ids, right sides odd ones.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import MODULUS, mix, portable_hash, portable_hash_sql
from ..plans.scratch import table

_HREF = 'href="([^"]+)"'


def _id_of_text(c):
    """A non-negative 48-bit id of a string."""
    return F.conv(F.substring(F.md5(c), 1, 12), 16, 10).cast("long")


def pairs(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(a, b) of a graph before it is symmetrised."""
    t = lambda n: table(spark, sf_dir, n)
    even, odd = (lambda c: (F.col(c) * 2).cast("long")), (lambda c: (F.col(c) * 2 + 1).cast("long"))
    if name == "ps":
        return t("lineitem").select(even("l_partkey").alias("a"), odd("l_suppkey").alias("b"))
    if name == "op":
        return t("lineitem").select(even("l_orderkey").alias("a"), odd("l_partkey").alias("b"))
    if name == "cs":
        orders = t("orders").select("o_orderkey", "o_custkey")
        return t("lineitem").select("l_orderkey", "l_suppkey").join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(even("o_custkey").alias("a"), odd("l_suppkey").alias("b"))
    if name == "cp":
        item = t("lineitem").select("l_orderkey", "l_partkey").distinct()
        return item.select("l_orderkey", F.col("l_partkey").alias("a")).join(item.select("l_orderkey", F.col("l_partkey").alias("b")), "l_orderkey").where("a < b").select("a", "b")
    if name == "ev":
        return consecutive_users(t("events")).select("a", "b")
    if name == "ek":
        return t("events").select(even("user_id").alias("a"), (F.get_json_object("props", "$.k").cast("long") * 2 + 1).alias("b"))
    if name == "web":
        href = F.explode(F.regexp_extract_all("html", F.lit(_HREF), F.lit(1)))
        return t("pages").select(even("page_id").alias("a"), href.alias("h")).select("a", (_id_of_text(F.col("h")) * 2 + 1).alias("b"))
    if name == "cv":
        turns = t("conversations").select("conv_id", "turn").distinct()
        here = (F.col("conv_id") * 1000 + F.col("turn")).cast("long")
        after = turns.select("conv_id", (F.col("turn") - 1).alias("turn"))
        return turns.join(after, ["conv_id", "turn"]).select(here.alias("a"), (here + 1).alias("b"))
    if name == "tree":
        nation, customer, supplier = t("nation"), t("customer"), t("supplier")
        n = lambda c: (F.col(c) + 1000).cast("long")
        up = nation.select(F.col("n_regionkey").cast("long").alias("a"), n("n_nationkey").alias("b"))
        down = customer.select(n("c_nationkey").alias("a"), (F.col("c_custkey") * 2 + 10000).alias("b"))
        return up.unionAll(down).unionAll(supplier.select(n("s_nationkey").alias("a"), (F.col("s_suppkey") * 2 + 10001).alias("b")))
    raise ValueError(name)


def consecutive_users(events: DataFrame) -> DataFrame:
    """Each event's user with the next event's, in order of (ts, event_id), where they differ: a, b, event_id.

    The order is global, so the next event is found by days: a day's last event meets the first event of the next day
    that has any, and no window spans more than a day.
    """
    day = F.to_date("ts")
    rows = events.select("user_id", "event_id", "ts", day.alias("day"))
    within = Window.partitionBy("day").orderBy("ts", "event_id")
    inner = rows.withColumn("b", F.lead("user_id").over(within))
    edge = rows.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"))
    following = edge.select("day", F.lead("first").over(Window.orderBy("day")).alias("next"))  # one row a day
    joined = inner.join(F.broadcast(following), "day").select(F.col("user_id").alias("a"), F.coalesce("b", "next").alias("b"), "event_id")
    return joined.where("b IS NOT NULL AND a <> b")


def symmetrised(ab: DataFrame) -> DataFrame:
    ab = ab.where("a <> b")
    return ab.select(F.col("a").alias("src"), F.col("b").alias("dst")).unionAll(ab.select(F.col("b").alias("src"), F.col("a").alias("dst"))).distinct()


def edges(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return symmetrised(pairs(spark, sf_dir, name))


PAIRS_SQL = {
    "ps": "SELECT 2*l_partkey AS a, 2*l_suppkey+1 AS b FROM lineitem",
    "op": "SELECT 2*l_orderkey AS a, 2*l_partkey+1 AS b FROM lineitem",
    "cs": "SELECT 2*o_custkey AS a, 2*l_suppkey+1 AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "cp": "SELECT x.l_partkey AS a, y.l_partkey AS b FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey WHERE x.l_partkey < y.l_partkey",
    "ev": "SELECT a, b FROM (SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b FROM events) WHERE b IS NOT NULL AND a <> b",
    "ek": "SELECT 2*user_id AS a, 2*CAST(json_extract_string(props, '$.k') AS BIGINT)+1 AS b FROM events",
    "web": "SELECT a, 2*CAST('0x' || substr(md5(h), 1, 12) AS BIGINT)+1 AS b FROM (SELECT 2*page_id AS a, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS h FROM pages)",
    "cv": "SELECT 1000*x.conv_id+x.turn AS a, 1000*x.conv_id+x.turn+1 AS b FROM conversations x JOIN conversations y ON x.conv_id = y.conv_id AND y.turn = x.turn+1",
    "tree": "SELECT CAST(n_regionkey AS BIGINT) AS a, CAST(n_nationkey AS BIGINT)+1000 AS b FROM nation UNION ALL SELECT CAST(c_nationkey AS BIGINT)+1000, 2*c_custkey+10000 FROM customer UNION ALL SELECT CAST(s_nationkey AS BIGINT)+1000, 2*s_suppkey+10001 FROM supplier",
}


def edges_sql(name: str) -> str:
    ab = f"(SELECT a, b FROM ({PAIRS_SQL[name]}) WHERE a <> b)"
    return f"SELECT DISTINCT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst FROM (SELECT a AS src, b AS dst FROM {ab} UNION ALL SELECT b, a FROM {ab})"


# ------------------------------------------------------------------------------------------------- generator and samples

#: Cumulative probabilities of the quadrants, in tenths.
_QUADRANTS = (5, 6, 7)


def rmat(spark: SparkSession, scale: int, count: int, seed: int = 1) -> DataFrame:
    """(i, src, dst): `count` draws, duplicates kept, from 2^scale vertices; each level hashes i anew."""
    return rmat_of(spark.range(count), scale, seed)


def rmat_of(ids: DataFrame, scale: int, seed: int = 1) -> DataFrame:
    """(i, src, dst): the draws of given numbers (id)."""
    levels = F.sequence(F.lit(seed).cast("long"), F.lit(seed + scale - 1).cast("long"))
    draws = F.transform(levels, lambda k: mix(mix(F.col("id")).bitwiseXOR(mix(k))) * 10)  # portable_hash(id, k)
    low, mid, high = (F.lit(q * MODULUS).cast("long") for q in _QUADRANTS)
    zero = F.lit(0).cast("long")
    down = F.aggregate("draws", zero, lambda s, u: s * 2 + (u >= mid).cast("long"))
    right = F.aggregate("draws", zero, lambda s, u: s * 2 + ((u >= low) & (u < mid) | (u >= high)).cast("long"))
    return ids.select(F.col("id").alias("i"), draws.alias("draws")).select("i", down.alias("src"), right.alias("dst"))


def rmat_sql(scale: int, count: int, seed: int = 1) -> str:
    return rmat_of_sql(scale, f"SELECT unnest(range({count})) AS i", seed)


def rmat_of_sql(scale: int, ids: str, seed: int = 1) -> str:
    src = dst = "0"
    columns = []
    for level in range(scale):
        columns.append(f"{portable_hash_sql('i', seed + level)} * 10 AS u{level}")
        src = f"({src} * 2 + CASE WHEN u{level} >= {_QUADRANTS[1] * MODULUS} THEN 1 ELSE 0 END)"
        dst = f"({dst} * 2 + CASE WHEN u{level} >= {_QUADRANTS[0] * MODULUS} AND u{level} < {_QUADRANTS[1] * MODULUS} OR u{level} >= {_QUADRANTS[2] * MODULUS} THEN 1 ELSE 0 END)"
    return f"SELECT i, CAST({src} AS BIGINT) AS src, CAST({dst} AS BIGINT) AS dst FROM (SELECT i, {', '.join(columns)} FROM ({ids}))"


def sample_updates(ab: DataFrame, share: int = 2, seed: int = 5) -> DataFrame:
    """The 90/10 stream: of the undirected edges a hash picks `share` per cent; nine in ten of these are insertions (taken
    out of the graph up front), one in ten a deletion. Columns a, b, op, spot (the stream's order)."""
    key = (F.col("a") % MODULUS * 31 + F.col("b") % MODULUS).cast("long")
    h = portable_hash(key, seed)
    picked = ab.where("a <> b").select("a", "b").distinct().withColumn("h", h).where(F.col("h") % 100 < share)
    return picked.select("a", "b", F.when(portable_hash(key, seed + 1) % 10 < 9, "I").otherwise("D").alias("op"), portable_hash(key, seed + 2).alias("spot"))


def sample_updates_sql(name: str, share: int = 2, seed: int = 5) -> str:
    key = f"(a % {MODULUS} * 31 + b % {MODULUS})"
    return (
        f"SELECT a, b, CASE WHEN {portable_hash_sql(key, seed + 1)} % 10 < 9 THEN 'I' ELSE 'D' END AS op, {portable_hash_sql(key, seed + 2)} AS spot "
        f"FROM (SELECT DISTINCT a, b FROM ({PAIRS_SQL[name]}) WHERE a <> b) WHERE {portable_hash_sql(key, seed)} % 100 < {share}"
    )
