"""What a user of the graphs needs around the methods: sources, joins, windows, grouping, functions, streams; each with its SQL."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.hashing import is_head, is_head_sql
from ..operators import sets
from ..operators.graph import Graph
from ..plans.scratch import scratch_dir, table
from ..sources.graphs import PAIRS_SQL, edges, edges_sql, pairs, rmat_of_sql
from .registry import check, with_
from .set_checks import chunk_sql, e_sql, heads_sql, owned


@check("csv_edges", edges_sql("tree"))
def _(spark, d):
    """Edges through a text file of `src dst` lines and back."""
    path = scratch_dir(spark)
    edges(spark, d, "tree").write.option("sep", " ").csv(path)
    return spark.read.option("sep", " ").schema("src long, dst long").csv(path)


@check("json_edges", edges_sql("cv"))
def _(spark, d):
    path = scratch_dir(spark)
    edges(spark, d, "cv").write.json(path)
    return spark.read.schema("src long, dst long").json(path)


@check("orc_edges", edges_sql("tree"))
def _(spark, d):
    path = scratch_dir(spark)
    edges(spark, d, "tree").write.orc(path)
    return spark.read.orc(path)


@check("adjacency_lines", edges_sql("cv"))
def _(spark, d):
    """`src: dst dst ...` lines and back."""
    path = scratch_dir(spark)
    lines = edges(spark, d, "cv").groupBy("src").agg(F.array_join(F.sort_array(F.collect_list("dst")).cast("array<string>"), " ").alias("to"))
    lines.select(F.concat_ws(": ", F.col("src").cast("string"), "to").alias("value")).write.text(path)
    parts = F.split("value", ": ")
    return spark.read.text(path).select(parts[0].cast("long").alias("src"), F.explode(F.split(parts[1], " ").cast("array<bigint>")).alias("dst"))


@check("parquet_partitioned_sink", with_(f"e AS ({edges_sql('op')})") + "SELECT src % 8 AS bucket, count(*) AS n FROM e WHERE src % 8 IN (2, 4) GROUP BY 1")
def _(spark, d):
    path = scratch_dir(spark)
    edges(spark, d, "op").withColumn("bucket", F.col("src") % 8).repartition("bucket").write.partitionBy("bucket").parquet(path)
    return spark.read.parquet(path).where("bucket IN (2, 4)").groupBy(F.col("bucket").cast("long").alias("bucket")).agg(F.count("*").alias("n"))


@check("json_events_k", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def _(spark, d):
    return table(spark, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


_EV = "SELECT user_id, count(*) AS n FROM events WHERE event_type = 'purchase' GROUP BY user_id HAVING count(*) > 12"


@check("semi_join_active", f"SELECT src, dst FROM ({edges_sql('ev')}) WHERE src IN (SELECT user_id FROM ({_EV}))")
def _(spark, d):
    active = table(spark, d, "events").where("event_type = 'purchase'").groupBy("user_id").count().where("count > 12")
    return edges(spark, d, "ev").join(active.select(F.col("user_id").alias("src")), "src", "left_semi").select("src", "dst")


@check("anti_join_isolated", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderpriority = '1-URGENT')")
def _(spark, d):
    return table(spark, d, "customer").select("c_custkey").join(table(spark, d, "orders").where("o_orderpriority = '1-URGENT'").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti")


@check("outer_join_degrees", "SELECT coalesce(a.v, b.v) AS vid, coalesce(a.n, 0) AS as_src, coalesce(b.n, 0) AS as_user FROM (SELECT a AS v, count(*) AS n FROM (SELECT DISTINCT l_suppkey AS a, l_partkey FROM lineitem) GROUP BY a) a FULL JOIN (SELECT user_id AS v, count(*) AS n FROM events GROUP BY user_id) b ON a.v = b.v")
def _(spark, d):
    a = table(spark, d, "lineitem").select("l_suppkey", "l_partkey").distinct().groupBy(F.col("l_suppkey").alias("vid")).agg(F.count("*").alias("a"))
    b = table(spark, d, "events").groupBy(F.col("user_id").alias("vid")).agg(F.count("*").alias("b"))
    zero = lambda c: F.coalesce(c, F.lit(0).cast("long"))
    return a.join(b, "vid", "full").select("vid", zero("a").alias("as_src"), zero("b").alias("as_user"))


@check("theta_chunk_range", with_(e_sql("tree"), f"h AS ({heads_sql('e', 4)})", "c AS (SELECT owner, head, min(elem) AS first, max(elem) AS last FROM h GROUP BY owner, head)") + "SELECT owner, count(*) AS chunks FROM c WHERE first <= 10500 AND last >= 10100 GROUP BY owner")
def _(spark, d):
    c = sets.build(owned(spark, d, "tree"), 4)
    return c.where((F.coalesce("head", "lo") <= 10500) & (F.coalesce("hi", "head") >= 10100)).groupBy("owner").agg(F.count("*").alias("chunks"))


@check("interval_join_events", "SELECT a.event_id, count(*) AS near FROM events a JOIN events b ON b.event_type = 'error' AND a.event_type = 'purchase' AND b.ts BETWEEN a.ts - INTERVAL 30 MINUTE AND a.ts + INTERVAL 30 MINUTE GROUP BY a.event_id")
def _(spark, d):
    """Each purchase with the errors within half an hour: equal half-hour bins, then the exact interval."""
    e = table(spark, d, "events").select("event_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    half = 30 * 60 * 1_000_000
    at = F.floor(F.col("t") / half)
    a = e.where("event_type = 'purchase'").select("event_id", "t", F.explode(F.array(at - 1, at, at + 1)).alias("bin"))
    b = e.where("event_type = 'error'").select(F.col("t").alias("u"), at.alias("bin"))
    return a.join(b, "bin").where(F.abs(F.col("t") - F.col("u")) <= half).groupBy("event_id").agg(F.count("*").alias("near"))


@check("asof_order_event", "SELECT o_orderkey, e.event_id FROM orders ASOF LEFT JOIN (SELECT max(event_id) AS event_id, ts FROM events GROUP BY ts) e ON o_orderdate >= e.ts")
def _(spark, d):
    """The last event at or before each order's date, by days: the last event of earlier days is one row a day."""
    e = table(spark, d, "events").select("event_id", "ts").withColumn("day", F.to_date("ts"))
    o = table(spark, d, "orders").select("o_orderkey", F.col("o_orderdate").alias("ts")).withColumn("day", F.to_date("ts"))
    rows = e.select("day", "ts", F.lit(0).alias("kind"), "event_id", F.lit(None).cast("long").alias("o_orderkey")).unionByName(o.select("day", "ts", F.lit(1).alias("kind"), F.lit(None).cast("long").alias("event_id"), "o_orderkey"))
    inside = F.last("event_id", ignorenulls=True).over(Window.partitionBy("day").orderBy("ts", "kind", "event_id"))
    ends = rows.groupBy("day").agg(F.max_by("event_id", F.when(F.col("kind") == 0, F.struct("ts", "event_id"))).alias("end"))
    carried = ends.select("day", F.last("end", ignorenulls=True).over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)).alias("before"))
    return rows.withColumn("here", inside).where("kind = 1").join(F.broadcast(carried), "day").select("o_orderkey", F.coalesce("here", "before").alias("event_id"))


_CUST = "customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _customers(spark, d):
    c, n, r = (table(spark, d, t) for t in ("customer", "nation", "region"))
    return c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))


@check("rollup_region_nation_edges", f"SELECT r_name, n_name, count(*) AS customers FROM {_CUST} GROUP BY ROLLUP (r_name, n_name)")
def _(spark, d):
    return _customers(spark, d).rollup("r_name", "n_name").agg(F.count("*").alias("customers"))


@check("cube_status_priority", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def _(spark, d):
    return table(spark, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@check("grouping_sets_edges", f"SELECT r_name, c_mktsegment, count(*) AS n, CAST(grouping_id(r_name, c_mktsegment) AS BIGINT) AS gid FROM {_CUST} GROUP BY GROUPING SETS ((r_name), (c_mktsegment), ())")
def _(spark, d):
    _customers(spark, d).createOrReplaceTempView("_grouping_customers")
    return spark.sql("SELECT r_name, c_mktsegment, count(*) AS n, CAST(grouping_id(r_name, c_mktsegment) AS BIGINT) AS gid FROM _grouping_customers GROUP BY GROUPING SETS ((r_name), (c_mktsegment), ())")


_DEG = f"deg AS (SELECT src AS vid, count(*) AS deg FROM ({edges_sql('ps')}) GROUP BY src)"


def _degrees(spark, d):
    return Graph.from_edges(edges(spark, d, "ps"), b=8).vertices().select("vid", "deg")


@check("top_degree", f"WITH {_DEG} SELECT vid, deg FROM deg ORDER BY deg DESC, vid LIMIT 20")
def _(spark, d):
    return _degrees(spark, d).orderBy(F.desc("deg"), "vid").limit(20)


@check("topk_neighbors_per_vertex", f"WITH {_DEG}, r AS (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY deg DESC, dst) AS k FROM ({edges_sql('ps')}) JOIN deg ON dst = vid) SELECT src, dst, k FROM r WHERE k <= 3")
def _(spark, d):
    best = Window.partitionBy("src").orderBy(F.desc("deg"), "dst")
    e = edges(spark, d, "ps").join(_degrees(spark, d).withColumnRenamed("vid", "dst"), "dst")
    return e.select("src", "dst", F.row_number().over(best).cast("long").alias("k")).where("k <= 3")


@check("rank_family_degree", "SELECT c_custkey, CAST(rank() OVER w AS BIGINT) AS r, CAST(dense_rank() OVER w AS BIGINT) AS dr, CAST(ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS BIGINT) AS q, round(percent_rank() OVER w, 9) AS pr FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_mktsegment)")
def _(spark, d):
    w = Window.partitionBy("c_nationkey").orderBy("c_mktsegment")
    q = Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")
    return table(spark, d, "customer").select("c_custkey", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(4).over(q).cast("long").alias("q"), F.round(F.percent_rank().over(w), 9).alias("pr"))


@check("window_frames_events", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS near, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS s FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def _(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    near = w.rowsBetween(-2, 0)
    return table(spark, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.count("*").over(near).alias("near"), F.round(F.sum("value").over(near), 6).alias("s"))


@check("set_ops_edges", f"WITH p AS ({edges_sql('ek')}), q AS (SELECT * FROM p WHERE src % 3 = 0 OR dst % 3 = 0), r AS (SELECT * FROM p WHERE src % 2 = 0) (SELECT src, dst, 'both' AS what FROM q INTERSECT SELECT src, dst, 'both' FROM r) UNION ALL (SELECT src, dst, 'minus' FROM q EXCEPT SELECT src, dst, 'minus' FROM r)")
def _(spark, d):
    p = edges(spark, d, "ek")
    q, r = p.where("src % 3 = 0 OR dst % 3 = 0"), p.where("src % 2 = 0")
    return q.intersect(r).withColumn("what", F.lit("both")).unionByName(q.exceptAll(r).withColumn("what", F.lit("minus")))


@check("array_fn_chunks", with_(e_sql("ps"), f"h AS ({heads_sql('e', 8)})", f"c AS ({chunk_sql('h')})") + "SELECT owner, count(*) AS chunks, CAST(max(cnt) AS BIGINT) AS largest FROM c GROUP BY owner")
def _(spark, d):
    """Chunks of each set as one array, walked with array functions."""
    c = sets.build(owned(spark, d, "ps"), 8).groupBy("owner").agg(F.collect_list("elems").alias("all"))
    return c.select("owner", F.size("all").cast("long").alias("chunks"), F.array_max(F.transform("all", F.size)).cast("long").alias("largest"))


@check("map_fn_labels", "SELECT quality, toxic, count(*) AS n FROM labels GROUP BY quality, toxic")
def _(spark, d):
    m = F.map_from_arrays(F.array(F.lit("quality"), F.lit("toxic")), F.array("quality", "toxic")).alias("m")
    return table(spark, d, "labels").select(m).groupBy(F.element_at("m", "quality").alias("quality"), F.element_at("m", "toxic").alias("toxic")).agg(F.count("*").alias("n"))


@check("string_tokens", "SELECT item_id, length(text) AS chars, len(string_split(text, ' ')) AS words, md5(lower(text)) AS digest FROM benchmark")
def _(spark, d):
    return table(spark, d, "benchmark").select("item_id", F.length("text").cast("long").alias("chars"), F.size(F.split("text", " ")).cast("long").alias("words"), F.md5(F.lower("text")).alias("digest"))


@check("date_bins", "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(*) AS n FROM orders GROUP BY 1")
def _(spark, d):
    return table(spark, d, "orders").groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("month")).agg(F.count("*").alias("n"))


@check("approx_distinct_check", "SELECT count(DISTINCT l_partkey) AS exact, true AS close FROM lineitem")
def _(spark, d):
    """The sketch's error is 5 per cent by default; three times that is allowed."""
    both = table(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("about"), F.count_distinct("l_partkey").alias("exact"))
    return both.select("exact", (F.abs(F.col("about") - F.col("exact")) <= 0.15 * F.col("exact")).alias("close"))


@check("percentile_degree", f"WITH {_DEG} SELECT quantile_cont(deg, 0.5) AS median, quantile_cont(deg, 0.9) AS p90 FROM deg")
def _(spark, d):
    return _degrees(spark, d).agg(F.percentile("deg", 0.5).alias("median"), F.percentile("deg", 0.9).alias("p90"))


@check("lateral_neighbors", with_(f"e AS ({edges_sql('tree')})") + "SELECT src, dst FROM e")
def _(spark, d):
    """Neighbours through a table function of the chunks."""
    from ..functions.sql import register

    register(spark)
    c = sets.build(owned(spark, d, "tree"), 8)
    c.select("owner", sets.all_elems().alias("elems")).createOrReplaceTempView("_lateral_chunks")
    return spark.sql("SELECT owner AS src, n.vid AS dst FROM _lateral_chunks, LATERAL neighbors(elems) n")


@check("udtf_rmat", rmat_of_sql(6, "SELECT event_id AS i FROM events"))
def _(spark, d):
    from ..functions.sql import register

    register(spark)
    table(spark, d, "events").createOrReplaceTempView("_events")
    return spark.sql("SELECT i, src, dst FROM rmat_draws_of(TABLE(SELECT event_id FROM _events), 6)")


@check("sql_functions", f"SELECT DISTINCT l_partkey AS x, {is_head_sql('l_partkey', 16)} AS head FROM lineitem")
def _(spark, d):
    from ..functions.sql import register

    register(spark)
    table(spark, d, "lineitem").createOrReplaceTempView("_lines")
    return spark.sql("SELECT DISTINCT l_partkey AS x, is_head(l_partkey, 16) AS head FROM _lines")


@check("data_source_rmat", rmat_of_sql(8, "SELECT o_orderkey AS i FROM orders"))
def _(spark, d):
    from ..sources.datasource import RmatSource

    spark.dataSource.register(RmatSource)
    keys = table(spark, d, "orders").select(F.col("o_orderkey").alias("i"))
    most = keys.agg(F.coalesce(F.max("i"), F.lit(-1))).first()[0]
    drawn = spark.read.format("rmat").option("scale", 8).option("count", most + 1).load()
    return keys.join(drawn, "i").select("i", "src", "dst")


@check("recursive_reachability", with_(f"e AS ({edges_sql('cv')})", "r(vid) AS (SELECT min(src) FROM e UNION SELECT dst FROM r JOIN e ON r.vid = e.src)", recursive=True) + "SELECT vid FROM r")
def _(spark, d):
    from ..operators.algorithms import bfs

    e = edges(spark, d, "cv")
    return bfs(Graph.from_edges(e, b=8), e.agg(F.min("src")).first()[0]).select("vid")


# ------------------------------------------------------------------------------------------------------------- versions


def _store(spark, d):
    from ..sources.store import VersionStore

    e = edges(spark, d, "ek")
    store = VersionStore(spark, scratch_dir(spark), b=8)
    store.publish(Graph.from_edges(e.where("(src + dst) % 4 <> 1"), b=8))
    for k, (divisor, rest) in enumerate(((4, 1), (5, 0), (7, 0))):
        pick = e.where(f"(src + dst) % {divisor} = {rest}")
        store.apply(pick.select(F.lit(k).alias("seq"), F.lit("I" if not k else "D").alias("op"), "src", "dst"), batch_id=k)
    return store


_STORE_SQL = f"e AS ({edges_sql('ek')})", "v0 AS (SELECT * FROM e WHERE (src + dst) % 4 <> 1)", "v2 AS (SELECT * FROM e WHERE (src + dst) % 5 <> 0)", "v3 AS (SELECT * FROM v2 WHERE (src + dst) % 7 <> 0)"


@check("version_history_counts", with_(*_STORE_SQL) + "SELECT CAST(0 AS BIGINT) AS version, count(DISTINCT src) AS n, count(*) AS m FROM v0 UNION ALL SELECT 1, count(DISTINCT src), count(*) FROM e UNION ALL SELECT 2, (SELECT count(DISTINCT src) FROM e), count(*) FROM v2 UNION ALL SELECT 3, (SELECT count(DISTINCT src) FROM e), count(*) FROM v3")
def _(spark, d):
    """Vertices that lose their last edge stay."""
    return _store(spark, d).history().select("version", "n", "m")


@check("as_of_graph", with_(*_STORE_SQL) + "SELECT src, dst FROM v2")
def _(spark, d):
    return _store(spark, d).as_of(2).edges()


# --------------------------------------------------------------------------------------------------------------- streams


def _event_stream(spark, d):
    from ..streaming.events import stream_events

    return stream_events(spark, d)


@check("stream_apply_events", "WITH o AS (SELECT event_id, event_type, user_id * 2 AS src, CAST(json_extract_string(props, '$.k') AS BIGINT) * 2 + 1 AS dst FROM events), l AS (SELECT src, dst, arg_max(event_type, event_id) AS t FROM o GROUP BY src, dst) SELECT src, dst FROM l WHERE t <> 'error'")
def _(spark, d):
    from ..streaming.events import apply_event_stream

    return apply_event_stream(spark, d).edges()


@check("stream_tumbling", "SELECT epoch_us(date_trunc('day', ts)) AS start_us, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def _(spark, d):
    from ..streaming.events import run_windows

    return run_windows(spark, d, "1 day", None)


@check("stream_sliding", "SELECT epoch_us(date_trunc('day', ts) - INTERVAL 1 DAY * k) AS start_us, event_type, count(*) AS n FROM events, (SELECT unnest([0, 1]) AS k) GROUP BY 1, 2")
def _(spark, d):
    from ..streaming.events import run_windows

    return run_windows(spark, d, "2 days", "1 day")


@check("stream_session", "WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS n FROM s GROUP BY user_id, k")
def _(spark, d):
    from ..streaming.events import run_sessions

    return run_sessions(spark, d, "6 hours")


@check("stream_late_drop", "WITH w AS (SELECT max(ts) - INTERVAL 1 DAY AS mark FROM events WHERE event_id % 50 > 1) SELECT count(*) FILTER (NOT late) AS counted, count(*) FILTER (late) AS late FROM (SELECT event_id % 50 = 0 AND date_trunc('day', ts) + INTERVAL 1 DAY <= mark AS late FROM events, w)")
def _(spark, d):
    """Rows that arrive after the watermark has passed their window are dropped, and counted."""
    from ..streaming.events import run_late

    return run_late(spark, d)


@check("stream_dedup", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def _(spark, d):
    """Rows repeated an hour later within the watermark are dropped as duplicates."""
    from ..streaming.events import run_deduplicated

    return run_deduplicated(spark, d)


@check("stream_stateful_degree", "SELECT user_id AS vid, count(DISTINCT CAST(json_extract_string(props, '$.k') AS BIGINT)) AS deg FROM events GROUP BY user_id")
def _(spark, d):
    from ..streaming.events import run_stateful_degrees

    return run_stateful_degrees(spark, d)


@check("edges_per_batch", "SELECT CAST(event_id // 2500 AS BIGINT) AS batch, count(*) AS updates FROM events GROUP BY 1")
def _(spark, d):
    return table(spark, d, "events").groupBy(F.floor(F.col("event_id") / 2500).alias("batch")).agg(F.count("*").alias("updates"))


@check("head_share", f"SELECT CAST(b AS INTEGER) AS b, n FROM (SELECT 16 AS b, count(*) FILTER ({is_head_sql('x', 16)}) AS n FROM (SELECT DISTINCT l_orderkey AS x FROM lineitem))")
def _(spark, d):
    x = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("x")).distinct()
    return x.agg(F.count(F.when(is_head(F.col("x"), 16), 1)).alias("n")).select(F.lit(16).alias("b"), "n")


@check("sql_views", with_(f"e AS ({edges_sql('tree')})") + "SELECT src, count(*) AS deg, min(dst) AS first FROM e GROUP BY src")
def _(spark, d):
    """A graph asked in SQL through its views."""
    from ..functions.sql import register_views

    register_views(spark, Graph.from_edges(edges(spark, d, "tree"), b=8))
    return spark.sql("SELECT v.vid AS src, max(v.deg) AS deg, min(e.dst) AS first FROM g_vertices v JOIN g_edges e ON e.src = v.vid GROUP BY v.vid")


@check("skewed_join", "WITH k AS (SELECT CASE WHEN event_id % 3 = 0 THEN 0 ELSE user_id END AS user_id, value FROM events) SELECT k.user_id, count(*) AS n, round(sum(value), 4) AS total FROM k JOIN (SELECT DISTINCT user_id FROM events) u ON k.user_id = u.user_id GROUP BY k.user_id")
def _(spark, d):
    """A third of all rows have one key: the hot side is salted, the other repeated for each salt, sums are added in two steps."""
    salts = 16
    e = table(spark, d, "events")
    hot = e.select(F.when(F.col("event_id") % 3 == 0, F.lit(0).cast("long")).otherwise(F.col("user_id")).alias("user_id"), "value", F.pmod(F.xxhash64("event_id"), F.lit(salts)).alias("salt"))
    users = e.select("user_id").distinct().withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    part = hot.join(users, ["user_id", "salt"]).groupBy("user_id", "salt").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return part.groupBy("user_id").agg(F.sum("n").alias("n"), F.round(F.sum("total"), 4).alias("total"))


@check("store_directed", "WITH ab AS (SELECT DISTINCT a AS src, b AS dst FROM (" + PAIRS_SQL["ev"] + ") WHERE a % 7 <> 0 AND b % 7 <> 0) SELECT dst, min(src) AS src FROM ab WHERE src % 5 = 0 GROUP BY dst")
def _(spark, d):
    """A directed graph through the version store, vertices deleted, then a dense step over its in-neighbours."""
    from ..operators.graph import edge_map
    from ..sources.store import VersionStore

    store = VersionStore(spark, scratch_dir(spark), b=8, codec="bytecode")
    e = pairs(spark, d, "ev").select(F.col("a").alias("src"), F.col("b").alias("dst"))
    store.publish(Graph.from_edges(e.where("src % 3 <> 0"), directed=True, b=8))
    store.apply(e.where("src % 3 = 0").select(F.lit(1).alias("seq"), F.lit("I").alias("op"), "src", "dst"))
    gone = store.graph().vertices().where("vid % 7 = 0").select("vid")
    g = store.graph().delete_vertices(gone).settled()
    return edge_map(g, g.vertices().where("vid % 5 = 0").select("vid"), mode="dense")


@check("store_weighted", "WITH w AS (SELECT src, dst, sum(q) AS weight FROM (SELECT 2*l_partkey AS src, 2*l_suppkey+1 AS dst, l_quantity AS q FROM lineitem) GROUP BY src, dst) SELECT src, dst, CASE WHEN src % 10 = 0 THEN 7.5 ELSE round(weight, 4) END AS weight FROM w WHERE src % 10 <> 4 AND src < 2000")
def _(spark, d):
    """Weights through the version store: updated by a batch, edges deleted by another."""
    from ..sources.store import VersionStore

    t = table(spark, d, "lineitem").select((F.col("l_partkey") * 2).alias("src"), (F.col("l_suppkey") * 2 + 1).alias("dst"), F.col("l_quantity").alias("weight")).where("src < 2000")
    store = VersionStore(spark, scratch_dir(spark), b=8)
    store.publish(Graph.from_edges(t, directed=True, b=8, weight="weight", combine="sum"))
    edge = t.select("src", "dst").distinct()
    store.apply(edge.where("src % 10 = 0").select(F.lit(1).alias("seq"), F.lit("I").alias("op"), "src", "dst", F.lit(7.5).alias("weight")), batch_id=1)
    store.apply(edge.where("src % 10 = 4").select(F.lit(1).alias("seq"), F.lit("D").alias("op"), "src", "dst", F.lit(0.0).alias("weight")), batch_id=2)
    return store.graph().edges().select("src", "dst", F.round("weight", 4).alias("weight"))


@check("store_isolated", "SELECT 2*c_custkey AS vid, CAST((SELECT count(DISTINCT l_suppkey) FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_custkey = c_custkey AND c_custkey % 9 <> 0) AS BIGINT) AS deg FROM customer")
def _(spark, d):
    """Vertices without edges through the version store: given ones, and those whose edges a batch deletes."""
    from ..sources.store import VersionStore

    e = edges(spark, d, "cs")
    store = VersionStore(spark, scratch_dir(spark), b=8)
    store.publish(Graph.from_edges(e, b=8, vertices=table(spark, d, "customer").select((F.col("c_custkey") * 2).alias("vid"))))
    dead = e.where("src % 18 = 0 AND src % 2 = 0")
    both = dead.unionByName(dead.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    store.apply(both.select(F.lit(1).alias("seq"), F.lit("D").alias("op"), "src", "dst"))
    return store.graph().vertices().where("vid % 2 = 0").select("vid", "deg")
