"""Hashing, chunks and set primitives on the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.codec import byte_length, byte_length_sql, decode_chunks, delta_decode, delta_encode, encode_chunks
from ..functions.hashing import is_head, is_head_sql, portable_hash, portable_hash_sql
from ..operators import sets
from ..plans.cost import tail_deltas
from ..plans.scratch import table
from ..sources.graphs import PAIRS_SQL, edges, edges_sql, rmat_of, rmat_of_sql
from .registry import check, with_


def owned(spark, sf_dir, graph):
    return edges(spark, sf_dir, graph).select(F.col("src").alias("owner"), F.col("dst").alias("elem"))


def heads_sql(source: str, b: int) -> str:
    """CTE body: owner, elem, head of distinct entries."""
    return f"SELECT owner, elem, last_value(CASE WHEN {is_head_sql('elem', b)} THEN elem END IGNORE NULLS) OVER (PARTITION BY owner ORDER BY elem ROWS UNBOUNDED PRECEDING) AS head FROM {source}"


def chunk_sql(source: str) -> str:
    tail = "head IS NULL OR elem <> head"
    return f"SELECT owner, head, min(elem) FILTER ({tail}) AS lo, max(elem) FILTER ({tail}) AS hi, CAST(count(*) FILTER ({tail}) AS INTEGER) AS cnt, coalesce(string_agg(CAST(elem AS VARCHAR), ',' ORDER BY elem) FILTER ({tail}), '') AS elems FROM {source} GROUP BY owner, head"


def flat(chunks):
    return chunks.select("owner", "head", "lo", "hi", "cnt", F.array_join(F.col("elems").cast("array<string>"), ",").alias("elems"))


def e_sql(graph: str) -> str:
    return f"e AS (SELECT src AS owner, dst AS elem FROM ({edges_sql(graph)}))"


_PARTS = "SELECT DISTINCT l_partkey AS x FROM lineitem"


@check("portable_hash", f"SELECT x, {portable_hash_sql('x')} AS h0, {portable_hash_sql('x', 5)} AS h5 FROM ({_PARTS})")
def _(spark, d):
    x = table(spark, d, "lineitem").select(F.col("l_partkey").alias("x")).distinct()
    return x.select("x", portable_hash(F.col("x")).alias("h0"), portable_hash(F.col("x"), 5).alias("h5"))


@check("head_flags", f"SELECT x, {is_head_sql('x', 4)} AS b4, {is_head_sql('x', 16)} AS b16, {is_head_sql('x', 256)} AS b256 FROM ({_PARTS})")
def _(spark, d):
    x = table(spark, d, "lineitem").select(F.col("l_partkey").alias("x")).distinct()
    return x.select("x", *(is_head(F.col("x"), b).alias(f"b{b}") for b in (4, 16, 256)))


for _graph, _b in (("ps", 8), ("cs", 16), ("op", 4), ("cp", 1), ("ps", 256)):

    def _build(spark, d, graph=_graph, b=_b):
        return flat(sets.build(owned(spark, d, graph), b))

    check(f"chunks_{_graph}_b{_b}", with_(e_sql(_graph), f"h AS ({heads_sql('e', _b)})") + chunk_sql("h"))(_build)


@check("chunks_by_ranges", with_(e_sql("ps"), f"h AS ({heads_sql('e', 8)})") + chunk_sql("h"))
def _(spark, d):
    return flat(sets.build(owned(spark, d, "ps"), 8, span=512))


@check("prefix_only_sets", with_(e_sql("op"), f"h AS ({heads_sql('e', 64)})") + "SELECT owner, CAST(count(*) AS BIGINT) AS size FROM h GROUP BY owner HAVING count(head) = 0")
def _(spark, d):
    c = sets.build(owned(spark, d, "op"), 64)
    return c.groupBy("owner").agg(F.count("head").alias("heads"), F.sum(sets.weight()).cast("long").alias("size")).where("heads = 0").select("owner", "size")


_DELTAS = with_(e_sql("ps"), f"h AS ({heads_sql('e', 8)})", "t AS (SELECT * FROM h WHERE head IS NULL OR elem <> head)", "d AS (SELECT owner, head, elem - coalesce(lag(elem) OVER (PARTITION BY owner, head ORDER BY elem), 0) AS delta FROM t)")


@check("delta_gaps", _DELTAS + "SELECT delta, count(*) AS n FROM d GROUP BY delta")
def _(spark, d):
    return tail_deltas(sets.build(owned(spark, d, "ps"), 8)).groupBy("delta").agg(F.count("*").alias("n"))


@check("byte_lengths", _DELTAS + f"SELECT owner, head, CAST(sum({byte_length_sql('delta')}) AS BIGINT) AS nbytes FROM d GROUP BY owner, head")
def _(spark, d):
    return tail_deltas(sets.build(owned(spark, d, "ps"), 8)).groupBy("owner", "head").agg(F.sum(byte_length(F.col("delta"))).cast("long").alias("nbytes"))


@check("byte_code_payload", _DELTAS + f"SELECT owner, head, CAST(sum({byte_length_sql('delta')}) AS INTEGER) AS nbytes FROM d GROUP BY owner, head")
def _(spark, d):
    return encode_chunks(sets.build(owned(spark, d, "ps"), 8).where("cnt > 0")).select("owner", "head", "nbytes")


@check("udf_bytecode_roundtrip", with_(e_sql("cs"), f"h AS ({heads_sql('e', 16)})") + chunk_sql("h"))
def _(spark, d):
    return flat(decode_chunks(encode_chunks(sets.build(owned(spark, d, "cs"), 16))))


@check("delta_roundtrip", with_(e_sql("ps"), f"h AS ({heads_sql('e', 8)})") + chunk_sql("h"))
def _(spark, d):
    c = sets.build(owned(spark, d, "ps"), 8)
    return flat(c.withColumn("elems", delta_decode(delta_encode(F.col("elems")))))


_SWEEP = tuple(2**k for k in range(1, 13))


@check("chunk_stats_sweep", "WITH " + e_sql("cs") + "\n" + "\nUNION ALL ".join(f"SELECT CAST({b} AS INTEGER) AS b, count(*) FILTER (head IS NOT NULL AND elem = head) AS heads, count(DISTINCT owner) FILTER (head IS NULL) AS prefixes, CAST(max(n) AS BIGINT) AS largest, count(DISTINCT owner) AS sets FROM (SELECT *, count(*) FILTER (head IS NULL OR elem <> head) OVER (PARTITION BY owner, head) AS n FROM ({heads_sql('e', b)}))" for b in _SWEEP))
def _(spark, d):
    base, out = owned(spark, d, "cs"), None
    for b in _SWEEP:
        row = sets.chunk_stats(sets.build(base, b)).select(F.lit(b).alias("b"), "heads", "prefixes", "largest", "sets")
        out = row if out is None else out.unionByName(row)
    return out


@check("tail_size_histogram", with_(e_sql("op"), f"h AS ({heads_sql('e', 4)})", f"c AS ({chunk_sql('h')})") + "SELECT cnt, count(*) AS n FROM c WHERE head IS NOT NULL GROUP BY cnt")
def _(spark, d):
    return sets.build(owned(spark, d, "op"), 4).where("head IS NOT NULL").groupBy("cnt").agg(F.count("*").alias("n"))


@check("rmat_edges", rmat_of_sql(10, "SELECT o_orderkey AS i FROM orders"))
def _(spark, d):
    """A draw for each order."""
    return rmat_of(table(spark, d, "orders").select(F.col("o_orderkey").alias("id")), 10)


@check("canonical_layout", with_(e_sql("ps"), f"h AS ({heads_sql('e', 8)})") + chunk_sql("h"))
def _(spark, d):
    """Built from halves in another order and united: the same rows."""
    base = owned(spark, d, "ps").withColumn("half", portable_hash(F.col("elem"), 3) % 2)
    return flat(sets.union(sets.build(base.where("half = 1").drop("half"), 8), base.where("half = 0").drop("half"), 8))


# -------------------------------------------------------------------------------------------------------- values and folds

_WEIGHTS = "SELECT l_partkey AS owner, l_suppkey AS elem, l_quantity AS val FROM lineitem"


def weights(spark, d):
    return table(spark, d, "lineitem").select(F.col("l_partkey").alias("owner"), F.col("l_suppkey").alias("elem"), F.col("l_quantity").alias("val"))


for _fold in ("sum", "min", "max"):

    def _folded(spark, d, how=_fold):
        return sets.entries(sets.build(weights(spark, d), 8, combine=how)).select("owner", "elem", F.round("val", 6).alias("val"))

    check(f"build_combine_{_fold}", f"SELECT owner, elem, round({_fold}(val), 6) AS val FROM ({_WEIGHTS}) GROUP BY owner, elem")(_folded)


@check("build_combine_last", "SELECT l_partkey AS owner, l_suppkey AS elem, arg_max(l_quantity, (l_orderkey * 10 + l_linenumber) * 1000 + l_quantity) AS val FROM lineitem GROUP BY 1, 2")
def _(spark, d):
    t = table(spark, d, "lineitem").select(F.col("l_partkey").alias("owner"), F.col("l_suppkey").alias("elem"), F.col("l_quantity").alias("val"), ((F.col("l_orderkey") * 10 + F.col("l_linenumber")) * 1000 + F.col("l_quantity")).alias("o"))
    return sets.entries(sets.build(t, 8, combine="last", order="o")).select("owner", "elem", "val")


@check("insert_combine_count", f"SELECT owner, elem, count(*) AS val FROM ({_WEIGHTS}) GROUP BY owner, elem")
def _(spark, d):
    """Counts of a set and of a batch are added."""
    w = weights(spark, d)
    first = sets.build(w.where("val < 25"), 8, combine="count")
    return sets.entries(sets.multi_insert(first, w.where("val >= 25"), 8, combine="count")).select("owner", "elem", "val")


@check("insert_combine_last", "SELECT l_partkey AS owner, l_suppkey AS elem, arg_max(l_quantity, (l_orderkey * 10 + l_linenumber) * 1000 + l_quantity) AS val FROM lineitem GROUP BY 1, 2")
def _(spark, d):
    """A batch with an order: its last value of an element counts, and replaces the set's."""
    order = (F.col("l_orderkey") * 10 + F.col("l_linenumber")) * 1000 + F.col("l_quantity")
    t = table(spark, d, "lineitem").select(F.col("l_partkey").alias("owner"), F.col("l_suppkey").alias("elem"), F.col("l_quantity").alias("val"), order.alias("o"), "l_orderkey")
    old, new = t.where("l_orderkey < 7000"), t.where("l_orderkey >= 7000")
    return sets.entries(sets.multi_insert(sets.build(old, 8, combine="last", order="o"), new, 8, order="o")).select("owner", "elem", "val")


@check("intersect_values_sum", f"WITH w AS (SELECT owner, elem, sum(val) AS val FROM ({_WEIGHTS}) GROUP BY owner, elem) SELECT owner, elem, round(2 * val, 6) AS val FROM w WHERE elem % 6 = 0")
def _(spark, d):
    w = sets.fold(weights(spark, d), "sum")
    both = sets.intersect(sets.build(w.where("elem % 2 = 0"), 8), sets.build(w.where("elem % 3 = 0"), 8), "sum")
    return sets.entries(both).select("owner", "elem", F.round("val", 6).alias("val"))


@check("range_agg_sum", f"SELECT owner, CAST(10 AS INTEGER) AS lo_bound, CAST(60 AS INTEGER) AS hi_bound, round(sum(val), 6) AS total FROM ({_WEIGHTS}) WHERE elem BETWEEN 10 AND 60 GROUP BY owner")
def _(spark, d):
    c = sets.build(weights(spark, d), 8, combine="sum")
    ranges = c.select("owner").distinct().select("owner", F.lit(10).alias("lo_bound"), F.lit(60).alias("hi_bound"))
    got = sets.range_agg(c, ranges).where("total <> 0")
    return got.withColumn("total", F.round("total", 6))


# ------------------------------------------------------------------------------------------------------ search and slicing

_PROBES = "p AS (SELECT DISTINCT 2*l_partkey AS owner, 2*l_suppkey + 2 * (l_linenumber % 3) - 2 AS e FROM lineitem)"


def probes(spark, d):
    t = table(spark, d, "lineitem")
    return t.select((F.col("l_partkey") * 2).alias("owner"), (F.col("l_suppkey") * 2 + 2 * (F.col("l_linenumber") % 3) - 2).cast("long").alias("e")).distinct()


@check("find_predecessor", with_(e_sql("ps"), _PROBES) + "SELECT p.owner, p.e, max(e.elem) AS pred FROM p LEFT JOIN e ON p.owner = e.owner AND e.elem <= p.e GROUP BY p.owner, p.e")
def _(spark, d):
    return sets.find(sets.build(owned(spark, d, "ps"), 8), probes(spark, d)).select("owner", "e", "pred")


@check("contains_probe", with_(e_sql("ps"), _PROBES) + "SELECT p.owner, p.e + 1 AS e, e.elem IS NOT NULL AS present FROM p LEFT JOIN e ON p.owner = e.owner AND e.elem = p.e + 1")
def _(spark, d):
    return sets.contains(sets.build(owned(spark, d, "ps"), 8), probes(spark, d).withColumn("e", F.col("e") + 1)).select("owner", "e", "present")


@check("map_elems", with_(e_sql("cs")) + "SELECT owner, elem, elem * 3 + 1 AS mapped FROM e")
def _(spark, d):
    return sets.map_elems(sets.build(owned(spark, d, "cs"), 16), lambda x: x * 3 + 1)


@check("smallest_head", with_(e_sql("ps")) + f"SELECT owner, min(CASE WHEN {is_head_sql('elem', 8)} THEN elem END) AS smallest_head FROM e GROUP BY owner")
def _(spark, d):
    return sets.smallest_head(sets.build(owned(spark, d, "ps"), 8))


@check("expose_roots", with_(e_sql("ps"), f"h AS (SELECT owner, elem, row_number() OVER (PARTITION BY owner ORDER BY elem) AS r, count(*) OVER (PARTITION BY owner) AS n FROM e WHERE {is_head_sql('elem', 8)})") + "SELECT owner, elem AS root FROM h WHERE r = n // 2 + 1")
def _(spark, d):
    return sets.expose(sets.build(owned(spark, d, "ps"), 8))


@check("set_size", with_(e_sql("op")) + "SELECT owner, count(*) AS size FROM e GROUP BY owner")
def _(spark, d):
    return sets.size(sets.build(owned(spark, d, "op"), 4))


@check("rank_select", with_(e_sql("ps")) + "SELECT owner, elem FROM (SELECT *, row_number() OVER (PARTITION BY owner ORDER BY elem) AS r FROM e) WHERE r = 12")
def _(spark, d):
    return sets.select_kth(sets.build(owned(spark, d, "ps"), 8), 12)


@check("rank_of", with_(e_sql("ps"), _PROBES) + "SELECT p.owner, p.e, count(e.elem) AS rank FROM p LEFT JOIN e ON p.owner = e.owner AND e.elem < p.e GROUP BY p.owner, p.e")
def _(spark, d):
    return sets.rank(sets.build(owned(spark, d, "ps"), 8), probes(spark, d))


@check("first_elements", with_(e_sql("ps")) + "SELECT owner, elem FROM (SELECT *, row_number() OVER (PARTITION BY owner ORDER BY elem) AS r FROM e) WHERE r <= 5")
def _(spark, d):
    return sets.first_elements(sets.build(owned(spark, d, "ps"), 8), 5)


@check("min_max_elem", with_(e_sql("cs")) + "SELECT owner, min(elem) AS least, max(elem) AS most FROM e GROUP BY owner")
def _(spark, d):
    return sets.min_max(sets.build(owned(spark, d, "cs"), 16))


@check("range_scan", with_(e_sql("cs")) + "SELECT owner, elem FROM e WHERE elem BETWEEN 40 AND 160")
def _(spark, d):
    return sets.range_scan(sets.build(owned(spark, d, "cs"), 16), 40, 160)


_K = 61
for _side, _where in (("low", f"elem < {_K}"), ("high", f"elem > {_K}")):

    def _cut(spark, d, side=_side):
        low, _, high = sets.split(sets.build(owned(spark, d, "ps"), 8), _K)
        return flat(low if side == "low" else high)

    check(f"split_{_side}", with_(e_sql("ps"), f"part AS (SELECT * FROM e WHERE {_where})", f"h AS ({heads_sql('part', 8)})") + chunk_sql("h"))(_cut)


@check("split_found", with_(e_sql("ps")) + f"SELECT DISTINCT owner FROM e WHERE elem = {_K}")
def _(spark, d):
    return sets.split(sets.build(owned(spark, d, "ps"), 8), _K)[1]


@check("concat_sets", with_(e_sql("ps"), f"h AS ({heads_sql('e', 8)})") + chunk_sql("h"))
def _(spark, d):
    low, found, high = sets.split(sets.build(owned(spark, d, "ps"), 8), _K)
    return flat(sets.concat_sets(low, found.withColumn("elem", F.lit(_K).cast("long")), high, 8))


# ---------------------------------------------------------------------------------------------------------- set operations

_HALVES = f"a AS (SELECT * FROM e WHERE {portable_hash_sql('owner + elem', 11)} % 3 > 0), c AS (SELECT * FROM e WHERE {portable_hash_sql('owner + elem', 12)} % 4 = 0)"


def halves(spark, d, graph="ps"):
    e = owned(spark, d, graph)
    key = F.col("owner") + F.col("elem")
    return e.where(portable_hash(key, 11) % 3 > 0), e.where(portable_hash(key, 12) % 4 == 0)


def _op_sql(body: str) -> str:
    return with_(e_sql("ps"), _HALVES, f"r AS ({body})", f"h AS ({heads_sql('r', 8)})") + chunk_sql("h")


_UNION, _MINUS = "SELECT * FROM a UNION SELECT * FROM c", "SELECT * FROM a EXCEPT SELECT * FROM c"
_BOTH = "SELECT * FROM a INTERSECT SELECT * FROM c"


@check("union_sets", _op_sql(_UNION))
def _(spark, d):
    a, c = halves(spark, d)
    return flat(sets.union(sets.build(a, 8), c, 8))


@check("multi_insert", _op_sql(_UNION))
def _(spark, d):
    a, c = halves(spark, d)
    return flat(sets.multi_insert(sets.build(a, 8), c.unionByName(c), 8))


@check("difference_sets", _op_sql(_MINUS))
def _(spark, d):
    a, c = halves(spark, d)
    return flat(sets.difference(sets.build(a, 8), c, 8))


@check("multi_delete", _op_sql(_MINUS))
def _(spark, d):
    a, c = halves(spark, d)
    return flat(sets.multi_delete(sets.build(a, 8), c.unionByName(c), 8))


@check("intersect_sets", _op_sql(_BOTH))
def _(spark, d):
    a, c = halves(spark, d)
    return flat(sets.intersect(sets.build(a, 8), sets.build(c, 8)))


@check("union_prefix_only", with_(e_sql("ps"), f"c AS (SELECT * FROM e WHERE NOT {is_head_sql('elem', 8)} AND {portable_hash_sql('elem', 4)} % 2 = 0)", f"a AS (SELECT * FROM e WHERE {portable_hash_sql('owner + elem', 11)} % 3 > 0)", f"r AS ({_UNION})", f"h AS ({heads_sql('r', 8)})") + chunk_sql("h"))
def _(spark, d):
    e, (a, _c) = owned(spark, d, "ps"), halves(spark, d)
    loose = e.where(~is_head(F.col("elem"), 8) & (portable_hash(F.col("elem"), 4) % 2 == 0))
    return flat(sets.union_prefix(sets.build(loose, 8), sets.build(a, 8), 8))


@check("union_values_sum", f"WITH w AS (SELECT owner, elem, sum(val) AS val FROM ({_WEIGHTS}) GROUP BY owner, elem), u AS (SELECT * FROM w WHERE elem % 2 = 0 UNION ALL SELECT * FROM w WHERE elem % 3 = 0) SELECT owner, elem, round(sum(val), 6) AS val FROM u GROUP BY owner, elem")
def _(spark, d):
    w = sets.fold(weights(spark, d), "sum")
    merged = sets.union(sets.build(w.where("elem % 2 = 0"), 8, combine="sum"), w.where("elem % 3 = 0"), 8, combine="sum")
    return sets.entries(merged).select("owner", "elem", F.round("val", 6).alias("val"))


@check("path_copy_touched", with_(e_sql("ps"), f"h AS ({heads_sql('e', 8)})", "delta AS (SELECT DISTINCT owner, elem FROM h WHERE owner % 50 = 0)", "c AS (SELECT owner, head, count(*) AS n FROM h GROUP BY owner, head)") + "SELECT count(*) AS chunks, CAST(sum(CASE WHEN owner % 50 = 0 THEN 1 ELSE 0 END) AS BIGINT) AS touched, CAST(sum(CASE WHEN owner % 50 = 0 THEN n ELSE 0 END) AS BIGINT) AS elements_copied FROM c")
def _(spark, d):
    from ..operators.baselines import path_copy

    e = owned(spark, d, "ps")
    return path_copy(sets.build(e, 8), e.where("owner % 50 = 0"), 8)


# ------------------------------------------------------------------------------------------------------ inverted index sets

_TOKENS = "post AS (SELECT DISTINCT token, doc_id FROM (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS token FROM documents))"


def postings(spark, d):
    """(owner: 48-bit id of the token, token, elem: doc_id)."""
    from ..sources.graphs import _id_of_text

    docs = table(spark, d, "documents").select("doc_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("token")).distinct()
    return docs.select(_id_of_text(F.col("token")).alias("owner"), "token", F.col("doc_id").alias("elem"))


def _docs_of(spark, d, token):
    from ..sources.graphs import _id_of_text

    index = sets.build(postings(spark, d).select("owner", "elem"), 16)
    return sets.entries(index.where(F.col("owner") == _id_of_text(F.lit(token)))).select(F.lit(0).cast("long").alias("owner"), "elem")


for _name, _sql in (("and", "INTERSECT"), ("or", "UNION"), ("not", "EXCEPT")):

    def _combine(spark, d, how=_name):
        a, c = _docs_of(spark, d, "the"), _docs_of(spark, d, "der")
        a, c2 = sets.build(a, 16), sets.build(c, 16)
        made = sets.intersect(a, c2) if how == "and" else sets.union(a, c, 16) if how == "or" else sets.difference(a, c, 16)
        return sets.entries(made).select(F.col("elem").alias("doc_id"))

    check(f"postings_{_name}", with_(_TOKENS) + f"SELECT doc_id FROM post WHERE token = 'the' {_sql} SELECT doc_id FROM post WHERE token = 'der'")(_combine)


@check("postings_add_docs", with_(_TOKENS) + "SELECT token, count(*) AS docs FROM post GROUP BY token HAVING count(*) > 20")
def _(spark, d):
    p = postings(spark, d)
    names = p.select("owner", "token").distinct()
    old, new = p.where("elem % 4 <> 0").select("owner", "elem"), p.where("elem % 4 = 0").select("owner", "elem")
    size = sets.size(sets.union(sets.build(old, 16), new, 16)).where("size > 20")
    return size.join(names, "owner").select("token", F.col("size").alias("docs"))


@check("postings_benchmark_overlap", with_("b AS (SELECT DISTINCT item_id, token FROM (SELECT item_id, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS token FROM benchmark))", _TOKENS) + "SELECT item_id, count(*) AS shared_tokens FROM b WHERE token IN (SELECT token FROM post) GROUP BY item_id")
def _(spark, d):
    items = table(spark, d, "benchmark").select("item_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("token")).distinct()
    known = postings(spark, d).select("token").distinct()
    return items.join(known, "token", "left_semi").groupBy("item_id").agg(F.count("*").alias("shared_tokens"))
