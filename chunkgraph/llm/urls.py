"""URL filter: frequent token combinations of labelled URLs become association rules, matched through an inverted index.

A written rule (host and path prefix) decides where one fits; the longest host, then the longest path wins. The labels
that the method learns from are those decisions, with every other URL as an example of allow, unless labels are given. Tokens of a URL are its host's
dot-separated parts (`h:`) and its path's parts (`p:`), whole; a path part with digits also gives its shape, with every run
of digits as `#`. Scheme and query are no tokens, since only host and path are judged. FP-growth finds the
combinations that reach the support; rules that reach the confidence and have no shorter rule with the same verdict are
kept, and a URL that no written rule fits is blocked when a block rule matches and no allow rule of higher confidence does.
Null URLs and those without `://` have empty host and path and get the method's verdict on no tokens: allow. Repeated rows are each
judged. Only support and confidence bound the rules; a template of very many tokens that most URLs share has as many
frequent sets as it has subsets, which FP-growth lists. Everything is DataFrame work inside the JVM.
"""

from __future__ import annotations

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import settle, table

# The written rules, (verdict, host, path).
RULES = (("block", "com", "en/"), ("allow", "example.com", "en/7"), ("allow", "net", "de/"), ("block", "example.net", "de/8"), ("block", "org", "es/"))
SUPPORT = 0.002
CONFIDENCE = 0.9
#: Up to so many learned rules are carried into the plan; more are joined.
LITERAL_RULES = 256
_BLOCK, _ALLOW = "label=block", "label=allow"


def parts(url: Column) -> tuple[Column, Column]:
    """Host, A-Z lower-cased, and path."""
    known = F.coalesce(url.contains("://"), F.lit(False))
    after = F.substring(url, F.instr(url, "://") + 3, F.length(url))
    host = F.regexp_extract(after, r"^[^/?#]*", 0)
    path = F.regexp_extract(F.substring(after, F.length(host) + 1, F.length(after)), r"(?s)^[^?#]*", 0)
    lowered = F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return F.when(known, lowered).otherwise(""), F.when(known, path).otherwise("")


def _fits(host: Column, path: Column, rule_host: str, rule_path: str) -> Column:
    return ((host == rule_host) | host.endswith(f".{rule_host}")) & path.startswith(f"/{rule_path}")


def written_rule(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """(rule, verdict) of the longest rule that fits, null where none does."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for kind, h, p in sorted(rules, key=lambda r: (len(r[1]) + len(r[2]), r)):
        fits = _fits(host, path, h, p)
        name, verdict = F.when(fits, f"{h}/{p}").otherwise(name), F.when(fits, kind).otherwise(verdict)
    return name, verdict


def tokens(host: Column, path: Column) -> Column:
    hosts = F.transform(F.split(host, r"\."), lambda x: F.concat(F.lit("h:"), x))
    named = F.split(path, r"[/._-]")
    paths = F.transform(named, lambda x: F.concat(F.lit("p:"), x))
    shapes = F.transform(F.filter(named, lambda x: x.rlike("[0-9]")), lambda x: F.concat(F.lit("p:"), F.regexp_replace(x, "[0-9]+", "#")))
    return F.array_distinct(F.filter(F.concat(hosts, paths, shapes), lambda x: F.length(x) > 2))


def learn(labelled: DataFrame, support: float = SUPPORT, confidence: float = CONFIDENCE) -> DataFrame:
    """labelled: items (array of tokens), verdict. All minimal rules: body (tokens), head, confidence, rare (the least frequent token).

    Every part of a frequent body is frequent, so level by level a body is covered when one of its parts with a token
    less is a rule or covered itself; rules that are not covered are minimal.
    """
    items = F.concat("items", F.array(F.concat(F.lit("label="), F.col("verdict"))))
    model = FPGrowth(itemsCol="items", minSupport=support, minConfidence=confidence).fit(labelled.select(items.alias("items")))
    marked = settle(model.freqItemsets.select(F.array_sort(F.filter("items", lambda x: ~x.startswith("label="))).alias("body"), F.get(F.filter("items", lambda x: x.startswith("label=")), 0).alias("head"), "freq"))
    whole = marked.where(F.col("head").isNull()).select("body", F.col("freq").alias("all"))
    bodies = settle(marked.where(F.col("head").isNotNull() & (F.size("body") > 0)).join(whole, "body").select("body", "head", (F.col("freq") / F.col("all")).alias("confidence")))
    is_rule = F.col("confidence") >= confidence
    below = kept = bodies.where((F.size("body") == 1) & is_rule)
    for k in range(2, (bodies.agg(F.max(F.size("body"))).first()[0] or 0) + 1):
        level = bodies.where(F.size("body") == k)
        part = F.explode(F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda i: F.filter("body", lambda x, j: j != i))).alias("part")
        covered = level.select("body", "head", part).join(below.select(F.col("body").alias("part"), "head"), ["part", "head"], "left_semi").select("body", "head").distinct().withColumn("covered", F.lit(True))
        marks = settle(level.join(covered, ["body", "head"], "left").select("body", "head", "confidence", F.coalesce("covered", F.lit(False)).alias("covered")))
        kept = kept.unionAll(marks.where(is_rule & ~F.col("covered")).select("body", "head", "confidence"))
        below = marks.where(is_rule | F.col("covered"))
    single = whole.where(F.size("body") == 1).select(F.get("body", 0).alias("token"), "all")
    rare = kept.select("body", F.explode("body").alias("token")).join(single, "token").groupBy("body").agg(F.min(F.struct("all", "token"))["token"].alias("rare"))
    return settle(kept.join(rare.distinct(), "body").select("body", "head", "confidence", "rare"))


def matched(items: Column, rules: list[tuple[list[str], str, float]], head: str) -> Column:
    """The highest confidence of the rules with this head whose tokens all occur in items; 0 where none matches. For few rules."""
    own = [(body, c) for body, v, c in rules if v == head]
    if not own:
        return F.lit(0.0)
    index: dict[str, list[int]] = {}
    for k, (body, _) in enumerate(own):
        for token in body:
            index.setdefault(token, []).append(k)
    postings = F.create_map(*(x for t, ks in sorted(index.items()) for x in (F.lit(t), F.array(*map(F.lit, ks)))))
    need, sure = F.array(*(F.lit(len(b)) for b, _ in own)), F.array(*(F.lit(c) for _, c in own))
    hits = F.flatten(F.transform(items, lambda t: F.coalesce(F.try_element_at(postings, t), F.array().cast("array<int>"))))
    full = F.filter(F.array_distinct(hits), lambda k: F.size(F.filter(hits, lambda x: x == k)) == F.get(need, k))
    return F.coalesce(F.array_max(F.transform(full, lambda k: F.get(sure, k))), F.lit(0.0))


def scored(known: DataFrame, learned: DataFrame, literal: int = LITERAL_RULES) -> DataFrame:
    """known (with items) and block, allow: as `matched` has them, in the row for few rules and by a join of tokens for many."""
    few = [(list(r["body"]), r["head"], float(r["confidence"])) for r in learned.limit(literal + 1).collect()]
    if len(few) <= literal:
        return known.select("*", matched(F.col("items"), few, _BLOCK).alias("block"), matched(F.col("items"), few, _ALLOW).alias("allow"))
    sets = known.select("items").distinct()
    met = sets.select("items", F.explode("items").alias("rare")).join(learned, "rare").where(F.size(F.array_except("body", "items")) == 0)
    best = lambda head: F.coalesce(F.max(F.when(F.col("head") == head, F.col("confidence"))), F.lit(0.0))
    sure = met.groupBy("items").agg(best(_BLOCK).alias("block"), best(_ALLOW).alias("allow"))
    return known.join(sure, "items", "left").withColumns({c: F.coalesce(c, F.lit(0.0)) for c in ("block", "allow")})


def judge(pages: DataFrame, labels: DataFrame | None = None, rules=RULES) -> DataFrame:
    """(page_id, url) -> page_id, host, path, rule, verdict. labels: page_id, verdict, to learn from instead of the rules."""
    host, path = parts(F.col("url"))
    split = pages.select("page_id", host.alias("host"), path.alias("path"))
    name, verdict = written_rule(F.col("host"), F.col("path"), rules)
    known = split.select("*", name.alias("rule"), verdict.alias("given"), tokens(F.col("host"), F.col("path")).alias("items"))
    taught = known.select("items", F.coalesce("given", F.lit("allow")).alias("verdict")) if labels is None else known.join(labels.select("page_id", "verdict"), "page_id").select("items", "verdict")
    method = F.when(F.col("block") > F.col("allow"), "block").otherwise("allow")
    return scored(known, learn(taught)).select("page_id", "host", "path", "rule", F.coalesce("given", method).alias("verdict"))


def query(spark, sf_dir):
    return judge(table(spark, sf_dir, "pages"))
