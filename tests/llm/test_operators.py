"""The training-data operators against plain versions, and on odd tables."""

import hashlib
import random
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from chunkgraph.llm import bpe, decontaminate, embeddings, fmindex, langid, minhash, pii, quality, repeats, suffixarray, urls
from chunkgraph.llm.components import components
from chunkgraph.llm.repeats import anchors

from ..compare import assert_same, connection
from ..conftest import DATA
from . import brute

ODD = [(1, None), (2, ""), (3, " \n\t"), (None, "one two three"), (4, "x" * 70_000), (5, "the same text " * 40), (6, "the same text " * 40), (7, "the same text " * 40), (7, "the same text " * 40), (8, "é ü 日本 " * 30), (9, "word " * 20_000), (10, "\x0b a  b \x85")]


def docs(spark, rows, extra=True):
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    # further columns, with names that the operators use inside
    return df.withColumns({c: F.lit("x") for c in ("digest", "spans", "score", "kept", "label")}).withColumn("lang", F.lit("en")).withColumn("n_chars", F.length("text").cast("long")) if extra else df


def prose(seed, count):
    r = random.Random(seed)
    base = [" ".join(r.choice(["aa", "b", "c é", "dd", "\n", "The", "of"]) for _ in range(r.randint(0, 40))) for _ in range(12)]
    return [(k, " ".join(r.choice(base) for _ in range(r.randint(0, 4)))) for k in range(count)]


def sorted_rows(df):
    return sorted(map(tuple, df.collect()), key=repr)


@pytest.fixture(scope="module")
def given(spark):
    rows = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{DATA}/documents.parquet").collect()]
    return spark.read.parquet(f"{DATA}/documents.parquet"), rows


# ---------------------------------------------------------------------------------------------------------------- repeats


@pytest.mark.parametrize("window", [5, 9, 50])
def test_repeats_equal_brute_force(spark, window):
    rows = prose(window, 60) + [(100, None), (101, ""), (7, prose(window, 60)[7][1])]
    words = fmindex.deduplicate(docs(spark, rows), window).select("doc_id", "n_words", "n_removed", F.sha2("kept", 256))
    assert sorted_rows(words) == sorted(brute.op7(rows, window), key=repr)
    raw = suffixarray.deduplicate(docs(spark, rows), window).select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256))
    assert sorted_rows(raw) == sorted(brute.op10(rows, window), key=repr)


def test_repeats_on_given_documents(given):
    df, rows = given
    assert sorted_rows(fmindex.report(df)) == sorted(brute.op7(rows), key=repr)
    assert sorted_rows(suffixarray.report(df)) == sorted(brute.op10(rows), key=repr)


def test_index_structures():
    r = random.Random(4)
    for _ in range(150):
        n, top = r.randint(0, 60), r.choice([0, 1, 3, 200])
        a = np.array([r.randint(0, top) for _ in range(n)], np.int64)
        assert suffixarray.difference_cover_order(a).tolist() == sorted(range(n), key=lambda i: a[i:].tolist())  # noqa: B023
    for _ in range(30):
        texts = [np.array([r.randint(1, 3) for _ in range(r.randint(1, 20))], np.int64) for _ in range(4)]
        index, q = fmindex.FmIndex(texts), np.array([r.randint(1, 4) for _ in range(15)])
        subs = {tuple(t[i:j]) for t in texts for i in range(len(t)) for j in range(i + 1, len(t) + 1)}
        longest = [max([0, *(n for n in range(1, 16 - p) if tuple(q[p : p + n]) in subs)]) for p in range(15)]
        assert index.matching_statistics(q).tolist() == longest


def test_anchors_cover_every_window_once():
    x = np.random.default_rng(1).integers(0, 3, 3000).astype(np.uint8)
    at, _, first, last = anchors(x, 8, 50)
    assert first[0] == 0 and last[-1] == 2950 and (first[1:] == last[:-1] + 1).all() and (at >= last).all() and (at + 8 <= first + 50).all()


# ---------------------------------------------------------------------------------------------------------- decontamination


def test_decontamination_equals_brute_force(spark, given):
    df, rows = given
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{DATA}/benchmark.parquet").collect()]
    items += [(900, None), (901, "  ??"), (902, "Only Three words"), (903, rows[0][1]), (904, "ÉCOLE"), (1, "twice the id")]
    rows = rows + [(5000, None), (5001, "… ONLY three   words! école ÉCOLE"), (5002, "")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = decontaminate.report(docs(spark, rows), bench)
    assert sorted_rows(got) == sorted(brute.op1(rows, items), key=repr)
    clean = {r["doc_id"] for r in decontaminate.remove_documents(docs(spark, rows), bench).collect()}
    assert clean == {x[0] for x in brute.op1(rows, items) if not x[5]}
    again = rows + rows[:9] + [(rows[0][0], "another text of the id"), (None, rows[0][1]), (None, rows[0][1])]
    assert sorted_rows(decontaminate.report(docs(spark, again), bench)) == sorted(brute.op1(again, items), key=repr)
    clean = [r["text"] for r in decontaminate.remove_documents(docs(spark, again), bench).collect()]
    assert sorted(clean, key=repr) == sorted([x[1] for x, y in zip(again, brute.op1(again, items)) if not y[5]], key=repr)
    left = {r["doc_id"]: r["text"] for r in decontaminate.remove_spans(docs(spark, rows), bench).collect()}
    assert left[5001] == "… école"


def test_empty_benchmark(spark):
    none = spark.createDataFrame([], "item_id long, text string")
    assert {r["contaminated"] for r in decontaminate.report(docs(spark, ODD[:5]), none).collect()} == {False}


def test_decontamination_sql(spark):
    c = connection(DATA)
    assert_same(decontaminate.query(spark, DATA), c, decontaminate.ORACLE_SQL)
    assert_same(embeddings.query(spark, DATA), c, embeddings.ORACLE_SQL)


# ------------------------------------------------------------------------------------------------------------------- tokens


def test_bpe_equals_the_library(spark, given):
    import public_tokenizers
    import tiktoken

    own = bpe.ByteBpe(bpe.default_ranks_path())
    library = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=own.ranks, special_tokens={})
    r = random.Random(3)
    pool = [" ", "  ", "\n", "\t", "\x1c", "\x85", "\xa0", "'s", "'ll", "a", "B", "é", "日本", "1", "²", "!", "$$", "\u200b", "\u3000", "👍🏽", "\u0301", "\x00", "<|endoftext|>"]
    texts = [t for _, t in given[1][:60]] + ["".join(r.choice(pool) for _ in range(r.randint(0, 14))) for _ in range(1500)] + ["ab" * 20_000]
    for t in texts:
        packed = own.encode(t)
        assert np.frombuffer(packed, "<u4").tolist() == library.encode_ordinary(t) and own.decode(packed) == t.encode()
    rows = [(k, t) for k, t in ODD if k]
    got = sorted_rows(bpe.digests(docs(spark, rows)))
    want = [(k, len(ids := library.encode_ordinary(t or "")), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()) for k, t in rows]
    assert got == sorted(want, key=repr)


# ------------------------------------------------------------------------------------------------------------ personal data


def plain_spans(t):
    digits = lambda s: re.sub("[^0-9]", "", s)
    kinds = (
        ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda s: True),
        ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda s: all(int(x) <= 255 for x in s.split("."))),
        ("card", r"[0-9]([\x20-]?[0-9])+", lambda s: 13 <= len(digits(s)) <= 19 and pii.luhn(digits(s))),
        ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", lambda s: 9 <= len(digits(s)) <= 15),
    )
    return [(k, m.start(), m.end()) for k, p, f in kinds for m in re.finditer(p, t) if f(m.group())]


def test_base_spans(given):
    r = random.Random(1)
    pool = ["1", "2", "25", "4", "0", ".", ".", "@", "a", "b", "-", "+", " ", "(", ")", "_", ".com", "é", "4111111111111111", "1.2.3.4", "x@y.z", "+1 234567890"]
    texts = [t for _, t in given[1]] + ["".join(r.choice(pool) for _ in range(r.randint(1, 18))) for _ in range(20_000)]
    for t in texts:
        assert pii.base_spans(t) == plain_spans(t)


def test_loose_formats_and_redaction(spark):
    model = pii.default_model()
    for text, kind in (("write to jane.doe [at] example dot com now", "email"), ("tel. (030) 555-1234 please", "phone"), ("credit card: 4111.1111.1111.1111 ok", "card")):
        assert [s["kind"] for s in pii.find_spans(text, model)] == [kind]
    for clean in ("meet at noon. dot the i", "version 2.0.31 of 2021-11-23", "isbn 978-3-1234-5678-9", "order 12345678 of 4556 7375 8689 9856 x"):
        assert not [s for s in pii.find_spans(clean, model) if not s["base"]]
    got = {r["doc_id"]: r["text"] for r in pii.redact_frame(docs(spark, [(1, "a@b.co and 10.0.0.1"), (2, None), (3, "")])).collect()}
    assert got == {1: "[EMAIL] and [IP]", 2: None, 3: ""}
    assert pii.report(docs(spark, ODD)).count() == len(ODD)


def test_addresses_in_words_are_proposed():
    model, text = pii.default_model(), "please contact jane.doe at example.org or call"
    assert pii.loose_candidates("jane at example.com") == [("email", 0, 19)]
    assert [(s["kind"], text[s["start"] : s["end"]]) for s in pii.find_spans(text, model)] == [("email", "jane.doe at example.org")]
    for clean in ("we met at noon. The train left", "look at home. It was fine", "they sat at tables.Some of them left"):
        assert not pii.find_spans(clean, model)


# -------------------------------------------------------------------------------------------------------------- classifiers


def test_quality_on_held_out_rows(spark):
    folder = DATA.replace("0.001", "0.01")
    got = quality.query(spark, folder)
    labels = spark.read.parquet(f"{folder}/labels.parquet")
    rows = got.join(labels, "doc_id").where("held_out").select("score", "predicted", "quality").collect()
    assert np.mean([r["predicted"] == r["quality"] for r in rows]) > 0.93
    assert all(0 <= r["score"] <= 1 for r in rows)


def test_quality_equals_plain_normal_equations(spark):
    """The sums over partitions give the ridge weights of the whole matrix, and the calibration a step function of the score."""
    r = np.random.default_rng(8)
    x = r.standard_normal((400, quality.STATISTICS)).astype("f4")
    y = (x[:, 0] + x[:, 1] ** 2 > 0.5).astype(int)
    df = spark.createDataFrame([(v.tolist(), int(t)) for v, t in zip(x, y)], "stats array<float>, target int").repartition(5)
    model = quality.fit(df)
    z = model.lift(x.astype(float))
    penalty = np.diag([*np.full(quality.FEATURES, model.ridge * 400 / (quality.FEATURES + 1)), 0.0]) + 1e-9 * np.eye(quality.FEATURES + 1)
    assert np.allclose(model.weights, np.linalg.solve(z.T @ z + penalty, z.T @ y), atol=1e-6)
    score = model.score(x.astype(float))
    assert (np.diff(score[np.argsort(model.raw(x.astype(float)))]) >= 0).all() and ((score >= 0.5) == y).mean() > 0.9


def test_quality_without_labels(spark):
    none = spark.createDataFrame([], "doc_id long, quality int")
    assert {r["score"] for r in quality.classify(docs(spark, ODD), none).collect()} == {0.5}


def test_language_on_held_out_rows(spark):
    folder = DATA.replace("0.001", "0.01")
    got = langid.query(spark, folder).join(spark.read.parquet(f"{folder}/documents.parquet").select("doc_id", "lang"), "doc_id")
    rows = got.where("held_out").collect()
    assert np.mean([r["lang"] == r["lang_pred"] for r in rows]) > 0.97


def test_language_equals_the_plain_kernel():
    """Scores from gathered rows are those of the dense kernel matrix, Nystroem map and ridge."""
    r = random.Random(3)
    words = {"a": ["la", "le", "une", "été"], "b": ["der", "die", "und", "für"], "c": ["the", "of", "and"]}
    texts = [(" ".join(r.choice(words[y]) for _ in range(r.randint(3, 30))), y) for y in "abc" * 20]
    flags = np.zeros(langid.SLOTS, bool)
    rows = [langid.presence(t, flags) for t, _ in texts]
    assert not flags.any()
    model = langid.fit(rows, [y for _, y in texts])
    sets = [set(x.tolist()) for x in rows]
    marks = [k for y in "abc" for k in [i for i, (_, z) in enumerate(texts) if z == y][: langid.LANDMARKS // 3]]
    kernel = lambda i, j: len(sets[i] & sets[j]) / (len(sets[i]) * len(sets[j])) ** 0.5
    full = np.array([[kernel(i, j) for j in marks] for i in range(len(texts))])
    values, vectors = np.linalg.eigh(full[marks])
    good = values > values.max() * 1e-6
    lifted = full @ (vectors[:, good] / np.sqrt(values[good]))
    target = np.array([[1.0 if y == name else -1.0 for name in "abc"] for _, y in texts])
    beta = np.linalg.solve(lifted.T @ lifted / 20 + langid.RIDGE * np.eye(lifted.shape[1]), lifted.T @ target / 20)
    assert np.allclose(model.scores(rows), lifted @ beta, atol=1e-3)
    assert model.predict([t for t, _ in texts])[0] == [y for _, y in texts]


def test_language_of_odd_rows(spark):
    got = {(r["doc_id"], r["lang_pred"]) for r in langid.classify(docs(spark, [*ODD, (20, "12 34 !")])).collect()}
    assert {(1, "und"), (2, "und"), (3, "und"), (20, "und"), (9, "en")} <= got
    none = spark.createDataFrame([], "doc_id long, text string, lang string")
    assert langid.classify(none).count() == 0


def test_url_rules(spark):
    cases = {
        "http://Example.COM/en/8": ("example.com", "/en/8", "com/en/", "block"), "https://a.example.com/en/77?x=1": ("a.example.com", "/en/77", "example.com/en/7", "allow"),
        "http://x.net/de/1": ("x.net", "/de/1", "net/de/", "allow"), "http://example.net/de/8#a": ("example.net", "/de/8", "example.net/de/8", "block"),
        "ftp://b.org/es/": ("b.org", "/es/", "org/es/", "block"), "http://notexample.com/fr": ("notexample.com", "/fr", None, "allow"),
        "no scheme": ("", "", None, "allow"), None: ("", "", None, "allow"), "http://é.com?q://z": ("é.com", "", None, "allow"), "": ("", "", None, "allow"),
    }
    df = spark.createDataFrame(list(enumerate(cases)), "page_id long, url string")
    got = {r["page_id"]: tuple(r)[1:] for r in urls.judge(df).collect()}
    assert [got[k] for k in range(len(cases))] == list(cases.values())


def test_url_rules_are_learned(spark):
    pages = [(k, f"http://{'bad' if k % 2 else 'good'}.host{k % 3}.io/p{k}") for k in range(60)]
    labels = spark.createDataFrame([(k, "block" if k % 2 else "allow") for k in range(40)], "page_id long, verdict string")
    got = urls.judge(spark.createDataFrame(pages, "page_id long, url string"), labels).collect()
    assert all((r["verdict"] == "block") == (r["page_id"] % 2 == 1) for r in got)


def test_url_rules_are_long_and_many(spark):
    schema = "page_id long, url string"
    subsets = [[c for i, c in enumerate("abcde") if k >> i & 1] for k in range(1, 32)]
    pages = [(k, f"http://one.io/{'x/'.join([*s, ''])}") for k, s in enumerate(subsets * 4)]
    labels = spark.createDataFrame([(k, "block" if k % 31 == 30 else "allow") for k in range(93)], "page_id long, verdict string")
    got = urls.judge(spark.createDataFrame(pages, schema), labels).collect()
    assert {r["page_id"] for r in got if r["verdict"] == "block"} == {30, 61, 92, 123}
    many = [(k, f"http://host{k % 400}.io/") for k in range(1200)]
    labels = spark.createDataFrame([(k, "block" if k % 2 else "allow") for k in range(800)], "page_id long, verdict string")
    got = urls.judge(spark.createDataFrame(many, schema), labels).collect()
    assert len(got) == 1200 and all((r["verdict"] == "block") == (r["page_id"] % 2 == 1) for r in got)


def test_learned_url_rules_equal_brute_force(spark):
    """All minimal rules by counting subsets of tokens, and the verdicts that they give."""
    from itertools import combinations

    r = random.Random(9)
    pages = [(k, f"http://{r.choice(['a', 'b', 'c'])}.{r.choice(['x', 'y'])}.org/{r.choice(['news', 'averylongsharedprefixone', 'averylongsharedprefixtwo'])}/{r.choice(['v12', 'v7', 'w'])}") for k in range(120)]
    verdict = {k: "block" if "prefixtwo" in u and "a." in u or "v7" in u and ".y." in u else "allow" for k, u in pages}
    split = lambda u: (u.split("//")[1].split("/")[0], "/" + "/".join(u.split("//")[1].split("/")[1:]))

    def items(u):
        host, path = split(u)
        parts = [p for p in re.split("[/._-]", path) if p]
        return {f"h:{x}" for x in host.split(".")} | {f"p:{x}" for x in parts} | {"p:" + re.sub("[0-9]+", "#", x) for x in parts if re.search("[0-9]", x)}

    sets = {k: items(u) for k, u in pages}
    counts, least = {}, 0.05 * len(pages)
    for k, s in sets.items():
        for n in range(1, len(s) + 1):
            for body in combinations(sorted(s), n):
                counts.setdefault(body, Counter())[verdict[k]] += 1
    rules = {(b, h): c[h] / sum(c.values()) for b, c in counts.items() for h in c if c[h] >= least and c[h] / sum(c.values()) >= 0.9}
    rules = {(b, h): c for (b, h), c in rules.items() if not any(g == h and set(a) < set(b) for a, g in rules)}
    df = spark.createDataFrame([(sorted(sets[k]), verdict[k]) for k, _ in pages], "items array<string>, verdict string")
    got = {(tuple(x["body"]), x["head"].removeprefix("label=")): x["confidence"] for x in urls.learn(df, 0.05, 0.9).collect()}
    assert got.keys() == rules.keys() and all(abs(got[k] - rules[k]) < 1e-9 for k in got)
    host, path = urls.parts(F.col("url"))
    tokens = spark.createDataFrame(pages, "page_id long, url string").select("page_id", urls.tokens(host, path).alias("t")).collect()
    assert all(set(x["t"]) == sets[x["page_id"]] for x in tokens)


def test_url_rules_joined_or_in_the_plan(spark):
    host, path = urls.parts(F.col("url"))
    pages = spark.read.parquet(f"{DATA.replace('0.001', '0.01')}/pages.parquet").select(host.alias("host"), path.alias("path"))
    known = pages.select("host", "path", urls.tokens(F.col("host"), F.col("path")).alias("items"), urls.written_rule(F.col("host"), F.col("path"))[1].alias("given")).localCheckpoint()
    learned = urls.learn(known.select("items", F.coalesce("given", F.lit("allow")).alias("verdict")))
    rules = [(set(r["body"]), r["head"]) for r in learned.collect()]
    assert rules and not any(h == g and a > b for a, h in rules for b, g in rules)
    columns = ("host", "path", "block", "allow")
    assert sorted_rows(urls.scored(known, learned, 10_000).select(*columns)) == sorted_rows(urls.scored(known, learned, 0).select(*columns))


# --------------------------------------------------------------------------------------------------------- near-duplicates


def test_components(spark):
    r = random.Random(2)
    links = [(r.randrange(200), r.randrange(200)) for _ in range(150)] + [(k, k + 1) for k in range(300, 420)]
    parent = {}

    def root(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        x, y = root(a), root(b)
        parent[max(x, y)] = min(x, y)
    got = {x["node"]: x["component"] for x in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {v: root(v) for v in parent if any(v in x for x in links if x[0] != x[1])}


def test_embeddings_equal_brute_force(spark):
    g = np.random.default_rng(3)
    base = g.standard_normal((40, 16))
    rows = [(k, (base[k % 40] + g.standard_normal(16) * (0.02 + 0.1 * (k % 3))).astype("f4").tolist(), k % 2) for k in range(300)]
    rows += [(k + 300, rows[k][1], rows[k][2]) for k in range(20)]  # copies
    odd = [(900, None, 1), (901, [0.0] * 16, 1), (902, [float("nan")] * 16, 1), (903, rows[0][1], None), (904, [None] * 16, 0), (905, [], 1)]
    df = spark.createDataFrame(rows + odd, "vec_id long, embedding array<float>, label int").repartition(4)
    x = np.array([np.array(r[1], "f4") for r in rows], float)
    x /= np.sqrt((x * x).sum(1, keepdims=True))
    label = np.array([r[2] for r in rows])
    link = (x @ x.T >= 0.98) & (label[:, None] == label[None, :])
    np.fill_diagonal(link, False)
    reach = np.arange(len(rows))
    while True:
        new = np.array([min(reach[i], *(reach[link[i]].tolist() or [reach[i]])) for i in range(len(rows))])
        if (new == reach).all():
            break
        reach = new
    got = {r["vec_id"]: (r["n_links"], r["component_id"], r["kept"]) for r in embeddings.near_duplicates(df).collect()}
    assert link.sum() > 100
    assert got == {k: (int(link[k].sum()), int(reach[k]), int(reach[k]) == k) for k in range(len(rows))} | {r[0]: (0, r[0], True) for r in odd}


def test_embeddings_of_other_types(spark):
    rows = [(1, [1e30, 0.0], "a"), (2, [1e60, 1.0], "a"), (3, [1e60, 1.0], "b"), (4, [1.0], "a"), (5, [2.0], "a"), (6, [-2.0], "a"), (7, [1e-300, 0.0], "a"), (None, [1.0, 0.0], "a"), (8, [1.0, 0.0], None)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label string").withColumn("component_id", F.lit("x")).withColumn("rep", F.lit(0))
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in embeddings.near_duplicates(df).collect()}
    assert got == {1: (2, 1), 2: (2, 1), 7: (2, 1), 3: (0, 3), 4: (1, 4), 5: (1, 4), 6: (0, 6), None: (0, None), 8: (0, 8)}
    edge = [(k, [float(np.cos(a)), float(np.sin(a))], 1) for k, a in enumerate((0.0, float(np.arccos(0.98)) - 1e-9, -float(np.arccos(0.98)) - 1e-9))]
    got = {r["vec_id"]: r["component_id"] for r in embeddings.near_duplicates(spark.createDataFrame(edge, "vec_id long, embedding array<double>, label int")).collect()}
    assert got == {0: 0, 1: 0, 2: 2}


def test_near_duplicates_equal_brute_force(spark):
    r = random.Random(6)
    vocabulary = [f"w{k}" for k in range(400)]
    base = [[r.choice(vocabulary) for _ in range(120)] for _ in range(12)]
    rows = []
    for k in range(120):
        words = list(base[k % 12])
        for _ in range(r.choice([0, 0, 1, 2, 6])):
            words[r.randrange(120)] = r.choice(vocabulary)
        rows.append((k, " ".join(words)))
    rows += [(200, None), (201, ""), (202, "!?"), (203, "short one"), (204, "Short, ONE")]
    df = docs(spark, rows)
    idf, shingles = minhash.document_frequencies(df), minhash.make_shingles()
    h = {k: shingles(t) for k, t in rows}
    parent = {k: k for k, _ in rows}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    keys = [k for k, _ in rows if len(h[k])]
    sims = {(a, b): minhash.similarity(h[a], h[b], idf) for i, a in enumerate(keys) for b in keys[i + 1 :]}
    for (a, b), s in sims.items():
        if s >= 0.8:
            x, y = root(a), root(b)
            parent[max(x, y)] = min(x, y)
    got = {x["doc_id"]: (x["component_id"], x["kept"]) for x in minhash.near_duplicates(df).collect()}
    assert got == {k: (root(k), root(k) == k) for k, _ in rows}
    kept = {x["doc_id"] for x in minhash.keep_first(df).collect()}
    assert kept == {k for k, _ in rows if root(k) == k}


def test_pairs_that_share_only_large_buckets(spark):
    """A family just under the threshold with pairs above it in the same large buckets: hubs alone miss some of them."""
    r = random.Random(11)
    head, rows = [f"t{k}" for k in range(400)], []
    for k in range(300):
        tail = [f"u{k}x{i}" for i in range(27)]
        if k % 5 == 1:  # a few more words as the one before
            tail[:3] = rows[-1][1].split()[400:403]
        rows.append((k, " ".join(head + tail)))
    r.shuffle(rows)
    df = docs(spark, rows)
    idf, shingles = minhash.document_frequencies(df), minhash.make_shingles()
    h = {k: shingles(t) for k, t in rows}
    pairs = [(k, k + 1) for k in range(0, 300, 5)]
    assert all(minhash.similarity(h[a], h[b], idf) >= 0.8 for a, b in pairs)
    assert all(0.75 < minhash.similarity(h[0], h[k], idf) < 0.8 for k in range(2, 300))
    got = {x["doc_id"]: x["component_id"] for x in minhash.near_duplicates(df).collect()}
    assert got == {k: k - 1 if k % 5 == 1 else k for k in range(300)}
    packed = [np.sort(h[k]).astype("<u4").tobytes() for k in range(40)] + [np.sort(np.tile(h[k][:50], k + 1)).astype("<u4").tobytes() for k in range(3)]
    block = minhash.Occurrences(packed, idf)
    plain = [[minhash.similarity(*(np.frombuffer(p, "<u4").astype(np.uint64) for p in (a, b)), idf) for b in packed] for a in packed]
    assert np.allclose(minhash.similarities(block, block), plain, rtol=0, atol=1e-6)


def test_near_duplicates_in_blocks_of_any_size(spark):
    """Three documents of one template that only share large buckets, and a chain; an own shingler, exact document frequencies."""
    r = random.Random(5)
    base, rows = [f"b{k}" for k in range(400)], []
    for k in range(303):
        words, key = list(base), k if k < 300 else 700 + k
        for _ in range(5 if k < 300 else 2):
            words[r.randrange(400)] = f"x{r.randrange(10**6)}"
        rows.append((key, " ".join(words)))
    rows += [(2000 + k, " ".join(f"c{i}" for i in range(4 * k, 4 * k + 100))) for k in range(30)]
    grams = {k: Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4)) for k, t in rows for w in [t.split()]}
    df = Counter(g for c in grams.values() for g in c)
    idf = {g: 1 + np.log((1 + len(rows)) / (1 + n)) / np.log(1 + len(rows)) for g, n in df.items()}
    parent, near = {k: k for k, _ in rows}, 0

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, (a, _) in enumerate(rows):
        for b, _ in rows[i + 1 :]:
            low, high = (sum(f(grams[a][g], grams[b][g]) * idf[g] for g in grams[a].keys() | grams[b].keys()) for f in (min, max))
            near += abs(low / high - 0.8) < 1e-4
            if low / high >= 0.8:
                x, y = root(a), root(b)
                parent[max(x, y)] = min(x, y)
    assert not near and len({root(k) for k in (1000, 1001, 1002)}) == 1
    for block in (None, 2):
        classes, labels = minhash.grouped(docs(spark, rows), block=block)
        named = {x["node"]: x["component"] for x in labels.collect()}
        assert {x["doc_id"]: named.get(x["node"], x["node"]) for x in classes.collect()} == {k: root(k) for k, _ in rows}


def test_odd_tables_everywhere(spark):
    for rows in (ODD, []):
        df = docs(spark, rows)
        for f in (fmindex.report, suffixarray.report, minhash.near_duplicates, bpe.digests, pii.report, langid.classify):
            assert f(df).count() == len(rows), f
        labels = spark.createDataFrame([(1, 1, 0), (6, 0, 1), (None, 1, 0), (9, None, 0)], "doc_id long, quality int, toxic int")
        assert quality.classify(df, labels).count() == len(rows)
        bench = spark.createDataFrame([(1, "word " * 12), (None, "the same text the same")], "item_id long, text string")
        assert decontaminate.report(df, bench).count() == len(rows)
        for f in (langid.keep_known, minhash.keep_first, pii.redact_frame, lambda x: decontaminate.remove_documents(x, bench)):
            out = f(df)
            assert out.columns == df.columns and out.count() <= len(rows)
        assert bpe.encode_decode(df).count() == len(rows)
    none = spark.createDataFrame([], "vec_id long, embedding array<float>, label int")
    assert embeddings.near_duplicates(none).count() == 0
    assert urls.judge(spark.createDataFrame([], "page_id long, url string")).count() == 0
    clash = spark.createDataFrame([(1, "http://a.com/en/x"), (None, None), (1, "http://a.com/en/x")], "page_id long, url string").withColumns({c: F.lit("x") for c in ("host", "path", "items", "block", "given")})
    assert sorted(r["verdict"] for r in urls.judge(clash).collect()) == ["allow", "block", "block"]


def test_pipeline(spark):
    import corpus_pipeline

    out = corpus_pipeline.run(spark, DATA)
    rows = out.collect()
    source = {r["doc_id"]: r for r in spark.read.parquet(f"{DATA}/documents.parquet").collect()}
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{DATA}/benchmark.parquet").collect()]
    kept = {x["doc_id"] for x in minhash.near_duplicates(spark.read.parquet(f"{DATA}/documents.parquet")).where("kept").collect()}
    leaky = {x[0] for x in brute.op1([(k, r["text"]) for k, r in source.items()], items) if x[5]}
    model = pii.default_model()
    want = {k: pii.redact(r["text"], pii.find_spans(r["text"], model)) for k, r in source.items() if k in kept and k not in leaky and langid.has_letter(r["text"])}
    assert {r["doc_id"]: r["text"] for r in rows} == want
    own = bpe.codec(bpe.default_ranks_path())
    assert all(bytes(r["ids"]) == own.encode(r["text"]) and r["n_tokens"] * 4 == len(r["ids"]) for r in rows)


def test_copied_passages_are_one_span_each_within_a_task(spark):
    """Forty documents with one passage of some 40 anchors: a task names each copy in a few spans, not in one an anchor."""
    r = random.Random(5)
    passage = " ".join(f"w{r.randrange(10**6)}" for _ in range(1000))
    d = docs(spark, [(k, f"own{k} {passage} end{k}") for k in range(40)], extra=False)
    spans = {row["doc_id"]: [tuple(x) for x in row["spans"]] for row in repeats.repeated_spans(d, fmindex.WordSource(), fmindex.word_index, fmindex.GRAM).collect()}
    assert sorted(spans) == list(range(1, 40))
    assert all((min(a for a, _ in x), max(b for _, b in x)) == (1, 1001) for x in spans.values())
    assert sum(len(x) <= 6 for x in spans.values()) >= 30
