"""Personal data: generators of high recall propose overlapping spans, boosted trees score them by format and context,
calibrated thresholds choose what is redacted.

Base spans (emails, addresses of the internet protocol, payment cards, phone numbers in the exact formats) always stay.
Further spans come from loose generators (obfuscated emails and addresses, longer addresses of the internet protocol,
national phone numbers, spaced or misgrouped card numbers) when the score of the trees, calibrated for each kind on
examples that they have not learned from, reaches the kind's threshold; of overlapping ones the best scored is kept.
Offsets count code points, the end is exclusive. Null text counts as empty; no rows are dropped; repeated rows are each
judged; columns other than doc_id and text are left alone. The trees learn from generated examples, not from the corpus.
"""

from __future__ import annotations

import bisect
import random
import re
from functools import lru_cache
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .boosting import BoostedTrees, isotonic, sigmoid
from .common import map_texts, text_slices

KINDS = ("email", "ip", "card", "phone")
SPAN_TYPE = "array<struct<kind:string,start:int,end:int,score:double,base:boolean>>"
#: A loose candidate is redacted only where the calibrated probability of its kind is this high.
PRECISION = {"email": 0.98, "ip": 0.98, "card": 0.98, "phone": 0.98}
CONTEXT = 28

# The exact formats. Look-behinds and possessive repeats only keep a failing start from being tried again
# inside the same run of characters; the matches are those of the plain patterns.
_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGITS = re.compile(r"[^0-9]+")

_LOOSE_EMAIL = re.compile(r"[A-Za-z0-9._%+-]{1,64}\s?(?:@|\[at\]|\(at\)|\s(?:at|AT)\s)\s?[A-Za-z0-9-]{1,63}(?:\s?(?:\.|\[dot\]|\(dot\)|\s(?:dot|DOT)\s)\s?[A-Za-z0-9-]{2,63}){1,4}")
_LOOSE_HINT = re.compile(r"@|\[at\]|\(at\)|\s(?:at|dot)\s", re.I)
_LOOSE_DIGITS = re.compile(r"(?<![0-9A-Za-z])(?:\+|\(|00)?[0-9](?:[\x20().\-/]{0,2}[0-9]){6,24}(?![0-9A-Za-z])")
_IP_GAP = r"\s?(?:\[\.\]|\(\.\)|\[dot\]|\(dot\)|\s\.\s|\sdot\s)\s?"
_HEX = "[0-9A-Fa-f]{1,4}"
_LOOSE_IP = re.compile(rf"(?<![0-9A-Za-z.])[0-9]{{1,3}}(?:{_IP_GAP}[0-9]{{1,3}}){{3}}(?![0-9A-Za-z])")
_LONG_IP = re.compile(rf"(?<![0-9A-Za-z:])(?:(?:{_HEX}:){{7}}{_HEX}|(?:{_HEX}:){{1,6}}(?::{_HEX}){{1,6}})(?![0-9A-Za-z:])")
_WORDS = {
    "email": re.compile(r"e-?mail|mail|contact|write|reach|adresse|correo|courriel", re.I),
    "ip": re.compile(r"\bip\b|host|server|addr|login|from", re.I),
    "card": re.compile(r"card|visa|master|credit|amex|karte|carte|tarjeta|payment", re.I),
    "phone": re.compile(r"phone|tel\b|tel[.:]|call|mobile|fax|cell|handy|t[ée]l[ée]", re.I),
    "other": re.compile(r"version|\bid\b|isbn|order|invoice|no\.|number|date|token|key|build|rev|price|serial", re.I),
}


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if k % 2 == 0 else d * 2 - 9 * (d > 4)
    return total % 10 == 0


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """Leftmost non-overlapping matches of each exact format that pass their test, in order of kind and start."""
    out = []
    done = 0
    for m in _DOMAIN.finditer(text):
        start = at = m.start()
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        if start < at:
            done = m.end()
            out.append(("email", start, done))
    for m in _IP.finditer(text):
        if all(len(p.lstrip("0")) <= 3 and int(p) <= 255 for p in m.group().split(".")):
            out.append(("ip", m.start(), m.end()))
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 13:
            digits = _DIGITS.sub("", m.group())
            if 13 <= len(digits) <= 19 and luhn(digits):
                out.append(("card", m.start(), m.end()))
    if "+" in text:
        for m in _PHONE.finditer(text):
            if 9 <= len(_DIGITS.sub("", m.group())) <= 15:
                out.append(("phone", m.start(), m.end()))
    return out


def loose_candidates(text: str) -> list[tuple[str, int, int]]:
    """Spans that may be personal data in looser formats; they may overlap one another and base spans."""
    out = []
    if _LOOSE_HINT.search(text):
        for m in _LOOSE_HINT.finditer(text):  # only around the sign, so long texts stay linear
            low = max(0, m.start() - 70)
            for e in _LOOSE_EMAIL.finditer(text, low, min(len(text), m.end() + 280)):
                if e.start() <= m.start() < e.end():
                    out.append(("email", e.start(), e.end()))
    for m in _LOOSE_DIGITS.finditer(text):
        n = len(_DIGITS.sub("", m.group()))
        if n <= 15:
            out.append(("phone", m.start(), m.end()))
        if 12 <= n <= 19:
            out.append(("card", m.start(), m.end()))
    if any(x in text for x in ("[.]", "(.)", " . ", "dot")):
        out += [("ip", m.start(), m.end()) for m in _LOOSE_IP.finditer(text)]
    if text.count(":") >= 3:
        out += [("ip", m.start(), m.end()) for m in _LONG_IP.finditer(text)]
    return list(dict.fromkeys(out))


def features(text: str, kind: str, start: int, end: int) -> list[float]:
    span, left, right = text[start:end], text[max(0, start - CONTEXT) : start], text[end : end + CONTEXT // 2]
    digits = _DIGITS.sub("", span)
    groups = [len(g) for g in re.findall(r"[0-9]+", span)] or [0]
    near = left + " " + right
    return [
        KINDS.index(kind), len(span), len(digits), len(groups), max(groups), min(groups), groups[-1],
        span.count("."), span.count("-"), span.count(" "), "(" in span, span.startswith("+"), span.startswith("00"),
        luhn(digits) if digits else 0, len(set(digits)), "[at]" in span.lower() or "(at)" in span.lower(), "@" in span,
        bool(re.search(r"dot", span, re.I)), *(bool(w.search(near)) for w in _WORDS.values()), left[-1:].isalnum() or right[:1].isalnum(), left.rstrip()[-1:] in (":", "=", "\""),
        span.count(":"), "::" in span, sum(c in "abcdefABCDEF" for c in span), max((int(g) for g in re.findall(r"[0-9]{1,9}", span)), default=0) > 255, "[.]" in span or "(.)" in span,
    ]


def _examples(seed: int, count: int) -> list[tuple[str, str, int, int, int]]:
    """Generated sentences with one candidate each: (text, kind, start, end, is personal data)."""
    r = random.Random(seed)
    word = lambda: "".join(r.choice(["an", "ti", "re", "er", "on", "schl", "ou", "es", "lle", "ra"]) for _ in range(r.randint(1, 4)))
    some = lambda n: "".join(r.choice("0123456789") for _ in range(n))
    prose = lambda: " ".join(word() for _ in range(r.randint(1, 6)))

    def card(valid: bool) -> str:
        while luhn(x := some(16)) != valid:
            pass
        return x

    grouped = lambda x, sep: sep.join(x[i : i + 4] for i in range(0, 16, 4))
    out = []
    for _ in range(count):
        way = r.randrange(16)
        cue, kind, good = "", "phone", 1
        if way == 0:
            kind, cue, span = "email", r.choice(["", "email ", "contact: ", "write to "]), f"{word()}{r.choice(['.', '_', ''])}{word()}{r.choice([' [at] ', '(at)', ' (at) ', '[at]'])}{word()}{r.choice(['.', ' [dot] ', ' dot ', '(dot)'])}{r.choice(['com', 'org', 'de', 'net'])}"
        elif way == 1:
            kind, good, span = "email", 0, f"{word()} at {word()}. {word()}"
        elif way == 2:
            cue, span = r.choice(["phone ", "tel. ", "call ", "mobile: ", "fax "]), r.choice([f"({some(3)}) {some(3)}-{some(4)}", f"0{some(3)} {some(7)}", f"{some(3)}-{some(3)}-{some(4)}", f"{some(3)}.{some(3)}.{some(4)}", f"00{some(2)} {some(3)} {some(7)}"])
        elif way == 3:
            good, cue, span = 0, r.choice(["", "order ", "id ", "serial ", "no. "]), some(r.randint(7, 15))
        elif way == 4:
            good, span = 0, r.choice([f"20{some(2)}-{r.randint(10, 12)}-{r.randint(10, 28)}", f"{r.randint(10, 28)}.{r.randint(10, 12)}.20{some(2)}", f"20{some(2)}-{r.randint(10, 12)}-{r.randint(10, 28)} {r.randint(10, 23)}"])
        elif way == 5:
            kind, cue, span = "card", r.choice(["card ", "visa ", "credit card: ", "payment "]), r.choice([grouped(card(True), r.choice([".", "/", "  "])), card(True)])
        elif way == 6:
            kind, good, cue, span = "card", 0, r.choice(["", "", "card ", "id ", "number "]), r.choice([card(False), grouped(card(False), r.choice([" ", "-", "."]))])
        elif way == 7:
            kind, good, span = "card", 0, f"{some(3)}.{some(3)}.{some(3)}.{some(3)}"
        elif way == 8:
            good, cue, span = 0, r.choice(["", "", "version ", "build "]), ".".join(some(r.randint(1, 3)) for _ in range(r.randint(4, 6))) + some(3)
        elif way == 9:
            good, cue, span = 0, r.choice(["", "isbn ", "price "]), r.choice([f"978-{some(1)}-{some(4)}-{some(4)}-{some(1)}", f"{some(3)} {some(3)} {some(3)}"])
        elif way == 10:
            kind, good, span = "email", 0, f"{word()}@{word()} . {word()}"
        elif way == 11:
            kind, cue, span = "ip", r.choice(["", "ip ", "host ", "server: ", "login from "]), r.choice(["[.]", "(.)", "[dot]", " dot "]).join(str(r.randrange(256)) for _ in range(4))
        elif way == 12:
            kind, good, cue, span = "ip", 0, r.choice(["", "version ", "items ", "price "]), r.choice([" . ", "[.]", " dot "]).join(str(x) for x in r.choice([[1, 2, 3, 4], [r.randrange(300, 1000) for _ in range(4)], [r.randrange(20), r.randrange(300, 1000), r.randrange(10), r.randrange(400, 1000)]]))
        elif way == 13:
            kind, cue, span = "ip", r.choice(["", "ip ", "host ", "server: ", "addr "]), r.choice([":".join(f"{r.randrange(1 << 16):x}" for _ in range(8)), "::".join(":".join(f"{r.randrange(1 << 16):x}" for _ in range(k)) for k in (r.randint(2, 4), r.randint(1, 3)))])
        elif way == 14:
            kind, good, cue, span = "ip", 0, r.choice(["", "time ", "id "]), r.choice([":".join(some(2) for _ in range(8)), f"{r.choice(['add', 'face', 'dead', 'be', 'a'])}::{r.choice(['fed', 'bad', 'cafe', 'c'])}"])
        else:
            good, cue, span = 0, "", r.choice([f"({some(3)}) {some(3)}-{some(4)}", f"{some(4)}-{some(4)}", f"{some(2)} {some(2)} {some(2)} {some(2)}"])
        before = f"{prose()} {cue}"
        out.append((f"{before}{span} {prose()}.", kind, len(before), len(before) + len(span), good))
    return out


@lru_cache(maxsize=1)
def default_model():
    """Trees and, for each kind, calibration knots: fitted on generated examples, calibrated on others."""
    table = lambda seed, n: (lambda e: (np.array([features(*x[:4]) for x in e], float), np.array([x[4] for x in e]), np.array([KINDS.index(x[1]) for x in e])))(_examples(seed, n))
    x, y, _ = table(11, 5000)
    trees = BoostedTrees(rounds=40).fit(x, y)
    x, y, kind = table(23, 4000)
    score = sigmoid(trees.margin(x))
    return trees, {name: isotonic(score[kind == k], y[kind == k]) for k, name in enumerate(KINDS)}


def calibrated(text: str, candidates: list[tuple[str, int, int]], model) -> np.ndarray:
    """The probability that each candidate is personal data of its kind."""
    trees, knots = model
    raw = sigmoid(trees.margin(np.array([features(text, *c) for c in candidates], float)))
    return np.array([np.interp(x, *knots[kind]) for x, (kind, _, _) in zip(raw, candidates)])


def held_out_quality(seed: int = 37, count: int = 4000) -> dict[str, tuple[float, float]]:
    """(precision, recall) of the trees on generated candidates of each kind that neither fit nor calibration has seen."""
    model, out = default_model(), {k: [0, 0, 0] for k in KINDS}
    for text, kind, start, end, good in _examples(seed, count):
        chosen = calibrated(text, [(kind, start, end)], model)[0] >= PRECISION[kind]
        out[kind][0] += chosen and good
        out[kind][1] += chosen
        out[kind][2] += good
    return {k: (hit / max(1, chosen), hit / max(1, good)) for k, (hit, chosen, good) in out.items()}


def find_spans(text: str | None, model) -> list[dict]:
    """All spans of one text, by kind and then start; base spans have score 1."""
    if not text:
        return []
    base = base_spans(text)
    out = [{"kind": k, "start": s, "end": e, "score": 1.0, "base": True} for k, s, e in base]
    taken = sorted((s, e) for _, s, e in base)
    clear = lambda s, e: (i := bisect.bisect_left(taken, (e,))) == 0 or reach[i - 1] <= s
    reach = list(accumulate((e for _, e in taken), max))  # the farthest end among the spans up to each
    loose = [c for c in loose_candidates(text) if clear(c[1], c[2])]
    if loose:
        scores = calibrated(text, loose, model)
        for score, (kind, start, end) in sorted(zip(scores.tolist(), loose), key=lambda x: (-x[0], x[1][1], x[1])):
            if score >= PRECISION[kind] and clear(start, end):
                bisect.insort(taken, (start, end))
                reach = list(accumulate((e for _, e in taken), max))
                out.append({"kind": kind, "start": start, "end": end, "score": score, "base": False})
    return sorted(out, key=lambda x: (KINDS.index(x["kind"]), x["start"]))


def detect(df: DataFrame) -> DataFrame:
    """(doc_id, text) -> doc_id, spans."""
    model = default_model()

    def make():
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32()), ("score", pa.float64()), ("base", pa.bool_())]))

        def work(batch):
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array([find_spans(t, model) for t in batch.column(1).to_pylist()], kind)], ["doc_id", "spans"])

        return work

    return map_texts(df.select("doc_id", F.col("text").cast("string").alias("text")), make, f"doc_id long, spans {SPAN_TYPE}")


def redact(text: str | None, spans: list[dict]) -> str | None:
    """The text with every span replaced by its kind in brackets; overlapping spans become one of the earlier kind."""
    if not spans:
        return text
    out, done = [], 0
    for s in sorted(spans, key=lambda x: (x["start"], -x["end"])):
        if s["start"] >= done:
            out += [text[done : s["start"]], f"[{s['kind'].upper()}]"]
        done = max(done, s["end"])
    return "".join([*out, text[done:]])


def redact_frame(df: DataFrame) -> DataFrame:
    """All columns of df, with the spans found in `text` redacted and n_chars, where present, counted anew."""
    model = default_model()
    at = df.columns.index("text")

    def run(batches):
        for batch in text_slices(batches):
            clean = pa.array([redact(t, find_spans(t, model)) for t in batch.column(at).to_pylist()], pa.string())
            yield batch.set_column(at, batch.schema.field(at), clean.cast(batch.schema.field(at).type))

    out = df.mapInArrow(run, df.schema)
    return out.withColumn("n_chars", F.length("text").cast(df.schema["n_chars"].dataType)) if "n_chars" in df.columns else out


def _listed(spans):
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])))


def report(df: DataFrame) -> DataFrame:
    """The result of op3: counts and a digest of the base spans, and the list of all spans."""
    found = detect(df)
    base = F.filter("spans", lambda s: s["base"])
    count = lambda kind: F.size(F.filter("spans", lambda s: s["base"] & (s["kind"] == kind))).cast("long").alias(f"n_{kind}")
    return found.select("doc_id", *(count(k) for k in KINDS), F.sha2(_listed(base), 256).alias("base_sha256"), _listed(F.col("spans")).alias("spans"))
