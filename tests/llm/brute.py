"""Plain Python versions of the operators, for tests."""

from __future__ import annotations

import hashlib
import re


def windows_removed(rows, elements, window):
    """rows: (doc_id, text). For each row, the set of positions in windows that a smaller doc_id has."""
    least = {}
    for doc, text in rows:
        e = elements(text)
        for i in range(len(e) - window + 1):
            k = e[i : i + window]
            least[k] = min(least.get(k, doc), doc)
    out = []
    for doc, text in rows:
        e, gone = elements(text), set()
        for i in range(len(e) - window + 1):
            if least[e[i : i + window]] < doc:
                gone.update(range(i, i + window))
        out.append(gone)
    return out


def op7(rows, window=50):
    words = lambda t: tuple((t or "").encode().split())
    out = []
    for (doc, text), gone in zip(rows, windows_removed(rows, words, window)):
        w = words(text)
        kept = b" ".join(x for i, x in enumerate(w) if i not in gone)
        out.append((doc, len(w), len(gone), hashlib.sha256(kept).hexdigest()))
    return out


def op10(rows, window=50):
    raw = lambda t: (t or "").encode()
    out = []
    for (doc, text), gone in zip(rows, windows_removed(rows, raw, window)):
        b = raw(text)
        runs = sum(i in gone and i - 1 not in gone for i in range(len(b)))
        out.append((doc, len(b), len(gone), runs, hashlib.sha256(bytes(x for i, x in enumerate(b) if i not in gone)).hexdigest()))
    return out


def op1(docs, items, window=10):
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m.group().lower(), t or ""))
    grams = {}
    for item, text in items:
        w = words(text)
        n = min(window, len(w))
        for i in range(len(w) - n + 1) if n else ():
            grams.setdefault(tuple(w[i : i + n]), set()).add(str(item))
    out = []
    for doc, text in docs:
        w, hit, own = words(text), set(), set()
        for n in {len(g) for g in grams}:
            for i in range(len(w) - n + 1):
                if items_ := grams.get(tuple(w[i : i + n])):
                    hit.update(range(i, i + n))
                    own |= items_
        out.append((doc, len(w), len(hit), len(own), hashlib.sha256(",".join(sorted(own)).encode()).hexdigest(), bool(hit)))
    return out
