"""Suffix-array deduplication over bytes: difference-cover construction in each shard, then adjacent prefixes compared.

Every text is its UTF-8 bytes (null: none); matches never cross documents. A byte that a 50-byte string covers is
removed when that string also starts in a document with a smaller doc_id; strings are judged on the input. Windows meet
in shards by their anchors (see `repeats`), so the sorted samples, their names and the merge are spread over all shards
and a shard's memory is bounded by the distinct text of its anchors. Shorter texts and rows with a null doc_id keep all
bytes; repeated rows are each judged; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .repeats import WINDOW, Source, ranges, repeated_spans, without_spans

#: Bytes in the grams that anchors are chosen from.
GRAM = 16


def _names(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
    """Order of the keys, a name (from 1) for each key by rank, and how many names there are."""
    order = np.argsort(keys)
    ranked = keys[order]
    name = np.empty(len(keys), np.int64)
    name[order] = np.cumsum(np.concatenate(([1], ranked[1:] != ranked[:-1])))
    return order, name, int(name[order[-1]]) if len(keys) else 0


def _triples(s: np.ndarray, at: np.ndarray) -> np.ndarray:
    """One sortable number for the three symbols at each position; ranks of pairs where three would not fit."""
    top = int(s.max(initial=0)) + 1
    if top**3 < 1 << 62:
        return (s[at] * top + s[at + 1]) * top + s[at + 2]
    _, pair, count = _names(s[at] * top + s[at + 1])
    return pair * top + s[at + 2] if (count + 1) * top < 1 << 62 else _names(s[at])[1] * (count + 1) + pair


def difference_cover_order(symbols: np.ndarray) -> np.ndarray:
    """Suffix array of an array of non-negative integers. The sample are the positions that 3 does not divide."""
    n = len(symbols)
    if n < 4:
        return np.array(sorted(range(n), key=lambda i: symbols[i:].tolist()), np.int64)
    s = np.concatenate((symbols.astype(np.int64) + 1, np.zeros(3, np.int64)))
    one, two = np.arange(1, n + (n % 3 == 1), 3), np.arange(2, n, 3)  # one dummy triple where n = 1 (mod 3)
    sample = np.concatenate((one, two))
    order, name, count = _names(_triples(s, np.minimum(sample, n)))
    if count < len(sample):
        order = difference_cover_order(name - 1)
    rank = np.zeros(n + 3, np.int64)
    rank[sample[order]] = np.arange(1, len(sample) + 1)
    rank[n:] = 0
    # the rest, by first symbol and the rank behind it
    rest, wide = np.arange(0, n, 3), np.int64(len(sample) + 2)
    rest = rest[np.argsort(s[rest] * wide + rank[rest + 1])]
    sorted_sample = sample[order]
    sorted_sample = sorted_sample[sorted_sample < n]
    first, second = sorted_sample[sorted_sample % 3 == 1], sorted_sample[sorted_sample % 3 == 2]
    # merge: among sample suffixes of either kind, how many come before each of the rest
    below = np.searchsorted(s[first] * wide + rank[first + 1], s[rest] * wide + rank[rest + 1])
    top = int(s.max()) + 1
    _, pair, _ = _names(np.concatenate((s[second] * top + s[second + 1], s[rest] * top + s[rest + 1])))
    key = pair * wide + rank[np.concatenate((second, rest)) + 2]
    below = below + np.searchsorted(key[: len(second)], key[len(second) :])
    out, taken = np.empty(n, np.int64), np.zeros(n, bool)
    spot = below + np.arange(len(rest))
    out[spot], taken[spot] = rest, True
    out[~taken] = sorted_sample
    return out


def adjacent_equal(text: np.ndarray, order: np.ndarray, window: int) -> np.ndarray:
    """For each row of the suffix array but the first: does it share `window` symbols with the row before?"""
    padded = np.concatenate((text.astype(np.int64), np.full(window, -1, np.int64)))
    same = np.ones(max(0, len(order) - 1), bool)
    live = np.arange(len(same))
    for k in range(window):
        if not len(live):
            break
        equal = padded[order[live + 1] + k] == padded[order[live] + k]
        same[live[~equal]] = False
        live = live[equal]
    return same


def byte_index(arena: np.ndarray, begin: np.ndarray, size: np.ndarray, windows: np.ndarray, doc: np.ndarray, window: int):
    """The index of a shard: (text, window number, smallest document that has the window) for all windows of its texts."""
    count = len(begin)
    start = np.cumsum(size + 1) - size - 1
    codes = np.zeros(int((size + 1).sum()), np.int64)
    body = np.ones(len(codes), bool)
    body[start + size] = False
    codes[body] = arena[ranges(begin, size)].astype(np.int64) + count
    codes[start + size] = np.arange(count)  # ends differ, so no match crosses one
    row = np.repeat(np.arange(count), windows)
    at = np.arange(len(row)) - np.repeat(np.cumsum(windows) - windows, windows)
    whole = np.zeros(len(codes), np.int64)
    whole[start[row] + at] = np.arange(1, len(row) + 1)
    order = difference_cover_order(codes)
    order = order[whole[order] > 0]  # suffixes that begin a window
    first = np.flatnonzero(np.concatenate(([True], ~adjacent_equal(codes, order, window))))
    number = whole[order] - 1
    least = np.empty(len(row), np.int64)
    least[number] = np.repeat(np.minimum.reduceat(doc[row[number]], first), np.diff(np.concatenate((first, [len(order)]))))
    return row, at, least


def repeated(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, digest, spans of bytes in windows that a smaller document has too."""
    return repeated_spans(docs, Source(), byte_index, min(GRAM, window), window)


def deduplicate(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans (maximal removed runs), kept (binary)."""

    def work(raw, spans):
        kept, done = [], 0
        for a, b in spans:
            kept.append(raw[done:a])
            done = b
        kept = b"".join([*kept, raw[done:]])
        return len(raw), len(raw) - len(kept), len(spans), kept

    whole = [F.octet_length("text"), F.lit(0), F.lit(0), F.encode("text", "UTF-8")]
    return without_spans(docs, repeated(docs, window), work, "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary", whole)


def report(docs: DataFrame) -> DataFrame:
    """The result of op10."""
    return deduplicate(docs).select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))
