"""Substring deduplication over words: a compressed full-text index for each shard, searched backward.

Words are runs of bytes other than space and U+0009 to U+000D, unchanged. A word that a window of 50 consecutive words
covers is removed when the window also starts in a document with a smaller doc_id; windows are judged on the input.
Each shard (see `repeats`) holds the transformed text of its distinct segments in a wavelet matrix over bit vectors with
block counts; every segment is streamed through it from its last word to its first, the state is the interval of matches
of the words read, cut to the window's length. Where the statistic reaches the window, the interval's smallest document
decides. Null text has no words; texts of fewer words, and rows with a null doc_id, keep all; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import repeats
from .bpe import Memo
from .common import keep_between_tasks
from .repeats import WINDOW, Source, repeated_spans, without_spans

#: Words in the grams that anchors are chosen from.
GRAM = 8


class BitVector:
    """Rank of ones by packed words and a count before each word."""

    def __init__(self, bits: np.ndarray):
        packed = np.packbits(bits, bitorder="little")
        self.words = np.zeros(len(bits) // 64 + 1, np.uint64)
        self.words.view(np.uint8)[: len(packed)] = packed
        self.before = np.concatenate(([0], np.cumsum(np.bitwise_count(self.words), dtype=np.int64)))[:-1]

    def rank(self, i: np.ndarray) -> np.ndarray:
        k = i >> 6
        mask = (np.uint64(1) << (i & 63).astype(np.uint64)) - np.uint64(1)
        return self.before[k] + np.bitwise_count(self.words[k] & mask)


class WaveletMatrix:
    def __init__(self, symbols: np.ndarray):
        self.size = len(symbols)
        self.levels, self.zeros = [], []
        self.depth = max(1, int(symbols.max(initial=0)).bit_length())
        for level in reversed(range(self.depth)):
            bits = (symbols >> level) & 1
            self.levels.append(BitVector(bits.astype(np.uint8)))
            self.zeros.append(int(len(bits) - bits.sum()))
            symbols = np.concatenate((symbols[bits == 0], symbols[bits == 1]))

    def descend(self, symbol: np.ndarray, i: np.ndarray) -> np.ndarray:
        """Where prefix length i of a symbol ends up at the lowest level."""
        for level, vector, zeros in zip(reversed(range(self.depth)), self.levels, self.zeros):
            ones = vector.rank(i)
            i = np.where((symbol >> level) & 1, zeros + ones, i - ones)
        return i


def suffix_order(codes: np.ndarray) -> tuple[np.ndarray, list[tuple[int, np.ndarray]]]:
    """Suffix array by doubling, with the ranks by the first 1, 2, 4 ... symbols."""
    n = len(codes)
    order = np.argsort(codes, kind="stable")
    ranks, size = [], 1
    rank = np.empty(n, np.int64)
    rank[order] = np.cumsum(np.concatenate(([0], codes[order][1:] != codes[order][:-1])))
    ranks.append((1, rank))
    while rank[order[-1]] < n - 1:
        after = np.zeros(n, np.int64)
        after[: n - size] = rank[size:] + 1
        key = rank * (n + 1) + after
        order = np.argsort(key)
        key = key[order]
        rank = np.empty(n, np.int64)
        rank[order] = np.cumsum(np.concatenate(([0], key[1:] != key[:-1])))
        size *= 2
        ranks.append((size, rank))
    return order, ranks


def run_starts(order: np.ndarray, ranks: list[tuple[int, np.ndarray]], length: int) -> np.ndarray:
    """The rows of a suffix array at which the first `length` symbols change."""
    same, done = np.ones(len(order) - 1, bool), 0
    for size, rank in reversed(ranks):
        if length - done >= size:
            at = np.minimum(order + done, len(order) - 1)
            r = rank[at]
            same &= (r[1:] == r[:-1]) & (order[1:] + done < len(order)) & (order[:-1] + done < len(order))
            done += size
    return np.flatnonzero(np.concatenate(([True], ~same))).astype(np.int32)


class FmIndex:
    """Index of several texts of integer symbols 1, 2, ..., each of a document; matches never cross texts.

    What is kept is the transformed text as a wavelet matrix, how many smaller symbols there are, where runs of rows that
    share window - 1 and window symbols begin, and the least document of each run of a window. The suffix array that it
    is made from goes.
    """

    def __init__(self, texts: list[np.ndarray], doc: np.ndarray | None = None, window: int = WINDOW):
        count, self.window = len(texts), window
        self.lengths = np.array([len(t) for t in texts], np.int64)
        ends = np.cumsum(self.lengths + 1) - 1
        flat = np.concatenate(texts) if count else np.zeros(0, np.int64)
        codes, body = np.zeros(int((self.lengths + 1).sum()), np.int64), np.ones(int((self.lengths + 1).sum()), bool)
        body[ends] = False
        codes[body], codes[ends] = flat + count, np.arange(count)
        order, ranks = suffix_order(codes)
        before = codes[order - 1]
        self.wavelet = WaveletMatrix(np.where(before >= count, before - count, 0))
        most = int(flat.max(initial=0)) + 2
        smaller = count + np.concatenate(([0, 0], np.cumsum(np.bincount(flat, minlength=most)[1:])))[:most]
        self.shift = smaller - self.wavelet.descend(np.arange(most), np.zeros(most, np.int64))
        self.size, self.cut, self.full = len(codes), run_starts(order, ranks, window - 1), run_starts(order, ranks, window)
        owner = np.arange(count) if doc is None else doc
        self.least = np.minimum.reduceat(owner[np.repeat(np.arange(count), self.lengths + 1)[order]], self.full)

    def step(self, symbol: np.ndarray, i: np.ndarray) -> np.ndarray:
        """Backward step of interval borders i by one symbol each."""
        return self.wavelet.descend(symbol, i) + self.shift[symbol]

    def shortened(self, low: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Intervals of a window's matches (by their first row) -> those of its first window - 1 symbols."""
        k = np.searchsorted(self.cut, low, side="right")
        return self.cut[k - 1].astype(np.int64), np.append(self.cut, self.size)[k].astype(np.int64)

    def least_document(self, low: np.ndarray) -> np.ndarray:
        return self.least[np.searchsorted(self.full, low, side="right") - 1]

    def find(self, pattern: np.ndarray) -> tuple[int, int]:
        """Interval of the rows that begin with a pattern."""
        low, high = np.array([0]), np.array([self.size])
        for symbol in pattern[::-1]:
            if not 0 < symbol < len(self.shift) - 1:
                return 0, 0
            low, high = self.step(np.array([symbol]), low), self.step(np.array([symbol]), high)
        return int(low[0]), int(high[0])

    def matching_statistics(self, text: np.ndarray) -> np.ndarray:
        """For each position, the length of the longest match with any indexed text; for any streamed text."""
        out, length = np.zeros(len(text), np.int64), 0
        for i in reversed(range(len(text))):
            length += 1
            while length:
                low, high = self.find(text[i : i + length])
                if low < high:
                    break
                length -= 1
            out[i] = length
        return out

    def windows(self, texts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(text, window start, least document that has the window) of texts whose substrings are all indexed.

        All texts are streamed side by side from their last symbol to their first. A text's state is the interval of the
        rows that begin with the symbols read last, the window's length of them at most: its matching statistic.
        """
        lengths = np.array([len(t) for t in texts], np.int64)
        lanes = np.argsort(-lengths, kind="stable")
        last, flat, lengths = np.cumsum(lengths)[lanes] - 1, np.concatenate(texts), lengths[lanes]
        low, high = np.zeros(len(lanes), np.int64), np.full(len(lanes), self.size, np.int64)
        row, at, least = [], [], []
        for t in range(int(lengths[0])):
            live = int(np.searchsorted(-lengths, -t, side="left"))  # lanes of more than t symbols
            symbol = flat[last[:live] - t]
            both = self.step(np.concatenate((symbol, symbol)), np.concatenate((low[:live], high[:live])))
            low, high = both[:live], both[live:]
            if t >= self.window - 1:
                row.append(lanes[:live])
                at.append(lengths[:live] - 1 - t)
                least.append(self.least_document(low))
                low, high = self.shortened(low)
        row, at, least = np.concatenate(row), np.concatenate(at), np.concatenate(least)
        by = np.lexsort((at, row))
        return row[by], at[by], least[by]


def word_index(arena: np.ndarray, begin: np.ndarray, size: np.ndarray, windows: np.ndarray, doc: np.ndarray, window: int):
    """The index of a shard: (text, window number, smallest document) for all windows of its texts."""
    raw, code = arena.tobytes(), {}
    new = code.setdefault
    texts = [np.array([new(w, len(code) + 1) for w in raw[a : a + n].split(b" ")], np.int64) for a, n in zip(begin.tolist(), size.tolist())]
    return FmIndex(texts, doc, window).windows(texts)


class WordSource(Source):
    """Words of a text, hashed; the raw bytes are the words joined by a space."""

    gap = 1
    hashes = Memo(xxhash.xxh3_64_intdigest)

    def forget(self) -> None:
        self.hashes.young, self.hashes.old = {}, {}

    def read(self, text: str):
        words = text.encode().split()
        get, miss = self.hashes.young.get, self.hashes.miss
        elements = np.array([get(w) or miss(w) for w in words], np.uint64)
        starts = np.concatenate(([0], np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)))
        return elements, np.frombuffer(b" ".join(words) + b" ", np.uint8), starts

    def ready(self) -> None:
        keep_between_tasks(repeats.__name__, self.forget)

    def __reduce__(self):
        return WordSource, ()


def repeated(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, digest, spans of words in windows that a smaller document has too."""
    return repeated_spans(docs, WordSource(), word_index, min(GRAM, window), window)


def deduplicate(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, n_words, n_removed, kept (binary: what is left, joined by a space)."""

    def work(text, spans):
        words, kept, done = text.split(), [], 0
        for a, b in spans:
            kept += words[done:a]
            done = b
        kept += words[done:]
        return len(words), len(words) - len(kept), b" ".join(kept)

    return without_spans(docs, repeated(docs, window), work, "doc_id long, n_words long, n_removed long, kept binary")


def report(docs: DataFrame) -> DataFrame:
    """The result of op7."""
    return deduplicate(docs).select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))
