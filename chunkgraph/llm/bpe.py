"""Byte-level BPE over a public rank file: a segment tree finds the leftmost pair of least rank.

Null text counts as empty and gives no tokens. Texts of any length are encoded whole. Nothing is trained.
Repeated rows are encoded each; further columns of the input are ignored, so their names cannot clash.
"""

from __future__ import annotations

import base64
import re
import struct

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import keep_between_tasks, map_texts

#: Entries of one generation of a worker's memo; when the young generation is full it becomes the old one.
MEMO_UNITS = 250_000
MEMO_LENGTH = 48

_NO_RANK = 1 << 40
#: The white space of the split pattern, as its regex engine defines it.
_SPACE = "\t-\r \x85\xa0  -     　"
#: Characters that Python's \\s has beyond that list.
_EXTRA_SPACE = "\x1c\x1d\x1e\x1f"


def default_ranks_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as file:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, file)}


def merge_piece(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Token ids of one piece of the split.

    A minimum tree over byte positions: leaf i holds the rank of the pair of tokens whose first begins at i. The root is
    the least rank, and going left where it can be found leads to its leftmost pair. A merge changes the leaves of the
    pair, of the token behind it and of the one before; each change climbs until it alters nothing.
    """
    known = ranks.get(piece)
    if known is not None:
        return [known]
    n, get, none = len(piece), ranks.get, _NO_RANK
    width = 1 << max(0, n - 2).bit_length()
    node = [none] * width
    node += [get(piece[i : i + 2], none) for i in range(n - 1)]
    node += [none] * (2 * width - len(node))
    for k in range(width - 1, 0, -1):
        a, b = node[2 * k], node[2 * k + 1]
        node[k] = a if a <= b else b
    end = list(range(1, n + 1))  # where the live token that starts at i ends
    before = list(range(-1, n))  # start of the live token in front
    token = [get(piece[i : i + 1]) for i in range(n)]
    least = node[1]
    while least != none:
        k = 1
        while k < width:
            k += k
            if node[k] != least:
                k += 1
        i = k - width
        j = end[i]
        stop = end[i] = end[j]
        token[i] = least  # a pair's rank is the id of the token that it makes
        changes = [(k, none)]
        if stop < n:
            before[stop] = i
            changes[0] = (k, get(piece[i : end[stop]], none))
        if j < n - 1:
            changes.append((j + width, none))
        if i:
            h = before[i]
            changes.append((h + width, get(piece[h:stop], none)))
        for k, rank in changes:
            node[k] = rank
            while k > 1:
                a, b = node[k], node[k ^ 1]
                if b < a:
                    a = b
                k >>= 1
                if node[k] == a:
                    break
                node[k] = a
        least = node[1]
    out, i = [], 0
    while i < n:
        out.append(token[i])
        i = end[i]
    return out


class Memo:
    """Two generations of results: what is used again survives, memory stays bounded."""

    def __init__(self, compute, most: int = MEMO_UNITS):
        self.compute, self.most, self.young, self.old = compute, most, {}, {}

    def miss(self, key):
        value = self.old.get(key)
        if value is None:
            value = self.compute(key)
        if len(key) <= MEMO_LENGTH:
            if len(self.young) >= self.most:
                self.old, self.young = self.young, {}
            self.young[key] = value
        return value


class ByteBpe:
    """Encoder and decoder; ids travel packed as little-endian unsigned 32-bit integers."""

    def __init__(self, ranks_path: str, pattern: str | None = None):
        import regex

        if pattern is None:
            import public_tokenizers

            pattern = public_tokenizers.PATTERN
        self.ranks = load_ranks(ranks_path)
        self.bytes_of = {rank: token for token, rank in self.ranks.items()}
        spelled = pattern.replace(r"[^\s", f"[^{_SPACE}").replace(r"\S", f"[^{_SPACE}]").replace(r"\s", f"[{_SPACE}]")
        self.pieces = regex.compile(spelled).findall
        self.units_plain = re.compile(r" ?\S+|\s+(?!\S)|\s").findall
        self.units_exact = re.compile(f" ?[^{_SPACE}]+|[{_SPACE}]+(?![^{_SPACE}])|[{_SPACE}]").findall
        self.of_piece = Memo(self.encode_piece, MEMO_UNITS // 2)
        self.of_unit = Memo(self.encode_unit)

    def encode_piece(self, piece: str) -> bytes:
        ids = merge_piece(piece.encode(), self.ranks)
        return struct.pack(f"<{len(ids)}I", *ids)

    def encode_unit(self, unit: str) -> bytes:
        pieces = self.pieces(unit)
        if len(pieces) == 1:
            return self.encode_piece(unit)
        get, miss = self.of_piece.young.get, self.of_piece.miss
        return b"".join([get(x) or miss(x) for x in pieces])

    def encode(self, text: str | None) -> bytes:
        if not text:
            return b""
        find = self.units_exact if any(c in text for c in _EXTRA_SPACE) else self.units_plain
        memo = self.of_unit
        return b"".join([memo.young.get(unit) or memo.miss(unit) for unit in find(text)])

    def decode(self, packed: bytes) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, struct.unpack(f"<{len(packed) // 4}I", packed)))


_LOADED: dict[tuple, ByteBpe] = {}


def codec(ranks_path: str, pattern: str | None = None) -> ByteBpe:
    """One codec a worker process; its memo lives until the process serves another operator."""
    key = (ranks_path, pattern)
    keep_between_tasks(__name__, _LOADED.clear)
    if key not in _LOADED:
        _LOADED[key] = ByteBpe(ranks_path, pattern)
    return _LOADED[key]


def encode_decode(df: DataFrame, ranks_path: str | None = None, pattern: str | None = None) -> DataFrame:
    """(doc_id, text) -> doc_id, n_tokens, ids (packed binary), decoded (binary)."""
    path = ranks_path or default_ranks_path()

    def make():
        bpe = codec(path, pattern)

        def work(batch):
            packed = [bpe.encode(text) for text in batch.column(1).to_pylist()]
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(x) // 4 for x in packed], pa.int64()), pa.array(packed, pa.binary()), pa.array([bpe.decode(x) for x in packed], pa.binary())], ["doc_id", "n_tokens", "ids", "decoded"])

        return work

    return map_texts(df.select("doc_id", F.col("text").cast("string").alias("text")), make, "doc_id long, n_tokens long, ids binary, decoded binary")


def digests(df: DataFrame, ranks_path: str | None = None) -> DataFrame:
    """The result of op2: token counts with digests of the ids and of the decoded bytes."""
    return encode_decode(df, ranks_path).select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))
