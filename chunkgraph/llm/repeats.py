"""Where long repeats can be: the shared frame of substring and suffix-array deduplication.

A text is a row of elements (words or bytes). A window is WINDOW consecutive elements; it is repeated where the same
window also starts in a document with a smaller id. The frame finds, without comparing all windows with all, small
groups inside which every pair of equal windows lies:

1. Of the grams (`gram` consecutive elements) in a window, the one with the least hash is its anchor. Equal windows have
   equal anchors at equal offsets, so only windows whose anchor occurs in two documents can be repeated. Each task packs
   (anchor, document) pairs into one blob a bucket; anchors that a task meets in two documents are known at once, and
   leave one mark for the other tasks, so a bucket gets at most one entry of an anchor from each task.
2. Documents with shared anchors cut the text around these into segments: all windows of one anchor, which overlap. Of
   equal segments (byte for byte) in one task only those of the smallest document go on; the others are repeated whole.
   Segments are packed into one blob a shard, each text once.
3. Segments go to shards by anchor. There equal ones are one text again, and an index of the different texts (an FM-index
   or a suffix array, by the caller) tells for each of their windows the smallest document that has it.

A hot anchor or a large group of copies so leaves one entry a task and distinct text. Results are exact whatever
the hashes are: they only decide where windows meet, and the index compares the elements themselves.

A document is named by doc_id and a hash of its text, so repeated ids with different texts stay apart. Rows with a null
doc_id have no order: nothing is removed from them and they remove nothing.
"""

from __future__ import annotations

import gc
import struct
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import forget, settle, text_slices

WINDOW = 50
#: Elements that one index of a shard covers, as far as whole anchors go.
SHARD_ELEMENTS = 1 << 18
#: A document of more elements is anchored in overlapping pieces.
PIECE = 1 << 20
#: Entries, or bytes of segments, that a task gathers before it packs them.
ENTRIES, ARENA = 1_000_000, 12 << 20
#: Bytes of texts that are compared at once.
COMPARED = 1 << 19
#: Longs in the bitmap that spares documents without shared anchors the join (a fixed size; all pass when it is full).
SIEVE_LONGS = 1 << 16

_M1, _M2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9)
#: Rolling hash of bytes: an odd base, its inverse modulo 2^64, a random value a byte.
_BASE = 0x5851F42D4C957F2D
_INVERSE = pow(_BASE, -1, 1 << 64)
_BYTE_VALUE = np.random.default_rng(41).integers(1, 1 << 63, 256, dtype=np.uint64)


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * _M1
    x = (x ^ (x >> np.uint64(29))) * _M2
    return x ^ (x >> np.uint64(32))


def gram_hashes(elements: np.ndarray, gram: int) -> np.ndarray:
    """Hash of each run of `gram` elements, doubling the length of what is combined; bytes by whole words of eight."""
    whole, have, total = None, 0, len(elements)
    if elements.dtype == np.uint8 and gram % 8 == 0 and total >= gram:
        words = np.ndarray(total - 7, "<u8", np.ascontiguousarray(elements), strides=(1,)).copy()
        n = total - gram + 1
        out = words[:n]
        for k in range(8, gram, 8):
            out = out * _M1 ^ (words[k : k + n] * _M2 + (words[k : k + n] >> np.uint64(33)))
        return out
    power, size, bit = elements.astype(np.uint64), 1, gram
    while True:
        if bit & 1:
            if whole is None:
                whole, have = power, size
            else:
                n = total - have - size + 1
                whole = whole[:n] * _M1 ^ (power[have : have + n] * _M2 + (power[have : have + n] >> np.uint64(33)))
                have += size
        bit >>= 1
        if not bit:
            break
        n = total - 2 * size + 1
        power = power[:n] * _M1 ^ (power[size : size + n] * _M2 + (power[size : size + n] >> np.uint64(33)))
        size *= 2
    return whole


def anchors(elements: np.ndarray, gram: int, window: int = WINDOW) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(position of the anchor, its hash, first window, last window) for each run of windows with one anchor; at most PIECE elements."""
    n = len(elements)
    if n < window:
        empty = np.zeros(0, np.int64)
        return empty, empty.astype(np.uint64), empty, empty
    keys = mixed(gram_hashes(elements, gram))
    width = window - gram + 1
    low = np.uint64((1 << 21) - 1)
    least, size = (keys & ~low) | np.arange(len(keys), dtype=np.uint64), 1
    while size * 2 <= width:
        least = np.minimum(least[:-size], least[size:])
        size *= 2
    if size < width:
        least = np.minimum(least[: len(least) - (width - size)], least[width - size :])
    at = (least & low).astype(np.int64)
    first = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
    last = np.concatenate((first[1:] - 1, [len(at) - 1]))
    at = at[first]
    return at, keys[at], first, last


class Source:
    """How a text is a row of elements. read(text) -> (elements, raw bytes, where each element begins in them)."""

    #: Bytes between two elements.
    gap = 0

    def ready(self) -> None:
        """Called when a task begins; a source that keeps anything between tasks says so here."""

    def read(self, text: str) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
        raw = np.frombuffer(text.encode(), np.uint8)
        return raw, raw, None

    def pieces(self, text: str, window: int) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray | None]]:
        """(offset, elements, raw, starts) of overlapping pieces; one, as a rule."""
        elements, raw, starts = self.read(text)
        offset = 0
        while True:
            stop = min(len(elements), offset + PIECE)
            if starts is None:
                yield offset, elements[offset:stop], raw[offset:stop], None
            else:
                yield offset, elements[offset:stop], raw[starts[offset] : starts[stop]] if offset < stop else raw, starts[offset : stop + 1] - starts[offset]
            if stop == len(elements):
                return
            offset = stop - window + 1


class Powers:
    """Powers of the base and of its inverse, as far as they were needed."""

    def __init__(self):
        self.up = self.down = np.ones(1, np.uint64)

    def upto(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = 1 << n.bit_length()
            self.up = np.concatenate(([np.uint64(1)], np.cumprod(np.full(size, _BASE, np.uint64))))
            self.down = np.concatenate(([np.uint64(1)], np.cumprod(np.full(size, _INVERSE, np.uint64))))
        return self.up[:n], self.down[:n]


def segment_digests(raw: np.ndarray, begin: np.ndarray, end: np.ndarray, powers: Powers) -> np.ndarray:
    up, down = powers.upto(len(raw) + 1)
    total = np.concatenate((np.zeros(1, np.uint64), np.cumsum(_BYTE_VALUE[raw] * up[: len(raw)])))
    return mixed((total[end] - total[begin]) * down[begin] + (end - begin).astype(np.uint64))


def ranges(begin: np.ndarray, size: np.ndarray) -> np.ndarray:
    """begin[0] .. begin[0] + size[0] - 1, begin[1] .. and so on, in one array."""
    shift = np.cumsum(size) - size
    return np.arange(int(size.sum()), dtype=np.int64) + np.repeat(begin - shift, size)


def same_bytes(arena: np.ndarray, begin: np.ndarray, size: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """For each pair of texts in the arena: are they equal?"""
    equal = (size[i] == size[j]) & (i != j)
    some = np.flatnonzero(equal)
    place = np.cumsum(size[i[some]]) // COMPARED
    for part in np.split(some, np.flatnonzero(np.diff(place)) + 1):
        if len(part):
            n = size[i[part]]
            differ = arena[ranges(begin[i[part]], n)] != arena[ranges(begin[j[part]], n)]
            equal[part] = np.add.reduceat(differ, np.cumsum(n) - n, dtype=np.int64) == 0
    return equal | (i == j)


def heads(*sorted_columns: np.ndarray) -> np.ndarray:
    """Where a new combination begins."""
    n = len(sorted_columns[0])
    if not n:
        return np.zeros(0, np.int64)
    change = np.zeros(n - 1, bool)
    for c in sorted_columns:
        change |= c[1:] != c[:-1]
    return np.flatnonzero(np.concatenate(([True], change)))


def sizes_of(first: np.ndarray, n: int) -> np.ndarray:
    return np.diff(np.concatenate((first, [n])))


# ------------------------------------------------------------------------------------------------------------- packing

def pack(plain: list[np.ndarray], small: list[np.ndarray]) -> bytes:
    """Arrays in one blob; those of small numbers are compressed by byte planes."""
    packer = zstandard.ZstdCompressor(level=1)
    parts = [x.tobytes() for x in plain]
    parts += [packer.compress(np.ascontiguousarray(x.view(np.uint8).reshape(len(x), x.itemsize).T).tobytes()) for x in small]
    return struct.pack(f"<{2 * len(parts)}I", *(v for x, p in zip([*plain, *small], parts) for v in (len(x), len(p)))) + b"".join(parts)


def unpack(blob: bytes, plain: str, small: str) -> list[np.ndarray]:
    """plain, small: the arrays' types, separated by spaces."""
    kinds = plain.split() + small.split()
    about, place, out = struct.unpack_from(f"<{2 * len(kinds)}I", blob), 8 * len(kinds), []
    opener = zstandard.ZstdDecompressor()
    for k, kind in enumerate(kinds):
        n, size = about[2 * k : 2 * k + 2]
        part = blob[place : place + size]
        place += size
        if k < len(plain.split()):
            out.append(np.frombuffer(part, kind))
        elif n:
            planes = np.frombuffer(opener.decompress(part, max_output_size=n * np.dtype(kind).itemsize), np.uint8)
            out.append(np.ascontiguousarray(planes.reshape(-1, n).T).view(kind).ravel())
        else:
            out.append(np.zeros(0, kind))
    return out


def joined(parts: list[list[np.ndarray]], k: int) -> np.ndarray:
    return np.concatenate([p[k] for p in parts])


# ---------------------------------------------------------------------------------------------- step 1: shared anchors

_ANCHOR_PLAIN, _ANCHOR_SMALL = "i8 i8 u4 u1 u4 u1", "u4 u4"
_PLACE_PLAIN, _PLACE_SMALL = "i8 i8", "u4 u4"


def document_bucket(ids: np.ndarray, digests: np.ndarray, buckets: int) -> np.ndarray:
    return (mixed(ids.view(np.uint64) ^ mixed(digests.view(np.uint64))) % np.uint64(buckets)).astype(np.int64)


def _steps(at: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Differences of ascending positions, anew in each document."""
    step = np.diff(at, prepend=0)
    starts = np.cumsum(counts) - counts
    step[starts] = at[starts]
    return step.astype(np.uint32)


def _unsteps(step: np.ndarray, counts: np.ndarray) -> np.ndarray:
    step, starts = step.astype(np.int64), np.cumsum(counts, dtype=np.int64) - counts
    total = np.cumsum(step)
    return total - np.repeat((total - step)[starts], counts) if len(starts) else total


def _place_rows(ids: np.ndarray, digests: np.ndarray, owner: np.ndarray, at: np.ndarray, buckets: int):
    """(document bucket, blob) of places; owner ascends, and positions ascend in each owner."""
    where = document_bucket(ids, digests, buckets)[owner]
    by = np.argsort(where, kind="stable")
    owner, at, where = owner[by], at[by], where[by]
    edges = np.concatenate((heads(where), [len(where)]))
    for a, b in zip(edges[:-1].tolist(), edges[1:].tolist()):
        used, counts = np.unique(owner[a:b], return_counts=True)
        yield int(where[a]), pack([ids[used], digests[used]], [counts.astype(np.uint32), _steps(at[a:b], counts)])


def _anchor_rows(source: Source, gram: int, buckets: int, window: int):
    """bucket, kind (0: anchors for a bucket of anchors; 1: places for a bucket of documents), blob."""
    schema = pa.schema([("bucket", pa.int32()), ("kind", pa.int32()), ("blob", pa.binary())])
    narrow = lambda k: ((k & np.uint64(0xFFFFFFFF)).astype(np.uint32), ((k >> np.uint64(32)) & np.uint64(255)).astype(np.uint8))

    def flush(docs, keys, owner, at):
        keys, owner, at = np.concatenate(keys), np.concatenate(owner), np.concatenate(at)
        ids, digests = (np.array([d[k] for d in docs], np.int64) for k in (0, 1))
        order = np.argsort(keys, kind="stable")
        first = heads(keys[order])
        own = ids[owner[order]]
        several = np.minimum.reduceat(own, first) != np.maximum.reduceat(own, first)
        known = np.zeros(len(keys), bool)
        known[order] = np.repeat(several, sizes_of(first, len(keys)))
        mark = keys[order[first[several]]]
        k, o, a = keys[~known], owner[~known], at[~known]
        bucket, mark_bucket = (k >> np.uint64(40)) % np.uint64(buckets), (mark >> np.uint64(40)) % np.uint64(buckets)
        by, mark_by = np.argsort(bucket, kind="stable"), np.argsort(mark_bucket, kind="stable")
        edge, mark_edge = np.searchsorted(bucket[by], np.arange(buckets + 1)), np.searchsorted(mark_bucket[mark_by], np.arange(buckets + 1))
        rows = []
        for b in range(buckets):
            part, marks = by[edge[b] : edge[b + 1]], mark[mark_by[mark_edge[b] : mark_edge[b + 1]]]
            if len(part) or len(marks):
                used, counts = np.unique(o[part], return_counts=True)
                rows.append((b, 0, pack([ids[used], digests[used], *narrow(k[part]), *narrow(marks)], [counts.astype(np.uint32), _steps(a[part], counts)])))
        rows += [(b, 1, blob) for b, blob in _place_rows(ids, digests, owner[known], at[known], buckets)]
        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), schema)], schema=schema)

    def run(batches):
        source.ready()
        docs, keys, owner, at, held = [], [], [], [], 0
        for batch in text_slices(batches, owner=__name__):
            for doc_id, digest, text in zip(*(c.to_pylist() for c in batch.columns)):
                for offset, elements, _, _ in source.pieces(text, window):
                    where, hashes, _, _ = anchors(elements, gram, window)
                    if len(where):
                        keys.append(hashes)
                        at.append(where + offset)
                        owner.append(np.full(len(where), len(docs), np.int64))
                        held += len(where)
                docs.append((doc_id, digest))
                if held >= ENTRIES:
                    yield from flush(docs, keys, owner, at)
                    docs, keys, owner, at, held = [], [], [], [], 0
        if held:
            yield from flush(docs, keys, owner, at)

    return run, "bucket int, kind int, blob binary"


def _shared_places(buckets: int):
    """All rows of some buckets -> bucket (of documents), blob: places of anchors that two documents have."""
    schema = pa.schema([("bucket", pa.int32()), ("blob", pa.binary())])

    def shared(blobs):
        parts = [unpack(x, _ANCHOR_PLAIN, _ANCHOR_SMALL) for x in blobs]
        ids, digests, counts = joined(parts, 0), joined(parts, 1), joined(parts, 6)
        wide = lambda low, high: joined(parts, low).astype(np.uint64) | (joined(parts, high).astype(np.uint64) << np.uint64(32))
        keys, marks = wide(2, 3), wide(4, 5)
        at = _unsteps(joined(parts, 7), counts)
        del parts
        owner = np.repeat(np.arange(len(ids)), counts)
        order = np.argsort(keys, kind="stable")
        first = heads(keys[order])
        if len(first):
            own = ids[owner[order]]
            several = (np.minimum.reduceat(own, first) != np.maximum.reduceat(own, first)) | np.isin(keys[order[first]], marks)
            found = np.zeros(len(keys), bool)
            found[order] = np.repeat(several, sizes_of(first, len(keys)))
            rows = list(_place_rows(ids, digests, owner[found], at[found], buckets))  # still in order of document and place
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), schema)], schema=schema)

    def run(batches):
        blobs: dict[int, list] = {}
        for batch in batches:
            passed = batch.filter(pc.equal(batch.column("kind"), 1))
            if passed.num_rows:
                yield pa.RecordBatch.from_arrays([passed.column("bucket"), passed.column("blob")], schema=schema)
            for b, kind, blob in zip(*(c.to_pylist() for c in batch.columns)):
                if not kind:
                    blobs.setdefault(b, []).append(blob)
        while blobs:
            yield from shared(blobs.popitem()[1])

    return run, "bucket int, blob binary"


# ------------------------------------------------------------------------------------- step 2 and 3: segments and shards

_SEGMENT_PLAIN, _SEGMENT_SMALL = "u8 u8 i8 i8", "u2 u4 u4 u4 u4 u1"
_SPAN = pa.schema([("doc_id", pa.int64()), ("digest", pa.int64()), ("start", pa.int64()), ("end", pa.int64())])


def _spans(doc, digest, start, end):
    if len(doc):
        yield pa.RecordBatch.from_arrays([pa.array(doc), pa.array(digest), pa.array(start), pa.array(end)], schema=_SPAN)


class _Places:
    """Positions by document, from blobs in any order."""

    def __init__(self, blobs: list[list[np.ndarray]]):
        if not blobs:
            self.ids = np.zeros(0, np.int64)
            return
        counts = joined(blobs, 2).astype(np.int64)
        self.at = _unsteps(joined(blobs, 3), counts)
        ids, digests = joined(blobs, 0), joined(blobs, 1)
        order = np.lexsort((digests, ids))
        self.ids, self.digests, self.counts = ids[order], digests[order], counts[order]
        self.start = (np.cumsum(counts) - counts)[order]

    def of(self, doc_id: int, digest: int) -> np.ndarray:
        a, b = np.searchsorted(self.ids, doc_id), np.searchsorted(self.ids, doc_id, side="right")
        mine = [k for k in range(a, b) if self.digests[k] == digest]
        return np.concatenate([self.at[self.start[k] : self.start[k] + self.counts[k]] for k in mine]) if mine else np.zeros(0, np.int64)


def _segment_rows(source: Source, gram: int, shards: int, window: int):
    schema = pa.schema([("shard", pa.int32()), ("blob", pa.binary()), *_SPAN])

    def flush(docs, held):
        key, digest, owner, first, count, size, arena = (np.concatenate(c) for c in zip(*held))
        ids, names = (np.array([d[k] for d in docs], np.int64) for k in (0, 1))
        begin = np.cumsum(size) - size
        order = np.lexsort((ids[owner], digest, key))
        start = heads(key[order], digest[order])
        group = np.empty(len(key), np.int64)
        group[order] = np.repeat(order[start], sizes_of(start, len(key)))
        alike = same_bytes(arena, begin, size, np.arange(len(key)), group)
        group[~alike] = np.flatnonzero(~alike)  # equal hash, other text: on its own
        whole = ids[owner] > ids[owner[group]]
        w = np.flatnonzero(whole)
        w = w[np.lexsort((first[w], owner[w]))]
        # segments that are repeated whole and meet are one span: a row a copied passage, however many anchors it has
        stop = first[w] + count[w] + window - 1
        new = np.flatnonzero(np.concatenate(([True], (owner[w[1:]] != owner[w[:-1]]) | (first[w[1:]] > stop[:-1])))) if len(w) else w
        until = np.maximum.reduceat(stop, new) if len(w) else stop
        w = w[new]
        n = len(w)
        none = [None] * n
        if n:
            deal = (np.arange(n) % shards).astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(deal), pa.array(none, pa.binary()), pa.array(ids[owner[w]]), pa.array(names[owner[w]]), pa.array(first[w]), pa.array(until)], schema=schema)
        left = np.flatnonzero(~whole)
        shard = ((key[left] >> np.uint64(24)) % np.uint64(shards)).astype(np.int32)
        by = np.lexsort((group[left], shard))
        left, shard = left[by], shard[by]
        edge = np.searchsorted(shard, np.arange(shards + 1))
        number, blob = [], []
        for s in range(shards):
            part = left[edge[s] : edge[s + 1]]
            if len(part):
                lead, code = np.unique(group[part], return_inverse=True)
                used, doc = np.unique(owner[part], return_inverse=True)
                text = arena[ranges(begin[lead], size[lead])]
                number.append(s)
                blob.append(pack([key[lead], digest[lead], ids[used], names[used]], [count[lead].astype(np.uint16), size[lead].astype(np.uint32), code.astype(np.uint32), doc.astype(np.uint32), first[part].astype(np.uint32), text]))
        m = len(number)
        null = pa.nulls(m, pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array(number, pa.int32()), pa.array(blob, pa.binary()), null, null, null, null], schema=schema)

    def run(batches):
        """Rows of some document buckets: first the blobs of places (doc_id null), then the texts."""
        opener, powers, docs, held, bytes_held = zstandard.ZstdDecompressor(), Powers(), [], [], 0
        told, places = [], None
        source.ready()
        for batch in text_slices(batches, "body", __name__):
            for doc_id, name, body in zip(*(batch.column(k).to_pylist() for k in ("doc_id", "digest", "body"))):
                if doc_id is None:
                    told.append(unpack(body, _PLACE_PLAIN, _PLACE_SMALL))
                    continue
                if places is None:
                    places = _Places(told)
                    told = []
                shared_at = places.of(doc_id, name)
                if not len(shared_at):
                    continue
                for offset, elements, raw, starts in source.pieces(opener.decompress(body).decode(), window):
                    where, key, first, last = anchors(elements, gram, window)
                    here = shared_at[(shared_at >= offset) & (shared_at < offset + len(elements))] - offset
                    if not len(here):
                        continue
                    marked = np.zeros(len(elements), bool)
                    marked[here] = True
                    keep = marked[where]
                    if not keep.any():
                        continue
                    key, first, last = key[keep], first[keep], last[keep]
                    stop = last + window
                    begin, end = (first, stop) if starts is None else (starts[first], starts[stop] - source.gap)
                    held.append((key, segment_digests(raw, begin, end, powers), np.full(len(key), len(docs), np.int64), first + offset, last - first + 1, end - begin, raw[ranges(begin, end - begin)]))
                    bytes_held += int((end - begin).sum()) + 60 * len(key)
                docs.append((doc_id, name))
                if bytes_held > ARENA:
                    yield from flush(docs, held)
                    docs, held, bytes_held = [], [], 0
        if held:
            yield from flush(docs, held)

    return run, "shard int, blob binary, doc_id long, digest long, start long, end long"


def _resolve(index: Callable, window: int):
    """Segments of whole shards -> doc_id, digest, start, end (elements that repeated windows cover)."""

    def shard(blobs):
        parts = [unpack(x, _SEGMENT_PLAIN, _SEGMENT_SMALL) for x in blobs]
        key, digest, ids, names = (joined(parts, k) for k in range(4))
        count, size, arena = joined(parts, 4).astype(np.int64), joined(parts, 5).astype(np.int64), joined(parts, 9)
        shift = lambda k: np.cumsum([0, *(len(p[k]) for p in parts)])[:-1]
        group = np.concatenate([p[6].astype(np.int64) + s for p, s in zip(parts, shift(0))])
        doc = np.concatenate([p[7].astype(np.int64) + s for p, s in zip(parts, shift(2))])
        first = joined(parts, 8).astype(np.int64)
        parts.clear()
        begin = np.cumsum(size) - size
        # equal texts of different tasks are one
        order = np.lexsort((digest, key))
        start = heads(key[order], digest[order])
        lead = np.empty(len(key), np.int64)
        lead[order] = np.repeat(order[start], sizes_of(start, len(key)))
        alike = same_bytes(arena, begin, size, np.arange(len(key)), lead)
        lead[~alike] = np.flatnonzero(~alike)
        mine = lead[group]
        order = np.lexsort((ids[doc], mine))
        mine, doc, first = mine[order], doc[order], first[order]
        start = heads(mine)
        least = np.repeat(ids[doc[start]], sizes_of(start, len(mine)))
        own = ids[doc]
        w = own > least
        yield from _spans(own[w], names[doc[w]], first[w], first[w] + count[mine[w]] + window - 1)
        mine, doc, first = mine[~w], doc[~w], first[~w]
        # anchors with several texts of several documents go to the index
        start = heads(mine)
        texts, owner = mine[start], ids[doc[start]]
        order = np.argsort(key[texts], kind="stable")
        texts, owner = texts[order], owner[order]
        edge = heads(key[texts])
        open_ = np.repeat(np.minimum.reduceat(owner, edge) != np.maximum.reduceat(owner, edge), sizes_of(edge, len(texts))) if len(texts) else np.zeros(0, bool)
        texts, owner = texts[open_], owner[open_]
        if not len(texts):
            return
        edge = np.concatenate((heads(key[texts]), [len(texts)]))
        elements = np.concatenate(([0], np.cumsum(count[texts] + window)))
        bounds = np.searchsorted(mine, texts), np.searchsorted(mine, texts, side="right")
        low = 0
        while low < len(texts):
            high = edge[max(np.searchsorted(edge, low, side="right"), np.searchsorted(elements[edge], elements[low] + SHARD_ELEMENTS, side="right") - 1)]
            some = texts[low:high]
            row, at, smallest = index(arena, begin[some], size[some], count[some], owner[low:high], window)
            hit = smallest < owner[low:high][row]
            row, at = row[hit], at[hit]
            if len(row):
                new = np.flatnonzero(np.concatenate(([True], (row[1:] != row[:-1]) | (at[1:] - at[:-1] > window))))
                until = np.concatenate((new[1:] - 1, [len(at) - 1]))
                r = row[new] + low
                n = bounds[1][r] - bounds[0][r]  # each run holds at every place of its text
                place = ranges(bounds[0][r], n)
                yield from _spans(ids[doc[place]], names[doc[place]], first[place] + np.repeat(at[new], n), first[place] + np.repeat(at[until] + window, n))
            low = high

    def run(batches):
        blobs: dict[int, list] = {}
        for batch in batches:
            passed = batch.filter(pc.is_valid(batch.column("doc_id")))
            if passed.num_rows:
                yield pa.RecordBatch.from_arrays([passed.column(n) for n in _SPAN.names], schema=_SPAN)
            for s, blob in zip(batch.column("shard").to_pylist(), batch.column("blob").to_pylist()):
                if blob is not None:
                    blobs.setdefault(s, []).append(blob)
        while blobs:
            yield from shard(blobs.popitem()[1])

    return run, "doc_id long, digest long, start long, end long"


def sieve(ids: DataFrame) -> Column:
    """A predicate on doc_id that is true for all ids of a frame and for few others, of a fixed size at any scale."""
    spot = F.pmod(F.xxhash64("doc_id"), F.lit(SIEVE_LONGS * 64))
    words = ids.select(spot.alias("s")).groupBy(F.shiftright("s", 6).alias("k")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("s").bitwiseAND(F.lit(63)).cast("int"))).alias("v")).collect()
    bits = [0] * SIEVE_LONGS
    for r in words:  # at most SIEVE_LONGS rows
        bits[r["k"]] = r["v"]
    table = F.from_json(F.lit(f"[{','.join(map(str, bits))}]"), "array<bigint>")
    return F.coalesce(F.call_function("getbit", F.get(table, F.shiftright(spot, 6).cast("int")), spot.bitwiseAND(F.lit(63)).cast("int")) == 1, F.lit(False))


def named(docs: DataFrame) -> DataFrame:
    text = F.col("text").cast("string")
    return docs.select("doc_id", F.xxhash64(text).alias("digest"), text.alias("text"))


def squeezed(texts: DataFrame, buckets: int = 1) -> DataFrame:
    """bucket, doc_id, digest, body: the text compressed, so that a shuffle moves less; null stays null."""

    def run(batches):
        packer = zstandard.ZstdCompressor(level=1)
        for batch in text_slices(batches, owner=__name__):
            bodies = [None if t is None else packer.compress(t.encode()) for t in batch.column(2).to_pylist()]
            ids, digests = (pc.fill_null(batch.column(k), 0).to_numpy(zero_copy_only=False) for k in (0, 1))
            yield pa.RecordBatch.from_arrays([pa.array(document_bucket(ids, digests, buckets), pa.int32()), batch.column(0), batch.column(1), pa.array(bodies, pa.binary())], ["bucket", "doc_id", "digest", "body"])

    return texts.select("doc_id", "digest", "text").mapInArrow(run, "bucket int, doc_id long, digest long, body binary")


def drop_shuffles(df: DataFrame) -> None:
    """Let the driver notice which shuffles nothing refers to any more; their files go."""
    gc.collect()
    df.sparkSession._jvm.System.gc()


def repeated_spans(docs: DataFrame, source: Source, index: Callable, gram: int, window: int = WINDOW) -> DataFrame:
    """doc_id, digest, spans: array of (start, end) in elements, sorted, maybe overlapping; only documents with any. Settled.

    index(arena, begin, size, windows, doc, window) -> (row, window number, smallest document with that window) of all
    windows of the texts at begin in the arena.
    """
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    texts = named(docs).where(F.col("doc_id").isNotNull() & (F.length("text") > 0))
    packed = texts.mapInArrow(*_anchor_rows(source, gram, parts, window))
    places = settle(packed.repartitionById(parts, F.col("bucket")).mapInArrow(*_shared_places(parts)))
    del packed
    drop_shuffles(places)
    null = F.lit(None).cast("long")
    told = places.select("bucket", null.alias("doc_id"), null.alias("digest"), F.col("blob").alias("body"))
    asked = squeezed(texts, parts).select("bucket", "doc_id", "digest", "body")
    rows = told.unionAll(asked).repartitionById(parts, F.col("bucket")).sortWithinPartitions(F.col("doc_id").asc_nulls_first())
    segments = rows.mapInArrow(*_segment_rows(source, gram, parts, window))
    found = segments.repartitionById(parts, F.col("shard")).mapInArrow(*_resolve(index, window))
    spans = settle(found.groupBy("doc_id", "digest").agg(F.array_sort(F.collect_list(F.struct("start", "end"))).alias("spans")))
    del told, asked, rows, segments, found
    drop_shuffles(spans)
    forget(places)
    return spans


def without_spans(docs: DataFrame, spans: DataFrame, work: Callable, schema: str, whole: list[Column] | None = None) -> DataFrame:
    """Each row of docs without its spans. work(text as bytes, merged spans) -> values; schema: doc_id and their names and types.

    Texts that no span can be of are not shuffled; with `whole`, the values that a text without spans gives as columns on
    `text` (not null), they stay in the JVM. The others are compressed and meet their spans.
    """
    texts, maybe = named(docs), sieve(spans.select("doc_id"))
    names, kinds = zip(*(c.split() for c in schema.split(", ")))
    types = [{"long": pa.int64(), "binary": pa.binary()}[k] for k in kinds]

    def rows(ids, out):
        return pa.RecordBatch.from_arrays([ids, *(pa.array(c, t) for c, t in zip(zip(*out), types[1:]))], list(names))

    def cut(batches):
        opener = zstandard.ZstdDecompressor()
        for batch in text_slices(batches, "body", __name__):
            if batch.num_rows:
                yield rows(batch.column(0), [work(b"" if body is None else opener.decompress(body), merged(spans)) for body, spans in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist())])

    def keep(batches):
        for batch in text_slices(batches, owner=__name__):
            if batch.num_rows:
                yield rows(batch.column(0), [work(t.encode(), []) for t in batch.column(1).to_pylist()])

    touched = squeezed(texts.where(maybe)).join(spans, ["doc_id", "digest"], "left").select("doc_id", "body", "spans").mapInArrow(cut, schema)
    plain = texts.where(~maybe).select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    if whole is None:
        return plain.mapInArrow(keep, schema).unionAll(touched)
    return plain.select("doc_id", *(c.cast(k).alias(n) for c, n, k in zip(whole, names[1:], kinds[1:]))).unionAll(touched)


def merged(spans: list[dict] | None) -> list[tuple[int, int]]:
    """Sorted disjoint runs; runs that touch become one."""
    out: list[list[int]] = []
    for s in spans or ():
        if out and s["start"] <= out[-1][1]:
            out[-1][1] = max(out[-1][1], s["end"])
        else:
            out.append([s["start"], s["end"]])
    return [tuple(x) for x in out]
