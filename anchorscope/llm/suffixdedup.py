"""Removal of repeated byte strings by suffix sorting with a difference cover.

A byte goes if it lies in a string of `MATCH` bytes that also starts earlier (in a document of smaller id, or in the
same one before); strings are judged on the input, and never cross documents.

Which part of the method is distributed. One global suffix array of 100 TB would be sorted, in full, several times over; but only suffixes that
agree in their first `MATCH` bytes have to meet. So the difference-cover sort runs inside tasks, each on whole groups of strings that
can share a window, and the groups are made by an exchange of their names. Every window of `MATCH` bytes holds `MATCH - GRAM + 1` grams of `GRAM` bytes, and the one
with the least hash (the first of equal ones) names the window; equal windows have equal names at equal places. The windows of one document that lie side by side
and share a name are a snippet.

1. Places. One pass over the texts sends name, digest and place of every snippet. Of equal ones (same gram hash, same 64-bit XXH3 of all bytes, same hashes of both
   flanks: 160 bits) the earliest stays, the others are repeats as a whole. Of different ones with one name, those are contested that share the
   `GRAM` bytes before or after the gram with another one: two snippets with an equal window share one of these flanks. All others hold no repeat.
2. Contested snippets meet their documents, and go as text to their names. Each task builds the suffix array of its snippets by difference cover: triples at places not
   divisible by three are sorted and named, the names are sorted by recursion unless all differ, the remaining suffixes are sorted by one
   byte and a sampled rank, and both are merged. Neighbours in the array are compared over their first `MATCH` bytes; of every
   run of equal ones all but the earliest start are repeats.
3. The ranges found meet the documents once more and are struck.

Hot groups. A task that has met a name in more than `HOT` different snippets deals these out by their digests, and marks the name for those that meet it less often; names so marked, and
those of more than `CROWD` contested snippets (a frequent phrase in ever new surroundings), are taken apart into single
windows, dealt out by 128-bit digests, of which the earliest start stays. A task sends of equal snippets or windows only the earliest that it has seen. So no name and no
string, however frequent, meets in one task.

What moves is packed: a row is a batch of places for one bucket of names or documents, as many buckets as the input has parts of `BUCKET_BYTES`. Documents are cut to the shared folder nowhere; what is
found is, and shuffles are freed as soon as it is.

Null and empty texts and those below `MATCH` bytes have nothing removed; a null id counts as larger than all; rows of equal
id are one document by place (equal rows get equal results, none repeats the other); empty tables give empty results;
other columns, of any name, pass through.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .spark import cut
from .text import in_slices, pieces, scramble, utf8_view

MATCH = 100
GRAM = 32
CROWD = 4000
HOT = 64
BUCKET_BYTES = 4 << 20
PARTITION_BYTES = 32 << 20
#: Snippets that a task holds before it sends them on.
HELD = 1 << 20
_CHUNK = 1 << 16
_LAST = (1 << 63) - 1
_RANGES, _CONTESTED, _TEXT = 0, 1, 2  # kinds of rows by document
_CALM, _HOT, _MARK, _DONE = 0, 1, 2, 3  # kinds of rows by name


# ---------------------------------------------------------------- suffix sorting


def suffix_array(s: np.ndarray, depth: int | None = None, cover: int = 1) -> np.ndarray:
    """Starts of the suffixes of s (integers of at least 1) in their order, by a difference cover modulo 3.

    depth: only the order by that many first symbols is needed; names that span it are not told apart any further.
    """
    n = len(s)
    if n < 4:
        return np.array(sorted(range(n), key=lambda i: s[i:].tolist()), np.int64)
    k = int(s.max()) + 1
    t = np.zeros(n + 4, np.int64)
    t[:n] = s
    # where n is 1 modulo 3 an empty suffix joins the sample, so that the two rows of names stay apart
    ones, twos = np.arange(1, n + (n % 3 == 1), 3), np.arange(2, n, 3)
    sample = np.concatenate([ones, twos])
    triples = (t[sample] * k + t[sample + 1]) * k + t[sample + 2]
    order = np.argsort(triples)
    new = np.ones(len(sample), bool)
    new[1:] = triples[order][1:] != triples[order][:-1]
    names = np.empty(len(sample), np.int64)
    names[order] = np.cumsum(new)
    if not new.all() and (depth is None or 3 * cover < depth):
        order = suffix_array(names, depth, 3 * cover)
        names[order] = np.arange(1, len(sample) + 1)
    elif depth is not None:
        names[order] = np.arange(1, len(sample) + 1)
    rank = np.zeros(n + 4, np.int64)
    rank[sample] = names
    sampled = sample[order]
    sampled = sampled[sampled < n]
    m = len(sample) + 2
    rest = np.arange(0, n, 3)
    by_one = t[rest] * m + rank[rest + 1]
    rest = rest[np.argsort(by_one)]
    first, second = sampled[sampled % 3 == 1], sampled[sampled % 3 == 2]
    ahead = np.searchsorted(t[first] * m + rank[first + 1], t[rest] * m + rank[rest + 1])
    ahead += np.searchsorted((t[second] * k + t[second + 1]) * m + rank[second + 2], (t[rest] * k + t[rest + 1]) * m + rank[rest + 2])
    # suffixes that agree in `depth` symbols have any order; the running maximum keeps places apart there too
    out, place = np.empty(n, np.int64), np.maximum.accumulate(ahead) + np.arange(len(rest))
    taken = np.zeros(n, bool)
    taken[place] = True
    out[place] = rest
    out[~taken] = sampled
    return out


def repeated_windows(snippets: list[bytes], doc: np.ndarray, start: np.ndarray, match: int) -> np.ndarray:
    """For every window of every snippet, in order: whether its bytes also start at an earlier (doc, place)."""
    lengths = np.array([len(x) for x in snippets], np.int64)
    counts = lengths - match + 1
    text = np.frombuffer(b"\0".join(snippets) + b"\0" * 8, np.uint8)
    n = int(lengths.sum()) + len(snippets)
    base = np.cumsum(lengths + 1) - lengths - 1
    symbols = text[:n].astype(np.int64) + 2
    symbols[base + lengths] = 1
    owner = np.repeat(np.arange(len(snippets)), counts)
    within = np.arange(len(owner)) - np.repeat(np.cumsum(counts) - counts, counts)
    window = np.full(n, -1, np.int64)
    window[base[owner] + within] = np.arange(len(owner))
    order = window[suffix_array(symbols, match)]
    order = order[order >= 0]
    at = base[owner[order]] + within[order]
    words = np.zeros(n, np.uint64)
    for k in range(8):
        words |= text[k : k + n].astype(np.uint64) << np.uint64(8 * k)
    same = np.ones(len(at) - 1, bool)
    for o in [*range(0, match - 7, 8), match - 8]:
        same &= words[at[1:] + o] == words[at[:-1] + o]
    group = np.concatenate([[0], np.cumsum(~same)])
    where, place = doc[owner[order]], start[owner[order]] + within[order]
    best = np.lexsort((place, where, group))
    head = best[np.flatnonzero(np.r_[True, group[best][1:] != group[best][:-1]])][group]
    out = np.zeros(len(owner), bool)
    out[order] = (where > where[head]) | ((where == where[head]) & (place > place[head]))
    return out


# ---------------------------------------------------------------- names of windows


def named_runs(data: np.ndarray, offsets: np.ndarray, match: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Row, first window (place in data), number of windows, name, and hashes of the flanks (0: not in it) of every run of windows with one name."""
    n = len(data)
    if n < match:
        return (np.zeros(0, np.int64),) * 3 + (np.zeros(0, np.uint64),) + (np.zeros(0, np.uint16),) * 2
    hashes = gram_hashes(data, gram)
    least = (hashes & ~np.uint64(0xFFFFFFFF)) | np.arange(len(hashes), dtype=np.uint64)
    width = match - gram + 1
    have = 1
    while have < width:
        step = min(have, width - have)
        np.minimum(least[:-step], least[step:], out=least[:-step])
        least = least[:-step]
        have += step
    name_at = least.astype(np.uint32)
    edges = [np.flatnonzero(name_at[1:] != name_at[:-1]) + 1, offsets[:-1], offsets[1:] - match + 1]
    begin = np.unique(np.concatenate(edges))
    begin = begin[(begin >= 0) & (begin < len(name_at))]
    stop = np.r_[begin[1:], len(name_at)]
    row = np.searchsorted(offsets, begin, "right") - 1
    valid = begin + match <= offsets[row + 1]
    row, begin, stop = row[valid], begin[valid], stop[valid]
    at = name_at[begin].astype(np.int64)
    flank = (hashes >> np.uint64(48)).astype(np.uint16) | np.uint16(1)
    left = np.where(begin <= at - gram, flank[np.maximum(at - gram, 0)], np.uint16(0))
    right = np.where(stop - 1 + match >= at + 2 * gram, flank[np.minimum(at + gram, len(flank) - 1)], np.uint16(0))
    return row, begin, stop - begin, hashes[at], left, right


def gram_hashes(data: np.ndarray, gram: int) -> np.ndarray:
    """Hashes of all strings of `gram` bytes (at least 8), from eight bytes loaded at every place."""
    n = len(data)
    padded = np.concatenate([data, np.zeros(16, np.uint8)])
    words = np.empty(n + 8, np.uint64)
    for k in range(8):
        part = words[k::8]
        part[:] = padded[k : k + 8 * len(part)].view("<u8") if k + 8 * len(part) <= len(padded) else np.concatenate([padded[k:], np.zeros(8, np.uint8)])[: 8 * len(part)].view("<u8")
    m = n - gram + 1
    h = np.zeros(m, np.uint64)
    for i, at in enumerate([*range(0, gram - 8, 8), gram - 8]):
        h += words[at : at + m] * np.uint64((0x9E3779B97F4A7C15 * (2 * i + 3)) & 0xFFFFFFFFFFFFFFFF | 1)
    return scramble(h)


# ---------------------------------------------------------------- packed rows


class Packed:
    """Columns of numbers as one string of bytes: the same bytes of all numbers side by side, as shuffles compress that well."""

    def __init__(self, *types: type):
        self.types = [np.dtype(t) for t in types]
        self.width = sum(t.itemsize for t in self.types)

    def pack(self, columns: list[np.ndarray]) -> bytes:
        return b"".join(np.ascontiguousarray(c, t).view(np.uint8).reshape(-1, t.itemsize).T.tobytes() for c, t in zip(columns, self.types, strict=True))

    def unpack(self, blobs: list[bytes]) -> list[np.ndarray]:
        """The columns of all blobs, one after the other."""
        out: list[list[np.ndarray]] = [[] for _ in self.types]
        for blob in blobs:
            raw, n, at = np.frombuffer(blob, np.uint8), len(blob) // self.width, 0
            for column, t in zip(out, self.types, strict=True):
                column.append(np.ascontiguousarray(raw[at : at + n * t.itemsize].reshape(t.itemsize, n).T).view(t).ravel())
                at += n * t.itemsize
        return [np.concatenate(c) if c else np.zeros(0, t) for c, t in zip(out, self.types, strict=True)]

    def by_bucket(self, buckets: np.ndarray, columns: list[np.ndarray]) -> Iterator[tuple[int, bytes]]:
        order = np.argsort(buckets, kind="stable")
        buckets, columns = buckets[order], [c[order] for c in columns]
        edges = np.flatnonzero(np.r_[True, buckets[1:] != buckets[:-1], True]) if len(buckets) else np.zeros(1, np.int64)
        for s, e in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
            yield int(buckets[s]), self.pack([c[s:e] for c in columns])


#: name, digest, document, hash of its text, start, windows, hashes of the flanks
PLACES = Packed(np.uint64, np.uint64, np.int64, np.uint32, np.uint32, np.uint8, np.uint16, np.uint16)
#: document, hash of its text, start, length
RANGES = Packed(np.int64, np.uint32, np.uint32, np.uint32)
#: document, hash of its text, start, windows, whether its name is crowded, name
CONTESTED = Packed(np.int64, np.uint32, np.uint32, np.uint8, np.uint8, np.uint64)
#: both halves of the digest, document, hash of its text, start
WINDOWS = Packed(np.uint64, np.uint64, np.int64, np.uint32, np.uint32)
NAMES = Packed(np.uint64)
_PACKED = T.StructType([T.StructField("bucket", T.LongType()), T.StructField("kind", T.ByteType()), T.StructField("blob", T.BinaryType())])


def _rows(rows: list[tuple[int, int, bytes]]) -> Iterator[pa.RecordBatch]:
    """Packed rows in batches of bounded size."""
    held, size = [], 0
    for row in rows:
        held.append(row)
        size += len(row[2])
        if size > 8 << 20:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*held, strict=True), (pa.int64(), pa.int8(), pa.binary()), strict=True)], names=_PACKED.names)
            held, size = [], 0
    if held:
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*held, strict=True), (pa.int64(), pa.int8(), pa.binary()), strict=True)], names=_PACKED.names)


def _by_bucket(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, dict[int, list[bytes]]]]:
    """Blobs by kind of one bucket after the other; rows come sorted by bucket."""
    now, blobs = None, {}
    for batch in batches:
        for bucket, kind, blob in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
            if bucket != now and blobs:
                yield now, blobs
                blobs = {}
            now = bucket
            blobs.setdefault(kind, []).append(blob)
    if blobs:
        yield now, blobs


def _size(docs: DataFrame) -> int:
    """The planner's estimate of the input in bytes."""
    return int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def _buckets(size: int) -> int:
    """A prime number of buckets for an input of `size` bytes; any number gives the same result."""
    n = min(1 << 20, max(251, size // BUCKET_BYTES))
    while any(n % k == 0 for k in range(2, int(n**0.5) + 1)):
        n += 1
    return n


def _dealt(rows: DataFrame, size: int) -> DataFrame:
    """rows by bucket: in the session's number of partitions, or more where `size` bytes would be too much for these."""
    n = min(1 << 20, size // PARTITION_BYTES)
    return rows.repartition(n, "bucket") if n > int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")) else rows.repartition("bucket")


def _keyed(doc_id, text) -> list:
    """doc: the id, null as the largest; th: 31 bits of the text's hash, to tell apart rows of one id."""
    return [F.coalesce(doc_id.cast("long"), F.lit(_LAST)).alias("doc"), F.shiftrightunsigned(F.xxhash64(text), 33).alias("th")]


def _home(doc: np.ndarray, th: np.ndarray, buckets: int) -> np.ndarray:
    return (doc ^ th.astype(np.int64)) % buckets


def _row_key(doc: np.ndarray, th: np.ndarray) -> np.ndarray:
    return scramble(doc.astype(np.int64).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + th.astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F))


def _earliest(a: np.ndarray, b: np.ndarray, doc: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """An order by (a, b), the group of each row in it, and whether it is the earliest of its group (rows of one place are all that)."""
    order = np.lexsort((b, a))
    a, b, doc, start = a[order], b[order], doc[order], start[order]
    new = np.r_[True, (a[1:] != a[:-1]) | (b[1:] != b[:-1])] if len(a) else np.zeros(0, bool)
    group, first = np.cumsum(new) - 1, np.ones(len(a), bool)
    sizes = np.diff(np.r_[np.flatnonzero(new), len(a)])
    many = np.flatnonzero(sizes[group] > 1) if len(a) else np.zeros(0, np.int64)
    if len(many):
        inner = many[np.lexsort((start[many], doc[many], group[many]))]
        head = np.flatnonzero(np.r_[True, group[inner][1:] != group[inner][:-1]])
        lead = inner[head[np.searchsorted(group[inner][head], group[inner])]]
        first[inner] = (doc[inner] == doc[lead]) & (start[inner] == start[lead])
    return order, group, first


def _shares(name: np.ndarray, flank: np.ndarray) -> np.ndarray:
    """Which rows share name (a number from 0) and flank (but 0) with another row."""
    key = name.astype(np.int64) * 65536 + flank
    order = np.argsort(key, kind="stable")
    same = key[order][1:] == key[order][:-1]
    out = np.zeros(len(key), bool)
    out[order] = np.r_[False, same] | np.r_[same, False]
    return out & (flank > 0)


# ---------------------------------------------------------------- passes


def _send_places(match: int, gram: int, buckets: int, hot: int):
    """Texts (doc, th, text) to packed places of snippets by name."""

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        digest = xxhash.xxh3_64_intdigest
        held: list[list[np.ndarray]] = []

        def flush() -> Iterator[pa.RecordBatch]:
            name, mark, doc, th, start, n, left, right = (np.concatenate(c) for c in zip(*held, strict=True))
            order, _, first = _earliest(name, mark, doc, start)
            late, early = order[~first], order[first]
            rows = [(k, _DONE, blob) for k, blob in RANGES.by_bucket(_home(doc[late], th[late], buckets), [doc[late], th[late], start[late], n[late].astype(np.uint32) + match - 1])]
            columns = [c[early] for c in (name, mark, doc, th, start, n, left, right)]
            name, mark = columns[:2]  # sorted by name, and by digest in it
            begin = np.flatnonzero(np.r_[True, name[1:] != name[:-1]])
            sizes = np.diff(np.r_[begin, len(name)])
            is_hot = np.repeat(sizes > hot, sizes)
            at = (scramble(np.where(is_hot, name ^ scramble(mark), name)) >> np.uint64(20)) % np.uint64(buckets)
            for kind, some in ((_CALM, ~is_hot), (_HOT, is_hot)):
                rows += [(k, kind, blob) for k, blob in PLACES.by_bucket(at[some].astype(np.int64), [c[some] for c in columns])]
            marked = name[begin[sizes > hot]]
            rows += [(k, _MARK, blob) for k, blob in NAMES.by_bucket(((scramble(marked) >> np.uint64(20)) % np.uint64(buckets)).astype(np.int64), [marked])]
            yield from _rows(rows)

        waiting = 0
        for batch in in_slices(batches):
            doc, th = batch.column(0).to_numpy(), batch.column(1).to_numpy().astype(np.uint32)
            data, offsets = utf8_view(batch.column(2))
            for a, b in pieces(offsets):
                part, cuts = data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
                row, begin, n, names, left, right = named_runs(part, cuts, match, gram)
                raw = part.tobytes()
                marks = np.fromiter((digest(raw[s:e]) for s, e in zip(begin.tolist(), (begin + n + match - 1).tolist(), strict=True)), np.uint64, len(begin))
                marks ^= scramble(left.astype(np.uint64) << np.uint64(16) | right)
                held.append([names, marks, doc[a:b][row], th[a:b][row], (begin - cuts[row]).astype(np.uint32), n.astype(np.uint8), left, right])
                waiting += len(row)
                if waiting > HELD:
                    yield from flush()
                    held, waiting = [], 0
        if waiting:
            yield from flush()

    return send


def _compare_places(match: int, buckets: int, crowd: int):
    """Packed places of whole names to ranges and contested snippets by document."""

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ranges: list[list[np.ndarray]] = []
        contested: list[list[np.ndarray]] = []

        def flush() -> Iterator[pa.RecordBatch]:
            rows = []
            for kind, packed, parts in ((_RANGES, RANGES, ranges), (_CONTESTED, CONTESTED, contested)):
                if parts:
                    columns = [np.concatenate(c) for c in zip(*parts, strict=True)]
                    rows += [(k, kind, blob) for k, blob in packed.by_bucket(_home(columns[0], columns[1], buckets), columns)]
                    parts.clear()
            yield from _rows(rows)

        waiting = 0
        for bucket, blobs in _by_bucket(batches):
            if _DONE in blobs:
                yield from _rows([(bucket, _RANGES, blob) for blob in blobs[_DONE]])
            marked = np.unique(NAMES.unpack(blobs.get(_MARK, []))[0])
            for kind in (_CALM, _HOT):
                name, mark, doc, th, start, n, left, right = PLACES.unpack(blobs.get(kind, []))
                if not len(name):
                    continue
                order, group, first = _earliest(name, mark, doc, start)
                name, doc, th, start, n, left, right = (c[order] for c in (name, doc, th, start, n, left, right))
                ranges.append([c[~first] for c in (doc, th, start, n.astype(np.uint32) + match - 1)])
                if kind == _HOT:
                    on, crowded = first, np.ones(len(name), bool)
                else:
                    number = np.cumsum(np.r_[True, name[1:] != name[:-1]]) - 1
                    one = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])  # one row of each different snippet
                    some = _shares(number[one], left[one]) | _shares(number[one], right[one])
                    crowded = (np.bincount(number[one], weights=some) > crowd)[number]
                    if len(marked):
                        is_marked = marked[np.minimum(np.searchsorted(marked, name), len(marked) - 1)] == name
                        crowded, on = crowded | is_marked, first & (some[group] | is_marked)
                    else:
                        on = first & some[group]
                contested.append([c[on] for c in (doc, th, start, n, crowded.astype(np.uint8), name)])
                waiting += len(name)
            if waiting > HELD:
                yield from flush()
                waiting = 0
        yield from flush()

    return compare


class _Index:
    """Packed columns by document and hash of its text."""

    def __init__(self, packed: Packed, blobs: list[bytes]):
        columns = packed.unpack(blobs)
        keys = _row_key(columns[0], columns[1])
        order = np.argsort(keys, kind="stable")
        self.keys, self.columns = keys[order], [c[order] for c in columns]

    def of(self, doc: np.ndarray, th: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
        """Row (of those asked for) and columns of all entries that belong to one of them."""
        keys = _row_key(doc, th)
        low, high = np.searchsorted(self.keys, keys), np.searchsorted(self.keys, keys, "right")
        row = np.repeat(np.arange(len(keys)), high - low)
        at = np.arange(len(row)) - np.repeat(np.cumsum(high - low) - (high - low), high - low) + low[row]
        true = (self.columns[0][at] == doc[row]) & (self.columns[1][at] == th[row])
        return row[true], [c[at[true]] for c in self.columns]


def _with_entries(batches: Iterator[pa.RecordBatch], packed: Packed) -> Iterator[tuple[pa.RecordBatch, _Index]]:
    """Slices of text rows of one bucket with the entries of that bucket; rows come sorted by bucket and kind, texts last."""
    now, blobs, index = None, [], None
    for batch in in_slices(batches):
        bucket, kind = batch.column(0).to_numpy(), batch.column(1).to_numpy()
        edges = np.flatnonzero((bucket[1:] != bucket[:-1]) | ((kind[1:] == _TEXT) != (kind[:-1] == _TEXT))) + 1
        for s, e in zip([0, *edges.tolist()], [*edges.tolist(), len(bucket)], strict=True):
            if bucket[s] != now:
                now, blobs, index = bucket[s], [], None
            if kind[s] != _TEXT:
                blobs += batch.column(2).slice(s, e - s).to_pylist()
            else:
                index = index or _Index(packed, blobs)
                yield batch.slice(s, e - s), index


def _send_texts(match: int, buckets: int):
    """Texts with their contested snippets to snippets by name; of crowded names, packed windows by digest."""

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        digest = xxhash.xxh3_128_digest
        held: list[list[np.ndarray]] = []
        names = ["bucket", "kind", "doc", "pos", "blob"]

        def packed(rows: list[tuple[int, int, bytes]]) -> Iterator[pa.RecordBatch]:
            for batch in _rows(rows):
                none = pa.nulls(batch.num_rows, pa.int64())
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), none, none, batch.column(2)], names=names)

        def flush() -> Iterator[pa.RecordBatch]:
            a, b, doc, th, start = (np.concatenate(c) for c in zip(*held, strict=True))
            order, _, first = _earliest(a, b, doc, start)
            late, early = order[~first], order[first]
            rows = [(k, _DONE, blob) for k, blob in RANGES.by_bucket(_home(doc[late], th[late], buckets), [doc[late], th[late], start[late], np.full(len(late), match, np.uint32)])]
            rows += [(k, _HOT, blob) for k, blob in WINDOWS.by_bucket((a[early] % np.uint64(buckets)).astype(np.int64), [c[early] for c in (a, b, doc, th, start)])]
            yield from packed(rows)

        waiting = 0
        for batch, index in _with_entries(batches, CONTESTED):
            row, (doc, th, start, n, crowded, name) = index.of(batch.column(3).to_numpy(), batch.column(4).to_numpy().astype(np.uint32))
            if not len(row):
                continue
            data, offsets = utf8_view(batch.column(5))
            raw = data.tobytes()
            begin, n, is_calm = offsets[row] + start, n.astype(np.int64), crowded == 0
            strings = [raw[s:e] for s, e in zip(begin[is_calm].tolist(), (begin + n + match - 1)[is_calm].tolist(), strict=True)]
            pos = th[is_calm].astype(np.int64) << 32 | start[is_calm]
            if len(strings):
                yield pa.RecordBatch.from_arrays([pa.array(name[is_calm].view(np.int64)), pa.array(np.full(len(strings), _CALM, np.int8)), pa.array(doc[is_calm]), pa.array(pos), pa.array(strings, pa.binary())], names=names)
            some = np.flatnonzero(~is_calm)
            if len(some):
                owner = np.repeat(some, n[some])
                shift = np.arange(len(owner)) - np.repeat(np.cumsum(n[some]) - n[some], n[some])
                marks = np.frombuffer(b"".join(digest(raw[s : s + match]) for s in (begin[owner] + shift).tolist()), np.uint64).reshape(-1, 2)
                held.append([marks[:, 0], marks[:, 1], doc[owner], th[owner], (start[owner] + shift).astype(np.uint32)])
                waiting += len(owner)
                if waiting > HELD:
                    yield from flush()
                    held, waiting = [], 0
        if waiting:
            yield from flush()

    return send


def _solve(match: int, buckets: int):
    """Snippets of whole names through the suffix sort, windows of whole digests by their earliest place, to packed ranges by document."""

    def sorted_ranges(doc: np.ndarray, pos: np.ndarray, strings: list[bytes]) -> list[np.ndarray]:
        start = pos & 0xFFFFFFFF
        counts = np.array([len(x) for x in strings], np.int64) - match + 1
        hit = repeated_windows(strings, doc, start, match) if len(strings) > 1 else np.zeros(int(counts.sum()), bool)
        owner = np.repeat(np.arange(len(strings)), counts)
        within = np.arange(len(owner)) - np.repeat(np.cumsum(counts) - counts, counts)
        edge = owner[1:] != owner[:-1]
        begin = np.flatnonzero(hit & np.r_[True, ~hit[:-1] | edge])
        stop = np.flatnonzero(hit & np.r_[~hit[1:] | edge, True])
        of = owner[begin]
        return [doc[of], (pos[of] >> 32).astype(np.uint32), (start[of] + within[begin]).astype(np.uint32), (within[stop] - within[begin] + match).astype(np.uint32)]

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: list[list[np.ndarray]] = []
        waiting = 0

        def flush() -> Iterator[pa.RecordBatch]:
            if found:
                columns = [np.concatenate(c) for c in zip(*found, strict=True)]
                found.clear()
                yield from _rows([(k, _RANGES, blob) for k, blob in RANGES.by_bucket(_home(columns[0], columns[1], buckets), columns)])

        name, doc, pos, strings, size = [], [], [], [], 0  # whole names, up to about a chunk of text, and one more begun

        def sort_held(last: bool) -> None:
            nonlocal name, doc, pos, strings, size
            end = len(name)
            while not last and end and name[end - 1] == name[-1]:
                end -= 1
            if end:
                found.append(sorted_ranges(np.array(doc[:end], np.int64), np.array(pos[:end], np.int64), strings[:end]))
                name, doc, pos, strings = name[end:], doc[end:], pos[end:], strings[end:]
                size = sum(map(len, strings))

        window_bucket, windows = None, []

        def first_windows() -> None:
            a, b, doc_, th, start = WINDOWS.unpack(windows)
            order, _, first = _earliest(a, b, doc_, start)
            late = order[~first]
            found.append([doc_[late], th[late], start[late], np.full(len(late), match, np.uint32)])

        for batch in in_slices(batches):
            keys, kinds, blobs = batch.column(0).to_numpy(), batch.column(1).to_numpy(), batch.column(4)
            calm = np.flatnonzero(kinds == _CALM)
            if len(calm):
                docs_, places = (batch.column(i).take(pa.array(calm)).to_numpy(zero_copy_only=False) for i in (2, 3))
                texts = blobs.take(pa.array(calm)).to_pylist()
                lengths = np.array([len(x) for x in texts])
                for s, e in _chunks(keys[calm], lengths):
                    name += keys[calm[s:e]].tolist()
                    doc += docs_[s:e].tolist()
                    pos += places[s:e].tolist()
                    strings += texts[s:e]
                    size += int(lengths[s:e].sum())
                    if size > _CHUNK:
                        sort_held(False)
            for i in np.flatnonzero(kinds == _HOT).tolist():
                if keys[i] != window_bucket and windows:
                    first_windows()
                    windows = []
                window_bucket = keys[i]
                windows.append(blobs[i].as_py())
            for i in np.flatnonzero(kinds == _DONE).tolist():
                yield from _rows([(int(keys[i]), _RANGES, blobs[i].as_py())])
            waiting = sum(len(x[0]) for x in found)
            if waiting > HELD:
                yield from flush()
        sort_held(True)
        if windows:
            first_windows()
        yield from flush()

    return solve


def _chunks(names: np.ndarray, lengths: np.ndarray) -> Iterator[tuple[int, int]]:
    """Ranges of rows of about half a chunk of text that end where a name ends, if one does."""
    ends = np.r_[np.flatnonzero(names[1:] != names[:-1]) + 1, len(names)]
    at, size = 0, np.r_[0, np.cumsum(lengths)]
    for e in ends.tolist():
        if size[e] - size[at] > _CHUNK // 2 or e == len(names):
            yield at, e
            at = e


def repeated_ranges(docs: DataFrame, buckets: int, size: int = 0, *, doc_id: str = "doc_id", text: str = "text", match: int = MATCH, gram: int = GRAM, crowd: int = CROWD, hot: int = HOT) -> DataFrame:
    """bucket, kind, blob: byte ranges to remove, which may overlap, packed as `RANGES` by bucket of the document."""
    if not 8 <= gram or 3 * gram > match + 1:
        raise ValueError("a gram needs 8 bytes and a flank as long as itself on one side of it in every window")
    id_, text_ = F.col(f"`{doc_id}`"), F.col(f"`{text}`")
    rows = docs.select(*_keyed(id_, text_), text_.alias("text")).filter(F.octet_length("text") >= match)
    places = rows.mapInArrow(_send_places(match, gram, buckets, hot), _PACKED)
    found = cut(_dealt(places, size).sortWithinPartitions("bucket").mapInArrow(_compare_places(match, buckets, crowd), _PACKED))
    contested = found.filter(F.col("kind") == _CONTESTED)
    home = F.pmod(F.col("doc").bitwiseXOR(F.col("th")), F.lit(buckets)).alias("bucket")
    texts = rows.select(home, F.lit(_TEXT).cast("byte").alias("kind"), F.lit(None).cast("binary").alias("blob"), "doc", "th", "text")
    both = _dealt(texts.unionByName(contested, allowMissingColumns=True), size).sortWithinPartitions("bucket", "kind")
    strings = both.mapInArrow(_send_texts(match, buckets), "bucket long, kind byte, doc long, pos long, blob binary")
    solved = _dealt(strings, size).sortWithinPartitions("kind", "bucket").mapInArrow(_solve(match, buckets), _PACKED)
    return found.filter(F.col("kind") == _RANGES).unionByName(cut(solved))


def remove_repeats(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """docs with __spans (flat starts and ends of the maximal removed byte runs) and __kept (the remaining bytes)."""
    names = docs.columns
    size = _size(docs)
    size = size if size < 1 << 60 else 0  # an estimate that Spark couldn't make
    buckets = _buckets(size)
    ranges = repeated_ranges(docs, buckets, size, doc_id=doc_id, text=text, **options)
    at = 5 + names.index(text)
    inner = docs.select(*_keyed(F.col(f"`{doc_id}`"), F.col(f"`{text}`")), *[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(names)])
    home = F.pmod(F.col("doc").bitwiseXOR(F.col("th")), F.lit(buckets)).alias("bucket")
    texts = inner.select(home, F.lit(_TEXT).cast("byte").alias("kind"), F.lit(None).cast("binary").alias("blob"), "*")
    both = _dealt(texts.unionByName(ranges, allowMissingColumns=True), size).sortWithinPartitions("bucket", "kind")
    fields = [T.StructField(f"c{i}", f.dataType) for i, f in enumerate(docs.schema.fields)]
    schema = T.StructType([*fields, T.StructField("__spans", T.ArrayType(T.LongType())), T.StructField("__kept", T.BinaryType())])

    def strike(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, index in _with_entries(batches, RANGES):
            row, (_, _, start, length) = index.of(batch.column(3).to_numpy(), batch.column(4).to_numpy().astype(np.uint32))
            data, offsets = utf8_view(batch.column(at))
            spans, kept = struck(data, offsets, row, start.astype(np.int64), length.astype(np.int64))
            yield pa.RecordBatch.from_arrays([*batch.columns[5:], spans, kept], names=schema.names)

    done = both.mapInArrow(strike, schema)
    return done.select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(names)], "__spans", "__kept")


def struck(data: np.ndarray, offsets: np.ndarray, row: np.ndarray, start: np.ndarray, length: np.ndarray) -> tuple[pa.Array, pa.Array]:
    """Maximal runs (flat starts and ends in the row) and the remaining bytes of every row, after ranges of rows are taken out."""
    begin = offsets[row] + start
    order = np.argsort(begin, kind="stable")
    begin, end, row = begin[order], (begin + length)[order], row[order]
    reach = np.maximum.accumulate(end) if len(end) else end
    new = np.r_[True, (begin[1:] > reach[:-1]) | (row[1:] != row[:-1])] if len(begin) else np.zeros(0, bool)
    at = np.flatnonzero(new)
    first, last, of = begin[at], reach[np.r_[at[1:], len(begin)] - 1] if len(at) else begin, row[at]
    flat = np.empty(2 * len(at), np.int64)
    flat[::2], flat[1::2] = first - offsets[of], last - offsets[of]
    counts = 2 * np.bincount(of, minlength=len(offsets) - 1)
    spans = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(counts)].astype(np.int32)), pa.array(flat))
    change = np.zeros(len(data) + 1, np.int8)
    np.add.at(change, first, 1)
    np.add.at(change, last, -1)
    keep = np.cumsum(change[:-1], dtype=np.int8) == 0
    left = np.r_[0, np.cumsum(keep)][offsets]
    kept = pa.Array.from_buffers(pa.large_binary(), len(offsets) - 1, [None, pa.py_buffer(left.astype(np.int64)), pa.py_buffer(np.ascontiguousarray(data[keep]))]).cast(pa.binary())
    return spans, kept


def report(docs: DataFrame) -> DataFrame:
    done = remove_repeats(docs.select("doc_id", "text"))
    n_bytes = F.octet_length(F.coalesce(F.col("text"), F.lit(""))).cast("long")
    return done.select("doc_id", n_bytes.alias("n_bytes"), (n_bytes - F.octet_length("__kept")).alias("n_removed"), (F.size("__spans") / 2).cast("long").alias("n_spans"), F.sha2("__kept", 256).alias("kept_sha256"))


def digest(kept: bytes) -> str:
    return hashlib.sha256(kept).hexdigest()
