"""Benchmark decontamination: a broadcast hash set of normalised test n-grams against training token windows.

Words are runs of ASCII letters and digits and of all non-ASCII characters, A-Z lower-cased. Every
window of `width` consecutive words of a test item (a shorter item is one window) is looked up at
every word of every document; a hit by hash is verified on the words themselves.

The test set goes to the workers in slices of at most `SLICE_WINDOWS` windows, so what is broadcast
is bounded whatever the size of the test set: each further slice is one more narrow pass that adds
its hits to those found before. Nothing is shuffled, so hot passages and copies cost no more than others.

Null and empty texts have no words and no hits; items without words have no windows; null item ids
are named "null"; repeated rows are judged one by one; columns of any name pass through unchanged.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .text import ALNUM, LOWER, PrefixHash, in_slices, pieces, scramble, utf8_view, word_bounds

WIDTH = 10
#: Windows in one broadcast slice: about 32 MB with their words.
SLICE_WINDOWS = 200_000
_WORD = re.compile(rb"[0-9a-z\x80-\xff]+")
_HITS = T.StructType([T.StructField("__words", T.LongType()), T.StructField("__spans", T.ArrayType(T.LongType())), T.StructField("__items", T.ArrayType(T.StringType()))])


def normalised_words(text: str | None) -> list[bytes]:
    return _WORD.findall((text or "").encode("utf-8", "replace").lower())


def windows_of(items: list[tuple[str, str | None]], width: int) -> Iterator[dict[tuple[bytes, ...], dict[str, None]]]:
    """Slices of window -> names of the items that hold it, each once."""
    found: dict[tuple[bytes, ...], dict[str, None]] = {}
    for name, text in items:
        words = normalised_words(text)
        n = min(width, len(words))
        for i in range(len(words) - n + 1 if n else 0):
            found.setdefault(tuple(words[i : i + n]), {})[name] = None
        if len(found) >= SLICE_WINDOWS:
            yield found
            found = {}
    yield found


def _mix(ids: np.ndarray) -> np.ndarray:
    h = np.zeros(len(ids), np.uint64)
    for column in ids.T:
        h = scramble(h * np.uint64(0x100000001B3) + column)
    return h


class Scanner:
    """Finds the windows of one slice in rows of text."""

    def __init__(self, windows: dict[tuple[bytes, ...], dict[str, None]]):
        vocabulary = sorted({w for key in windows for w in key})
        flat = np.frombuffer(b"".join(vocabulary), np.uint8)
        ends = np.cumsum([len(w) for w in vocabulary], dtype=np.int64)
        self.vocabulary = np.unique(PrefixHash(flat).of(np.r_[0, ends[:-1]], ends)) if vocabulary else np.zeros(0, np.uint64)
        self.windows = windows
        word_hash = dict(zip(vocabulary, PrefixHash(flat).of(np.r_[0, ends[:-1]], ends), strict=True)) if vocabulary else {}
        self.hashes = {}
        for n in sorted({len(k) for k in windows}):
            self.hashes[n] = np.unique(_mix(np.array([[word_hash[w] for w in k] for k in windows if len(k) == n], np.uint64)))

    def scan(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, dict[int, tuple[list[tuple[int, int]], set[str]]]]:
        """Words by row, and for rows with hits the word spans [from, to) and item names."""
        data = LOWER[data]
        starts, ends, bounds = word_bounds(data, offsets, ALNUM)
        n_words, found = np.diff(bounds), {}
        if not len(starts) or not len(self.vocabulary):
            return n_words, found
        hashes = PrefixHash(data).of(starts, ends)
        known = self.vocabulary[np.minimum(np.searchsorted(self.vocabulary, hashes), len(self.vocabulary) - 1)] == hashes
        stops = np.unique(np.concatenate([np.flatnonzero(~known), bounds[1:]]))
        at_known = np.flatnonzero(known)
        run = np.zeros(len(starts), np.int64)  # known words in a row from each word on
        run[at_known] = stops[np.searchsorted(stops, at_known, "right")] - at_known
        text = data.tobytes()
        for width, wanted in self.hashes.items():
            at = np.flatnonzero(run >= width)
            for some in np.array_split(at, max(1, len(at) // 500_000)):
                h = _mix(hashes[some[:, None] + np.arange(width)])
                for i in some[wanted[np.minimum(np.searchsorted(wanted, h), len(wanted) - 1)] == h].tolist():
                    key = tuple(text[s:e] for s, e in zip(starts[i : i + width].tolist(), ends[i : i + width].tolist(), strict=True))
                    if names := self.windows.get(key):  # the exact check
                        row = int(np.searchsorted(bounds, i, "right")) - 1
                        spans, items = found.setdefault(row, ([], set()))
                        spans.append((i - int(bounds[row]), i - int(bounds[row]) + width))
                        items.update(names)
        return n_words, found


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def _pass(docs: DataFrame, text: str, windows, first: bool) -> DataFrame:
    """One narrow pass: adds the hits of one slice to the columns __words, __spans, __items."""
    slice_ = docs.sparkSession.sparkContext.broadcast(windows)
    schema = docs.schema if not first else T.StructType([*docs.schema.fields, *_HITS.fields])

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(slice_.value)
        for batch in in_slices(batches):
            n = batch.num_rows
            at = batch.schema.get_field_index(text)
            words, spans, items = [], [[] for _ in range(n)], [[] for _ in range(n)]
            if not first:
                spans, items = ([list(x or []) for x in batch.column(batch.schema.get_field_index(c)).to_pylist()] for c in ("__spans", "__items"))
            data, offsets = utf8_view(batch.column(at))
            for a, b in pieces(offsets):
                count, found = scanner.scan(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                words.append(count)
                for row, (got, names) in found.items():
                    old = spans[a + row]
                    spans[a + row] = [x for s in merged(got + list(zip(old[::2], old[1::2], strict=True))) for x in s]
                    items[a + row] = sorted({*items[a + row], *names})
            kept = [c for i, c in enumerate(batch.columns) if batch.schema.field(i).name not in ("__words", "__spans", "__items")]
            new = [pa.array(np.concatenate(words) if words else [], pa.int64()), pa.array(spans, pa.list_(pa.int64())), pa.array(items, pa.list_(pa.string()))]
            yield pa.RecordBatch.from_arrays([*kept, *new], names=[f.name for f in schema.fields])

    return docs.mapInArrow(scan, schema)


def find_hits(docs: DataFrame, items: DataFrame, *, text: str = "text", item_id: str = "item_id", item_text: str = "text", width: int = WIDTH) -> DataFrame:
    """docs with __words (word count), __spans (flat, sorted, disjoint word ranges) and __items (names of items found); columns of docs of these names are replaced."""
    rows = ((("null" if r[0] is None else str(r[0])), r[1]) for r in items.select(F.col(f"`{item_id}`"), F.col(f"`{item_text}`")).toLocalIterator())
    names = docs.columns
    inner = docs.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(names)])
    for k, slice_ in enumerate(windows_of(rows, width)):
        inner = _pass(inner, f"c{names.index(text)}", slice_, k == 0)
    new = _HITS.fieldNames()
    return inner.select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(names) if c not in new], *new)


def _found(docs: DataFrame, items: DataFrame, text: str, width: int) -> DataFrame:
    """docs with their columns as c0, c1 and so on, and the hits."""
    return find_hits(docs.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(docs.columns)]), items, text=f"c{docs.columns.index(text)}", width=width)


def report(docs: DataFrame, items: DataFrame, *, doc_id: str = "doc_id", text: str = "text", width: int = WIDTH) -> DataFrame:
    """Per document: words, words inside occurrences of windows, items found and their digest."""
    found = find_hits(docs.select(doc_id, text), items, text=text, width=width)
    hit = F.aggregate(F.sequence(F.lit(0), F.greatest(F.size("__spans") - 2, F.lit(0)), F.lit(2)), F.lit(0).cast("long"), lambda s, i: s + F.coalesce(F.get("__spans", i + 1) - F.get("__spans", i), F.lit(0)))
    return found.select(
        doc_id, F.col("__words").alias("n_words"), hit.alias("n_hit"), F.size("__items").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", F.array_sort("__items")), 256).alias("items_sha256"), (F.size("__spans") > 0).alias("contaminated"),
    )


def digest(names: list[str]) -> str:
    return hashlib.sha256(",".join(sorted(names)).encode()).hexdigest()


def remove_documents(docs: DataFrame, items: DataFrame, *, text: str = "text", width: int = WIDTH) -> DataFrame:
    """Documents without any occurrence of a window; columns as before."""
    return _found(docs, items, text, width).filter(F.size("__spans") == 0).select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(docs.columns)])


def remove_spans(docs: DataFrame, items: DataFrame, *, text: str = "text", width: int = WIDTH) -> DataFrame:
    """All documents, with the bytes from the first to the last word of every hit span cut out of the text."""
    found, names = _found(docs, items, text, width), docs.columns

    def trim(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in in_slices(batches):
            at, where = names.index(text), batch.schema.get_field_index("__spans")
            texts, spans = batch.column(at).to_pylist(), batch.column(where).to_pylist()
            for i, s in enumerate(spans):
                if s:
                    raw = texts[i].encode("utf-8", "replace")
                    words = [m.span() for m in _WORD.finditer(raw.lower())]
                    for a, b in reversed(list(zip(s[::2], s[1::2], strict=True))):
                        raw = raw[: words[a][0]] + raw[words[b - 1][1] :]
                    texts[i] = raw.decode("utf-8", "replace")
            columns = [pa.array(texts, pa.string()) if i == at else c for i, c in enumerate(batch.columns)]
            yield pa.RecordBatch.from_arrays(columns[: len(names)], names=names)

    return found.mapInArrow(trim, docs.schema)
