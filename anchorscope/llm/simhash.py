"""SimHash near-duplicates through a segment-popcount embedding.

A fingerprint has a bit for each of 64 votes over the XXH64 (seed 42) of its word shingles. Cutting it into
segments of `SEGMENT` bits and counting the ones of each gives a vector; changing one bit moves one
coordinate by one, so the Manhattan distance of two vectors never exceeds the Hamming distance of their fingerprints.

Pairs within `distance` are found by a grid range join on these vectors. The coordinates form two halves; of
3 units of distance one half holds at most one. A cell of the grid is one value of one half's vector. Every
fingerprint lies in its own cell of each half, and, where the sum of the half is odd, is also sent to the cells one unit away:
two cells one unit apart differ in the parity of that sum, so each such pair meets in the even one. What meets is verified on the whole fingerprints.

Equal fingerprints are one node before anything is joined. A cell is searched breadth first: each
fingerprint reached is compared with those not reached yet, and only the links of this search come out, at most one for each
fingerprint of the cell, not its pairs; a dense group of near copies costs little as few stay unreached. Cells of more than
`BLOCK` fingerprints are dealt out as pairs of blocks, so no task holds an unbounded cell and no pair is lost.

Null and empty texts have fingerprint zero and are linked like any other; a null id names no component (one of only such rows has a null id);
repeated rows come out as often as they went in; empty tables give empty results; other columns are not touched.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .components import components
from .spark import cut
from .text import LOWER, NOT_SPACE, in_slices, pieces, utf8_view, word_bounds

SHINGLE = 3
DISTANCE = 3
SEGMENT = 2
BLOCK = 20_000


def fingerprints_of(data: np.ndarray, offsets: np.ndarray, shingle: int = SHINGLE) -> np.ndarray:
    """Fingerprints (uint64) of the rows of a byte view."""
    import xxhash

    data = LOWER[data]
    starts, ends, bounds = word_bounds(data, offsets, NOT_SPACE)
    out = np.zeros(len(offsets) - 1, np.uint64)
    if not len(starts):
        return out
    # words with one space between, so that a shingle is a slice
    lengths = ends - starts
    to = np.cumsum(lengths + 1)
    at = to - lengths - 1
    joined = np.full(int(to[-1]), 32, np.uint8)
    joined[np.repeat(at - np.concatenate([[0], np.cumsum(lengths)[:-1]]), lengths) + np.arange(int(lengths.sum()))] = data[NOT_SPACE[data]]
    text = joined.tobytes()
    counts = np.diff(bounds)
    n_shingles = np.where(counts >= shingle, counts - shingle + 1, np.minimum(counts, 1))
    row = np.repeat(np.arange(len(counts)), n_shingles)
    begin = bounds[:-1][row] + np.arange(len(row)) - np.repeat(np.cumsum(n_shingles) - n_shingles, n_shingles)
    end = begin + np.minimum(shingle, counts[row]) - 1
    digest = xxhash.xxh64_intdigest
    hashes = np.fromiter((digest(text[s:e], 42) for s, e in zip(at[begin].tolist(), (at[end] + lengths[end]).tolist(), strict=True)), np.uint64, len(row))
    bits = np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    some = np.flatnonzero(n_shingles)
    votes = np.add.reduceat(bits, (np.cumsum(n_shingles) - n_shingles)[some], axis=0, dtype=np.int32)
    out[some] = np.packbits(votes * 2 > n_shingles[some, None], axis=1, bitorder="little").view(np.uint64).ravel()
    return out


def fingerprint(docs: DataFrame, *, text: str = "text", out: str = "fingerprint", shingle: int = SHINGLE) -> DataFrame:
    """docs with the 64-bit fingerprint as a long in place of the text."""
    names = [c for c in docs.columns if c not in (out, text)]
    schema = T.StructType([*[docs.schema[c] for c in names], T.StructField(out, T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in in_slices(batches):
            data, offsets = utf8_view(batch.column(batch.schema.get_field_index(text)))
            parts = [fingerprints_of(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], shingle) for a, b in pieces(offsets)]
            values = np.concatenate(parts) if parts else np.zeros(0, np.uint64)
            yield pa.RecordBatch.from_arrays([*[batch.column(batch.schema.get_field_index(c)) for c in names], pa.array(values.view(np.int64))], names=schema.names)

    return docs.select(*[F.col(f"`{c}`") for c in docs.columns]).mapInArrow(run, schema)


def embedding(prints: np.ndarray, segment: int = SEGMENT) -> np.ndarray:
    """One row of segment popcounts for each fingerprint."""
    bits = np.unpackbits(prints.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    return bits.reshape(len(prints), 64 // segment, segment).sum(axis=2, dtype=np.uint8)


def cells_of(prints: np.ndarray, segment: int = SEGMENT) -> tuple[np.ndarray, np.ndarray]:
    """(cell, index of the fingerprint) for all cells that a fingerprint goes to."""
    vectors = embedding(prints, segment)
    dims = vectors.shape[1] // 2
    weights = np.uint64(segment + 1) ** np.arange(dims, dtype=np.uint64)
    cells, owners = [], []
    everyone = np.arange(len(prints))
    for half in (0, 1):
        v = vectors[:, half * dims : (half + 1) * dims]
        own = (v.astype(np.uint64) * weights).sum(axis=1, dtype=np.uint64) * np.uint64(2) + np.uint64(half)
        cells.append(own)
        owners.append(everyone)
        odd = np.flatnonzero(v.sum(axis=1) % 2 == 1)
        for d in range(dims):
            step = np.uint64(2) * weights[d]
            up, down = odd[v[odd, d] < segment], odd[v[odd, d] > 0]
            cells += [own[up] + step, own[down] - step]
            owners += [up, down]
    return np.concatenate(cells), np.concatenate(owners)


def search(prints: np.ndarray, distance: int = DISTANCE) -> tuple[np.ndarray, np.ndarray]:
    """Links of a breadth-first search over the fingerprints of one cell: as connected as all pairs within the distance."""
    left, frontier, a, b = np.unique(prints), [], [], []
    while len(left):
        if not frontier:
            frontier, left = [left[0]], left[1:]
            continue
        x = frontier.pop()
        near = np.bitwise_count(left ^ x) <= distance
        if near.any():
            met, left = left[near], left[~near]
            a.append(np.full(len(met), x, np.uint64))
            b.append(met)
            frontier.extend(met)
    return (np.concatenate(a), np.concatenate(b)) if a else (np.zeros(0, np.uint64), np.zeros(0, np.uint64))


def links(nodes: DataFrame, *, distance: int = DISTANCE, segment: int = SEGMENT, block: int = BLOCK) -> DataFrame:
    """nodes (fp long, distinct). Returns (a, b): links that connect all that pairs within the distance connect."""
    if distance > 3:
        raise ValueError("the two halves prove pairs within 3 bits only")

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            prints = batch.column(0).to_numpy().view(np.uint64)
            for some in np.array_split(prints, max(1, len(prints) // 50_000)):
                cells, owners = cells_of(some, segment)
                yield pa.RecordBatch.from_arrays([pa.array(cells.view(np.int64)), pa.array(some[owners].view(np.int64))], names=["cell", "fp"])

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held_cells, held_prints = np.zeros(0, np.int64), np.zeros(0, np.uint64)

        def found(cells: np.ndarray, prints: np.ndarray) -> pa.RecordBatch:
            same = np.flatnonzero(np.r_[True, cells[1:] != cells[:-1]]) if len(cells) else np.zeros(0, np.int64)
            sizes = np.diff(np.r_[same, len(cells)])
            a, b = [], []
            two = same[sizes == 2]  # most meetings are of two
            ok = np.bitwise_count(prints[two] ^ prints[two + 1]) <= distance if len(two) else np.zeros(0, bool)
            a.append(prints[two[ok]])
            b.append(prints[two[ok] + 1])
            for s, n in zip(same[sizes > 2].tolist(), sizes[sizes > 2].tolist(), strict=True):
                x, y = search(prints[s : s + n], distance)
                a.append(x)
                b.append(y)
            a, b = np.concatenate(a), np.concatenate(b)
            return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

        for batch in batches:
            cells = np.concatenate([held_cells, batch.column(0).to_numpy()])
            prints = np.concatenate([held_prints, batch.column(1).to_numpy().view(np.uint64)])
            last = int(np.searchsorted(cells, cells[-1])) if len(cells) else 0
            yield found(cells[:last], prints[:last])
            held_cells, held_prints = cells[last:], prints[last:]
        yield found(held_cells, held_prints)

    spread_out = nodes.select("fp").mapInArrow(spread, "cell long, fp long")
    crowded = spread_out.groupBy("cell").agg(F.count("*").alias("n")).filter(F.col("n") > block).select("cell", F.ceil(F.col("n") / (block / 2)).cast("int").alias("parts"))
    crowded = cut(crowded)
    if crowded.isEmpty():
        dealt = spread_out
    else:
        # each member of a crowded cell goes to all pairs of blocks that hold its own block
        own = F.pmod(F.xxhash64("fp"), F.col("parts")).cast("int")
        pair = F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda o: F.xxhash64("cell", F.least(o, own), F.greatest(o, own)) * 2 + 1)
        dealt = spread_out.join(crowded, "cell", "left").withColumn("cell", F.explode(F.coalesce(pair, F.array("cell")))).select("cell", "fp")
    met = dealt.repartition("cell").sortWithinPartitions("cell").mapInArrow(meet, "a long, b long")
    return met.distinct()


def _grouped(docs: DataFrame, doc_id: str, text: str, distance: int, shingle: int) -> DataFrame:
    """doc_id, th (hash of the text), fp, component (fingerprint that names the group), component_id."""
    narrow = docs.select(F.col(f"`{doc_id}`").alias("doc_id"), F.xxhash64(F.col(f"`{text}`")).alias("th"), F.col(f"`{text}`").alias("text"))
    prints = cut(fingerprint(narrow, out="fp", shingle=shingle))
    nodes = cut(prints.groupBy("fp").agg(F.min("doc_id").alias("least")))
    parts = components(links(nodes, distance=distance))
    named = nodes.join(parts.withColumnRenamed("node", "fp"), "fp", "left").withColumn("component", F.coalesce("component", "fp"))
    least = named.groupBy("component").agg(F.min("least").alias("component_id"))
    return prints.join(named.join(least, "component").select("fp", "component", "component_id"), "fp")


def near_duplicates(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", distance: int = DISTANCE, shingle: int = SHINGLE) -> DataFrame:
    """doc_id, fp (long) and component_id: the least doc_id among all documents that links lead to."""
    return _grouped(docs, doc_id, text, distance, shingle).select("doc_id", "fp", "component_id")


def report(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    found = near_duplicates(docs, doc_id=doc_id, text=text)
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row of each group of near-duplicates: one with the least id, or of a group without ids any; columns as before."""
    key = lambda i, t: F.concat_ws("|", F.coalesce(i.cast("string"), F.lit("null")), t.cast("string"))
    found = _grouped(docs, doc_id, text, DISTANCE, SHINGLE).filter(F.col("doc_id").eqNullSafe(F.col("component_id")))
    chosen = found.groupBy("component").agg(F.min(key(F.col("doc_id"), F.col("th"))).alias("_key")).select("_key").distinct()
    names = docs.columns
    rows = docs.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(names)], key(F.col(f"`{doc_id}`"), F.xxhash64(F.col(f"`{text}`"))).alias("_key"))
    kept = rows.join(chosen, "_key", "left_semi").dropDuplicates(["_key"])
    return kept.select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(names)])
