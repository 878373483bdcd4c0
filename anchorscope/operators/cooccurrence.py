"""Best answers of many cues: exact counts of all pairs of a pool of records, by blocks of cues that a task counts by sorting numbers.

Entities are numbered once and the pool is written as numbers. A task goes through that file for its block of cues, so no pair is ever shuffled;
a block is sized by its pairs and halved if they turn out too many, so what a task holds does not grow with the pool. Only the best answers of a cue leave the task.
Going through the file takes blocks times mentions, small steps that grow with the square of the pool; the pairs themselves grow as the pool does.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.fs as pafs
import pyarrow.parquet as pq
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.session import cut

#: Pairs that a task buffers before it adds them up; a block of more than twice as many different ones is halved.
PAIRS_AT_ONCE = 6_000_000
#: Different pairs that a block may have at most by the sizes of its cues, in units of the above; most have far fewer, as frequent pairs repeat.
UNITS = 4
#: Entities whose names a task may hold.
VOCABULARY = 5_000_000
#: Mentions that are numbered in one call.
MENTIONS_AT_ONCE = 1_000_000

_NAMES: dict[tuple, pa.Array] = {}


def _open(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else f"file://{uri}")


def names_of(files: list[str]) -> pa.Array:
    """All entities in order of names (bytes); their places are their numbers. Held by a worker for the pool it counts in last."""
    key = tuple(files)
    if key not in _NAMES:
        parts = []
        for uri in files:
            fs, path = _open(uri)
            parts += pq.read_table(path, columns=["entity"], filesystem=fs)["entity"].chunks
        names = pa.chunked_array(parts, pa.string()).combine_chunks()
        _NAMES.clear()
        _NAMES[key] = names.take(pc.sort_indices(names))
    return _NAMES[key]


def numbered(records: DataFrame, files: list[str]) -> DataFrame:
    """lens, ids: records as numbers, many in a row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0

        def out() -> pa.RecordBatch:
            facts = pa.chunked_array(held).combine_chunks()
            ids = pc.index_in(facts.flatten(), value_set=names_of(files)).to_numpy(zero_copy_only=False).astype(np.int32)
            lens = pc.list_value_length(facts).to_numpy(zero_copy_only=False).astype(np.int32)
            return pa.RecordBatch.from_arrays([pa.array([lens.tobytes()], pa.binary()), pa.array([ids.tobytes()], pa.binary())], ["lens", "ids"])

        for batch in batches:
            held.append(batch.column(0))
            size += len(batch.column(0).flatten())
            if size >= MENTIONS_AT_ONCE:
                yield out()
                held, size = [], 0
        if size:
            yield out()

    return records.select("facts").mapInArrow(run, "lens binary, ids binary")


def add_up(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Different keys in order, and their counts added up."""
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    begin = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
    return keys[begin], np.add.reduceat(counts, begin)


def runs(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Different keys in order, and how often each occurs."""
    keys.sort()
    begin = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
    return keys[begin], np.diff(np.r_[begin, len(keys)])


def pairs_of_chunk(lens: np.ndarray, ids: np.ndarray, place: np.ndarray, asked: np.ndarray) -> np.ndarray:
    """asked: by entity, if it is a cue of the block; place: its place there. place of cue * number of entities + answer, for all answers of all records that mention a cue (the cue itself too)."""
    at = np.flatnonzero(asked.take(ids))
    ends = np.cumsum(lens, dtype=np.int64)
    record = np.searchsorted(ends, at, side="right")
    size = lens[record].astype(np.int64)
    first = np.repeat(ends[record] - size - (np.cumsum(size) - size), size)
    return np.repeat(place[ids[at]].astype(np.int64) * len(place), size) + ids[first + np.arange(len(first))]


def count_block(chunks: Iterator[tuple[np.ndarray, np.ndarray]], cues: np.ndarray, entities: int) -> tuple[np.ndarray, np.ndarray] | None:
    """keys (place in cues * entities + answer) in order and their counts, of all records; None if they are too many for several cues at once."""
    place, asked = np.zeros(entities, np.int32), np.zeros(entities, bool)
    asked[cues] = True
    place[cues] = np.arange(len(cues), dtype=np.int32)
    keys, counts, held, size = np.empty(0, np.int64), np.empty(0, np.int64), [], 0

    def flush() -> tuple[np.ndarray, np.ndarray]:
        new = runs(np.concatenate(held))
        return new if not len(keys) else add_up(np.r_[keys, new[0]], np.r_[counts, new[1]])

    for lens, ids in chunks:
        found = pairs_of_chunk(lens, ids, place, asked)
        if len(found):
            held.append(found)
            size += len(found)
        if size >= PAIRS_AT_ONCE:
            (keys, counts), held, size = flush(), [], 0
            if len(keys) > 2 * PAIRS_AT_ONCE and len(cues) > 1:
                return None
    return flush() if held else (keys, counts)


def count_in_parts(chunks: Callable[[], Iterator[tuple[np.ndarray, np.ndarray]]], cues: np.ndarray, entities: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """cues, keys, counts: the block, or its halves if it holds too many pairs."""
    todo = [cues]
    while todo:
        some = todo.pop()
        counted = count_block(chunks(), some, entities)
        if counted is None:
            todo += [some[::2], some[1::2]]
        else:
            yield some, *counted


def best_of(keys: np.ndarray, counts: np.ndarray, cues: np.ndarray, entities: int, support: int, named: np.ndarray) -> np.ndarray:
    """Which pairs are among the `support` best of their cue (ties by number) or have a named answer; never the cue itself."""
    cue, ans = np.divmod(keys, entities)
    keep = named[ans]
    itself = cues[cue] == ans
    counts = np.where(itself, 0, counts)
    edge = np.flatnonzero(np.r_[True, cue[1:] != cue[:-1], True])
    for b, e in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
        if e - b <= support:
            keep[b:e] = True
            continue
        c = counts[b:e]
        least = np.partition(c, e - b - support)[e - b - support]
        above = c > least
        keep[b:e] |= above
        keep[b + np.flatnonzero(c == least)[: support - int(above.sum())]] = True
    return keep & ~itself


def best_of_many(records: DataFrame, cues: DataFrame, support: int, named: DataFrame) -> tuple[DataFrame, DataFrame] | None:
    """cues (cue, distinct) -> (cue, ans, c: exact counts of the `support` best answers, ties by name, and of the answers `named`), (cue, c: sum of all answers).

    None if the pool has more entities than a task may hold the names of.
    """
    records = cut(records.select("facts"))
    words = cut(records.select((F.size("facts") - 1).cast("long").alias("others"), F.explode("facts").alias("entity")).groupBy("entity").agg(F.sum("others").alias("c")))
    entities = words.count()
    if entities > VOCABULARY:
        return None
    asked = cut(cues.join(words.withColumnRenamed("entity", "cue"), "cue"))
    blocks = (asked.agg(F.sum(F.least("c", F.lit(entities)))).first()[0] or 0) // (UNITS * PAIRS_AT_ONCE) + 1
    names, aims = words.inputFiles(), cut(named.select(F.col("ans").alias("entity")).distinct()).inputFiles()
    pool = cut(numbered(records, names)).inputFiles()

    def chunks() -> Iterator[tuple[np.ndarray, np.ndarray]]:
        for uri in pool:
            fs, path = _open(uri)
            with pq.ParquetFile(path, filesystem=fs, pre_buffer=False) as file:
                for batch in file.iter_batches(batch_size=1, use_threads=False):
                    lens, ids = (np.frombuffer(batch.column(c)[0].as_buffer(), np.int32) for c in ("lens", "ids"))
                    yield lens, ids

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        every = names_of(names)
        number = lambda x: pc.index_in(x, value_set=every).drop_null().to_numpy(zero_copy_only=False).astype(np.int64)
        own, wanted = number(pa.array(frame["cue"], pa.string())), np.zeros(len(every), bool)
        for uri in aims:
            fs, path = _open(uri)
            for part in pq.read_table(path, columns=["entity"], filesystem=fs)["entity"].chunks:
                wanted[number(part)] = True
        out = []
        for some, keys, counts in count_in_parts(chunks, own, len(every)):
            keep = best_of(keys, counts, some, len(every), support, wanted)
            cue, ans = np.divmod(keys[keep], len(every))
            out.append(pd.DataFrame({"cue": every.take(pa.array(some[cue])).to_pandas(), "ans": every.take(pa.array(ans)).to_pandas(), "c": counts[keep]}))
        return pd.concat(out)

    block = F.pmod(F.xxhash64("cue"), F.lit(blocks))
    parts = asked.select("cue", block.alias("block")).repartition(max(1, blocks), "block")
    best = parts.groupBy("block").applyInPandas(run, "cue string, ans string, c long")
    return cut(best), asked
