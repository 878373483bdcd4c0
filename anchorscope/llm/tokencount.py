"""Exact token counts of long texts by overlap resynchronisation.

A text of at most `chunk` characters is encoded as it is. A longer one is encoded in overlapping chunks,
with the place where every pre-token starts. The pre-tokeniser reads from left to right and looks at most
`GUARD` characters ahead, and tokens never cross pre-tokens; so in a chunk that began at a true boundary all
starts before its last `GUARD` characters are true. A start that this chunk and the next one have in common is thus
a boundary from which both go on alike: the count is spliced there. If the overlap holds no such
start (one endless word or run of white space), it is doubled and the next chunk encoded again, in the end from
the last place that is proven, and then twice as far as before; so the count equals that of the text encoded at once, and the work stays in proportion to the text.

Texts of one chunk go pre-token by pre-token through a bounded table of counts already taken, if all their
characters are Latin (below U+0250, where all versions of Unicode agree on letters, digits and spaces) and no special token is named in
them; what the table lacks, and all other texts, the tokenizer encodes. Pre-tokens are encoded each by itself, so counts are the same.

Memory is bounded by a chunk, not by the document, unless one pre-token spans it.

Null and empty texts have 0 tokens and 0 bytes; every row is counted by itself; other columns are not read.
"""

from __future__ import annotations

import json
from collections import ChainMap
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

CHUNK = 1 << 15
OVERLAP = 256
#: Longest look-ahead of the pre-tokeniser and longest special token, with room to spare.
GUARD = 32
_BATCH_CHARS = 1 << 21
#: Pre-tokens whose counts a worker keeps: at most about 150 MB.
_TABLE = 1_000_000
#: The byte-level pre-tokeniser's pattern, with white space named so that all libraries read it alike (a fixed value).
_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+"
_loaded: dict[str, tuple] = {}


def load(path: str):
    """The tokenizer for counting, and a copy whose offsets keep leading spaces, once a worker."""
    if path not in _loaded:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer, processors

        plain, exact = Tokenizer.from_file(path), Tokenizer.from_file(path)
        for t in (plain, exact):
            t.no_truncation()
            t.no_padding()
        exact.post_processor = processors.ByteLevel(trim_offsets=False)
        _loaded[path] = plain, exact
    return _loaded[path]


class Counts:
    """Token counts of short texts by way of their pre-tokens."""

    def __init__(self, plain):
        import regex

        self.many = getattr(plain, "encode_batch_fast", plain.encode_batch)
        self.split = regex.compile(_PATTERN).findall
        self.odd = regex.compile("[^\x00-\u024f]").search
        self.special = [t.content for t in plain.get_added_tokens_decoder().values()]
        state = json.loads(plain.to_str())
        plain_bytes = state.get("normalizer") is None and (state.get("pre_tokenizer") or {}).get("type") == "ByteLevel" and not state["pre_tokenizer"].get("add_prefix_space") and state["pre_tokenizer"].get("use_regex", True)
        self.by_piece = plain_bytes and state["model"]["type"] == "BPE"
        self.table: dict[str, int] = {}

    def of(self, texts: list[str]) -> list[int]:
        table, out, wait, direct = self.table, [0] * len(texts), [], []
        for i, s in enumerate(texts):
            if not self.by_piece or self.odd(s) or any(t in s for t in self.special):
                direct.append(i)
            else:
                wait.append((i, self.split(s)))
        new = list({p for _, some in wait for p in some if p not in table})
        counts = dict(zip(new, map(len, self.many(new, add_special_tokens=False)), strict=True)) if new else {}
        if len(table) + len(counts) > _TABLE:
            table = ChainMap(counts, table)  # for this call only; the table keeps what came first
        else:
            table.update(counts)
        get = table.__getitem__
        for i, some in wait:
            out[i] = sum(map(get, some))
        if direct:
            for i, e in zip(direct, self.many([texts[i] for i in direct], add_special_tokens=False), strict=True):
                out[i] = len(e)
        return out


class _Chunk:
    """The places in the text where pre-tokens of a chunk start, and the number of tokens before each."""

    def __init__(self, encoding, begin: int, end: int):
        words = np.array([-1 if w is None else w for w in encoding.word_ids], np.int64)
        first = np.ones(len(words), bool)
        first[1:] = (words[1:] != words[:-1]) | (words[1:] < 0)  # a special token has no word
        self.before = np.flatnonzero(first)
        self.starts = np.array(encoding.offsets, np.int64).reshape(-1, 2)[self.before, 0] + begin
        self.begin, self.end, self.tokens = begin, end, len(words)

    def rank(self, place: int) -> int:
        """Tokens before a place at which a pre-token starts."""
        i = int(np.searchsorted(self.starts, place))
        return int(self.before[i]) if i < len(self.starts) else self.tokens


def count_long(text: str, exact, chunk: int = CHUNK, overlap: int = OVERLAP) -> int:
    """Tokens of one text, never encoded at once."""
    n = len(text)
    encode = lambda a, b: _Chunk(exact.encode(text[a:b], add_special_tokens=False), a, b)
    total, place, current = 0, 0, encode(0, min(n, chunk))  # `place`: a true boundary up to which all is counted; `current` holds it
    while current.end < n:
        wide, end = overlap, min(n, current.end + chunk)
        true = current.starts[(current.starts >= place) & (current.starts < current.end - GUARD)]
        while True:
            begin = max(place, current.end - wide)
            if begin == place:  # nothing to align with: from the proven place on, twice as much, so that each character is encoded a few times at most
                following = encode(place, min(n, place + 2 * (current.end - place) + chunk))
                break
            following = encode(begin, end)
            common = np.intersect1d(true, following.starts[following.starts > begin])
            if len(common):
                total += current.rank(int(common[-1])) - current.rank(place)
                place = int(common[-1])
                break
            wide *= 2
        current = following
    return total + current.tokens - current.rank(place)


def count_tokens(docs: DataFrame, path: str, *, text: str = "text", out: str = "n_tokens", chunk: int = CHUNK, overlap: int = OVERLAP) -> DataFrame:
    """docs with the number of tokens that the tokenizer file at `path` (on every worker) gives for the whole text."""
    names = [c for c in docs.columns if c != out]
    docs = docs.select(*[F.col(f"`{c}`") for c in names])
    schema = T.StructType([*docs.schema.fields, T.StructField(out, T.LongType())])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        plain, exact = load(path)
        counter = Counts(plain)
        for batch in batches:
            column = batch.column(batch.schema.get_field_index(text))
            lengths = pc.fill_null(pc.utf8_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64)
            counts = np.zeros(len(lengths), np.int64)
            short = np.flatnonzero((lengths > 0) & (lengths <= chunk))
            cuts = np.cumsum(lengths[short]) // _BATCH_CHARS
            for some in np.split(short, np.flatnonzero(np.diff(cuts)) + 1) if len(short) else []:
                texts = column.take(pa.array(some)).to_pylist()
                counts[some] = counter.of(texts)
            for i in np.flatnonzero(lengths > chunk).tolist():
                counts[i] = count_long(column[i].as_py(), exact, chunk, overlap)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(counts)], names=schema.names)

    return docs.mapInArrow(count, schema)


def report(docs: DataFrame, path: str, *, doc_id: str = "doc_id", text: str = "text", limit: int = 512) -> DataFrame:
    """Per document: bytes of the text, its tokens, and whether these are more than `limit`."""
    counted = count_tokens(docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text")), path)
    return counted.select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
