"""Toxicity by class-conditional Kneser-Ney models of word pairs.

Counts. For each class c (toxic, ordinary) n_c(v, w) is the number of documents of the class that hold the word w right after v (or at the
start): a repetitive text teaches no more than a short one. The lower order counts continuations, as Kneser-Ney estimates do:
u_c(w), the number of different contexts (a preceding word in a document) that w goes on from.

Discounts. Of a count n the discount takes all up to D_c and the share 1 - `keep` of the rest; what it frees goes, whole, to the next order:
    P_c(w | v) = keep * max(n_c(v, w) - D_c, 0) / n_c(v) + f_c(v) * ((1 - LOWER) * C(w | v) + LOWER * P_c(w))
    P_c(w)     = keep * max(u_c(w) - D'_c, 0) / u_c + f * S(w)
with f the share of the mass that the discount frees (of a context never met: 1). The discounts of the toxic class are given. That of words in the ordinary class frees the
same share of mass, else the larger class, having seen more rare words, would win every rare word; that of pairs is larger by the ratio of the masses of both classes.

Shared backoff. C and S are counts that both classes have in common: the lesser of their two shares of a pair in its context, or of a word, brought to sum
one (where a context has no common pair, LOWER is 1; S is mixed with the uniform distribution over the vocabulary by weight `FLOOR`). Expressions that neither
class has in more than D_c documents thus have the same probability in both, and what both use alike backs off to the same value.

Levels. Two such models are fitted: the whole one (`WHOLE`: every count above the usual discount of .75 stays, so each pair that one toxic document holds tells) and a damped one
(`DISCOUNT`, `KEEP`), in which only what many documents of one class hold tells. No value of either is left out.

A document has four differences, each over its number of words: for both levels the one of words, and the one of contexts and pairs (the log-likelihood ratio less that of words). A logistic curve weighs them.
As they are sums over words, the fitted model is one table key -> weighted value. It goes to the workers in slices of at most `SLICE_WORDS` rows, each slice one narrow pass that adds to the sums; with several, a pass is
written to the shared folder before the next, so that a worker holds one slice at a time.

The counts come from all labelled rows of the training folds; the weights of the curve from all
labelled rows of a fold left out of the counts, by Newton steps whose sums the workers take. Labels, language, source and id are no inputs of a score.

Words are runs of letters, digits and non-ASCII characters, A-Z lower-cased, known by a 63-bit hash. Null, empty and wordless texts have
difference 0, so the score of the curve at 0; rows with null id or null label teach nothing; of several labels of an id the
largest counts; repeated rows are scored by themselves; without labels of both classes the score is the share of toxic labels
(0 if there are none); empty tables give empty results; other columns, of any name, pass through, but for score and predicted, which are replaced.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .spark import cut
from .text import ALNUM, LOWER, PrefixHash, in_slices, pieces, scramble, utf8_view, word_bounds

#: The damped level: discounts of the toxic class (of a pair, of a word), and the share of a count above them that stays with it.
DISCOUNT = (3.0, 3.0)
KEEP = 0.01
#: The whole level, in the same form.
WHOLE = ((0.75, 0.75), 1.0)
#: Weight of the lower order against the pairs that both classes have in common.
LOWER_ORDER = 0.5
FLOOR = 0.01
#: Values nearer to 0 than this are rounding.
LEAST = 1e-12
#: Rows of the model in one broadcast: 12 bytes each, and 4 to 8 for where the slots begin.
SLICE_WORDS = 4_000_000
#: Counts above this are one step of the search for the ordinary discount.
MOST = 10_000
#: Labels are joined by broadcast up to so many rows of about 24 bytes, else by a shuffle.
BROADCAST_LABELS = 2_000_000
#: The context of a first word, and what marks a word as a context.
START = 0x2545F4914F6CDD1D
_CONTEXT = 0x5851F42D4C957F2D
_LOW = (1 << 63) - 1
#: Pairs that a task holds before it tallies them.
_HELD = 1 << 20


def fold(doc_id: Column) -> Column:
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(5))


def words_of(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes (int64, not negative) of all words of the rows, and n + 1 offsets of the rows in them."""
    data = LOWER[data]
    starts, ends, bounds = word_bounds(data, offsets, ALNUM)
    hashes = PrefixHash(data).of(starts, ends) if len(starts) else np.zeros(0, np.uint64)
    return (hashes >> np.uint64(1)).astype(np.int64), bounds


def pairs_of(words: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The word before each word (`START` for the first of a row), and the key of both."""
    before = np.empty(len(words), np.int64)
    before[1:] = words[:-1]
    before[bounds[:-1][np.diff(bounds) > 0]] = START
    return before, ((before << 17) & _LOW | before >> 46) ^ words


def _pair_key(before: Column, word: Column) -> Column:
    """The same key as a column; both hashes are 63 random bits, so turning one of them keeps (a, b) and (b, a) apart."""
    turned = F.shiftleft(before, 17).bitwiseAND(F.lit(_LOW)).bitwiseOR(F.shiftright(before, 46))
    return turned.bitwiseXOR(word)


def _slots(keys: np.ndarray, slots: int) -> np.ndarray:
    return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(65 - slots.bit_length())).astype(np.int64)


def arranged(keys: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Keys and values by slot, and where each slot begins."""
    slots = 1 << max(10, int(len(keys)).bit_length())
    slot = _slots(keys, slots)
    order = np.argsort(slot, kind="stable")
    begin = np.zeros(slots + 1, np.int32)
    np.cumsum(np.bincount(slot, minlength=slots), out=begin[1:])
    return keys[order], values[order], begin


class Table:
    """key -> value, on the arrays as they are `arranged`."""

    def __init__(self, keys: np.ndarray, values: np.ndarray, begin: np.ndarray):
        self.keys, self.values, self.begin = keys, values, begin

    def get(self, words: np.ndarray) -> np.ndarray:
        slot = _slots(words, len(self.begin) - 1)
        at, end = self.begin[slot], self.begin[slot + 1]
        out = np.zeros(len(words), np.float32)
        left = np.flatnonzero(at < end)
        while len(left):
            hit = self.keys[at[left]] == words[left]
            out[left[hit]] = self.values[at[left[hit]]]
            left = left[~hit]
            at[left] += 1
            left = left[at[left] < end[left]]
        return out


def _tallied(rows: DataFrame, of_pairs: bool) -> DataFrame:
    """rows: text, toxic. Counts of documents, not yet summed: of pairs (before, word, toxic, ordinary), or of words (word, u1, u0, n1, n0)
    as what goes on from different contexts (u) and as contexts that different words go on from (n), toxic and ordinary ones."""
    names = ["before", "word", "toxic", "ordinary"] if of_pairs else ["word", "u1", "u0", "n1", "n0"]

    def pairs(before: np.ndarray, word: np.ndarray, toxic: np.ndarray) -> list[np.ndarray]:
        order = np.lexsort((word, before))
        before, word, bad = before[order], word[order], np.r_[0, np.cumsum(toxic[order])]
        begin = np.flatnonzero(np.r_[True, (before[1:] != before[:-1]) | (word[1:] != word[:-1])])
        end = np.r_[begin[1:], len(word)]
        return [before[begin], word[begin], bad[end] - bad[begin], (end - begin) - (bad[end] - bad[begin])]

    def words(before: np.ndarray, word: np.ndarray, toxic: np.ndarray) -> list[np.ndarray]:
        keys, at = np.unique(np.r_[word, before], return_inverse=True)
        counts = [np.bincount(half, weights=is_, minlength=len(keys)).astype(np.int64) for half in (at[: len(word)], at[len(word) :]) for is_ in (toxic, 1 - toxic)]
        return [keys, *counts]

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []

        def tally() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(c) for c in (pairs if of_pairs else words)(*(np.concatenate(c) for c in zip(*held, strict=True)))], names=names)

        waiting = 0
        for batch in in_slices(batches):
            toxic = batch.column(1).to_numpy(zero_copy_only=False).astype(np.int64)
            data, offsets = utf8_view(batch.column(0))
            for a, b in pieces(offsets):
                word, bounds = words_of(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                before, key = pairs_of(word, bounds)
                row = np.repeat(np.arange(b - a), np.diff(bounds))
                _, once = np.unique(scramble(key.astype(np.uint64) + scramble(row.astype(np.uint64))), return_index=True)
                held.append([before[once], word[once], toxic[a:b][row[once]]])
                waiting += len(once)
                if waiting > _HELD:
                    yield tally()
                    held, waiting = [], 0
        if waiting:
            yield tally()

    return rows.select("text", F.col("toxic").cast("int")).mapInArrow(count, ", ".join(f"{n} long" for n in names))


def matching_discount(histogram: list[tuple[int, int]], total: int, share: float) -> float:
    """The discount up to which counts hold `share` of the mass of a class. histogram: (count, expressions of that count)."""
    n, m = (np.array(c, float) for c in zip(*histogram, strict=True))
    low, high = 0.0, float(MOST)
    for _ in range(80):
        middle = (low + high) / 2
        low, high = (middle, high) if float(np.sum(np.minimum(n, middle) * m)) < share * total else (low, middle)
    return high


def fit(rows: DataFrame, levels: tuple | None = None) -> DataFrame:
    """rows: text, toxic (0 or 1). The model as key -> value under `DISCOUNT` and `KEEP`; with levels (discounts, keep), as key, of_word and a value v0, v1 ... of each. All values but zeros."""
    damped = levels is None
    levels = ((DISCOUNT, KEEP),) if damped else levels
    counts = cut(_tallied(rows, False).groupBy("word").agg(*[F.sum(c).alias(c) for c in ("u1", "u0", "n1", "n0")]))
    freed = [F.sum(F.least(F.col("u1").cast("double"), F.lit(float(d[1])))) for d, _ in levels]
    mass1, mass0, vocabulary, *freed = counts.agg(F.sum("u1"), F.sum("u0"), F.sum(F.when(F.col("u1") + F.col("u0") > 0, 1)), *freed).first()
    each = range(len(levels))
    names = ["value"] if damped else ["of_word", *[f"v{j}" for j in each]]
    if not mass0 or not mass1:
        return counts.select(F.col("word").alias("key"), *[F.lit(n == "of_word" or 0.0).alias(n) for n in names]).limit(0)
    n, share = {"1": mass1, "0": mass0}, [f / mass1 for f in freed]
    histogram = counts.filter("u0 > 0").groupBy(F.least("u0", F.lit(MOST)).alias("n")).agg(F.count("*").alias("m")).collect()  # at most MOST rows
    of_words = [{"1": d[1], "0": matching_discount([tuple(r) for r in histogram], mass0, s)} for (d, _), s in zip(levels, share, strict=True)]
    of_pairs = [{"1": d[0], "0": d[0] * mass0 / mass1} for d, _ in levels]
    own = lambda j, k, discount: levels[j][1] * F.greatest(F.col(k) - F.lit(discount), F.lit(0.0))
    # words: u is log P_toxic(w) - log P_ordinary(w); both classes free the same share
    common = F.least(*[F.col(f"u{c}") / n[c] for c in n])
    whole = counts.agg(F.sum(common)).first()[0]
    shared = ((1 - FLOOR) * common / whole if whole > 0 else F.lit(0.0)) + (FLOOR if whole > 0 else 1.0) / vocabulary
    columns = []
    for j in each:
        p = {c: own(j, f"u{c}", of_words[j][c]) / n[c] + (1 - levels[j][1] * (1 - share[j])) * shared for c in n}
        keeps = (own(j, "u1", of_words[j]["1"]) > 0) | (own(j, "u0", of_words[j]["0"]) > 0)
        columns += [*[p[c].alias(f"p{c}_{j}") for c in n], F.when(keeps, F.log(p["1"]) - F.log(p["0"])).otherwise(0.0).alias(f"u_{j}")]
    words = counts.filter("u1 > 0 or u0 > 0").select("word", *columns)
    # pairs that both classes have, or that keep mass of their own: the value of any other is 0
    pairs = _tallied(rows, True).groupBy("before", "word").agg(F.sum("toxic").alias("k1"), F.sum("ordinary").alias("k0"))
    least = {c: min(d[c] for d in of_pairs) for c in n}
    pairs = cut(pairs.filter((F.col("k1") > 0) & (F.col("k0") > 0) | (F.col("k1") > least["1"]) | (F.col("k0") > least["0"])))
    pairs = pairs.join(counts.select(F.col("word").alias("before"), "n1", "n0"), "before")
    part = {c: F.when(F.col(f"n{c}") > 0, F.col(f"k{c}") / F.col(f"n{c}")).otherwise(0.0) for c in n}
    kept = [F.when(F.col(f"n{c}") > 0, own(j, f"k{c}", of_pairs[j][c]) / F.col(f"n{c}")).otherwise(0.0).alias(f"o{c}_{j}") for j in each for c in n]
    pairs = cut(pairs.select("before", "word", F.least(part["1"], part["0"]).alias("both"), *kept))
    # contexts: l is log f_toxic(v) - log f_ordinary(v)
    contexts = pairs.groupBy("before").agg(F.sum("both").alias("all_both"), *[(1 - F.sum(f"o{c}_{j}")).alias(f"f{c}_{j}") for j in each for c in n])
    contexts = cut(contexts.withColumns({f"l_{j}": F.log(f"f1_{j}") - F.log(f"f0_{j}") for j in each}))
    lower = F.when(F.col("all_both") > 0, F.lit(LOWER_ORDER)).otherwise(1.0)
    in_common = F.when(F.col("all_both") > 0, F.col("both") / F.col("all_both")).otherwise(0.0)
    values = []
    for j in each:
        given = {c: F.col(f"o{c}_{j}") + F.col(f"f{c}_{j}") * ((1 - lower) * in_common + lower * F.col(f"p{c}_{j}")) for c in n}
        values.append(F.log(given["1"]) - F.log(given["0"]) - F.col(f"l_{j}") - F.col(f"u_{j}"))
    rows_of = lambda table, key, of_word, values: table.select(key.alias("key"), *([] if damped else [F.lit(of_word).alias("of_word")]), *[v.alias(m) for v, m in zip(values, names[-len(levels) :], strict=True)])
    model = rows_of(pairs.join(contexts, "before").join(words, "word"), _pair_key(F.col("before"), F.col("word")), False, values)
    model = model.unionByName(rows_of(words, F.col("word"), True, [F.col(f"u_{j}") for j in each]))
    model = model.unionByName(rows_of(contexts, F.col("before").bitwiseXOR(F.lit(_CONTEXT)), False, [F.col(f"l_{j}") for j in each]))
    told = [F.abs(m) >= LEAST for m in names[-len(levels) :]]
    return cut(model.filter(functools.reduce(lambda a, b: a | b, told)))


def _add_pass(docs: DataFrame, text: str, model, first: bool) -> DataFrame:
    """One narrow pass: what the keys of one slice add to the sums of each row, of words and of contexts and pairs."""
    added = [T.StructField("__words", T.DoubleType()), T.StructField("__pairs", T.DoubleType()), T.StructField("__n", T.LongType())]
    schema = T.StructType([*docs.schema.fields, *(added if first else [])])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = Table(*model.value)
        for batch in in_slices(batches):
            names = batch.schema.names
            data, offsets = utf8_view(batch.column(names.index(text)))
            sums, lengths = np.zeros((2, len(offsets) - 1)), np.zeros(len(offsets) - 1, np.int64)
            for a, b in pieces(offsets):
                words, bounds = words_of(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                lengths[a:b] = np.diff(bounds)
                rows = np.flatnonzero(np.diff(bounds))
                if len(rows):
                    before, key = pairs_of(words, bounds)
                    sums[0, a + rows] = np.add.reduceat(table.get(words).astype(np.float64), bounds[:-1][rows])
                    sums[1, a + rows] = np.add.reduceat(table.get(before ^ _CONTEXT).astype(np.float64) + table.get(key), bounds[:-1][rows])
            kept = [c for n, c in zip(names, batch.columns, strict=True) if n not in ("__words", "__pairs", "__n")]
            if not first:
                sums = sums + np.stack([batch.column(names.index(n)).to_numpy() for n in ("__words", "__pairs")])
            yield pa.RecordBatch.from_arrays([*kept, pa.array(sums[0]), pa.array(sums[1]), pa.array(lengths)], names=schema.names)

    return docs.mapInArrow(add, schema)


class Model:
    """A fitted model: the table of values, in slices, and the curve (slope, bias) of the score."""

    def __init__(self, table: DataFrame | None, slope: float, bias: float):
        self.table, self.slope, self.bias = table, slope, bias
        self.parts = -(-table.count() // SLICE_WORDS) if table is not None else 0
        self.only = self._slice(0) if self.parts == 1 else None

    def _slice(self, k: int):
        """A broadcast of at most about SLICE_WORDS rows."""
        part = self.table if self.parts == 1 else self.table.filter(F.pmod(F.xxhash64("key"), F.lit(self.parts)) == k)
        rows = part.select("key", F.col("value").cast("float").alias("value")).toArrow()  # toPandas would hold an object for each row
        return self.table.sparkSession.sparkContext.broadcast(arranged(rows["key"].to_numpy(), rows["value"].to_numpy()))

    def sums(self, docs: DataFrame, text: str) -> DataFrame:
        """docs with __words, __pairs (sums of values over the words) and __n (words). No column of docs may be named so, or __x."""
        for k in range(self.parts):
            slice_ = self.only or self._slice(k)
            docs = _add_pass(docs, text, slice_, k == 0)
            if not self.only:
                docs = cut(docs)
                slice_.destroy()
        return docs if self.parts else docs.select("*", F.lit(0.0).alias("__words"), F.lit(0.0).alias("__pairs"), F.lit(0).cast("long").alias("__n"))

    def differences(self, docs: DataFrame, text: str) -> DataFrame:
        """docs with __x: the difference of the length-normalised log-likelihoods."""
        x = F.when(F.col("__n") > 0, (F.col("__words") + F.col("__pairs")) / F.col("__n")).otherwise(0.0)
        return self.sums(docs, text).withColumn("__x", x).drop("__words", "__pairs", "__n")

    def score(self, docs: DataFrame, *, text: str = "text") -> DataFrame:
        """docs with score (0 to 1) and predicted (0 or 1)."""
        names = docs.columns
        inner = docs.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(names)])
        out = self.differences(inner, f"c{names.index(text)}").withColumn("__score", 1 / (1 + F.exp(-(F.lit(self.slope) * F.col("__x") + F.lit(self.bias)))))
        kept = [F.col(f"c{i}").alias(c) for i, c in enumerate(names) if c not in ("score", "predicted")]
        return out.select(*kept, F.col("__score").alias("score"), (F.col("__score") >= 0.5).cast("int").alias("predicted"))


def curve(rows: DataFrame, names: list[str]) -> tuple[list[float], float]:
    """Weights and bias of the logistic curve through rows (the named columns, toxic), by damped Newton steps. A task of a step gives one row of sums."""

    def sums(w: np.ndarray, scale: np.ndarray) -> list[np.ndarray]:
        def of_task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros(1 + len(w) + len(w) ** 2)
            for batch in batches:
                *x, y = (c.to_numpy(zero_copy_only=False).astype(np.float64) for c in batch.columns)
                z = np.stack([*x, np.ones(len(y))], 1) / scale
                p = 1 / (1 + np.exp(-np.clip(z @ w, -500, 500)))
                total += np.r_[np.sum(np.logaddexp(0, np.where(y > 0, -(z @ w), z @ w))), z.T @ (p - y), (z.T @ (z * (p * (1 - p))[:, None])).ravel()]
            yield pa.RecordBatch.from_arrays([pa.array([total.tolist()])], names=["sums"])

        total = np.sum([r["sums"] for r in rows.select(*names, "toxic").mapInArrow(of_task, "sums array<double>").collect()] + [np.zeros(1 + len(w) + len(w) ** 2)], axis=0)
        return [total[0] + 0.5 * np.sum(held * w**2), total[1 : 1 + len(w)] + held * w, total[1 + len(w) :].reshape(len(w), -1) + np.diag(held)]

    scale = np.array([max(1e-9, float(v) ** 0.5) if v else 1.0 for v in rows.agg(*[F.avg(F.col(n) ** 2) for n in names]).first()] + [1.0])
    held = np.array([1e-2] * len(names) + [1e-6])
    w = np.zeros(len(scale))
    loss, gradient, curvature = sums(w, scale)
    size = 1.0
    for _ in range(60):
        step = size * np.linalg.solve(curvature, gradient)
        if np.abs(step).max() < 1e-6:
            break
        tried = sums(w - step, scale)
        if tried[0] <= loss:
            w, (loss, gradient, curvature), size = w - step, tried, 1.0
        else:
            size /= 2
    w = w / scale
    return w[:-1].tolist(), float(w[-1])


def train(docs: DataFrame, labels: DataFrame, *, doc_id: str = "doc_id", text: str = "text") -> Model:
    """Counts from folds 1 to 3, the weights of the curve from fold 4; fold 0 is held out."""
    marks = labels.filter("toxic in (0, 1) and doc_id is not null").groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic")).withColumn("fold", fold(F.col("doc_id"))).filter("fold > 0")
    marks = cut(marks)
    seen = {(r["toxic"], r["taught"]): r["n"] for r in marks.groupBy("toxic", (F.col("fold") < 4).alias("taught")).agg(F.count("*").alias("n")).collect()}
    bad, all_ = sum(n for (t, _), n in seen.items() if t == 1), sum(seen.values())
    if not all(seen.get((t, True)) for t in (0, 1)):
        share = min(max(bad / all_ if all_ else 0.0, 1e-12), 1 - 1e-12)
        return Model(None, 0.0, math.log(share / (1 - share)))
    marks = F.broadcast(marks) if all_ <= BROADCAST_LABELS else marks
    rows = docs.select(F.col(f"`{doc_id}`").alias("doc_id"), F.col(f"`{text}`").alias("text")).join(marks, "doc_id").select("text", "toxic", "fold")
    table = fit(rows.filter("fold < 4"), (WHOLE, (DISCOUNT, KEEP)))
    left = rows.filter("fold = 4") if seen.get((0, False)) and seen.get((1, False)) else rows
    x, names = left.select("text", "toxic"), []
    for j in range(2):
        level = Model(table.select("key", F.col(f"v{j}").alias("value")).filter(F.abs("value") >= LEAST), 1.0, 0.0)
        names += [f"words{j}", f"pairs{j}"]
        over_n = [F.when(F.col("__n") > 0, F.col(f"__{n[:-1]}") / F.col("__n")).otherwise(0.0).alias(n) for n in names[-2:]]
        x = cut(level.sums(x, "text").select(*["text"][j:], "toxic", *names[:-2], *over_n))
        if level.only:
            level.only.destroy()
    weights, bias = curve(x, names)
    value = sum(F.col(f"v{j}") * F.when(F.col("of_word"), weights[2 * j]).otherwise(weights[2 * j + 1]) for j in range(2))
    return Model(cut(table.select("key", value.alias("value")).filter(F.abs("value") >= LEAST)), 1.0, bias)


def report(docs: DataFrame, labels: DataFrame) -> DataFrame:
    scored = train(docs, labels).score(docs.select("doc_id", "text"))
    return scored.select("doc_id", F.coalesce(fold(F.col("doc_id")) == 0, F.lit(False)).alias("held_out"), "score", "predicted")


def remove_toxic(docs: DataFrame, labels: DataFrame, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Documents that the score leaves; columns as before."""
    names = docs.columns
    rows = docs.select(*[F.col(f"`{c}`").alias(f"d{i}") for i, c in enumerate(names)])
    scored = train(docs, labels, doc_id=doc_id, text=text).score(rows, text=f"d{names.index(text)}")
    return scored.filter("predicted = 0").select(*[F.col(f"d{i}").alias(c) for i, c in enumerate(names)])
