"""Approximate nearest neighbours: a forest of random-projection trees searched through one shared priority queue.

Largest inner product becomes a nearest-direction search by one more coordinate, sqrt(M^2 - |x|^2) with M the largest
norm. Trees are fitted on a sample of at most `SAMPLE` distinct vectors: every node splits its sample by the hyperplane midway
between two of its vectors. Then every vector is sent down every tree, however many there are.

A query walks all trees at once: one queue holds the nodes seen but not entered, ordered by the sum of squared margins on
the way; the best is taken, followed to a leaf, and the siblings left behind go into the queue. It stops after leaves that
hold, in sum over the trees, `search_share(n)` of the n vectors (in the sample's proportion): 64 nearly random coordinates
need a large share of a small table, and less of a larger one. From some 4000 vectors on that is less than one exact pass, below it an exact pass would cost less.
The candidates in these leaves, and no others, are reranked by exact inner products in double precision: leaves that lie side by side form a unit, a query goes once to
each unit with the list of its leaves there, and the unit gives the best `k + 1` of them. The best of all units remain.

Measured recall at 20 (share of the true 20 nearest): see README.

Equal vectors are one point with its smallest ids (a result never needs more of them than `k` + 1), so a hot vector costs no
more than another; units of more than `BLOCK` points are searched in blocks, and queries come in blocks of about `QUERIES`. What is broadcast
is the forest, bounded by `SAMPLE` and `TREES`.

Vectors that are null, zero or hold null or non-finite components take no part, as do rows with a null id and vectors of another length than most;
repeated rows (equal id and vector) are one candidate; fewer than k others give fewer rows; empty tables give
empty results; other columns are not read.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .spark import cut

SAMPLE = 32_768
TREES = 6
BLOCK = 50_000
QUERIES = 50_000
#: Units of leaves in a tree, at least.
UNITS = 8
SEED = 7


def search_share(n: int) -> float:
    """Leaves to visit, as a share of the table summed over all trees, for n vectors."""
    return min(3.0, 1.1 * (2000 / max(1, n)) ** (1 / 7))


def leaves_for(n: int, sample: int) -> int:
    """Leaves of a tree: about twice the square root of n, while the sample has eight vectors for each."""
    return max(1, min(2 ** (round(np.log2(max(1, n)) / 2) + 1), sample // 8))


class Forest:
    """Trees as flat arrays: normal and offset of every node, children (negative: leaf number - 1)."""

    def __init__(self, sample: np.ndarray, trees: int, leaf: float, seed: int = SEED):
        draw = np.random.default_rng(seed)
        self.trees = []
        for _ in range(trees):
            normals, offsets, children, sizes = [], [], [], []

            def grow(some: np.ndarray) -> int:
                if len(some) > leaf:
                    a, b = sample[draw.choice(some, 2, replace=False)]
                    normal = a - b
                    norm = np.linalg.norm(normal)
                    normal = normal / norm if norm > 0 else draw.standard_normal(sample.shape[1])
                    side = sample[some] @ normal
                    offset = float(np.median(side))
                    right = side > offset
                    if right.any() and not right.all():
                        node = len(normals)
                        normals.append(normal)
                        offsets.append(offset)
                        children.append([0, 0])
                        children[node] = [grow(some[~right]), grow(some[right])]
                        return node
                sizes.append(len(some) / len(sample))
                return -len(sizes)

            root = grow(np.arange(len(sample)))
            self.trees.append((root, np.array(normals, np.float32).reshape(-1, sample.shape[1]), np.array(offsets, np.float32), np.array(children, np.int64).reshape(-1, 2), np.array(sizes)))

    def leaves(self, x: np.ndarray) -> np.ndarray:
        """The leaf of each row in each tree."""
        out = np.zeros((len(x), len(self.trees)), np.int32)
        for t, (root, normals, offsets, children, _) in enumerate(self.trees):
            at = np.full(len(x), root, np.int64)
            while (inner := np.flatnonzero(at >= 0)).size:
                node = at[inner]
                right = np.einsum("ij,ij->i", x[inner], normals[node]) > offsets[node]
                at[inner] = children[node, right.astype(int)]
            out[:, t] = -at - 1
        return out

    def visit(self, q: np.ndarray, share: float) -> list[tuple[int, int]]:
        """(tree, leaf) of the leaves that the shared queue reaches until they hold `share` of the sample in sum."""
        margins = [normals @ q - offsets for _, normals, offsets, _, _ in self.trees]
        queue = [(0.0, t, tree[0]) for t, tree in enumerate(self.trees)]
        heapq.heapify(queue)
        found, held = [], 0.0
        while queue and held < share:
            bound, t, at = heapq.heappop(queue)
            _, _, _, children, sizes = self.trees[t]
            while at >= 0:
                m = float(margins[t][at])
                near, far = (1, 0) if m > 0 else (0, 1)
                heapq.heappush(queue, (bound + m * m, t, int(children[at, far])))
                at = int(children[at, near])
            found.append((t, -at - 1))
            held += sizes[-at - 1]
        return found


def parts_of(frames: Iterator[pd.DataFrame], n: int) -> Iterator[pd.DataFrame]:
    """Frames of at most n rows, as every row goes out many times over."""
    for frame in frames:
        for a in range(0, len(frame), n):
            yield frame.iloc[a : a + n]


def clean(rows: DataFrame, vec_id: str, vector: str) -> DataFrame:
    """vec_id, v: usable vectors as doubles."""
    v = F.col(f"`{vector}`").cast("array<double>")
    finite = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    return rows.select(F.col(f"`{vec_id}`").cast("long").alias("vec_id"), v.alias("v")).filter(F.col("vec_id").isNotNull() & (F.size("v") > 0) & finite & F.exists("v", lambda x: x != 0))


def search(rows: DataFrame, queries: DataFrame, k: int, *, vec_id: str = "vec_id", vector: str = "embedding", trees: int = TREES, share: float | None = None, sample: int = SAMPLE, seed: int = SEED) -> DataFrame:
    """query_id, rank (from 1), vec_id, score: for every query its k best rows found but itself (by id)."""
    spark = rows.sparkSession
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    every = clean(rows, vec_id, vector)
    asked = clean(queries, vec_id, vector).withColumn("p", F.xxhash64("v")).distinct()
    # equal vectors are one point p with its k + 1 smallest ids
    ids = every.withColumn("p", F.xxhash64("v")).select("p", "vec_id").distinct()
    ids = ids.withColumn("n", F.row_number().over(Window.partitionBy("p").orderBy("vec_id"))).filter(F.col("n") <= k + 1).groupBy("p").agg(F.sort_array(F.collect_list("vec_id")).alias("ids"))  # k + 1 at most
    points = cut(every.withColumn("p", F.xxhash64("v")).groupBy("p").agg(F.first("v").alias("v")))
    shape = points.groupBy(F.size("v").alias("d")).agg(F.count("*").alias("n"), F.max(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x)).alias("m")).orderBy(F.desc("n"), "d").first()
    if shape is None:
        return empty
    dims, largest, n = shape["d"], shape["m"], shape["n"]
    share = search_share(n) if share is None else share
    points = points.filter(F.size("v") == dims)
    picked = points.orderBy(F.xxhash64("p"), "p").limit(sample).select("v").toPandas()  # bounded: `sample` vectors

    def lifted(x: np.ndarray) -> np.ndarray:
        more = np.sqrt(np.maximum(0.0, largest - np.einsum("ij,ij->i", x, x)))
        return np.c_[x, more].astype(np.float32) / np.float32(max(1e-30, np.sqrt(largest)))

    picked = np.stack(picked["v"].to_numpy())
    leaves = leaves_for(n, len(picked))
    grown = Forest(lifted(picked), trees, len(picked) / leaves, seed)
    forest = spark.sparkContext.broadcast(grown)
    most = max(len(t[4]) for t in grown.trees)  # leaves of the largest tree
    width = max(1, most // max(UNITS, -(-n // BLOCK)))  # leaves of a unit
    units = -(-most // width)

    def place(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in parts_of(frames, 1000):
            if len(frame):
                at = forest.value.leaves(lifted(np.stack(frame["v"].to_numpy())))
                t = at.shape[1]
                unit = np.arange(t) * units + at // width
                yield pd.DataFrame({"unit": unit.ravel(), "leaf": at.ravel() % width, "p": np.repeat(frame["p"].to_numpy(), t), "v": [v for v in frame["v"] for _ in range(t)]})

    def visit(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in parts_of(frames, 256):
            out = []
            for p, v in zip(frame["p"], frame["v"], strict=True):
                x = np.append(np.asarray(v, float), 0.0).astype(np.float32)
                by: dict[int, list[int]] = {}
                for t, at in forest.value.visit(x / np.float32(max(1e-30, np.linalg.norm(x))), share):
                    by.setdefault(t * units + at // width, []).append(at % width)
                out += [(unit, some, p, v) for unit, some in by.items()]
            if out:
                yield pd.DataFrame(out, columns=["unit", "leaves", "p", "v"])

    distinct = cut(asked.filter(F.size("v") == dims).groupBy("p").agg(F.first("v").alias("v")))
    deals = max(1, -(-distinct.count() // QUERIES))
    placed = points.mapInPandas(place, "unit int, leaf int, p long, v array<double>")
    blocks = cut(placed.groupBy("unit").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("parts")))  # one row a unit
    placed = placed.join(F.broadcast(blocks.filter("parts > 1")), "unit", "left").withColumn("block", F.when(F.col("parts") > 1, F.pmod(F.xxhash64("p"), F.col("parts"))).otherwise(0).cast("int")).drop("parts")
    placed = placed.withColumn("deal", F.explode(F.sequence(F.lit(0), F.lit(deals - 1)))) if deals > 1 else placed.withColumn("deal", F.lit(0))
    visits = distinct.repartition(max(8, spark.sparkContext.defaultParallelism), "p").mapInPandas(visit, "unit int, leaves array<int>, p long, v array<double>").join(F.broadcast(blocks), "unit")
    visits = visits.withColumn("block", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).drop("parts").withColumn("deal", F.pmod(F.xxhash64("p"), F.lit(deals)).cast("int"))

    def rerank(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not len(left) or not len(right):
            return pd.DataFrame({"q": np.zeros(0, np.int64), "p": np.zeros(0, np.int64), "score": np.zeros(0)})
        left = left.sort_values("leaf", kind="stable")
        x, names, leaf = np.stack(left["v"].to_numpy()), left["p"].to_numpy(), left["leaf"].to_numpy()
        edges = np.searchsorted(leaf, np.arange(width + 1))
        out = []
        for a in range(0, len(right), 256):
            some = right.iloc[a : a + 256]
            q, asked_by = np.stack(some["v"].to_numpy()), some["p"].to_numpy()
            enters = np.zeros((len(q), width), bool)
            for i, those in enumerate(some["leaves"]):
                enters[i, those] = True
            s = np.full((len(q), len(x)), -np.inf)
            for at in np.flatnonzero(edges[1:] > edges[:-1]):
                who = np.flatnonzero(enters[:, at])
                if len(who):
                    s[who, edges[at] : edges[at + 1]] = q[who] @ x[edges[at] : edges[at + 1]].T
            keep = min(k + 1, s.shape[1])
            # all that tie with the last one kept, as ids decide between them
            edge = np.partition(s, s.shape[1] - keep, axis=1)[:, s.shape[1] - keep]
            i, j = np.nonzero((s >= edge[:, None]) & (s > -np.inf))
            out.append(pd.DataFrame({"q": asked_by[i], "p": names[j], "score": s[i, j]}))
        return pd.concat(out)

    key = ["unit", "block", "deal"]
    found = placed.groupBy(*key).cogroup(visits.groupBy(*key)).applyInPandas(rerank, "q long, p long, score double")
    # the same pair from several trees; then the best points of each query vector
    found = found.groupBy("q", "p").agg(F.max("score").alias("score"))
    best = found.withColumn("n", F.rank().over(Window.partitionBy("q").orderBy(F.desc("score")))).filter(F.col("n") <= k + 1).drop("n")
    members = best.join(ids, "p").select("q", F.explode("ids").alias("vec_id"), "score")
    members = members.withColumn("n", F.row_number().over(Window.partitionBy("q").orderBy(F.desc("score"), "vec_id"))).filter(F.col("n") <= k + 1).drop("n")
    results = asked.select(F.col("vec_id").alias("query_id"), F.col("p").alias("q")).distinct().join(members, "q").filter("vec_id <> query_id")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return results.select("query_id", rank.cast("int").alias("rank"), "vec_id", "score").filter(F.col("rank") <= k)


def report(vectors: DataFrame, k: int = 20, every: int = 20) -> DataFrame:
    return search(vectors, vectors.filter(F.col("vec_id") % every == 0), k)
