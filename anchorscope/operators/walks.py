"""Walks over memory graphs: transition probabilities, visit-coupled walks, round-synchronous walks by joins, path quality."""

from __future__ import annotations

import hashlib
from bisect import bisect_right
from itertools import accumulate

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import RecallConfig
from ..functions import u01
from ..functions.session import cut

PATHS = "target string, role string, walk_id int, nodes array<string>, weights array<double>, n_edges int, quality double"
#: Kept edges of one target that a task walks on; a larger graph is walked in rounds of joins.
LOCAL_EDGES = 500_000


def transition_probs(edges: DataFrame, visits: DataFrame | None = None, alpha: float = 1.0, weighting: str = "strength") -> DataFrame:
    """edges (target, src, dst, w) -> p, in proportion to w * (1 / (1 + visits of dst)) ** alpha over the edges of src."""
    rows = edges.withColumn("_w", F.col("w") if weighting == "strength" else F.lit(1.0))
    if visits is not None:
        seen = visits.select("target", F.col("entity").alias("dst"), "visits")
        rows = rows.join(seen, ["target", "dst"], "left").withColumn("visits", F.coalesce("visits", F.lit(0)))
    else:
        rows = rows.withColumn("visits", F.lit(0))
    rows = rows.withColumn("_w", F.col("_w") * F.pow(1 / (1 + F.col("visits")), F.lit(float(alpha))))
    return rows.select("target", "src", "dst", "w", "visits", (F.col("_w") / F.sum("_w").over(Window.partitionBy("target", "src"))).alias("p"))


def draw(*parts) -> float:
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:8], 16) / 4294967296.0


def walk_graph(edges: list[tuple[str, str, float]], target: str, starts: list[str], cfg: RecallConfig, role: str, first: int = 0, vis: dict[str, int] | None = None) -> list[tuple[list[str], list[float]]]:
    """The walks of one target, one after the other: a walk sees the visits of earlier walks only."""
    out: dict[str, list[tuple[str, float]]] = {}
    for src, dst, w in sorted(edges):
        out.setdefault(src, []).append((dst, w if cfg.weighting == "strength" else 1.0))
    true_w = {(s, d): w for s, d, w in edges}
    vis, walks = vis if vis is not None else {}, []
    for r in range(first, cfg.r):
        node = starts[r % len(starts)] if starts else None
        if node is None:
            break
        nodes, weights = [node], []
        for step in range(cfg.max_edges):
            ways = [(d, w / (1 + vis.get(d, 0)) ** cfg.alpha) for d, w in out.get(node, []) if not (cfg.self_avoiding and d in nodes)]
            if not ways:
                break
            sums = list(accumulate(w for _, w in ways))
            at = min(bisect_right(sums, draw(cfg.seed, target, role, r, step) * sums[-1]), len(ways) - 1)
            weights.append(true_w[node, ways[at][0]])
            node = ways[at][0]
            nodes.append(node)
        for v in nodes:
            vis[v] = vis.get(v, 0) + 1
        walks.append((nodes, weights))
    return walks


def local_edges(edges: DataFrame, role: str) -> DataFrame:
    """Kept edges; for neighbour walks without those that touch the target."""
    rows = edges.filter("kept").select("target", "src", "dst", "w").distinct()
    return rows if role == "forget" else rows.filter((F.col("src") != F.col("target")) & (F.col("dst") != F.col("target")))


def sample_walks(edges: DataFrame, nodes: DataFrame, cfg: RecallConfig, role: str = "forget") -> DataFrame:
    """Paths of cfg.r walks for each target. A local graph is bounded by the recall budget and walked in one task; larger ones are walked in rounds
    (`coupled_rounds`, which knows neither self-avoiding walks nor weighted starts and raises if asked for).

    Forget walks start at the target; neighbour walks at its strong neighbours of hop 1, in turn by strength or in proportion to it.
    Walks without an edge are dropped.
    """
    tau_n = cfg.tau if cfg.tau_n is None else cfg.tau_n
    base = local_edges(edges, role).select("target", "src", "dst", "w", F.lit(None).cast("double").alias("strength"))
    strong = nodes.filter((F.col("hop") == 1) & (F.col("strength") >= tau_n - 1e-12)).select("target", F.col("entity").alias("src"), F.lit(None).cast("string").alias("dst"), F.lit(None).cast("double").alias("w"), "strength")
    large = base.groupBy("target").agg(F.count("*").alias("n")).filter(F.col("n") > LOCAL_EDGES).select("target")
    large = cut(large)
    apart = None
    if not large.isEmpty():
        if cfg.self_avoiding or (role == "neighbor" and cfg.start == "weighted"):
            raise ValueError("graphs this large are walked in rounds, which know neither self-avoiding walks nor weighted starts")
        at = F.row_number().over(Window.partitionBy("target").orderBy(F.desc("strength"), "src")) - 1
        begin = strong.select("target", at.alias("at"), F.col("src").alias("node")) if role == "neighbor" else large.select("target", F.lit(0).alias("at"), F.col("target").alias("node"))
        apart = coupled_rounds(edges.join(F.broadcast(large), "target", "left_semi"), begin.join(F.broadcast(large), "target", "left_semi"), cfg, role)
        base, strong = base.join(F.broadcast(large), "target", "left_anti"), strong.join(F.broadcast(large), "target", "left_anti")
    rows = base.unionByName(strong) if role == "neighbor" else base

    def run(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        target = key[0]
        is_edge = frame["dst"].notna()
        links = list(frame.loc[is_edge, ["src", "dst", "w"]].itertuples(index=False, name=None))
        starts = [target]
        if role == "neighbor":
            ordered = sorted(frame.loc[~is_edge, ["strength", "src"]].itertuples(index=False, name=None), key=lambda x: (-x[0], x[1]))
            starts = [s for _, s in ordered]
            if cfg.start == "weighted" and ordered:
                sums = list(accumulate(s for s, _ in ordered))
                starts = [ordered[min(bisect_right(sums, draw(cfg.seed, target, "start", r) * sums[-1]), len(ordered) - 1)][1] for r in range(cfg.r)]
        found = [(target, role, i, n, w, len(w), sum(w) / len(w)) for i, (n, w) in enumerate(walk_graph(links, target, starts, cfg, role)) if w]
        return pd.DataFrame(found, columns=["target", "role", "walk_id", "nodes", "weights", "n_edges", "quality"])

    walked = rows.groupBy("target").applyInPandas(run, PATHS)
    return walked if apart is None else walked.unionByName(apart)


def walk_rounds(edges: DataFrame, starts: DataFrame, *, r: int, l: int, seed: int = 42, role: str = "forget", weighting: str = "strength") -> DataFrame:  # noqa: E741
    """All walks step by step as joins, for graphs of any size (visits not coupled: alpha 0).

    starts: target, node. Integer counts of the edges (c) give exact choices: the edge whose running count covers draw * total.
    Returns target, walk_id, step, node, w (weight of the edge taken; null at step 0).
    """
    w = Window.partitionBy("target", "src")
    weight = F.col("c") if weighting == "strength" else F.lit(1).cast("long")
    hi = F.sum(weight).over(w.orderBy("dst").rowsBetween(Window.unboundedPreceding, 0))
    ways = cut(edges.filter("kept").select("target", "src", "dst", "w", (hi - weight).alias("lo"), hi.alias("hi"), F.sum(weight).over(w).alias("total")))
    now = starts.select("target", F.explode(F.sequence(F.lit(0), F.lit(r - 1))).alias("walk_id"), F.lit(0).alias("step"), "node", F.lit(None).cast("double").alias("w"))
    out = now
    for step in range(l):
        point = F.floor(u01(seed, "target", F.lit(role), "walk_id", F.lit(str(step))) * F.col("total"))
        moved = now.select("target", "walk_id", F.col("node").alias("src")).join(ways, ["target", "src"]).filter((point >= F.col("lo")) & (point < F.col("hi")))
        now = cut(moved.select("target", "walk_id", F.lit(step + 1).alias("step"), F.col("dst").alias("node"), "w"))  # else every step would repeat those before
        out = out.unionByName(now)
    return out


def coupled_rounds(edges: DataFrame, starts: DataFrame, cfg: RecallConfig, role: str = "forget", batch: int = 8) -> DataFrame:
    """Visit-coupled walks for graphs of any size: `batch` walks at once, step by step as joins; a batch sees the visits of the batches before.

    With `batch` 1 these are the walks one after the other. starts: target, at (from 0), node: walk i starts at the node at i modulo their number.
    """
    base = cut(local_edges(edges, role))
    many = starts.groupBy("target").agg(F.count("*").alias("of"))
    starts = cut(starts.join(many, "target"))
    w = Window.partitionBy("target", "src").orderBy("dst").rowsBetween(Window.unboundedPreceding, 0)
    visits, out = None, None
    for first in range(0, cfg.r, batch):
        p = transition_probs(base, visits, cfg.alpha, cfg.weighting)
        ways = cut(p.select("target", "src", "dst", "w", F.sum("p").over(w).alias("hi")).withColumn("lo", F.coalesce(F.lag("hi").over(Window.partitionBy("target", "src").orderBy("dst")), F.lit(0.0))))
        last = ways.groupBy("target", "src").agg(F.max("hi").alias("all"))
        ids = starts.select("target", "at", "of", "node", F.explode(F.sequence(F.lit(first), F.lit(min(first + batch, cfg.r) - 1))).alias("walk_id"))
        now = ids.filter(F.col("walk_id") % F.col("of") == F.col("at")).select("target", "walk_id", F.lit(0).alias("step"), "node", F.lit(None).cast("double").alias("w"))
        steps = now
        for step in range(cfg.max_edges):
            at = now.select("target", "walk_id", F.col("node").alias("src")).join(last, ["target", "src"])
            at = at.withColumn("point", u01(cfg.seed, "target", F.lit(role), "walk_id", F.lit(str(step))) * F.col("all"))
            now = cut(at.join(ways, ["target", "src"]).filter("point >= lo and point < hi").select("target", "walk_id", F.lit(step + 1).alias("step"), F.col("dst").alias("node"), "w"))
            steps = steps.unionByName(now)
        steps = cut(steps)
        out = steps if out is None else out.unionByName(steps)
        seen = steps.groupBy("target", F.col("node").alias("entity")).agg(F.count("*").alias("visits"))
        visits = cut(seen if visits is None else visits.unionByName(seen).groupBy("target", "entity").agg(F.sum("visits").alias("visits")))
    return paths_of(out, role)


def paths_of(steps: DataFrame, role: str = "forget") -> DataFrame:
    """Steps of walks as paths with their quality, the mean weight of their edges."""
    ordered = F.array_sort(F.collect_list(F.struct("step", "node", "w")))
    rows = steps.groupBy("target", "walk_id").agg(ordered.alias("p")).filter(F.size("p") > 1)  # l + 1 steps at most
    weights = F.transform(F.filter("p", lambda x: x["w"].isNotNull()), lambda x: x["w"])
    quality = F.aggregate(weights, F.lit(0.0), lambda s, x: s + x) / F.size(weights)
    return rows.select("target", F.lit(role).alias("role"), "walk_id", F.transform("p", lambda x: x["node"]).alias("nodes"), weights.alias("weights"), F.size(weights).alias("n_edges"), quality.alias("quality"))


def filter_paths(paths: DataFrame, eta: float, eta_mode: str = "absolute", dedup: bool = False) -> DataFrame:
    """Paths of quality eta or more (inclusive); `quantile`: eta is a quantile of each target's and role's qualities, as typical weights differ by carrier."""
    if eta_mode == "quantile":
        least = F.percentile("quality", F.lit(float(eta))).over(Window.partitionBy("target", "role"))
        paths = paths.withColumn("_eta", least).filter(F.col("quality") >= F.col("_eta") - 1e-12).drop("_eta")
    else:
        paths = paths.filter(F.col("quality") >= eta - 1e-12)
    return paths.dropDuplicates(["target", "role", "nodes"]) if dedup else paths


def expected_visits(edges: DataFrame, starts: DataFrame, l: int, weighting: str = "strength") -> DataFrame:  # noqa: E741
    """Expected visits of every node in one walk of at most l edges at alpha 0, by propagation: target, entity, visits."""
    p = transition_probs(edges.filter("kept"), alpha=0.0, weighting=weighting).select("target", "src", "dst", "p")
    now = starts.select("target", F.col("node").alias("entity"), F.lit(1.0).alias("visits"))
    out = now
    for _ in range(l):
        now = now.withColumnRenamed("entity", "src").join(p, ["target", "src"]).groupBy("target", F.col("dst").alias("entity")).agg(F.sum(F.col("visits") * F.col("p")).alias("visits"))
        out = out.unionByName(now)
    return out.groupBy("target", "entity").agg(F.sum("visits").alias("visits"))


def visit_counts(paths: DataFrame) -> DataFrame:
    return paths.select("target", F.explode("nodes").alias("entity")).groupBy("target", "entity").agg(F.count("*").alias("visits"))
