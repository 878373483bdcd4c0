"""Recall strength, edge weights and the K-hop expansion into a local memory graph, for all requests in one job a hop."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import RecallConfig
from ..functions.session import cut
from ..sources.responder import PoolResponder


@dataclass
class RecallGraph:
    """nodes (target, entity, hop, strength, c), edges (target, src, dst, hop, c, s, w, kept), log (target, hop, iterations, calls, new_nodes)."""

    nodes: DataFrame
    edges: DataFrame
    log: DataFrame


def mention_strength(mentions: DataFrame, n: int | None = None, denominators: DataFrame | None = None) -> DataFrame:
    """Share of the responses to an anchor that mention an entity; mentions are distinct by response."""
    counts = mentions.groupBy("target", "anchor", "hop", "entity").agg(F.count("*").alias("c"))
    if denominators is None:
        return counts.withColumn("s", F.col("c") / F.lit(n))
    return counts.join(denominators, ["target", "anchor"]).withColumn("s", F.col("c") / F.col("n_resp")).drop("n_resp")


def edge_weights(strengths: DataFrame, need: int, norm: str = "extracted") -> DataFrame:
    """target, src, dst, hop, c, s, w, kept. Weights share out an anchor's mentions among all extracted or only kept neighbours."""
    rows = strengths.withColumn("kept", F.col("c") >= need)
    counted = F.col("c") if norm == "extracted" else F.when(F.col("kept"), F.col("c"))
    total = F.sum(counted).over(Window.partitionBy("target", "anchor"))
    w = F.col("c") / total
    w = w if norm == "extracted" else F.when(F.col("kept"), w).otherwise(0.0)
    return rows.select("target", F.col("anchor").alias("src"), F.col("entity").alias("dst"), (F.col("hop") + 1).alias("hop"), "c", "s", w.alias("w"), "kept")


def merge_strength(old: DataFrame, new: DataFrame) -> DataFrame:
    """Counts (target, anchor, entity, c, n) of two rounds of elicitation add up."""
    return old.unionByName(new).groupBy("target", "anchor", "entity").agg(F.sum("c").alias("c"), F.sum("n").alias("n")).withColumn("s", F.col("c") / F.col("n"))


def expand(requests: DataFrame, responder: PoolResponder, cfg: RecallConfig) -> RecallGraph:
    """Semi-naive expansion: every hop asks only about strong nodes first reached in the hop before.

    A hop is one job for all targets. Its edges are written to the shared folder; visited nodes are
    never collected, only the frontier's emptiness comes back to the driver.
    """
    frontier = cut(requests.select("target", F.col("target").alias("anchor"), F.lit(0).alias("hop")).distinct())
    visited = frontier.select("target", F.col("anchor").alias("entity"))
    spent = frontier.select("target").distinct().withColumn("spent", F.lit(0).cast("long"))
    edges, firsts, logs = [], [], []
    for hop in range(cfg.k):
        if cfg.budget is not None:
            rank = F.row_number().over(Window.partitionBy("target").orderBy(F.desc("rank_s"), "anchor"))
            ranked = frontier if "rank_s" in frontier.columns else frontier.withColumn("rank_s", F.lit(1.0))
            frontier = cut(ranked.join(spent, "target").withColumn("at", rank).filter(F.col("at") + F.col("spent") <= cfg.budget).select("target", "anchor", "hop"))
        if frontier.isEmpty():
            break
        asked = frontier.groupBy("target").agg(F.count("*").alias("iterations"))
        responses = responder.respond(frontier.select("target", "anchor", "hop"))
        if responder.short_pool == "shrink":
            responses = cut(responses)
            strengths = mention_strength(responder.extract(responses), denominators=responder.denominators(responses))
        else:
            strengths = mention_strength(responder.extract(responses), n=cfg.n)
        found = edge_weights(strengths, cfg.need, cfg.norm) if responder.short_pool == "empty" else edge_weights(strengths, 1, cfg.norm).withColumn("kept", F.col("s") >= cfg.tau - 1e-12)
        found = cut(found)
        edges.append(found)
        fresh = found.filter("kept").groupBy("target", F.col("dst").alias("entity")).agg(F.max("s").alias("s"), F.max("c").alias("c")).join(visited, ["target", "entity"], "left_anti")
        fresh = cut(fresh.select("target", "entity", F.lit(hop + 1).alias("hop"), "s", "c"))
        firsts.append(fresh)
        logs.append(asked.join(fresh.groupBy("target").agg(F.count("*").alias("new_nodes")), "target", "left").select("target", F.lit(hop).alias("hop"), "iterations", (F.col("iterations") * cfg.n).alias("calls"), F.coalesce("new_nodes", F.lit(0)).cast("long").alias("new_nodes")))
        spent = spent.join(asked, "target", "left").select("target", (F.col("spent") + F.coalesce("iterations", F.lit(0))).alias("spent"))
        visited = visited.unionByName(fresh.select("target", "entity"))
        frontier = fresh.select("target", F.col("entity").alias("anchor"), "hop", F.col("s").alias("rank_s"))
    all_edges = edges[0]
    for e in edges[1:]:
        all_edges = all_edges.unionByName(e)
    reached = firsts[0]
    for f in firsts[1:]:
        reached = reached.unionByName(f)
    log = logs[0]
    for x in logs[1:]:
        log = log.unionByName(x)
    pick = {"max": F.max("s"), "mean": F.avg("s"), "first": F.min_by("s", F.struct("hop", "src"))}[cfg.strength_agg]
    strength = all_edges.filter("kept").groupBy("target", F.col("dst").alias("entity")).agg(pick.alias("strength"), F.max("c").alias("c"))
    nodes = reached.select("target", "entity", "hop").join(strength, ["target", "entity"])
    roots = requests.select("target").distinct().select("target", F.col("target").alias("entity"), F.lit(0).alias("hop"), F.lit(1.0).alias("strength"), F.lit(cfg.n).cast("long").alias("c"))
    return RecallGraph(cut(roots.unionByName(nodes)), all_edges, cut(log))


def back_edges(graph: RecallGraph) -> DataFrame:
    """Kept edges that lead to a node first reached earlier or at the same hop: recorded, never expanded again."""
    nodes = graph.nodes.select("target", F.col("entity").alias("dst"), F.col("hop").alias("first_hop"))
    return graph.edges.filter("kept").join(nodes, ["target", "dst"]).filter(F.col("first_hop") < F.col("hop")).select("target", "src", "dst", "hop", "first_hop", "c")


def graph_profile(graph: RecallGraph) -> DataFrame:
    """By target: nodes, kept edges, mean out-degree, density, entropy of weights (bits, of kept edges by source, averaged)."""
    kept = graph.edges.filter("kept")
    n = graph.nodes.groupBy("target").agg(F.count("*").alias("nodes"), F.max("hop").alias("max_hop"))
    by_src = kept.withColumn("p", F.col("c") / F.sum("c").over(Window.partitionBy("target", "src")))
    by_src = by_src.groupBy("target", "src").agg(F.count("*").alias("deg"), (-F.sum(F.col("p") * F.log2("p"))).alias("h"))
    e = by_src.groupBy("target").agg(F.sum("deg").alias("edges"), F.avg("deg").alias("out_degree"), F.avg("h").alias("weight_entropy"))
    rows = n.join(e, "target", "left")
    density = F.when(F.col("nodes") > 1, F.col("edges") / (F.col("nodes") * (F.col("nodes") - 1)))
    return rows.select("target", "nodes", "max_hop", F.coalesce("edges", F.lit(0)).cast("long").alias("edges"), F.round("out_degree", 6).alias("out_degree"), F.round(density, 6).alias("density"), F.round("weight_entropy", 6).alias("weight_entropy"))


def recall_overhead(log: DataFrame, nodes: DataFrame) -> DataFrame:
    """Per target: iterations, calls, bound n * iterations, nodes of the graph."""
    i = log.groupBy("target").agg(F.sum("iterations").alias("iterations"), F.sum("calls").alias("calls"))
    v = nodes.groupBy("target").agg(F.count("*").alias("nodes"))
    return i.join(v, "target").select("target", "iterations", "calls", "nodes", F.round(F.col("iterations") / F.col("nodes"), 6).alias("iterations_per_node"))


def save_graph(graph: RecallGraph, path: str, buckets: int = 16) -> None:
    """Parquet by hash bucket of the target, so a later run reads only its targets' buckets."""
    for name in ("nodes", "edges", "log"):
        df = getattr(graph, name).withColumn("bucket", F.pmod(F.xxhash64("target"), F.lit(buckets)).cast("int"))
        df.repartition("bucket").write.mode("overwrite").partitionBy("bucket").parquet(f"{path}/{name}")


def load_graph(spark, path: str) -> RecallGraph:
    return RecallGraph(*[spark.read.parquet(f"{path}/{name}").drop("bucket") for name in ("nodes", "edges", "log")])
