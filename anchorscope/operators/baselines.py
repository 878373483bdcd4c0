"""Forget-set generators that graph recall is compared with, and their parts.

All give pairs (target, cue, ans, n): what a sample asks by and what it answers, with multiplicity.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import RecallConfig
from ..functions import cosine, u01
from ..functions.session import cut
from ..sources.responder import PoolResponder
from . import recall, walks
from .supervision import met_with

def hop_one(requests: DataFrame, mentions: DataFrame, n: int, seed: int, conditioning: str = "soft") -> DataFrame:
    """target, entity, c from n responses to the bare target."""
    frontier = requests.select("target", F.col("target").alias("anchor"), F.lit(0).alias("hop"))
    responder = PoolResponder(mentions, n=n, seed=seed, conditioning=conditioning)
    return recall.mention_strength(responder.extract(responder.respond(frontier)), n=n).select("target", "entity", "c", "s")


def flat_recall(requests: DataFrame, mentions: DataFrame, seed: int = 42) -> DataFrame:
    """A single description: one response, no repetition, no hops."""
    return hop_one(requests, mentions, 1, seed).select("target", "entity")


def direct_qa(requests: DataFrame, mentions: DataFrame, *, n: int = 20, seeds: tuple[int, ...] = (42, 43), agree: int | None = None) -> DataFrame:
    """Candidates of hop one that independent draws confirm: target, entity, asked, agreed, kept."""
    rows = None
    for s in seeds:
        one = hop_one(requests, mentions, n, s).select("target", "entity")
        rows = one if rows is None else rows.unionByName(one)
    need = len(seeds) if agree is None else agree
    return rows.groupBy("target", "entity").agg(F.count("*").alias("agreed")).select("target", "entity", F.lit(len(seeds)).alias("asked"), "agreed", (F.col("agreed") >= need).alias("kept"))


def expert_probe(requests: DataFrame, mentions: DataFrame, labels: DataFrame, doc_of: str = "record_id", agree_seed: int = 43, n: int = 20) -> DataFrame:
    """All records that mention the target (external passages), a sample for each co-mention; records of documents labelled poor or
    toxic go, and a second responder must agree."""
    aim = mentions.join(requests, mentions["entity"] == requests["target"]).select("target", "record_id")
    doc = F.substring_index(F.col(doc_of), ":", 1).cast("long")
    bad = labels.filter("quality = 0 or toxic = 1").select(F.col("doc_id").alias("_doc")).distinct()
    good = aim.withColumn("_doc", doc).join(bad, "_doc", "left_anti").select("target", "record_id")
    pairs = good.join(mentions, "record_id").filter("entity <> target").groupBy("target", "entity").agg(F.count("*").alias("n"))
    second = hop_one(requests, mentions, n, agree_seed).select("target", "entity")
    return pairs.join(second, ["target", "entity"], "left_semi")


def profile_truth(requests: DataFrame, mentions: DataFrame) -> DataFrame:
    """All facts of the target from the joins themselves: target, entity, n."""
    rows = met_with(mentions, requests.select(F.col("target").alias("cue"))).withColumnRenamed("cue", "target")
    return rows.filter("entity <> target").groupBy("target", "entity").agg(F.count("*").alias("n"))


def topk_pages(events: DataFrame, k: int = 20) -> DataFrame:
    """Most viewed pages: `k` in the properties of view events stands for the page."""
    page = F.from_json("props", "k int")["k"]
    return events.filter("event_type = 'view'").groupBy(page.cast("long").alias("page_id")).agg(F.count("*").alias("views")).orderBy(F.desc("views"), "page_id").limit(k)


def html_paragraphs(pages: DataFrame) -> DataFrame:
    """page_id, at, paragraph: contents of <p> elements without tags, white space folded."""
    found = pages.select("page_id", F.posexplode(F.regexp_extract_all("html", F.lit("(?s)<p>(.*?)</p>"), F.lit(1))).alias("at", "raw"))
    text = F.trim(F.regexp_replace(F.regexp_replace("raw", "<[^>]*>", " "), "[ \\t\\r\\n]+", " "))
    return found.select("page_id", "at", text.alias("paragraph")).filter("paragraph <> ''")


def paragraph_qa(pages: DataFrame, top: DataFrame) -> DataFrame:
    """Paragraphs of the most viewed pages, each text once (its first place): page_id, at, paragraph, views."""
    rows = html_paragraphs(pages).join(top, "page_id")
    first = Window.partitionBy("paragraph").orderBy("page_id", "at")
    return rows.withColumn("_n", F.row_number().over(first)).filter("_n = 1").drop("_n")


def record_paragraphs(requests: DataFrame, mentions: DataFrame, theta: float = 0.9) -> DataFrame:
    """Paragraph questions where a pool's records are the paragraphs: target, entity, n (kept paragraphs that state it).

    All records of a target are read; one goes if its set of entities is within cosine theta of an earlier one that stays.
    Keep-first is in order of record_id, one target a task; only records that share a rare entity are compared.
    """
    import math
    from collections import Counter

    import pandas as pd

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        sets = sorted((r, set(g)) for r, g in zip(frame["record_id"], frame["facts"], strict=True))
        often = Counter(x for _, g in sets for x in g)
        kept: list[set] = []
        by: dict[str, list[int]] = {}
        for _, g in sets:
            # sets within theta share theta ** 2 of the larger one at least, so one of the first rare entities of each
            head = sorted(g, key=lambda x: (often[x], x))[: len(g) - math.ceil(theta * theta * len(g) - 1e-9) + 1]
            near = {i for x in head for i in by.get(x, ())}
            if all(len(g & kept[i]) < theta * math.sqrt(len(g) * len(kept[i])) - 1e-9 for i in near):
                for x in head:
                    by.setdefault(x, []).append(len(kept))
                kept.append(g)
        target = frame["target"].iloc[0]
        count = Counter(x for g in kept for x in g if x != target)
        return pd.DataFrame({"target": target, "entity": list(count), "n": list(count.values())})

    rows = met_with(mentions, requests.select(F.col("target").alias("cue"))).withColumnRenamed("cue", "target").groupBy("target", "record_id").agg(F.collect_set("entity").alias("facts"))
    return rows.groupBy("target").applyInPandas(run, "target string, entity string, n long")


def close_pairs(vectors: DataFrame, theta: float, *, key: str = "vec_id", vector: str = "embedding", bits: int | None = None, miss: float = 0.001) -> tuple[DataFrame, DataFrame]:
    """(pairs, equal), both k0, k (k0 < k): different vectors within cosine theta of each other, whatever their labels, and the least key of equal vectors with the others.

    Candidates are pairs that share a bucket of random hyperplanes in one of several tables, so many that a pair at theta itself is missed with probability `miss` at most; every
    candidate is checked exactly. Of equal vectors the least key stands for all in the pairs. Meant for near copies: the tables needed grow fast as theta falls below 0.8.
    """
    rows = vectors.select(F.col(key).cast("long").alias("k"), F.col(vector).cast("array<double>").alias("v")).filter("k is not null and v is not null and size(v) > 0")
    rows = rows.filter(F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x)) & F.exists("v", lambda x: x != 0))
    rows = cut(rows.withColumn("h", F.md5(F.to_json("v"))))
    one = cut(rows.groupBy("h").agg(F.min("k").alias("k"), F.first("v").alias("v")))
    same = rows.select("h", "k").join(one.select("h", F.col("k").alias("k0")), "h").filter("k0 < k").select("k0", "k")
    shape = one.groupBy(F.size("v").alias("d")).agg(F.count("*").alias("n")).orderBy(F.desc("n")).first()
    if shape is None:
        return same, same
    bits = bits or min(24, max(6, math.ceil(math.log2(max(2, shape["n"]) / 16))))
    alike = (1 - math.acos(min(1.0, theta)) / math.pi) ** bits
    tables = max(1, math.ceil(math.log(miss) / math.log(1 - alike))) if alike < 1 else 1

    def place(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        draw = np.random.default_rng(7)
        planes = draw.standard_normal((shape["d"], tables * bits))
        for frame in frames:
            for at in range(0, len(frame), 2000):
                some = frame.iloc[at : at + 2000]
                side = (np.stack(some["v"].to_numpy()) @ planes > 0).reshape(len(some), tables, bits)
                bucket = (side * (1 << np.arange(bits))).sum(axis=2) + (np.arange(tables, dtype=np.int64) << bits)
                yield pd.DataFrame({"bucket": bucket.ravel(), "k": np.repeat(some["k"].to_numpy(), tables)})

    one = one.filter(F.size("v") == shape["d"])
    placed = cut(one.select("k", "v").mapInPandas(place, "bucket long, k long"))
    pairs = placed.join(placed.select("bucket", F.col("k").alias("k0")), "bucket").filter("k0 < k").select("k0", "k").distinct()
    near = pairs.join(one.select("k", "v"), "k").join(one.select(F.col("k").alias("k0"), F.col("v").alias("v0")), "k0")
    near = near.filter(cosine(F.col("v"), F.col("v0")) >= theta).select("k0", "k")
    return cut(near), cut(same)


def semantic_dedup_any(vectors: DataFrame, theta: float, *, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """Keys to keep: those without an earlier vector within cosine theta. Order-free. Rows without a usable vector are close to none."""
    pairs, equal = close_pairs(vectors, theta, key=key, vector=vector)
    return vectors.select(key).join(pairs.unionByName(equal).select(F.col("k").alias(key)).distinct(), key, "left_anti")


def semantic_dedup_greedy(vectors: DataFrame, theta: float, *, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """Keep-first: a vector goes if it is close to an earlier one that stays. Decided in rounds on the table of close pairs, never on all vectors:
    what has no earlier vector left stays, what is close to one that stays goes."""
    pairs, equal = close_pairs(vectors, theta, key=key, vector=vector)
    gone = equal.select("k")  # the first of equal vectors stays, or goes because of one before it, which rules out the others too
    while not pairs.isEmpty():
        stays = pairs.select("k0").distinct().join(pairs.select(F.col("k").alias("k0")).distinct(), "k0", "left_anti")
        out = cut(pairs.join(stays, "k0", "left_semi").select("k").distinct())
        gone = gone.unionByName(out)
        left = pairs.join(stays, "k0", "left_anti").join(out, "k", "left_anti")
        pairs = cut(left.join(out.withColumnRenamed("k", "k0"), "k0", "left_anti"))
    return vectors.select(key).join(gone.withColumnRenamed("k", key).distinct(), key, "left_anti")


def neighbor_general(mentions: DataFrame, nodes: DataFrame, m: int = 20, seed: int = 42) -> DataFrame:
    """General neighbours in place of our own: the first m entities in keyed order that are in no target's graph, the same for all: target, entity, at."""
    free = mentions.join(nodes.select("entity").distinct(), "entity", "left_anti").select("entity").distinct()
    first = free.orderBy(u01(seed, "entity"), "entity").limit(m)
    at = F.row_number().over(Window.partitionBy("target").orderBy(u01(seed, "entity"), "entity"))
    return nodes.select("target").distinct().crossJoin(F.broadcast(first)).select("target", "entity", at.alias("at"))  # m rows by target


def graph_recall_pairs(requests: DataFrame, mentions: DataFrame, cfg: RecallConfig, coverage: float | None = None) -> tuple[DataFrame, DataFrame, recall.RecallGraph]:
    """(forget, neighbor) pairs (target, cue, ans, n) of the full method, with its graph.

    coverage: walks double until every target's paths meet that share of its nodes, or `r_max` is reached.
    """
    graph = recall.expand(requests, PoolResponder(mentions, n=cfg.n, seed=cfg.seed, conditioning=cfg.conditioning, replace=cfg.replace, short_pool=cfg.short_pool), cfg)
    reached = graph.nodes.filter("hop > 0").select("target", F.col("entity").alias("node")).distinct()
    while True:
        forget = walks.filter_paths(walks.sample_walks(graph.edges, graph.nodes, cfg), cfg.eta, cfg.eta_mode, cfg.dedup_paths)
        if coverage is None or cfg.r * 2 > cfg.r_max:
            break
        met = cut(forget).select("target", F.explode("nodes").alias("node")).distinct().withColumn("met", F.lit(1.0))
        share = reached.join(met, ["target", "node"], "left").groupBy("target").agg(F.avg(F.coalesce("met", F.lit(0.0))).alias("share"))
        if share.filter(F.col("share") < coverage).isEmpty():
            break
        cfg = cfg.but(r=cfg.r * 2)
    neighbor = walks.filter_paths(walks.sample_walks(graph.edges, graph.nodes, cfg, "neighbor"), cfg.eta, cfg.eta_mode, cfg.dedup_paths)
    steps = lambda p: p.select("target", F.posexplode("nodes").alias("pos", "node"), F.element_at("nodes", 1).alias("origin"), F.size("nodes").alias("len"))
    f = steps(forget).filter("node <> target").groupBy("target", F.col("node").alias("cue")).agg(F.count("*").alias("n")).select("target", "cue", F.col("target").alias("ans"), "n")
    g = steps(neighbor).filter("node <> origin").groupBy("target", F.col("node").alias("cue"), F.col("origin").alias("ans")).agg(F.count("*").alias("n"))
    return f, g, graph
