"""The full method in one call."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .config import RecallConfig
from .functions.session import cut
from .metrics import forget_coverage
from .operators import recall, supervision, walks
from .operators.entities import anchor_forms
from .sources.responder import PoolResponder, dedup_pool


@dataclass
class Supervision:
    graph: recall.RecallGraph
    paths: DataFrame
    forget: DataFrame
    neighbor: DataFrame
    coverage: DataFrame


def graph_recall(requests: DataFrame, source, cfg: RecallConfig | None = None, texts: DataFrame | None = None) -> Supervision:
    """requests and a source of answers -> graph, paths, forget and neighbour samples.

    requests: target, or request_id and anchor_text: a name or a sentence `name is ...`, whose words then condition the first answers.
    source: mentions of a pool (record_id, entity), or a responder (a live model, recorded answers). texts: record_id, text of a pool.

    Walks are doubled until every target's forget set covers `coverage_target` of its graph or `r_max` is reached; walks
    are a prefix-stable sequence, so what was drawn before stays. Targets unknown to the source give a graph of one node and no samples.
    """
    cfg = cfg or RecallConfig()
    terms = None
    if "target" not in requests.columns:
        forms = cut(anchor_forms(requests))
        terms = forms.select("target", F.explode(F.split("terms", ",")).alias("entity")).filter("entity <> ''")
        requests = forms.filter("target <> ''").select("target").distinct()
    if isinstance(source, DataFrame):
        if cfg.dedup_pool:
            if texts is None:
                raise ValueError("dedup_pool compares texts of records: give them")
            source = cut(dedup_pool(source, texts))
        who = PoolResponder(source, n=cfg.n, seed=cfg.seed, conditioning=cfg.conditioning, replace=cfg.replace, short_pool=cfg.short_pool, keep_return=cfg.keep_return_edges, terms=terms)
    else:
        who = source
    graph = recall.expand(requests, who, cfg)
    mentions, told = who.evidence()
    texts = told if texts is None else texts
    while True:
        paths = walks.sample_walks(graph.edges, graph.nodes, cfg)
        paths = cut(walks.filter_paths(paths, cfg.eta, cfg.eta_mode, cfg.dedup_paths))
        pairs = supervision.path_pairs(paths)
        forget = cut(supervision.forget_samples(pairs, supervision.event_statements(pairs, mentions, texts), obj_rule=cfg.obj_rule, style=cfg.style))
        coverage = cut(forget_coverage(forget, graph.nodes, cfg.coverage_unit))
        if cfg.r * 2 > cfg.r_max or coverage.filter(coverage["coverage"] < cfg.coverage_target).isEmpty():
            break
        cfg = cfg.but(r=cfg.r * 2)
    aside = walks.filter_paths(walks.sample_walks(graph.edges, graph.nodes, cfg, "neighbor"), cfg.eta, cfg.eta_mode, cfg.dedup_paths)
    near = supervision.path_pairs(cut(aside))
    neighbor = cut(supervision.neighbor_samples(near, supervision.event_statements(near, mentions, texts), answer=cfg.answer, style=cfg.style))
    return Supervision(graph, paths, forget, neighbor, coverage)
