"""Relational operators against brute force, and queries that read their own tables."""

import numpy as np
import pytest

from anchorscope.operators import relational
from anchorscope.plans import QUERIES, method

from .test_oracles import test_twin as twin


@pytest.mark.parametrize("name", ["brute_neighbors", "grid_cross", "rollup_graph", "graph_profile"])
def test_more_twins(spark, data, name):
    twin(spark, data, name)


def test_neighbors_by_blocks(spark, monkeypatch):
    """F8: all pairs by products of blocks, over several blocks and broadcasts; unusable vectors take no part."""
    draw = np.random.default_rng(5)
    v = draw.standard_normal((300, 8)).round(1)
    v[7] = v[3]
    rows = [(i, [float(x) for x in v[i]]) for i in range(300)] + [(300, [0.0] * 8), (301, None), (302, [1.0] * 7 + [None]), (303, [float("nan")] + [1.0] * 7)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(3)
    monkeypatch.setattr(relational, "BLOCK", (16, 32))
    monkeypatch.setattr(relational, "QUERIES_AT_ONCE", 20)
    got = {}
    for r in relational.brute_neighbors(df.filter("vec_id % 10 = 0"), df, 5).orderBy("query_id", "rank").collect():
        got.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    unit = v / np.linalg.norm(v, axis=1, keepdims=True)
    assert sorted(got) == list(range(0, 300, 10))
    for q, found in got.items():
        score = {i: round(float(unit[q] @ unit[i]), 6) for i in range(300) if i != q}
        want = sorted(score, key=lambda i: (-score[i], i))[:5]
        assert [i for i, _ in found] == want
        assert [s for _, s in found] == [pytest.approx(score[i], abs=2e-6) for i in want]


@pytest.mark.parametrize("name", ["recall_edges_k3", "graph_profile", "rollup_graph"])
def test_graphs_are_of_the_query(spark, data, name, monkeypatch):
    """what an earlier query of the session built isn't taken over, so the tables are read."""
    read = []
    monkeypatch.setattr(method.carriers, "basket", lambda *a, f=method.carriers.basket: read.append(a[1]) or f(*a))
    for _ in range(2):
        QUERIES[name](spark, data)
    assert read == [data, data]
