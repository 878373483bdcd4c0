"""Every query with an SQL twin gives the same rows as DuckDB (a sample of them here; the driver compares all)."""

from pathlib import Path

import duckdb
import pytest

from anchorscope import queries as core

FAST = [
    "mention_strength", "edge_weights_retained", "recall_edges_k3", "recall_budgeted", "walks_rounds_alpha0", "forget_samples", "neighbor_samples", "gen_direct_qa", "table_probs", "bounded_two_steps", "ga_kl_two_steps",
    "audit_trail", "forget_set_audit", "stream_late_rows", "stream_sliding", "set_operations_all", "cogrouped", "forget_scores", "freq_cosine", "attribute_recovery", "interval_events", "asof_last_view", "band_price_parts", "pivot_scores", "stream_interval_join", "stream_append_closed", "hops_from_target",
]


@pytest.mark.parametrize("name", FAST)
def test_twin(spark, data, name):
    con = duckdb.connect()
    for p in Path(data).glob("*.parquet"):
        con.execute(f"create view {p.stem} as select * from read_parquet('{p}')")
    df = core.queries()[name](spark, data)
    con.execute(core.oracle_sql()[name])
    columns = [c[0] for c in con.description]
    norm = lambda rows, names: sorted(tuple(f"{r[i]:.9g}" if isinstance(r[i], float) else str(r[i]) for i in sorted(range(len(names)), key=lambda i: names[i])) for r in rows)
    assert sorted(columns) == sorted(df.columns)
    assert norm(df.collect(), df.columns) == norm(con.fetchall(), columns)
