"""The corpus pipeline as a whole."""

import hashlib

import corpus_pipeline
from anchorscope.llm import decontam, mixing, sharding, simhash, toxicity


def test_pipeline_runs_stage_by_stage(spark, data):
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert len(names) == 5 and corpus_pipeline.ORACLE_SQL is None
    docs = spark.read.parquet(f"{data}/documents.parquet")
    result = corpus_pipeline.run(spark, data)
    rows = result.collect()
    assert [*docs.columns, "shard", "slot"] == result.columns
    labels, bench = (spark.read.parquet(f"{data}/{t}.parquet") for t in ("labels", "benchmark"))
    left = {r["doc_id"] for r in toxicity.report(docs, labels).filter("predicted = 0").collect()}
    kept = {r["doc_id"] for r in simhash.report(docs.filter(docs["doc_id"].isin(sorted(left)))).filter("doc_id = component_id").collect()}
    clean = {r["doc_id"] for r in decontam.report(docs.filter(docs["doc_id"].isin(sorted(kept))), bench).filter("not contaminated").collect()}
    # mixing and sharding once more by brute force: the copies that the (twin-tested) sizes ask for, dealt out by fractional rank
    mixed = [(r["doc_id"], r["taken"] // r["size"]) for r in mixing.report(docs.filter(docs["doc_id"].isin(sorted(clean)))).collect() if r["size"]]
    assert sorted(r["doc_id"] for r in rows) == sorted(i for i, n in mixed for _ in range(n))
    draw = lambda i: (int(hashlib.md5(f"{sharding.SEED}|{i}".encode()).hexdigest()[:13], 16) + 0.5) / (1 << 52)
    by_source = {}
    for r in rows:
        by_source.setdefault("null" if r["source"] is None else "=" + r["source"], []).append(r["doc_id"])
    ranked = sorted(((k + 0.5) / len(ids), s, i) for s, ids in by_source.items() for k, i in enumerate(sorted(ids, key=lambda i: (draw(i), str(i)))))
    want = sorted((i, ((at + 1) * 40 - 1) // len(ranked)) for at, (_, _, i) in enumerate(ranked))
    assert sorted((r["doc_id"], r["shard"]) for r in rows) == want
    sizes = {}
    for r in rows:
        sizes[r["shard"]] = sizes.get(r["shard"], 0) + 1
    assert max(sizes.values()) - min(sizes.get(i, 0) for i in range(40)) <= 1


def test_stages_pass_empty_tables(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, data)
        assert docs.count() == 0
