"""Sources and sinks: recorded answers, the word table function, sample export, stream sink."""

import json

from anchorscope import streaming
from anchorscope.operators import supervision
from anchorscope.sources import datasource


def test_recorded_answers(spark, tmp_path):
    datasource.register(spark)
    for k in range(2):
        (tmp_path / f"part{k}.json").write_text("\n".join(json.dumps({"target": "T", "anchor": "A", "hop": 0, "iter": 10 * k + i, "text": None if i == 1 else f"x{i}"}) for i in range(3)))
    rows = spark.read.format("recorded_answers").option("path", str(tmp_path)).load()
    assert rows.select("iter").count() == 6
    assert sorted((r["iter"], r["text"]) for r in rows.collect()) == [(0, "x0"), (1, None), (2, "x2"), (10, "x0"), (11, None), (12, "x2")]
    words = spark.sql("select t.at, t.word from (select 'One, two' as s) d, lateral words_with_places(d.s) t").collect()
    assert sorted(map(tuple, words)) == [(0, "one"), (1, "two")]


def test_export(spark, tmp_path):
    rows = spark.createDataFrame([("s1", "T", "forget", "Which?", "T a")], "sample_id string, target string, role string, question string, answer string")
    supervision.export_samples(rows, str(tmp_path / "out"))
    back = spark.read.json(str(tmp_path / "out")).collect()[0]
    assert back["role"] == "forget" and list(back["loss_mask"]) == [0, 1, 1]


def test_stream_store_is_idempotent(spark, data, tmp_path):
    schema = spark.read.parquet(f"{data}/events.parquet").schema
    stream = streaming.event_stream(spark, f"{data}/events.parque[t]", schema)
    counts = streaming.window_counts(stream, delay="1 minute")
    q = streaming.merge_into_store(counts, str(tmp_path / "store"), str(tmp_path / "ck"))
    q.awaitTermination()
    assert spark.read.parquet(str(tmp_path / "store")).count() > 0
