"""Sharding by proportional stratified interleaving.

Rows of each source are shuffled by a seeded draw and ranked; a row's fractional rank is
(rank + 1/2) / rows of its source. All rows in the order of fractional rank are then cut into
equal runs, so every shard holds the mixture of sources and the numbers of rows differ by one at most
(law `rows`). Equal texts get no common shard: a group of copies can be larger than a shard.

Both rankings use `ordering.running`, so neither a hot source nor the whole table meets in one task.

Null ids, texts and sources are ordinary values (a null source is a source of its own, size counts a null text as empty);
repeated rows get slots of their own, which of them gets which is arbitrary as they are equal; an
empty table gives an empty result; other columns pass through. Columns of the names given out are replaced.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .ordering import running
from .spark import by_size, cut, u01

SEED = 17


def shard(docs: DataFrame, shards: int, *, doc_id: str = "doc_id", source: str = "source", text: str = "text", seed: int = SEED) -> DataFrame:
    """docs with shard (from 0) and slot (gapless from 0 in each shard)."""
    names = [c for c in docs.columns if c not in ("shard", "slot")]
    id_, text_ = F.col(f"`{doc_id}`"), F.col(f"`{text}`")
    rows = docs.select(
        *[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(names)],
        F.coalesce(F.concat(F.lit("="), F.col(f"`{source}`").cast("string")), F.lit("null")).alias("_source"),
        u01(id_, seed=seed).alias("_u"), F.coalesce(id_.cast("string"), F.lit("")).alias("_id"), F.coalesce(F.md5(text_), F.lit("")).alias("_text"),
    )
    by_source = by_size(rows.groupBy("_source").agg(F.count("*").alias("_n")))
    rows = running(rows, ["_source"], "_u", ["_id", "_text"], out="_rank", sizes=by_source)
    rows = rows.join(by_source.select("_source", F.col("_n").alias("_of")), "_source")
    rows = rows.withColumn("_f", (F.col("_rank") + 0.5) / F.col("_of")).drop("_u", "_rank", "_of", "_text", "_id")
    total = by_source.agg(F.coalesce(F.sum("_n"), F.lit(0)).alias("_n")).withColumn("_all", F.lit(0))
    rows = running(rows, [], "_f", ["_source"], out="_at", sizes=total)
    count = total.select(F.col("_n").alias("_total"))
    rows = rows.crossJoin(F.broadcast(count))  # one row
    number = F.expr(f"((_at + 1) * {int(shards)} - 1) div _total")
    rows = rows.withColumn("_shard", number)
    return rows.select(
        *[F.col(f"c{i}").alias(c) for i, c in enumerate(names)],
        F.col("_shard").cast("int").alias("shard"), (F.col("_at") - F.expr(f"(_shard * _total) div {int(shards)}")).alias("slot"),
    )


def report(docs: DataFrame, shards: int, *, doc_id: str = "doc_id", text: str = "text", source: str = "source") -> DataFrame:
    """The shard and slot of every document with its size and checksum; texts themselves are not moved."""
    text_ = F.coalesce(F.col(text), F.lit(""))
    narrow = docs.select(
        doc_id, source, (F.octet_length(text_) + 16).cast("long").alias("size"), F.crc32(text_.cast("binary")).alias("text_crc32"), F.md5(F.col(text)).alias("_md5"),
    )
    out = shard(cut(narrow), shards, doc_id=doc_id, source=source, text="_md5")
    return out.select(doc_id, "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def write_shards(sharded: DataFrame, path: str) -> None:
    """One folder of Parquet files a shard, rows in slot order."""
    sharded.repartition("shard").sortWithinPartitions("shard", "slot").write.mode("overwrite").partitionBy("shard").parquet(path)
