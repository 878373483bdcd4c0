"""Carriers: adapters from tables to pool_mentions(record_id, entity), distinct."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import words
from ..functions.session import cut, small
from . import table


def pairs(df: DataFrame, record, entity) -> DataFrame:
    return df.select(record.cast("string").alias("record_id"), entity.cast("string").alias("entity")).filter("record_id is not null and entity is not null").distinct()


def basket(spark: SparkSession, sf_dir: str, column: str) -> DataFrame:
    """An order is a response; the values of a part column on its lines are entities."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    if column == "l_partkey":
        return pairs(lines, F.col("l_orderkey"), F.col("l_partkey"))
    part = table(spark, sf_dir, "part").select("p_partkey", column)
    return pairs(lines.join(part, lines["l_partkey"] == part["p_partkey"]), F.col("l_orderkey"), F.col(column))


def hour_users(spark: SparkSession, sf_dir: str, width: str = "1 hour") -> DataFrame:
    """A tumbling window of events is a response; its users are entities."""
    start = F.date_format(F.window(F.col("ts").cast("timestamp"), width)["start"], "yyyy-MM-dd HH:mm:ss")
    return pairs(table(spark, sf_dir, "events").select(start.alias("w"), "user_id"), F.col("w"), F.col("user_id"))


def star_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row a distinct line item with the typed facts as an array."""
    t = lambda n: table(spark, sf_dir, n)
    nation = t("nation").join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    supplier = t("supplier").join(nation, F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", F.col("n_name").alias("snation"), F.col("r_name").alias("sregion"))
    customer = t("customer").join(nation, F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", F.col("n_name").alias("cnation"), F.col("r_name").alias("cregion"))
    lines = t("lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    rows = lines.join(t("orders").select("o_orderkey", "o_custkey", "o_orderpriority"), F.col("l_orderkey") == F.col("o_orderkey"))
    rows = rows.join(t("part").select("p_partkey", "p_name", "p_brand", "p_type"), F.col("l_partkey") == F.col("p_partkey")).join(supplier, F.col("l_suppkey") == F.col("s_suppkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))
    kinds = {"cust": "o_custkey", "part": "l_partkey", "supp": "l_suppkey", "name": "p_name", "brand": "p_brand", "type": "p_type", "snation": "snation", "cnation": "cnation", "sregion": "sregion", "cregion": "cregion", "priority": "o_orderpriority"}
    return rows.select(F.col("l_orderkey").cast("string").alias("order_id"), F.concat_ws(":", "l_orderkey", "l_linenumber", "l_partkey").alias("record_id"), typed_facts(kinds).alias("facts"))


def typed_facts(kinds: dict[str, str]):
    return F.array(*[F.concat(F.lit(f"{k}:"), F.col(c).cast("string")) for k, c in kinds.items()])


def mentions_of(records: DataFrame) -> DataFrame:
    """Mentions (record_id, entity) of records (record_id, facts: distinct, none null), which go along: what is looked up by record then needs no shuffle."""
    rows = records.select("record_id", F.explode("facts").alias("entity"))
    rows._records = records
    return rows


def records_of(mentions: DataFrame) -> DataFrame | None:
    """The records of a pool with all their entities, if the pool was made of them."""
    return getattr(mentions, "_records", None)


def cut_pool(mentions: DataFrame) -> DataFrame:
    """A pool written to the shared folder, by record if it was made of records."""
    records = records_of(mentions)
    return cut(mentions) if records is None else mentions_of(cut(records))


def some_records(mentions: DataFrame, condition: Column) -> DataFrame:
    """The mentions of the records for which a condition on record_id holds."""
    records = records_of(mentions)
    return mentions.filter(condition) if records is None else mentions_of(records.filter(condition))


def _by_record(lines: DataFrame, record: str) -> DataFrame:
    """Distinct mentions by record: one row a line is shuffled, not one a fact. A record has a few lines."""
    facts = F.array_compact(F.array_distinct(F.flatten(F.collect_set("facts"))))
    return mentions_of(lines.filter(F.col(record).isNotNull()).groupBy(F.col(record).alias("record_id")).agg(facts.alias("facts")))


def star_facts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A line item is a response; typed values of its star join are entities."""
    return _by_record(star_lines(spark, sf_dir), "record_id")


def customer_facts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An order, with the facts of all its lines, is a response."""
    return _by_record(star_lines(spark, sf_dir), "order_id")


def doc_lines(spark: SparkSession, sf_dir: str, chunk: int = 2000) -> DataFrame:
    """record_id, text: lines of documents of all languages, long ones in chunks, so no record floods a graph."""
    docs = table(spark, sf_dir, "documents").select("doc_id", F.posexplode(F.split("text", "\n")).alias("line", "text"))
    parts = F.transform(F.sequence(F.lit(0), F.floor((F.greatest(F.length("text"), F.lit(1)) - 1) / chunk).cast("int")), lambda i: F.struct(i.alias("i"), F.substring("text", i * chunk + 1, F.lit(chunk)).alias("text")))
    rows = docs.select("doc_id", "line", F.explode(parts).alias("c"))
    name = F.concat_ws(":", "doc_id", F.col("line") + 1)
    return rows.select(F.when(F.col("c.i") == 0, name).otherwise(F.concat_ws(":", name, F.col("c.i"))).alias("record_id"), F.col("c.text").alias("text"))


def words_in_band(records: DataFrame, min_len: int, low: int, share: float) -> DataFrame:
    """records (record_id, text) -> mentions of words met in at least `low` records and at most a share of all, so the band widens with the table. Texts are taken apart once."""
    records = cut(records.select("record_id", F.array_distinct(F.filter(words(F.col("text")), lambda w: F.length(w) >= min_len)).alias("words")))
    rows = records.select("record_id", F.explode("words").alias("entity"))
    total = records.agg(F.count("*").alias("of"))  # one row
    band = rows.groupBy("entity").agg(F.count("*").alias("df")).filter(F.col("df") >= low).crossJoin(F.broadcast(total)).filter(F.col("df") <= F.col("of") * F.lit(share)).select("entity")
    return rows.join(small(band), "entity").select("record_id", "entity")


def doc_words(spark: SparkSession, sf_dir: str, min_len: int = 6, low: int = 5, share: float = 0.04) -> DataFrame:
    """A line of a document is a response; its words in a band of record frequency are entities."""
    rows = words_in_band(doc_lines(spark, sf_dir).filter(F.length("text") >= 20), min_len, low, share)
    return mentions_of(rows.groupBy("record_id").agg(F.collect_set("entity").alias("facts")))


def dialog_words(spark: SparkSession, sf_dir: str, min_len: int = 4, low: int = 3, share: float = 0.35) -> DataFrame:
    """An assistant turn is a response; its words in a band are entities."""
    turns = table(spark, sf_dir, "conversations").filter("role = 'assistant'")
    return words_in_band(turns.select(F.concat_ws(":", "conv_id", "turn").alias("record_id"), "text"), min_len, low, share)


def frequent(pool: DataFrame, n: int, like: str | None = None) -> DataFrame:
    """The n most frequent entities (ties by name) as requests; targets are picked by rank so that every size has some."""
    rows = pool.filter(F.col("entity").like(like)) if like else pool
    top = rows.groupBy("entity").agg(F.count("*").alias("df")).orderBy(F.desc("df"), "entity").limit(n)
    return top.select(F.col("entity").alias("target"))
