"""Entity extraction: lexicons, mentions of texts, typed values, aliases, user-supplied extractors."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import words
from ..functions.session import small


def tokens(text, rule: str = "words"):
    """`words`: runs of a-z of the lower-cased text; `letters`: runs of Unicode letters, lower-cased."""
    return words(text) if rule == "words" else F.transform(F.regexp_extract_all(text, F.lit("(\\p{L}+)"), F.lit(1)), F.lower)


def build_lexicon(docs: DataFrame, *, text: str = "text", key: str = "doc_id", rule: str = "words", min_len: int = 6, min_df: int = 5, max_df_share: float | None = 0.2, by: str | None = None) -> DataFrame:
    """entity, df: words in a band of document frequency, for each value of `by` (null too); the upper end is a share of the documents, so it grows with them (None: no end)."""
    group = [by] if by else []
    rows = docs.select(key, *group, F.explode(F.array_distinct(tokens(F.col(text), rule))).alias("entity")).filter(F.length("entity") >= min_len)
    lexicon = rows.groupBy(*group, "entity").agg(F.count("*").alias("df")).filter(F.col("df") >= min_df)
    if max_df_share is not None:
        if by:
            total = docs.groupBy(F.col(by).alias("_by")).agg(F.count("*").alias("_docs"))
            return lexicon.join(total, F.col(by).eqNullSafe(F.col("_by"))).filter(F.col("df") <= F.col("_docs") * max_df_share).drop("_by", "_docs")
        total = docs.agg(F.count("*").alias("_docs"))  # one row
        return lexicon.crossJoin(F.broadcast(total)).filter(F.col("df") <= F.col("_docs") * max_df_share).drop("_docs")
    return lexicon


def extract_mentions(responses: DataFrame, lexicon: DataFrame, *, keys: list[str], text: str = "text", rule: str = "words") -> DataFrame:
    """Distinct lexicon words of each response; a refusal (null) mentions nothing."""
    rows = responses.select(*keys, F.explode(F.array_distinct(tokens(F.col(text), rule))).alias("entity"))
    return rows.join(lexicon.select("entity"), "entity", "left_semi").select(*keys, "entity")


def column_mentions(df: DataFrame, record: str, entity: str) -> DataFrame:
    return df.select(F.col(record).cast("string").alias("record_id"), F.col(entity).cast("string").alias("entity")).distinct()


def typed_mentions(df: DataFrame, record: str, kinds: dict[str, str]) -> DataFrame:
    """One entity `kind:value` for each typed column."""
    values = F.array(*[F.concat(F.lit(f"{k}:"), F.col(c).cast("string")) for k, c in kinds.items()])
    return df.select(F.col(record).cast("string").alias("record_id"), F.explode(values).alias("entity")).filter("entity is not null").distinct()


def extract_with(responses: DataFrame, extract: Callable[[list[str]], list[list[str]]], *, text: str = "text") -> DataFrame:
    """Mentions by a user's extractor (a named-entity model), called on batches of texts."""

    @F.pandas_udf("array<string>")
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in batches:
            yield pd.Series(extract(batch.fillna("").tolist()))

    keys = [c for c in responses.columns if c != text]
    return responses.select(*keys, F.explode(F.array_distinct(run(F.col(text)))).alias("entity"))


def fold_name(name):
    """Lower-cased, punctuation to spaces, single spaces."""
    return F.trim(F.regexp_replace(F.lower(name), "[^a-z0-9]+", " "))


def canonicalize(mentions: DataFrame, aliases: DataFrame) -> DataFrame:
    """Entities folded, then replaced by the canonical name of aliases (alias, canonical); duplicates that arise are dropped."""
    table = small(aliases.select(fold_name(F.col("alias")).alias("_alias"), F.col("canonical")).dropDuplicates(["_alias"]))
    rows = mentions.withColumn("_alias", fold_name(F.col("entity"))).join(table, "_alias", "left")
    return rows.withColumn("entity", F.coalesce("canonical", "_alias")).drop("_alias", "canonical").distinct()


def anchor_forms(requests: DataFrame) -> DataFrame:
    """Requests (request_id, anchor_text): the name before the first ` is `, and description words as further conditions."""
    described = F.instr("anchor_text", " is ") > 0
    name = F.when(described, F.substring_index("anchor_text", " is ", 1)).otherwise(F.col("anchor_text"))
    rest = F.when(described, F.expr("substring(anchor_text, instr(anchor_text, ' is ') + 4)")).otherwise("")
    terms = F.array_sort(F.array_distinct(F.filter(words(rest), lambda w: F.length(w) >= 4)))
    return requests.select("request_id", F.trim(name).alias("target"), F.when(described, "description").otherwise("name").alias("anchor_kind"), F.array_join(terms, ",").alias("terms"))


def validate_request(requests: DataFrame, pool: DataFrame, aliases: DataFrame | None = None) -> DataFrame:
    """request_id, reason: empty, unknown, ambiguous (an alias of several entities) or ok."""
    known = pool.select(F.col("entity").alias("target")).distinct().withColumn("known", F.lit(True))
    rows = requests.select("request_id", F.trim("target").alias("target")).join(known, "target", "left")
    if aliases is not None:
        meanings = aliases.groupBy(F.col("alias").alias("target")).agg(F.countDistinct("canonical").alias("meanings"))
        rows = rows.join(meanings, "target", "left")
    else:
        rows = rows.withColumn("meanings", F.lit(0))
    reason = F.when(F.col("target") == "", "empty").when(F.coalesce("meanings", F.lit(0)) > 1, "ambiguous").when(F.col("known").isNull() & (F.coalesce("meanings", F.lit(0)) == 0), "unknown").otherwise("ok")
    return rows.select("request_id", F.coalesce(reason, F.lit("empty")).alias("reason"))
