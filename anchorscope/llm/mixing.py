"""Mixing sources to target weights by Pareto order sampling.

Every source gets a target number of words: its weight's share of the whole mix, at most `cap` times its
own words, with what is cut off dealt out again by weight. A source's ratio target / words is split into
certain whole copies of each of its documents and a sample that brings the words still missing.

In that sample a document is included with probability p = min(1, c * odds), by default in proportion to its words (`inclusion` gives other odds); c is such that the words expected are
those missing. Documents of p = 1 are certain, and taken. The others are ranked by (u / (1 - u)) / (p / (1 - p)) with a keyed draw u, and those that come first are
taken, in fixed size: the prefix whose words come nearest to what is missing.

c is found on the table of different odds in a source (as many rows as there are lengths of documents, or values of `inclusion`: round these).
The cumulative words are found in buckets of the rank (`ordering.running`), so a hot source spreads over many tasks.

Null texts have size 0; a null source is a source of its own and comes last; documents of size 0, or of odds that aren't positive, take no more than the whole copies;
equal rows are interchangeable, each is drawn by itself; an empty table gives an empty result; other columns pass through.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .ordering import running
from .spark import by_size, cut, u01

SEED = 23
WEIGHTS = (5, 2, 1)
SHARE = 1.5
CAP = 2


def n_words(text: Column) -> Column:
    """Number of runs of anything but space and the controls from tab to carriage return."""
    squeezed = F.regexp_replace(F.coalesce(text, F.lit("")), "[^\\x20\\x09-\\x0D]+", "x")
    return F.length(F.translate(squeezed, " \t\n\x0b\x0c\r", "")).cast("long")


def source_targets(sizes: DataFrame, *, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, cap: float = CAP) -> DataFrame:
    """sizes: _source (null allowed), _size, one row a source. Adds _target.

    Sources in order of cap * size / weight are full while the level that all others would get is above theirs.
    """
    place = Window.orderBy(F.col("_source").asc_nulls_last())
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(F.row_number().over(place) - 1, F.lit(len(weights))) + 1).cast("int"))
    by_level = Window.orderBy("_level", F.col("_source").asc_nulls_last())
    earlier, later = by_level.rowsBetween(Window.unboundedPreceding, -1), by_level.rowsBetween(0, Window.unboundedFollowing)
    t = sizes.withColumn("_weight", weight).withColumn("_level", cap * F.col("_size") / F.col("_weight"))
    t = t.withColumn("_left", share * F.sum("_size").over(Window.partitionBy()) - cap * F.coalesce(F.sum("_size").over(earlier), F.lit(0)))
    t = t.withColumn("_open", F.col("_left") / F.sum("_weight").over(later)).withColumn("_full", F.col("_level") <= F.col("_open"))
    level = F.max(F.when(~F.col("_full"), F.col("_open"))).over(Window.partitionBy())  # that of the first source below its cap
    return t.select("_source", "_size", F.when(F.col("_full"), cap * F.col("_size").cast("double")).otherwise(level * F.col("_weight")).alias("_target"))


def _odds_level(rows: DataFrame, targets: DataFrame) -> DataFrame:
    """_key, _least (odds from which a document is certain, null if none is), _c and _left (words to be drawn): one row a source. rows: _key, _odds, _words."""
    levels = rows.filter("_words > 0 and _odds > 0").groupBy("_key", "_odds").agg(F.sum("_words").alias("_w")).join(targets.select("_key", "_miss"), "_key")
    down = Window.partitionBy("_key").orderBy(F.desc("_odds"))
    above = F.coalesce(F.sum("_w").over(down.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    levels = levels.withColumn("_left", F.col("_miss") - above).withColumn("_rest", F.sum(F.col("_odds") * F.col("_w")).over(down.rowsBetween(0, Window.unboundedFollowing)))
    levels = levels.withColumn("_certain", F.min((F.col("_left") * F.col("_odds") >= F.col("_rest")).cast("int")).over(down.rowsBetween(Window.unboundedPreceding, 0)) == 1)
    open_ = F.struct(F.col("_odds").alias("o"), F.col("_left").alias("l"), (F.col("_left") / F.col("_rest")).alias("c"))
    out = levels.groupBy("_key").agg(F.min(F.when(F.col("_certain"), F.col("_odds"))).alias("_least"), F.max(F.when(~F.col("_certain"), open_)).alias("_open"))
    return out.select("_key", "_least", F.coalesce("_open.c", F.lit(0.0)).alias("_c"), F.coalesce("_open.l", F.lit(0.0)).alias("_left"))


def mix(rows: DataFrame, *, doc_id: str, source: str, size: str, tie: str | None = None, inclusion: Column | None = None, seed: int = SEED, measured: DataFrame | None = None, **rules) -> DataFrame:
    """rows with _source_size, _target and _copies (whole copies of the row that the mix takes).

    inclusion: odds of a document inside its source, its words if not given. measured: the same rows with the columns that odds and sums need, where rows are dear to read several times.
    """
    names = rows.columns
    words = F.coalesce(F.col(f"`{size}`").cast("long"), F.lit(0))
    source_, odds = F.col(f"`{source}`").cast("string"), F.coalesce((inclusion if inclusion is not None else words).cast("double"), F.lit(0.0))
    measured = (rows if measured is None else measured).select(source_.alias("_source"), words.alias("_words"), odds.alias("_odds"))
    rows = rows.select(
        *[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(names)], source_.alias("_source"), words.alias("_words"), odds.alias("_odds"), u01(F.col(f"`{doc_id}`"), seed=seed).alias("_u"),
        F.coalesce(F.col(f"`{doc_id}`").cast("string"), F.lit("")).alias("_id"), F.coalesce(F.col(f"`{tie}`").cast("string") if tie else F.lit(""), F.lit("")).alias("_tie"),
    )
    sums = measured.groupBy("_source").agg(F.sum("_words").alias("_size"), F.count("*").alias("_n"))
    targets = source_targets(sums, **rules).join(sums.select(F.col("_source").alias("_s"), "_n"), F.col("_source").eqNullSafe(F.col("_s"))).drop("_s")
    ratio = F.when(F.col("_size") > 0, F.col("_target") / F.col("_size")).otherwise(0.0)
    # a hair below a whole number is that number, else rounding would ask for one more copy of nothing
    targets = targets.withColumn("_whole", F.floor(ratio + 1e-9)).withColumn("_miss", F.greatest(F.lit(0.0), F.col("_target") - F.col("_whole") * F.col("_size")))
    targets = by_size(targets.select(F.coalesce(F.concat(F.lit("="), "_source"), F.lit("null")).alias("_key"), "_size", "_n", "_target", "_whole", "_miss"))
    key = F.coalesce(F.concat(F.lit("="), "_source"), F.lit("null"))
    rows = rows.withColumn("_key", key)
    level = by_size(_odds_level(measured.withColumn("_key", key), targets))
    rows = rows.join(targets, "_key").join(level, "_key", "left")
    drawn = (F.col("_words") > 0) & (F.col("_odds") > 0)
    certain = drawn & F.coalesce(F.col("_odds") >= F.col("_least"), F.lit(False))
    p = F.col("_c") * F.col("_odds")
    open_ = drawn & ~certain & (p > 0) & (p < 1)
    rows = rows.withColumn("_certain", certain).withColumn("_pareto", F.when(open_, (F.col("_u") / (1 - F.col("_u"))) / (p / (1 - p))))
    # a place in (0, 1) that orders as the Pareto ratio does, and is evenly spread where all odds are alike; rows that aren't drawn lie anywhere and weigh nothing
    mean = F.least(F.lit(0.999), F.greatest(F.lit(0.001), F.col("_left") / F.greatest(F.lit(1), F.col("_size"))))
    scaled = F.col("_pareto") * (mean / (1 - mean))
    rows = rows.withColumn("_place", F.coalesce(scaled / (1 + scaled), F.col("_u"))).withColumn("_weight", F.when(F.col("_pareto").isNotNull(), F.col("_words")).otherwise(F.lit(0)))
    rows = running(rows, ["_key"], "_place", ["_pareto", "_id", "_tie", "_words"], value="_weight", out="_before", sizes=targets.select("_key", "_n"))
    # the prefix nearest to what is missing: a document is in if at least half of it fits
    more = F.when(F.col("_certain") | (F.col("_pareto").isNotNull() & (F.col("_before") + F.col("_words") / 2 <= F.col("_left"))), 1).otherwise(0)
    return rows.select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(names)], F.col("_size").alias("_source_size"), F.col("_target"), (F.col("_whole") + more).cast("long").alias("_copies"))


def report(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", source: str = "source") -> DataFrame:
    """Per document: its words, those of its source, the source's target, and the words that the mix takes."""
    narrow = cut(docs.select(doc_id, source, n_words(F.col(text)).alias("size"), F.md5(F.col(text)).alias("_md5")))
    out = mix(narrow, doc_id=doc_id, source=source, size="size", tie="_md5")
    return out.select(doc_id, "size", F.col("_source_size").alias("source_size"), F.col("_target").alias("target"), (F.col("_copies") * F.col("size")).alias("taken"))


def repeat_rows(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", source: str = "source") -> DataFrame:
    """The mix itself: every document as often as it is taken; columns as before."""
    names = docs.columns
    sized = docs.select(*[F.col(f"`{c}`").alias(f"d{i}") for i, c in enumerate(names)], n_words(F.col(f"`{text}`")).alias("_n"), F.md5(F.col(f"`{text}`")).alias("_md5"))
    at = {c: f"d{i}" for i, c in enumerate(names)}
    measured = cut(sized.select(at[source], "_n"))
    out = mix(sized, doc_id=at[doc_id], source=at[source], size="_n", tie="_md5", measured=measured)
    return out.filter("_copies > 0").withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies").cast("int")))).select(*[F.col(at[c]).alias(c) for c in names])
