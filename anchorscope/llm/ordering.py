"""Running counts and sums in a random order, without one task for a whole group.

Rows carry a position key in [0, 1) that is spread evenly inside each group. A group is cut into
buckets of that key, about `per_bucket` rows each; bucket totals are summed up first, rows then
inside their own bucket only. A hot group thus spreads over many tasks.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def running(df: DataFrame, groups: list[str], key: str, ties: list, value: str | None = None, *, per_bucket: int = 4096, out: str = "before", sizes: DataFrame | None = None) -> DataFrame:
    """Adds `out`: number of rows (or sum of `value`) that come earlier in the group's order by key, ties.

    groups: columns without null. sizes: rows by group as (*groups, _n), if already known.
    """
    one = groups or ["_all"]
    if not groups:
        df = df.withColumn("_all", F.lit(0))
    sizes = sizes if sizes is not None else df.groupBy(*one).agg(F.count("*").alias("_n"))
    sizes = sizes.select(*one, F.greatest(F.lit(1), F.ceil(F.col("_n") / per_bucket)).cast("long").alias("_parts"))
    df = df.join(sizes, one).withColumn("_bucket", F.least(F.floor(F.col(key) * F.col("_parts")), F.col("_parts") - 1)).drop("_parts")
    amount = F.col(value) if value else F.lit(1).cast("long")
    totals = df.groupBy(*one, "_bucket").agg(F.sum(amount).alias("_sum"))
    # bucket totals are thousands of times fewer than rows; a second level keeps each window short
    totals = totals.withColumn("_super", F.floor(F.col("_bucket") / per_bucket))
    upper = totals.groupBy(*one, "_super").agg(F.sum("_sum").alias("_upper"))
    earlier = (Window.unboundedPreceding, -1)
    upper = upper.select(*one, "_super", F.coalesce(F.sum("_upper").over(Window.partitionBy(*one).orderBy("_super").rowsBetween(*earlier)), F.lit(0)).alias("_skip"))
    totals = totals.join(upper, [*one, "_super"]).select(
        *one, "_bucket",
        (F.col("_skip") + F.coalesce(F.sum("_sum").over(Window.partitionBy(*one, "_super").orderBy("_bucket").rowsBetween(*earlier)), F.lit(0))).alias("_start"),
    )
    inside = Window.partitionBy(*one, "_bucket").orderBy(key, *ties).rowsBetween(*earlier)
    df = df.join(totals, [*one, "_bucket"])
    df = df.withColumn(out, F.col("_start") + F.coalesce(F.sum(amount).over(inside), F.lit(0)))
    return df.drop("_bucket", "_start", *([] if groups else ["_all"]))
