"""Small session helpers: shared folder, lineage cuts, unsigned text forms."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or what setCheckpointDir set. On one machine (tests) a local one will do; a cluster without either raises."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder.rstrip("/")
    jvm = spark.sparkContext._jsc.sc()
    if jvm.getCheckpointDir().isEmpty():
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="shared-"))
    return jvm.getCheckpointDir().get().rstrip("/")


@contextmanager
def freeing_shuffles(spark: SparkSession) -> Iterator[None]:
    """While it lasts, the shuffle files of a write go as soon as the written table is whole."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    old = spark.conf.get(key, None)
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.unset(key) if old is None else spark.conf.set(key, old)


def cut(df: DataFrame) -> DataFrame:
    """A table written to the shared folder and read again: lineage ends here, lost executors lose nothing, and the shuffles behind it are freed."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/stage-{uuid.uuid4().hex}"
    with freeing_shuffles(spark):
        df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def u01(*keys: Column | str, seed: int | str) -> Column:
    """A draw in (0, 1) from the md5 of seed and keys; other engines get the same value from the same text."""
    text = F.concat_ws("|", F.lit(str(seed)), *[F.coalesce((F.col(k) if isinstance(k, str) else k).cast("string"), F.lit("null")) for k in keys])
    return (F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("double") + 0.5) / float(1 << 52)


#: Rows of a small table that may be broadcast; beyond them it is joined by a shuffle.
BROADCAST_ROWS = 100_000


def by_size(df: DataFrame) -> DataFrame:
    """A narrow table (some numbers and a name a row), written once and marked for broadcast if it has few enough rows."""
    df = cut(df)
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df
