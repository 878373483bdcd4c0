"""Lineage cuts in the shared folder, and size-checked broadcasts."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of a narrow table that may be broadcast; beyond them a shuffle join serves.
BROADCAST_ROWS = 200_000


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or what setCheckpointDir set; on one machine (tests) a folder of our own, on a cluster without either an error."""
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


def cut(df: DataFrame) -> DataFrame:
    """df written as Parquet in the shared folder and read again; the shuffles behind it are freed."""
    spark, key = df.sparkSession, "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    path = f"{shared_folder(spark)}/cut-{uuid.uuid4().hex}"
    old = spark.conf.get(key, None)
    spark.conf.set(key, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.unset(key) if old is None else spark.conf.set(key, old)
    return spark.read.schema(df.schema).parquet(path)


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """A table marked for broadcast only if it has at most `rows` rows (df should be cheap to count, as a cut one is)."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df
