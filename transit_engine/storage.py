"""Written intermediates in the shared folder, and networks that a session has already built."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def scratch_root(spark: SparkSession) -> str:
    """spark.checkpoint.dir as the session has it; a folder below the warehouse only where it is unset."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        spark.sparkContext.setCheckpointDir(spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_checkpoints")
        root = spark.sparkContext.getCheckpointDir()
    return root.rstrip("/")


def written(df: DataFrame) -> DataFrame:
    """df written as Parquet to the scratch folder and read back: cuts the lineage, survives executors."""
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/tables/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: A compressed file's bytes stand for up to this many in a hash table on the driver.
UNPACKED = 8


def sorted_if_large(df: DataFrame) -> DataFrame:
    """df with a hint to join by sorting where it would be broadcast for its file's size but is larger unpacked."""
    limit = df.sparkSession._jsparkSession.sessionState().conf().autoBroadcastJoinThreshold()
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return df.hint("merge") if size * UNPACKED > limit else df


_KEPT: dict[tuple, object] = {}


def once(spark: SparkSession, name: str, make: Callable[[], object]):
    """What make() gave when this session first asked under this name. Holds plans over written
    tables, never data."""
    key = (spark.sparkContext.applicationId, name)
    if key not in _KEPT:
        _KEPT[key] = make()
    return _KEPT[key]
