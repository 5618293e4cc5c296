"""Lineage cuts that outlive executors."""

from __future__ import annotations

import gc
import tempfile
import time
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder; a temporary one only where none is set and the driver is the whole cluster (tests)."""
    sc = spark.sparkContext
    current = sc._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get()
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
    if not named and not sc.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="erfocus-"))
    return sc._jsc.sc().getCheckpointDir().get()


def shared_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """Materialise once in the shared folder and forget how it was made.

    A checkpoint keeps the size that was estimated for its plan.  Joins multiply such estimates, so that over
    rounds of joins they would grow to numbers of millions of digits; the rows are taken without them.
    """
    spark = df.sparkSession
    shared_dir(spark)
    rows = df.checkpoint(eager=True)._jdf
    return DataFrame(spark._jsparkSession.internalCreateDataFrame(rows.queryExecution().toRdd(), rows.schema(), False), spark)


def freed(df: DataFrame) -> DataFrame:
    """freed(cut(...)): large shuffle files of what was cut go now, not when the driver next collects its garbage.

    A driver that only plans collects it seldom, so that files of all steps would lie beside each other.  What Python lets
    go is let go in the driver's JVM a little later, so that it is asked several times, for a second in all.
    """
    gc.collect()
    for _ in range(4):
        df.sparkSession._jvm.System.gc()
        time.sleep(0.25)
    return df


#: A broadcast of so many rows of a few numbers takes tens of megabytes.
BROADCAST_ROWS = 500_000


def sized(df: DataFrame, max_rows: int = BROADCAST_ROWS) -> DataFrame:
    """A narrow table that cut() has materialised, with a broadcast hint only if it is counted to be small.

    Anything else would be worked out once for the count and again for the join: see held().
    """
    return F.broadcast(df) if df.limit(max_rows + 1).count() <= max_rows else df


def held(df: DataFrame, max_rows: int = BROADCAST_ROWS) -> DataFrame:
    """A narrow table materialised once, counted where it lies, and hinted to be broadcast only if it is small."""
    return sized(cut(df), max_rows)
