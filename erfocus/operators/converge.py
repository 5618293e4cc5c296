"""Signs of a chain's steady state."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def steady(trace: DataFrame, window: int = 500, eps: float = 0.01) -> DataFrame:
    """(run_id, step): the first step whose last window of proposals accepted at most a share eps; null if none.

    Without labels the acceptance rate stands in for accuracy.
    """
    w = Window.partitionBy("run_id").orderBy("step").rowsBetween(-(window - 1), 0)
    rows = trace.select("run_id", "step", F.avg(F.col("accepted").cast("int")).over(w).alias("rate"), F.count(F.lit(1)).over(w).alias("n"))
    return rows.groupBy("run_id").agg(F.min(F.when((F.col("n") == window) & (F.col("rate") <= eps), F.col("step"))).alias("step"))


def quiet(eps: float = 0.0) -> Callable[[list], bool]:
    """A function for Settings.until: the last proposals accepted at most a share eps."""
    return lambda tail: bool(tail) and sum(r[-1] for r in tail) <= eps * len(tail)
