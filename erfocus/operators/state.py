"""Configurations: which entity each mention is in, as rows beside the mention table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from erfocus.functions.rand import h32


def init(members: DataFrame, how: str = "singletons", seed: int = 1, k: int = 8, prev: DataFrame | None = None, run_id: int = 0) -> DataFrame:
    """(run_id, mention_id, entity_id) of distinct members; an entity's id is its smallest mention."""
    rows = members.select("mention_id").distinct()
    if how == "singletons":
        rows = rows.withColumn("entity_id", F.col("mention_id"))
    elif how == "single":
        least = rows.agg(F.min("mention_id").alias("entity_id"))
        rows = rows.crossJoin(F.broadcast(least))
    elif how == "random":
        rows = rows.withColumn("__b", F.pmod(h32(F.concat_ws("|", F.lit(f"init|{seed}"), F.col("mention_id").cast("string"))), F.lit(k)))
        rows = _named(rows)
    elif how == "previous":
        if prev is None:
            raise ValueError("the previous state is needed")
        rows = _named(rows.join(prev.select("mention_id", F.col("entity_id").alias("__b")), "mention_id", "left").withColumn("__b", F.coalesce("__b", "mention_id")))
    else:
        raise ValueError(f"{how} is no initial state")
    return rows.select(F.lit(run_id).alias("run_id"), "mention_id", "entity_id")


def _named(rows: DataFrame) -> DataFrame:
    """Groups __b named by their smallest mention."""
    least = rows.groupBy("__b").agg(F.min("mention_id").alias("entity_id"))
    return rows.join(least, "__b").select("mention_id", "entity_id")


def canonical(state: DataFrame) -> DataFrame:
    """The same state with entities named by their smallest mention."""
    least = state.groupBy("run_id", "entity_id").agg(F.min("mention_id").alias("least"))
    return state.join(least, ["run_id", "entity_id"]).select("run_id", "mention_id", F.col("least").alias("entity_id"))


def apply_moves(state: DataFrame, moves: DataFrame) -> DataFrame:
    """state with (run_id, mention_id, entity_to) carried out; entities keep the names given."""
    moved = state.join(moves.select("run_id", "mention_id", "entity_to"), ["run_id", "mention_id"], "left")
    return moved.select("run_id", "mention_id", F.coalesce("entity_to", "entity_id").alias("entity_id"))
