"""What query-focused resolution is compared with."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from erfocus.operators.components import connected_components
from erfocus.operators.durable import cut
from erfocus.operators.state import init


def pairwise(edges: DataFrame, threshold: float, members: DataFrame, weight: str = "w", run_id: int = 0, of: DataFrame | None = None) -> DataFrame:
    """(run_id, mention_id, entity_id): pairs at or over a threshold, closed transitively; others alone.

    of: (mention_id, rep), where edges are those of classes (score.class_edges): a class with any link is linked whole.
    """
    links = edges.where(F.col(weight) >= threshold).select("i", "j")
    if of is not None:
        links = cut(links)
        linked = links.select(F.explode(F.array("i", "j")).alias("rep")).distinct()
        links = links.union(of.join(linked, "rep", "left_semi").select(F.col("mention_id").alias("i"), F.col("rep").alias("j")))
    parts = connected_components(links, "i", "j")
    rows = members.select("mention_id").distinct().join(parts.withColumnRenamed("node", "mention_id"), "mention_id", "left")
    return rows.select(F.lit(run_id).alias("run_id"), "mention_id", F.coalesce("component", "mention_id").alias("entity_id"))


def blocked(mentions: DataFrame, key: Column, run_id: int = 0) -> DataFrame:
    """Hard blocks as entities; mentions whose key is null are alone."""
    rows = mentions.select("mention_id", F.coalesce(key.cast("string"), F.concat(F.lit("\0"), F.col("mention_id").cast("string"))).alias("__b"))
    least = rows.groupBy("__b").agg(F.min("mention_id").alias("entity_id"))
    return rows.join(least, "__b").select(F.lit(run_id).alias("run_id"), "mention_id", "entity_id")


def same_string(mentions: DataFrame, run_id: int = 0) -> DataFrame:
    """Entities of equal normalised strings."""
    from erfocus.functions.strings import normal

    return blocked(mentions, normal(F.col("mention")), run_id)


def alone(mentions: DataFrame, run_id: int = 0) -> DataFrame:
    return init(mentions, "singletons", run_id=run_id)
