"""Connected components by alternating star contractions.

Each round replaces edges by edges to smaller neighbours until only stars are left, so the
number of rounds grows with the logarithm of the longest path.  Every step is an aggregation
with a map-side part or an equi-join that adaptive execution may split; no vertex's
neighbourhood is ever gathered into one row.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from erfocus.operators.durable import cut


def _state(edges: DataFrame) -> tuple:
    row = edges.agg(
        F.count(F.lit(1)).alias("n"),
        F.sum(F.xxhash64("a", "b").cast("decimal(20,0)")).alias("h"),
    ).first()
    return row["n"], row["h"]


def _large_star(edges: DataFrame) -> DataFrame:
    """Hang every larger neighbour of a vertex on the vertex's smallest neighbour (or itself)."""
    both = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    return (
        both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
    )


def _small_star(edges: DataFrame) -> DataFrame:
    """Hang a vertex and its smaller neighbours on the smallest of them; here b < a holds."""
    least = edges.groupBy("a").agg(F.min("b").alias("m"))
    moved = edges.join(least, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return moved.union(least.select("a", F.col("m").alias("b"))).distinct()


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """Edges (any orderable type) -> (node, component): the smallest node reachable.

    Nodes without an edge to another node do not appear.  Null ends and self loops are ignored;
    an empty table gives an empty result.
    """
    low = edges.select(F.greatest(F.col(a), F.col(b)).alias("a"), F.least(F.col(a), F.col(b)).alias("b"), (F.col(a) != F.col(b)).alias("ok"))
    stars = cut(low.where("ok").select("a", "b").distinct())
    before = _state(stars)
    for _ in range(max_rounds):
        if not before[0]:
            break
        stars = cut(_small_star(_large_star(stars)))
        after = _state(stars)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError("components did not settle")
    members = stars.select(F.col("a").alias("node"), F.col("b").alias("component"))
    roots = stars.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct()
    return members.union(roots)
