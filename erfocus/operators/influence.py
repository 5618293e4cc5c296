"""Influence of mentions on a query: feature scores, decay, inversion."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from erfocus.functions import features
from erfocus.operators.durable import held

DECAY_P = 0.05
STEPS = 100


def score(canopy: DataFrame, mentions: DataFrame, queries: DataFrame, specs: Iterable[features.FeatureSpec] = features.PAIRWISE, similarity: DataFrame | None = None, level: str = "document") -> DataFrame:
    """(query_id, mention_id, infl): the log-linear score of each canopy mention with its query.

    similarity: (query_id, mention_id, cos) for the tiers; without it the strings' q-gram Jaccard is used.
    Contexts are fetched for canopy members only; queries are worked out once.
    """
    m = features.prepare(mentions.select("mention_id", "mention", "context"), level, "a").select("mention_id", "a")
    q = features.prepare(queries.select("query_id", "mention", "context"), level, "b").select("query_id", "b")
    pairs = canopy.select("query_id", "mention_id")
    if similarity is not None:
        pairs = pairs.join(similarity.withColumnRenamed("cos", "__s"), ["query_id", "mention_id"], "left")
        s = F.col("__s")
    else:
        s = features.text_similarity(F.col("a"), F.col("b"))
    rows = m.join(pairs, "mention_id").join(held(q), "query_id")
    return rows.select("query_id", "mention_id", features.total(specs, F.col("a"), F.col("b"), s).alias("infl"))


def negative_binomial(k: Column, r: int, p: Column | float) -> Column:
    """Chance of k failures before the r-th success."""
    p = p if isinstance(p, Column) else F.lit(p)
    ways = F.lit(1.0)
    for i in range(1, r):
        ways = ways * (k + i) / i
    return ways * F.pow(p, r) * F.pow(1 - p, k)


def decay(scores: DataFrame, r: int = 1, p: float = DECAY_P, unit: str = "rank") -> DataFrame:
    """(query_id, mention_id, infl, pos, weight): the most influential first, weights falling with place.

    unit 'rank': place is the rank, and p at most 5 / n, so that large canopies keep weight in their tails;
    'score': place is the distance to the best score in hundredths of the range.
    """
    w = Window.partitionBy("query_id")
    if unit == "rank":
        pos = F.row_number().over(w.orderBy(F.desc("infl"), "mention_id")) - 1
        effective = F.least(F.lit(p), F.lit(5.0) / F.count(F.lit(1)).over(w))
    elif unit == "score":
        top, low = F.max("infl").over(w), F.min("infl").over(w)
        pos = F.when(top == low, 0).otherwise(F.floor(STEPS * (top - F.col("infl")) / (top - low)))
        effective = F.lit(p)
    else:
        raise ValueError(f"unit {unit} is neither rank nor score")
    placed = scores.withColumn("pos", pos.cast("int")).withColumn("__p", effective)
    return placed.withColumn("weight", negative_binomial(F.col("pos"), r, F.col("__p"))).drop("__p")


def invert(scores: DataFrame) -> DataFrame:
    """(query_id, mention_id, infl, weight): one less the score normalised to 0..1 in the query's canopy."""
    w = Window.partitionBy("query_id")
    top, low = F.max("infl").over(w), F.min("infl").over(w)
    return scores.withColumn("weight", F.when(top == low, 1.0).otherwise(1.0 - (F.col("infl") - low) / (top - low)))


def normalised(weights: DataFrame) -> DataFrame:
    """(query_id, mention_id, p): weights as shares of their query's."""
    return weights.withColumn("p", F.col("weight") / F.sum("weight").over(Window.partitionBy("query_id"))).select("query_id", "mention_id", "p")
