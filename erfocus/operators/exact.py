"""Exact inference over all set partitions of a few mentions: what chains are held against."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MAX_N = 9


def partitions(ids: DataFrame, max_n: int = MAX_N) -> DataFrame:
    """(partition): arrays of entity names, by mentions in order of their ids; names are places of smallest members.

    Grown by one mention a step in a recursive query: a mention joins an entity before it or makes its own.
    """
    spark = ids.sparkSession
    n = ids.count()
    if n > max_n:
        raise ValueError(f"{n} mentions are too many for an enumeration")
    if not n:
        return spark.createDataFrame([], "partition array<int>")
    return spark.sql(
        f"""WITH RECURSIVE grown(k, partition) AS (
          SELECT 1, array(1)
          UNION ALL
          SELECT k + 1, concat(partition, array(e)) FROM (SELECT k, partition, explode(array_append(array_distinct(partition), k + 1)) AS e FROM grown WHERE k < {n})
        ) SELECT partition FROM grown WHERE k = {n}"""
    )


def partition_posterior(ids: DataFrame, edges: DataFrame, temperature: float = 1.0, max_n: int = MAX_N) -> DataFrame:
    """(partition, score, prob): every configuration, its score and its share of the normaliser."""
    order = ids.select("mention_id").distinct()
    listed = order.agg(F.sort_array(F.collect_list("mention_id")).alias("ids"))
    place = lambda c: F.array_position("ids", F.col(c)).cast("int")
    known = edges.crossJoin(F.broadcast(listed)).select(place("i").alias("a"), place("j").alias("b"), "w").where("a > 0 AND b > 0")
    packed = F.broadcast(known.agg(F.collect_list(F.struct("a", "b", "w")).alias("es")))
    same = lambda e: F.when(F.get(F.col("partition"), e["a"] - 1) == F.get(F.col("partition"), e["b"] - 1), e["w"]).otherwise(F.lit(0).cast("long"))
    score = F.aggregate("es", F.lit(0).cast("long"), lambda s, e: s + same(e))
    rows = partitions(order, max_n).crossJoin(packed).select("partition", score.alias("score"))
    top = F.broadcast(rows.agg(F.max("score").alias("top")))
    weighted = rows.crossJoin(top).withColumn("z", F.exp((F.col("score") - F.col("top")) / F.lit(temperature)))
    total = F.broadcast(weighted.agg(F.sum("z").alias("total")))
    return weighted.crossJoin(total).select("partition", "score", (F.col("z") / F.col("total")).alias("prob"))


def map_partition(posterior: DataFrame) -> DataFrame:
    """(partition, score) of the best configuration; of equals the first in array order."""
    return posterior.orderBy(F.desc("score"), "partition").limit(1).select("partition", "score")


def map_query_cluster(ids: DataFrame, edges: DataFrame, query: int) -> DataFrame:
    """(mention_id): the query's entity in the best configuration."""
    best = map_partition(partition_posterior(ids, edges))
    listed = ids.select("mention_id").distinct().agg(F.sort_array(F.collect_list("mention_id")).alias("ids"))
    rows = best.crossJoin(listed).select(F.inline(F.arrays_zip("ids", "partition")))
    own = rows.where(F.col("ids") == query).select(F.col("partition").alias("e"))
    return rows.join(F.broadcast(own), rows["partition"] == F.col("e")).select(F.col("ids").alias("mention_id"))


def marginal_query(ids: DataFrame, edges: DataFrame, query: int, temperature: float = 1.0) -> DataFrame:
    """(mention_id, p_coref): the chance that a mention is of the query's entity, all else summed out."""
    post = partition_posterior(ids, edges, temperature)
    listed = F.broadcast(ids.select("mention_id").distinct().agg(F.sort_array(F.collect_list("mention_id")).alias("ids")))
    rows = post.crossJoin(listed).withColumn("own", F.get("partition", F.array_position("ids", F.lit(query).cast("long")).cast("int") - 1))
    each = rows.select("prob", "own", F.inline(F.arrays_zip("ids", "partition")))
    return each.groupBy(F.col("ids").alias("mention_id")).agg(F.sum(F.when(F.col("partition") == F.col("own"), F.col("prob")).otherwise(0.0)).alias("p_coref"))
