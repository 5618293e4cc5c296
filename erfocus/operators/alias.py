"""Alias tables: biased draws of mentions at constant cost, one row per query."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

TABLE = "query_id long, prob array<double>, alias array<int>, ids array<long>"


def vose(p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(prob, alias) of weights, by pairing places that have too little with places that have too much."""
    n = len(p)
    total = p.sum()
    scaled = p * (n / total) if total > 0 else np.ones(n)
    prob, alias = np.ones(n), np.arange(n, dtype=np.int32)
    small = [i for i in range(n) if scaled[i] < 1]
    large = [i for i in range(n) if scaled[i] >= 1]
    scaled = scaled.copy()
    while small and large:
        s, g = small.pop(), large[-1]
        prob[s], alias[s] = scaled[s], g
        scaled[g] -= 1 - scaled[s]
        if scaled[g] < 1:
            small.append(large.pop())
    return prob, alias


def build(weights: DataFrame) -> DataFrame:
    """A row per query from (query_id, mention_id, weight); places are in the order of mention ids."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("mention_id")
        prob, alias = vose(pdf["weight"].to_numpy(dtype=float))
        return pd.DataFrame({"query_id": [pdf["query_id"].iloc[0]], "prob": [prob.tolist()], "alias": [alias.tolist()], "ids": [pdf["mention_id"].tolist()]})

    return weights.select("query_id", "mention_id", "weight").groupBy("query_id").applyInPandas(run, TABLE)


def draw(u1: Column, u2: Column) -> Column:
    """The mention drawn from a table's row by two uniforms."""
    n = F.size("ids")
    i = F.least(F.floor(u1 * n).cast("int"), n - 1)
    return F.get(F.col("ids"), F.when(u2 < F.get(F.col("prob"), i), i).otherwise(F.get(F.col("alias"), i)))


def place(u1: float, u2: float, prob: np.ndarray, alias: np.ndarray) -> int:
    i = min(int(u1 * len(prob)), len(prob) - 1)
    return i if u2 < prob[i] else int(alias[i])


def mass(table: DataFrame) -> DataFrame:
    """(query_id, mention_id, p): the probabilities that the table's arrays encode."""
    n = F.size("ids")
    cells = table.select("query_id", "ids", n.alias("n"), F.inline(F.arrays_zip("prob", "alias", F.sequence(F.lit(0), n - 1).alias("i"))))
    own = cells.select("query_id", F.get("ids", F.col("i")).alias("mention_id"), (F.col("prob") / F.col("n")).alias("p"))
    other = cells.select("query_id", F.get("ids", F.col("alias")).alias("mention_id"), ((1 - F.col("prob")) / F.col("n")).alias("p"))
    return own.union(other).groupBy("query_id", "mention_id").agg(F.sum("p").alias("p"))


def cdf_draw(weights: DataFrame, draws: DataFrame) -> DataFrame:
    """(query_id, draw, mention_id) by inverse cumulative weights: the same law by a range join, for checks."""
    w = Window.partitionBy("query_id").orderBy("mention_id")
    share = F.col("weight") / F.sum("weight").over(Window.partitionBy("query_id"))
    spans = weights.withColumn("share", share).withColumn("high", F.sum("share").over(w)).withColumn("low", F.lag("high", 1, 0.0).over(w))
    last = F.lead("mention_id").over(w).isNull()
    spans = spans.withColumn("high", F.when(last, 1.1).otherwise(F.col("high")))
    return draws.join(spans, (draws["query_id"] == spans["query_id"]) & (draws["u"] >= spans["low"]) & (draws["u"] < spans["high"])).select(draws["query_id"], "draw", "mention_id")


def presample(table: DataFrame, k: int, seed: int = 1) -> DataFrame:
    """(query_id, draw, mention_id): k draws of each table, to be stored beside it."""
    from erfocus.functions.rand import SPAN, h32

    rows = table.withColumn("draw", F.explode(F.sequence(F.lit(1), F.lit(k))))
    u = lambda s: h32(F.concat_ws("|", F.lit(str(seed)), F.col("query_id").cast("string"), F.col("draw").cast("string"), F.lit(s))) / SPAN
    return rows.select("query_id", "draw", draw(u("a"), u("b")).alias("mention_id"))


def table_bytes(table: DataFrame) -> DataFrame:
    """(query_id, bytes): a double and an unsigned integer a member."""
    return table.select("query_id", (F.size("ids").cast("long") * 12).alias("bytes"))


def spill(table: DataFrame, path: str) -> DataFrame:
    """Tables, or presampled draws, written to Parquet by query and read again: for more queries than memory holds.

    A selection then reads its own query's row alone, as files hold the least and greatest id of each part.
    """
    table.repartitionByRange("query_id").sortWithinPartitions("query_id").write.mode("overwrite").parquet(path)
    return table.sparkSession.read.parquet(path)
