"""Canopies: mentions that may be of a query's entity, by an inverted q-gram index, and other ways to block."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from erfocus.functions.strings import normal, qgrams
from erfocus.operators.components import connected_components
from erfocus.operators.durable import cut, held


def string_table(mentions: DataFrame) -> DataFrame:
    """(string, n_mentions) of distinct normalised surface forms; many mentions share few."""
    return mentions.select(normal(F.col("mention")).alias("string")).where("string IS NOT NULL").groupBy("string").agg(F.count(F.lit(1)).alias("n_mentions"))


def postings(strings: DataFrame, q: int = 3) -> DataFrame:
    """(gram, string), flat: a frequent gram is many rows, not one."""
    return strings.select(F.explode(qgrams(F.col("string"), q)).alias("gram"), "string")


def gram_df(strings: DataFrame, q: int = 3) -> DataFrame:
    """(gram, n_strings, n_mentions)."""
    return strings.select(F.explode(qgrams(F.col("string"), q)).alias("gram"), "n_mentions").groupBy("gram").agg(F.count(F.lit(1)).alias("n_strings"), F.sum("n_mentions").alias("n_mentions"))


def build_index(mentions: DataFrame, table: str, q: int = 3, buckets: int = 64) -> None:
    """Persist strings, postings and gram counts as tables bucketed by their probe keys; the one full scan."""
    from erfocus.sources.io import write_bucketed

    strings = string_table(mentions)
    write_bucketed(strings, f"{table}_strings", "string", buckets)
    strings = mentions.sparkSession.table(f"{table}_strings")
    write_bucketed(postings(strings, q), f"{table}_postings", "gram", buckets)
    write_bucketed(gram_df(strings, q), f"{table}_grams", "gram", buckets)


def probes(queries: DataFrame, grams: DataFrame | None, q: int = 3, min_shared: int = 3) -> DataFrame:
    """(query_id, gram, need): the grams that must be probed.

    A string that shares min_shared of a query's g grams has one of any g - min_shared + 1 of them; with
    counts the rarest are taken, so that postings of frequent grams are left alone.
    """
    rows = queries.select("query_id", qgrams(F.col("mention"), q).alias("grams")).where("grams IS NOT NULL")
    rows = rows.select("query_id", F.least(F.lit(min_shared), F.size("grams")).alias("need"), F.size("grams").alias("g"), F.explode("grams").alias("gram"))
    if grams is None:
        return rows.select("query_id", "gram", "need")
    counted = grams.join(held(rows.select("gram").distinct()), "gram").select("gram", "n_strings")
    ranked = rows.join(counted, "gram", "left").withColumn("k", F.row_number().over(Window.partitionBy("query_id").orderBy(F.coalesce("n_strings", F.lit(0)), "gram")))
    return ranked.where("k <= g - need + 1").select("query_id", "gram", "need")


#: Queries of a call whose grams are broadcast: some tens of grams each.
MAX_BROADCAST_QUERIES = 20_000


def candidates(queries: DataFrame, index: DataFrame, grams: DataFrame | None = None, q: int = 3, min_shared: int = 3) -> DataFrame:
    """(query_id, string, shared, sim) of strings that share at least min_shared grams (all, if a query has fewer).

    Queries are worked out once and counted where they lie; the index is read once.
    """
    asked = cut(queries.select("query_id", "mention"))
    small = F.broadcast if asked.limit(MAX_BROADCAST_QUERIES + 1).count() <= MAX_BROADCAST_QUERIES else lambda df: df
    found = index.join(small(probes(asked, grams, q, min_shared)), "gram").select("query_id", "string", "need").distinct()
    # Short rows, but each takes the making of its grams: they are dealt to tasks by number, not by bytes.
    found = found.repartition(int(queries.sparkSession.conf.get("spark.sql.shuffle.partitions")), "query_id", "string")
    own = small(asked.select("query_id", qgrams(F.col("mention"), q).alias("own")))
    shared = F.size(F.array_intersect(qgrams(F.col("string"), q), F.col("own")))
    verified = found.join(own, "query_id").withColumn("shared", shared).where("shared >= need")
    sim = F.col("shared") / (F.size(qgrams(F.col("string"), q)) + F.size("own") - F.col("shared"))
    return verified.select("query_id", "string", F.col("shared").cast("long").alias("shared"), sim.alias("sim"))


def canopy(mentions: DataFrame, queries: DataFrame, index: str | None = None, q: int = 3, min_shared: int = 3) -> DataFrame:
    """(query_id, mention_id, shared, sim) of each query's canopy, all queries in one plan.

    With a persisted index only the buckets of the rarest query grams are read; without one the distinct
    strings are matched directly.  The strings found are written down and counted; mentions are joined last, by
    their strings, in the one pass over them that the result takes.
    """
    spark = mentions.sparkSession
    if index:
        strings = candidates(queries, spark.table(f"{index}_postings"), spark.table(f"{index}_grams"), q, min_shared)
    else:
        strings = candidates(queries, postings(string_table(mentions), q), None, q, min_shared)
    keyed = mentions.select("mention_id", normal(F.col("mention")).alias("string"))
    return keyed.join(held(strings), "string").select("query_id", "mention_id", "shared", "sim")


def top_canopy(found: DataFrame, size: int) -> DataFrame:
    """Each query's best size mentions by shared grams; the rest are cut, the smallest ids first kept."""
    w = Window.partitionBy("query_id").orderBy(F.desc("shared"), "mention_id")
    return found.withColumn("__k", F.row_number().over(w)).where(F.col("__k") <= size).drop("__k")


def selectivity(found: DataFrame) -> DataFrame:
    """(query_id, sel): the number of mentions the approximate match returns."""
    return found.groupBy("query_id").agg(F.count(F.lit(1)).alias("sel"))


def gold_selectivity(mentions: DataFrame, queries: DataFrame) -> DataFrame:
    """(query_id, sel): the true size of each query's entity, for the design of workloads."""
    sizes = mentions.groupBy("gold").agg(F.count(F.lit(1)).alias("sel"))
    return queries.select("query_id", "gold").join(sizes, "gold").select("query_id", "sel")


def ranked(df: DataFrame, *order, name: str = "rn") -> DataFrame:
    """A row number over the whole table without bringing it to one task: ranks in ranges, then ranges' offsets."""
    ranges = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    parts = cut(df.repartitionByRange(ranges, *order).withColumn("__p", F.spark_partition_id()))
    local = parts.withColumn("__k", F.row_number().over(Window.partitionBy("__p").orderBy(*order)))
    sizes = parts.groupBy("__p").agg(F.count(F.lit(1)).alias("__n"))
    offsets = sizes.select("__p", F.coalesce(F.sum("__n").over(Window.orderBy("__p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__o"))
    return local.join(F.broadcast(offsets), "__p").withColumn(name, F.col("__k") + F.col("__o")).drop("__p", "__k", "__o")


def sorted_neighborhood(mentions: DataFrame, window: int = 3) -> DataFrame:
    """(a, b): mentions at most window - 1 places apart in the order of their normalised strings."""
    rows = ranked(mentions.select(normal(F.col("mention")).alias("k"), "mention_id"), "k", "mention_id").select("rn", "mention_id")
    left = rows.select(F.col("mention_id").alias("x"), F.explode(F.transform(F.sequence(F.lit(1), F.lit(window - 1)), lambda d: F.col("rn") + d)).alias("rn"))
    pairs = left.join(rows, "rn")
    return pairs.select(F.least("x", "mention_id").alias("a"), F.greatest("x", "mention_id").alias("b"))


def by_key(mentions: DataFrame, key) -> DataFrame:
    """(block, mention_id): hard blocks."""
    return mentions.select(key.alias("block"), "mention_id")


def by_vector(vectors: DataFrame, planes: int = 12, dims: int = 64, seed: int = 1) -> DataFrame:
    """(block, mention_id): sign bits of fixed random projections of column embedding."""
    from erfocus.functions.rand import py_h32

    bits = F.lit("")
    for p in range(planes):
        plane = F.array(*[F.lit(py_h32(f"{seed}|{p}|{d}") / 2**31 - 1.0) for d in range(dims)])
        dot = F.aggregate(F.zip_with("embedding", plane, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
        bits = F.concat(bits, F.when(dot > 0, "1").otherwise("0"))
    return vectors.select(bits.alias("block"), "mention_id")


def by_influence(scores: DataFrame, least: float | None = None, top: int | None = None) -> DataFrame:
    """Implicit blocks: mentions of enough influence, or each query's most influential."""
    if least is not None:
        scores = scores.where(F.col("infl") >= least)
    if top is not None:
        w = Window.partitionBy("query_id").orderBy(F.desc("infl"), "mention_id")
        scores = scores.withColumn("__k", F.row_number().over(w)).where(F.col("__k") <= top).drop("__k")
    return scores


def merge(found: DataFrame) -> DataFrame:
    """(query_id, component): queries whose canopies overlap, directly or through others, are of one model.

    Links go through mentions by each mention's smallest query, so no mention's queries are paired.  found is read
    several times: it should lie written down.
    """
    least = found.groupBy("mention_id").agg(F.min("query_id").alias("least"))
    links = found.join(least, "mention_id").where("query_id <> least").select(F.col("query_id").alias("a"), F.col("least").alias("b")).distinct()
    parts = connected_components(links).withColumnRenamed("node", "query_id")
    return found.select("query_id").distinct().join(parts, "query_id", "left").select("query_id", F.coalesce("component", "query_id").alias("component"))
