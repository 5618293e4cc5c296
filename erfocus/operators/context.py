"""Context of mentions: levels, term statistics and cosine similarity."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F



def words(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), r"[\s.,]+"), lambda w: w != "")


def term_stats(documents: DataFrame, text_col: str = "text") -> DataFrame:
    """(term, df, tf) over texts; repeats in a text count in tf only."""
    all_words = words(F.col(text_col))
    once = F.transform(F.array_distinct(all_words), lambda w: F.struct(w.alias("term"), F.lit(1).alias("df"), F.lit(0).alias("tf")))
    each = F.transform(all_words, lambda w: F.struct(w.alias("term"), F.lit(0).alias("df"), F.lit(1).alias("tf")))
    rows = documents.select(F.inline(F.concat(once, each)))
    return rows.groupBy("term").agg(F.sum("df").alias("df"), F.sum("tf").alias("tf"))


def context_terms(mentions: DataFrame, level: str = "document") -> DataFrame:
    """(mention_id, term) of distinct context words."""
    if level == "none":
        return mentions.select("mention_id", F.lit("").alias("term")).where("1 = 0")
    return mentions.select("mention_id", F.explode(F.array_distinct(F.col(f"context.{level}"))).alias("term"))


def tfidf(terms: DataFrame, n_docs: int | None = None) -> DataFrame:
    """(mention_id, term, w) of unit length, w in proportion to log(N / df); a term of every mention has no weight."""
    n = n_docs if n_docs is not None else terms.select("mention_id").distinct().count()
    idf = terms.groupBy("term").agg(F.log(F.lit(float(max(n, 1))) / F.count(F.lit(1))).alias("idf"))
    weighted = terms.join(idf, "term").where("idf > 0")
    norm = weighted.groupBy("mention_id").agg(F.sqrt(F.sum(F.col("idf") * F.col("idf"))).alias("norm"))
    return weighted.join(norm, "mention_id").select("mention_id", "term", (F.col("idf") / F.col("norm")).alias("w"))


def cosine(vectors: DataFrame, pairs: DataFrame, a: str = "query_id", b: str = "mention_id") -> DataFrame:
    """(a, b, cos) of pairs of mention ids; pairs without a common term have 0, those with a side without a vector null."""
    left = vectors.select(F.col("mention_id").alias(a), "term", F.col("w").alias("wa"))
    right = vectors.select(F.col("mention_id").alias(b), "term", F.col("w").alias("wb"))
    dots = pairs.select(a, b).join(left, a).join(right, [b, "term"]).groupBy(a, b).agg(F.sum(F.col("wa") * F.col("wb")).alias("cos"))
    has = vectors.select("mention_id").distinct()
    rows = pairs.select(a, b).join(dots, [a, b], "left").join(has.select(F.col("mention_id").alias(a), F.lit(True).alias("__a")), a, "left").join(has.select(F.col("mention_id").alias(b), F.lit(True).alias("__b")), b, "left")
    return rows.select(a, b, F.when(F.col("__a") & F.col("__b"), F.coalesce("cos", F.lit(0.0))).alias("cos"))


def apply(queries: DataFrame, level: str, keywords: tuple[str, ...] = ()) -> DataFrame:
    """Queries whose context is only of a level (none, paragraph, document), with these keywords."""
    empty = F.array().cast("array<string>")
    keep = {"none": (), "paragraph": ("paragraph",), "document": ("paragraph", "document")}[level]
    new = F.struct(
        *[(F.col(f"context.{k}") if k in keep else empty).alias(k) for k in ("paragraph", "document")],
        F.array(*map(F.lit, keywords)).cast("array<string>").alias("keywords"),
        F.col("context.extra").alias("extra"),
    )
    return queries.withColumn("context", new)


def salient(canopy_terms: DataFrame, wanted: DataFrame, top: int = 3) -> DataFrame:
    """(query_id, term, lift): terms most particular to some mentions of a canopy, as keyword proposals.

    canopy_terms: (query_id, mention_id, term); wanted: (query_id, mention_id).
    """
    marked = canopy_terms.join(wanted.withColumn("__in", F.lit(1)), ["query_id", "mention_id"], "left")
    counts = marked.groupBy("query_id", "term").agg(F.count_if(F.col("__in").isNotNull()).alias("inside"), F.count_if(F.col("__in").isNull()).alias("outside"))
    from pyspark.sql import Window

    lift = (F.col("inside") - F.col("outside")).alias("lift")
    w = Window.partitionBy("query_id").orderBy(F.desc("lift"), "term")
    return counts.select("query_id", "term", lift).withColumn("__k", F.row_number().over(w)).where(F.col("__k") <= top).drop("__k")
