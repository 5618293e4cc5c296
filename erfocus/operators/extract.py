"""Mentions out of text."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from erfocus.operators.durable import cut, held

SHORT_BLOCK = 1000


def pattern_mentions(documents: DataFrame, pattern: str, radius: int = 100, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, startpos, mention, before, after) of a pattern's matches, by place from 1.

    The pattern's own groups must be non-capturing.  The text is split at matches, so places of equal matches
    are told apart.
    """
    hits = documents.where(F.col(text_col).rlike(pattern)).select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), F.regexp_extract_all(text_col, F.lit(f"({pattern})"), F.lit(1)).alias("hits"), F.split(text_col, pattern, -1).alias("gaps"))
    rows = hits.select("doc_id", "text", "hits", "gaps", F.posexplode("hits").alias("k", "mention"))
    length = lambda parts: F.aggregate(parts, F.lit(0), lambda s, x: s + F.char_length(x))
    start = length(F.slice("gaps", 1, F.col("k") + 1)) + length(F.slice("hits", 1, F.col("k"))) + 1
    placed = rows.withColumn("startpos", start.cast("int"))
    size = F.char_length("mention")
    low = F.greatest(F.lit(1), F.col("startpos") - radius)
    return placed.select("doc_id", "startpos", "mention", F.substring("text", low, F.col("startpos") - low).alias("before"), F.substring("text", F.col("startpos") + size, F.lit(radius)).alias("after"))


def passages(documents: DataFrame, watchlist: DataFrame, max_rows: int = 100_000) -> DataFrame:
    """(item_id, doc_id): watchlist texts contained in documents verbatim.

    A text's longest word picks candidate documents by an equi-join, so that no document is compared with all.
    """
    # The first and last word of a passage may be parts of a document's words.
    inner = F.slice(F.split("text", " "), 2, F.greatest(F.size(F.split("text", " ")) - 2, F.lit(0)))
    core = F.array_max(F.transform(F.filter(inner, lambda w: w != ""), lambda w: F.struct(F.char_length(w).alias("n"), w.alias("w"))))["w"]
    items = watchlist.where("text IS NOT NULL AND text <> ''").select("item_id", F.col("text").alias("passage"), core.alias("word"))
    docs = documents.where("text IS NOT NULL").select("doc_id", "text")
    words = docs.select("doc_id", F.explode(F.array_distinct(F.split("text", " "))).alias("word"))
    items = cut(items)
    n = items.count()
    few = F.broadcast(items) if n <= max_rows else items
    few = few.where("word IS NOT NULL")
    # Candidates are ids, so that texts need not be exchanged to meet them.
    found = held(words.join(few.select("item_id", "word").distinct(), "word").select("doc_id", "item_id", "word"))
    found = docs.join(found, "doc_id").join(few, ["item_id", "word"]).where(F.col("text").contains(F.col("passage"))).select("item_id", "doc_id")
    # Passages of one or two words may stand inside words: they are a query set, looked up block by block in each text.
    short = items.where("word IS NULL").select("item_id", "passage")
    blocks = -(-short.count() // SHORT_BLOCK)
    for b in range(blocks):
        block = short.where(F.pmod(F.xxhash64("item_id", "passage"), F.lit(blocks)) == b).agg(F.collect_list(F.struct("item_id", "passage")).alias("ps"))
        hits = docs.crossJoin(F.broadcast(block)).select("doc_id", F.explode(F.filter("ps", lambda p: F.col("text").contains(p["passage"]))).alias("p"))
        found = found.union(hits.select("p.item_id", "doc_id"))
    return found
