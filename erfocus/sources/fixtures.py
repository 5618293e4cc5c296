"""Mention tables derived from the given tables; each is SQL that both engines understand.

Noise and topics come from hashes of keys, so nothing is random and nothing is stored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from erfocus.functions.rand import sql_h32
from erfocus.sources.schema import CONTEXT, MENTION

#: Of ten topic tokens, how many name the mention's entity.
INFORMATIVE = 8
VARIANTS = 9


def noisy(name: str, key: str, engine: str, variants: int = VARIANTS) -> str:
    """SQL of a surface form of 'adjective noun', chosen by the key."""
    v = f"({sql_h32(f"'v|' || {key}", engine)} % {variants})"
    a, b = f"split_part({name}, ' ', 1)", f"split_part({name}, ' ', 2)"
    return (
        f"CASE {v} WHEN 0 THEN {name} WHEN 1 THEN upper({name}) WHEN 2 THEN substr({a}, 1, 1) || '. ' || {b} WHEN 3 THEN {a} || {b}"
        f" WHEN 4 THEN substr({name}, 1, length({name}) - 1) WHEN 5 THEN {b} || ', ' || {a} WHEN 6 THEN 'the ' || {a} || ' ' || {b}"
        f" WHEN 7 THEN substr({a}, 1, 1) || substr({a}, 3, length({a})) || ' ' || {b} ELSE {b} END"
    )


def topic(name: str, key: str, engine: str, informative: int = INFORMATIVE) -> str:
    """SQL of a context token: of the entity, or one of fifty that say nothing."""
    c = sql_h32(f"'c|' || {key}", engine)
    return f"CASE WHEN {c} % 10 < {informative} THEN 'topic_' || replace({name}, ' ', '_') ELSE 'topic_' || cast({sql_h32(f"'o|' || {key}", engine)} % 50 AS varchar(9)) END"


def part_sql(engine: str, variants: int = VARIANTS, informative: int = INFORMATIVE) -> str:
    key = "cast(p_partkey AS varchar(20))"
    div = "p_partkey div 20" if engine == "spark" else "p_partkey // 20"
    array = "array" if engine == "spark" else "list_value"
    return f"""SELECT p_partkey AS mention_id, cast({div} AS bigint) AS doc_id, cast(p_partkey % 20 AS int) AS startpos,
  {noisy('p_name', key, engine, variants)} AS mention, {array}({topic('p_name', key, engine, informative)}) AS paragraph,
  {array}({topic('p_name', key, engine, informative)}, lower(p_brand), lower(split_part(p_type, ' ', 1)), lower(split_part(p_type, ' ', 2))) AS document, p_name AS gold
FROM part"""


def line_sql(engine: str, gold: str = "name") -> str:
    key = "cast(l_orderkey AS varchar(20)) || '|' || cast(startpos AS varchar(9))"
    array = "array" if engine == "spark" else "list_value"
    surface = noisy("p_name", key, engine)
    mention = surface if gold == "name" else f"({surface}) || ' ' || lower(p_brand)"
    return f"""SELECT l_orderkey * 1000 + startpos AS mention_id, l_orderkey AS doc_id, cast(startpos AS int) AS startpos, {mention} AS mention,
  {array}({topic('p_name', key, engine)}) AS paragraph,
  {array}({topic('p_name', key, engine)}, lower(p_brand), 'supplier_' || cast(l_suppkey AS varchar(20)), 'flag_' || lower(l_returnflag)) AS document,
  {"p_name" if gold == "name" else "cast(l_partkey AS varchar(20))"} AS gold
FROM (SELECT l.*, p_name, p_brand, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate) AS startpos
      FROM lineitem l JOIN part ON l_partkey = p_partkey) x"""


def customer_sql(engine: str) -> str:
    key = "cast(o_orderkey AS varchar(20))"
    v = f"({sql_h32(f"'v|' || {key}", engine)} % 4)"
    array = "array" if engine == "spark" else "list_value"
    return f"""SELECT o_orderkey AS mention_id, o_orderkey AS doc_id, 0 AS startpos,
  CASE {v} WHEN 0 THEN c_name WHEN 1 THEN upper(c_name) WHEN 2 THEN substr(c_name, 1, length(c_name) - 1) ELSE substr(c_name, 10, length(c_name)) END AS mention,
  {array}(lower(c_mktsegment), lower(n_name)) AS paragraph, {array}(lower(c_mktsegment), lower(n_name), lower(o_orderpriority)) AS document,
  cast(o_custkey AS varchar(20)) AS gold
FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey"""


def with_context(flat: DataFrame) -> DataFrame:
    """Columns paragraph and document folded into the context."""
    context = F.struct(
        "paragraph", "document", F.array().cast("array<string>").alias("keywords"), F.create_map().cast("map<string,string>").alias("extra")
    ).cast(CONTEXT)
    return flat.select("mention_id", "doc_id", F.col("startpos").cast("int").alias("startpos"), "mention", context.alias("context"), "gold")


def _views(spark: SparkSession, sf_dir: str, *names: str) -> dict[str, DataFrame]:
    return {n: spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in names}


def part_mentions(spark: SparkSession, sf_dir: str, variants: int = VARIANTS, informative: int = INFORMATIVE) -> DataFrame:
    body = part_sql("spark", variants, informative).replace("FROM part", "FROM {part}")
    return with_context(spark.sql(body, **_views(spark, sf_dir, "part")))


def line_mentions(spark: SparkSession, sf_dir: str, gold: str = "name") -> DataFrame:
    body = line_sql("spark", gold).replace("FROM lineitem l JOIN part", "FROM {lineitem} l JOIN {part}")
    return with_context(spark.sql(body, **_views(spark, sf_dir, "lineitem", "part")))


def customer_mentions(spark: SparkSession, sf_dir: str) -> DataFrame:
    body = customer_sql("spark").replace("FROM orders JOIN customer", "FROM {orders} JOIN {customer}").replace("JOIN nation", "JOIN {nation}")
    return with_context(spark.sql(body, **_views(spark, sf_dir, "orders", "customer", "nation")))


def _words(text):
    from erfocus.functions.strings import tokens

    return tokens(text)


def document_mentions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A mention a document: the first six words of its longest sentence; context: that sentence's paragraph, and all words.

    The gold label is left null; near_copy_gold() makes one.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    sentences = F.filter(F.transform(F.split("text", "[.\n]"), lambda s: F.trim(s)), lambda s: s != "")
    longest = F.array_max(F.transform(sentences, lambda s, i: F.struct(F.char_length(s).alias("n"), (-i).alias("i"), s.alias("s"))))["s"]
    rows = docs.select("doc_id", "text", F.explode(F.array(longest)).alias("sentence")).where("sentence IS NOT NULL")
    paragraph = F.get(F.filter(F.split("text", "\n"), lambda p: p.contains(F.col("sentence"))), F.lit(0))
    flat = rows.select(
        F.col("doc_id").alias("mention_id"),
        "doc_id",
        F.lit(0).alias("startpos"),
        F.array_join(F.slice(F.split("sentence", " "), 1, 6), " ").alias("mention"),
        F.array_distinct(F.filter(F.split(F.lower(F.coalesce(paragraph, F.col("sentence"))), r"[\s.,]+"), lambda w: w != "")).alias("paragraph"),
        F.array_distinct(F.filter(F.split(F.lower("text"), r"[\s.,]+"), lambda w: w != "")).alias("document"),
        F.lit(None).cast("string").alias("gold"),
    )
    return with_context(flat)


EMAIL = r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}"


def email_mentions(spark: SparkSession, sf_dir: str, radius: int = 100) -> DataFrame:
    """Addresses in documents with their places; context: the words around."""
    from erfocus.operators.extract import pattern_mentions

    found = pattern_mentions(spark.read.parquet(f"{sf_dir}/documents.parquet"), EMAIL, radius)
    near = F.array_distinct(_words(F.concat_ws(" ", "before", "after")))
    flat = found.select((F.col("doc_id") * 1_000_000 + F.col("startpos")).alias("mention_id"), "doc_id", "startpos", "mention", near.alias("paragraph"), near.alias("document"), F.lower("mention").alias("gold"))
    return with_context(flat)


def page_mentions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Titles of pages; context: the visible text's words."""
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    title = F.trim(F.regexp_extract("html", r"(?is)<title>(.*?)</title>", 1))
    visible = F.regexp_replace(F.regexp_replace("html", r"(?is)<(script|style|title).*?</\1>|<!--.*?-->", " "), r"<[^>]*>", " ")
    near = F.array_distinct(F.filter(F.split(F.lower(visible), r"[\s.,]+"), lambda w: w != ""))
    flat = pages.select(F.col("page_id").alias("mention_id"), F.col("page_id").alias("doc_id"), F.lit(0).alias("startpos"), title.alias("mention"), near.alias("paragraph"), near.alias("document"), F.lower(F.regexp_replace(title, r"\s+", " ")).alias("gold"))
    return with_context(flat)


def conversation_mentions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first six words of turns."""
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet")
    near = F.array_distinct(F.filter(F.split(F.lower("text"), r"[\s.,]+"), lambda w: w != ""))
    flat = turns.select((F.col("conv_id") * 1000 + F.col("turn")).alias("mention_id"), F.col("conv_id").alias("doc_id"), F.col("turn").alias("startpos"), F.array_join(F.slice(F.split("text", " "), 1, 6), " ").alias("mention"), near.alias("paragraph"), near.alias("document"), F.col("conv_id").cast("string").alias("gold"))
    return with_context(flat)


def event_mentions(spark: SparkSession, sf_dir: str, events: DataFrame | None = None) -> DataFrame:
    """User handles in events, some with a digit dropped, with their time; also over a stream."""
    events = events if events is not None else spark.read.parquet(f"{sf_dir}/events.parquet")
    from erfocus.functions.rand import h32

    handle = F.concat(F.lit("user"), F.col("user_id").cast("string"))
    dropped = F.pmod(h32(F.concat(F.lit("v|"), F.col("event_id").cast("string"))), F.lit(4)) == 0
    return events.select(
        F.col("event_id").alias("mention_id"),
        F.col("user_id").alias("doc_id"),
        F.when(dropped, F.substring(handle, F.lit(1), F.char_length(handle) - 1)).otherwise(handle).alias("mention"),
        F.array("event_type", F.concat(F.lit("k"), F.get_json_object("props", "$.k"))).alias("paragraph"),
        F.col("user_id").cast("string").alias("gold"),
        F.col("ts").cast("timestamp").alias("ts"),
    )


def embedding_mentions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").alias("mention_id"), "embedding", F.col("label").cast("string").alias("gold"))


#: The worked example: entities of four (with the query), two and one mentions; a pair of them misleads by its words.
TOY = [
    (0, 0, "J. Marsh", ["harbour", "pilot", "ferry"], "a"),
    (1, 1, "Jo Marsh", ["pilot", "ferry"], "a"),
    (2, 2, "Captain Marsh", ["harbour", "ferry"], "a"),
    (3, 3, "the pilot", ["harbour", "pilot", "ferry"], "a"),
    (4, 4, "J. Marsh", ["organ", "choir"], "b"),
    (5, 5, "Joan Marsh", ["organ", "choir", "chapel"], "b"),
    (6, 6, "Salt Marsh", ["heron", "reed"], "c"),
]


def toy(spark: SparkSession) -> DataFrame:
    rows = [(i, d, 0, m, (c, c, [], {}), g) for i, d, m, c, g in TOY]
    return spark.createDataFrame(rows, T.StructType(MENTION.fields))


#: Of the first names in hash order, how many mentions exact inference takes: of the query's, another and a third.
FEW = (4, 2, 1)


def few_mentions(mentions: DataFrame) -> DataFrame:
    """The mentions of exact inference, with `own`, the query's: of three names of a table the first plain mention and the next ones.

    Where a name has fewer mentions, all it has are taken.
    """
    from erfocus.functions.rand import h32

    plain = mentions.where(F.lower("mention") == F.col("gold")).groupBy("gold").agg(F.min("mention_id").alias("first"))
    order = (h32(F.concat(F.lit("name|"), F.col("gold"))), "gold")
    named = plain.orderBy(*order).limit(len(FEW)).withColumn("r", F.row_number().over(Window.orderBy(*order)))
    named = named.withColumn("own", F.min_by("first", "r").over(Window.partitionBy(F.lit(0))))
    rows = mentions.join(F.broadcast(named), "gold")
    k = F.row_number().over(Window.partitionBy("r").orderBy(F.col("mention_id") != F.col("first"), "mention_id"))
    return rows.withColumn("k", k).where(F.col("k") <= F.get(F.array(*map(F.lit, FEW)), F.col("r") - 1)).select(*mentions.columns, "own")
