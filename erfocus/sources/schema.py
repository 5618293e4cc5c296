"""Schemas of mentions, queries, states and traces."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

CONTEXT = T.StructType(
    [
        T.StructField("paragraph", T.ArrayType(T.StringType())),
        T.StructField("document", T.ArrayType(T.StringType())),
        T.StructField("keywords", T.ArrayType(T.StringType())),
        T.StructField("extra", T.MapType(T.StringType(), T.StringType())),
    ]
)
MENTION = T.StructType(
    [
        T.StructField("mention_id", T.LongType()),
        T.StructField("doc_id", T.LongType()),
        T.StructField("startpos", T.IntegerType()),
        T.StructField("mention", T.StringType()),
        T.StructField("context", CONTEXT),
        T.StructField("gold", T.StringType()),
    ]
)
STATE = "run_id int, mention_id long, entity_id long"
TRACE = "run_id int, step int, query_id long, kind string, m long, e_from long, e_to long, delta long, accepted boolean"


class MentionSchema:
    """The fixed columns of a mention table; other columns may ride along."""

    @staticmethod
    def validate(df: DataFrame, gold: bool = False) -> DataFrame:
        have = {f.name: f.dataType.simpleString() for f in df.schema}
        for f in MENTION:
            if f.name == "gold" and not gold:
                continue
            if f.name not in have:
                raise ValueError(f"a mention table needs the column {f.name}")
            if have[f.name] != f.dataType.simpleString():
                raise ValueError(f"{f.name} is {have[f.name]}, not {f.dataType.simpleString()}")
        return df


@dataclass(frozen=True)
class QueryNode:
    """A template of the entity asked for: a mention of the table, or one declared by the user (a negative id)."""

    mention: str
    query_id: int = -1
    paragraph: tuple[str, ...] = ()
    document: tuple[str, ...] = ()
    keywords: tuple[str, ...] = ()
    gold: str | None = field(default=None, compare=False)

    def frame(self, spark: SparkSession) -> DataFrame:
        return query_frame(spark, [self])


def query_frame(spark: SparkSession, nodes: list[QueryNode]) -> DataFrame:
    rows = [(n.query_id, -1, 0, n.mention, (list(n.paragraph), list(n.document), list(n.keywords), {}), n.gold) for n in nodes]
    return spark.createDataFrame(rows, MENTION).withColumnRenamed("mention_id", "query_id")


def as_queries(mentions: DataFrame) -> DataFrame:
    """Mentions of the table as query nodes."""
    return mentions.withColumn("query_id", F.col("mention_id"))
