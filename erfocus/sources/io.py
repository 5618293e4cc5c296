"""Readers and writers of mention tables, indexes and answers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erfocus.sources.schema import CONTEXT, MENTION, MentionSchema


def read_mentions(spark: SparkSession, path: str, columns: dict[str, str] | None = None, format: str = "parquet", schema=None, **options) -> DataFrame:
    """A mention table from Parquet, CSV, JSON or text; columns maps mention columns to SQL of the source's.

    Missing context is empty and missing gold null, so that a plain (id, text) table is enough.
    """
    reader = spark.read.format(format).options(**options)
    source = (reader.schema(schema) if schema is not None else reader).load(path)
    given = columns or {c: c for c in source.columns}
    empty = F.struct(F.array().cast("array<string>").alias("paragraph"), F.array().cast("array<string>").alias("document"), F.array().cast("array<string>").alias("keywords"), F.create_map().cast("map<string,string>").alias("extra"))
    out = []
    for f in MENTION:
        if f.name in given:
            value = F.expr(given[f.name]).cast(f.dataType)
        elif f.name == "context":
            value = empty.cast(CONTEXT)
        elif f.name in ("doc_id", "startpos"):
            value = F.lit(0).cast(f.dataType)
        else:
            value = F.lit(None).cast(f.dataType)
        out.append(value.alias(f.name))
    return MentionSchema.validate(source.select(*out))


def read_mention_stream(spark: SparkSession, path: str, schema, max_files: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int, mode: str = "overwrite") -> None:
    """A table whose joins on key need no shuffle; rows of a key lie together for row-group pruning."""
    df.write.mode(mode).bucketBy(buckets, key).sortBy(key).format("parquet").saveAsTable(table)


def write_answers(df: DataFrame, path: str, partition: str | None = None, mode: str = "overwrite") -> None:
    writer = df.write.mode(mode)
    (writer.partitionBy(partition) if partition else writer).parquet(path)
