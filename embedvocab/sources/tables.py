"""Readers for the given tables and for inputs that users bring, and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

LEXICON = T.StructType([T.StructField("lemma", T.StringType()), T.StructField("target_lang", T.StringType()), T.StructField("sense", T.IntegerType()),
                        T.StructField("target", T.StringType()), T.StructField("cues", T.ArrayType(T.StringType()))])
CLICKS = T.StructType([T.StructField("u", T.StringType()), T.StructField("v", T.StringType()), T.StructField("kind", T.StringType()), T.StructField("n", T.LongType())])
EXPOSURES = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("user_id", T.LongType()), T.StructField("lemma_id", T.IntegerType()),
                          T.StructField("ts", T.TimestampType()), T.StructField("success", T.BooleanType())])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; timestamps without a zone become timestamps in the session's zone, which streams and unix_micros need."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    zoned = {f.name: F.col(f.name).cast("timestamp") for f in df.schema if isinstance(f.dataType, T.TimestampNTZType)}
    return df.withColumns(zoned) if zoned else df


def exposures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_id, user_id, lemma_id, ts, success, event_type): each event as a reader's exposure to a lemma; an error is a lapse."""
    return table(spark, sf_dir, "events").select(
        "event_id", "user_id", F.get_json_object("props", "$.k").cast("int").alias("lemma_id"), "ts", (F.col("event_type") != "error").alias("success"), "event_type", "value")


def read_lexicon(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(LEXICON).json(path)


def read_stopwords(spark: SparkSession, path: str) -> DataFrame:
    """(lemma) from a text file, one a line."""
    return spark.read.text(path).select(F.lower(F.trim("value")).alias("lemma")).filter("lemma <> ''").distinct()


def read_clicks(spark: SparkSession, path: str) -> DataFrame:
    """(u, v, n) from tab-separated source, target, kind and count; a target without a page of its own is a stop."""
    rows = spark.read.schema(CLICKS).option("sep", "\t").csv(path)
    return rows.select("u", F.when(F.col("kind") == "link", F.col("v")).alias("v"), "n").groupBy("u", "v").agg(F.sum("n").alias("n"))


def write_augmented(docs: DataFrame, path: str, by: str = "lang") -> None:
    docs.write.mode("overwrite").partitionBy(by).parquet(path)


def write_json(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").json(path)
