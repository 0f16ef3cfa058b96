"""Readers' state and click counts over streams of exposures."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from embedvocab.functions.memory import Boost
from embedvocab.sources.shared import new_path

STATE = "lemmas array<int>, h array<double>, last array<double>, n array<int>, late array<int>"
OUT = "user_id long, lemma_id int, exposures int, half_life double, last_day double, late int"


def replay(stream: DataFrame, p: Boost = Boost(), forget_days: float | None = None) -> DataFrame:
    """(user_id, lemma_id, exposures, half_life, last_day, late) after each batch, for the lemmas that it touched.

    A reader's state has an entry for each lemma met. Exposures are folded in order of time within a batch; those from before the
    last revision seen are counted in ``late`` and taken as if they came at it, so only in-order input equals the batch replay. With
    ``forget_days``, lemmas not met for so long, by the reader's own latest exposure, leave the state and start anew.
    """

    def fold(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = {lemma: rest for lemma, *rest in zip(*state.get, strict=True)} if state.exists else {}
        rows = pd.concat(list(batches)).sort_values(["d", "event_id"])
        touched = {}
        for lemma, d in zip(rows["lemma_id"].astype(int).tolist(), rows["d"].tolist(), strict=True):
            if lemma in held:
                h, last, n, late = held[lemma]
                recall = 2.0 ** (-max(0.0, d - last) / max(h, 1e-6))
                held[lemma] = [h * (p.a * max(h, 1e-6) ** -p.b * p.c**-recall + p.d), max(last, d), n + 1, late + (d < last)]
            else:
                held[lemma] = [p.initial, float(d), 1, 0]
            touched[lemma] = held[lemma]
        if forget_days is not None:
            latest = max(v[1] for v in held.values())
            held = {lemma: v for lemma, v in held.items() if v[1] >= latest - forget_days}
        state.update((list(held), *([v[i] for v in held.values()] for i in range(4))))
        yield pd.DataFrame([(key[0], lemma, n, h, last, late) for lemma, (h, last, n, late) in touched.items()], columns=["user_id", "lemma_id", "exposures", "half_life", "last_day", "late"])

    rows = stream.select("user_id", "lemma_id", "event_id", (F.unix_micros("ts") / 86_400_000_000.0).alias("d"))
    return rows.groupBy("user_id").applyInPandasWithState(fold, OUT, STATE, "update", GroupStateTimeout.NoTimeout)


def clicks(stream: DataFrame, window: str = "1 day", watermark: str = "1 day", slide: str | None = None) -> DataFrame:
    """(window_start, user_id, clicks); events later than the watermark are left out. With a slide, windows overlap."""
    rows = stream.filter("event_type = 'click'").withWatermark("ts", watermark)
    return rows.groupBy(F.window("ts", window, slide), "user_id").agg(F.count(F.lit(1)).alias("clicks")).select(F.col("window.start").alias("window_start"), "user_id", "clicks")


def reading_sessions(stream: DataFrame, pause: str = "12 hours", watermark: str = "1 day") -> DataFrame:
    """(user_id, session_start, exposures, hours): what a reader meets without a pause so long, and the time from the first to the last."""
    rows = stream.withWatermark("ts", watermark).groupBy(F.session_window("ts", pause), "user_id").agg(F.count(F.lit(1)).alias("exposures"), F.min("ts").alias("_a"), F.max("ts").alias("_b"))
    return rows.select("user_id", F.col("_a").alias("session_start"), "exposures", ((F.unix_micros("_b") - F.unix_micros("_a")) / 3.6e9).alias("hours"))


def stream_of(spark: SparkSession, path: str, per_trigger: int = 8) -> DataFrame:
    """Events of a Parquet folder or file as a stream of exposures."""
    from pyspark.sql import types as T

    schema = spark.read.parquet(path).schema
    glob = path if path.endswith("/") else None
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger)
    raw = reader.parquet(glob) if glob else reader.option("pathGlobFilter", path.rsplit("/", 1)[1]).parquet(path.rsplit("/", 1)[0])
    ts = F.col("ts").cast("timestamp") if isinstance(schema["ts"].dataType, T.TimestampNTZType) else F.col("ts")
    return raw.select("event_id", "user_id", F.get_json_object("props", "$.k").cast("int").alias("lemma_id"), ts.alias("ts"), (F.col("event_type") != "error").alias("success"), "event_type")


def drained(result: DataFrame) -> DataFrame:
    """All rows that a query gives until its input is read, each batch a folder of a table that driver and executors share.

    A batch that is repeated replaces its folder, so no row comes twice. Rows of one key may come in several batches.
    """
    spark = result.sparkSession
    at = new_path(spark)

    def keep(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{at}/rows/batch={batch}")

    result.writeStream.foreachBatch(keep).outputMode("update").option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(result.schema).parquet(f"{at}/rows/*")
