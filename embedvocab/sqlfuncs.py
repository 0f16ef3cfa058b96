"""The same methods for SQL users: functions and views of a session."""

from __future__ import annotations

from pyspark.sql import SparkSession

from embedvocab.functions.memory import Boost
from embedvocab.operators import corpus, coverage, revisit
from embedvocab.plans import fixtures as fx


def register(spark: SparkSession, sf_dir: str | None = None, p: Boost = Boost()) -> None:
    """SQL functions recall, boost, understanding, priority, to_days, draw and table functions segments, sentences_of; with tables, views words, lemma_ranks, gaps, reader_state, answers.

    SQL functions are expanded by the analyzer, so they cost what the column functions cost.
    """
    for name, args, body in (
        ("recall", "t_days DOUBLE, h DOUBLE", "pow(2.0D, -(CASE WHEN t_days < 0 THEN 0.0D ELSE t_days END) / CASE WHEN h < 1e-6D THEN 1e-6D ELSE h END)"),
        ("boost", "h DOUBLE, r DOUBLE", f"{p.a}D * pow(greatest(h, 1e-6D), -{p.b}D) * pow({p.c}D, -r) + {p.d}D"),
        ("understanding", "r DOUBLE, g DOUBLE", "r + g - r * g"),
        ("priority", "p DOUBLE, gamma DOUBLE", "p * gamma"),
        ("to_days", "words DOUBLE", f"words / {float(revisit.WPM * 60 * revisit.HOURS)}D"),
        ("draw", "k STRING", "CAST(conv(substr(md5(k), 1, 8), 16, 10) AS DOUBLE) / 4294967296.0D"),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS DOUBLE RETURN {body}")
    for name, columns, pattern in (("segments", "i INT, segment STRING", r"\\p{L}+|[^\\p{L}]+"), ("sentences_of", "i INT, sentence STRING", "[^.!?]+[.!?]*")):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(t STRING) RETURNS TABLE ({columns}) RETURN SELECT pos, col FROM posexplode(regexp_extract_all(t, '{pattern}', 0))")
    if sf_dir is None:
        return
    words = corpus.number_words(fx.english_words(spark, sf_dir))
    found = corpus.occurrences(words)
    words.createOrReplaceTempView("words")
    coverage.ranks(coverage.frequencies(found)).createOrReplaceTempView("lemma_ranks")
    revisit.gaps(found).createOrReplaceTempView("gaps")
    fx.reader_states(spark, sf_dir)[0].createOrReplaceTempView("reader_state")
    fx.answers(spark, sf_dir).createOrReplaceTempView("answers")
