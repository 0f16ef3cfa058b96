import pytest
from pyspark.sql import functions as F

from embedvocab import sqlfuncs
from embedvocab.functions import memory, rng
from embedvocab.plans import fixtures as fx


def test_sql_functions_equal_columns(spark, smoke):
    sqlfuncs.register(spark, smoke)
    a = spark.sql("SELECT recall(2.0D, 3.0D) r, boost(2.0D, 0.5D) g, understanding(0.5D, 0.5D) p, priority(0.75D, 2.0D) q, to_days(36000.0D) d, draw('42|1|7') u").first()
    b = spark.range(1).select(memory.recall(F.lit(2.0), F.lit(3.0)), memory.boost(F.lit(2.0), F.lit(0.5)), F.lit(0.75), F.lit(1.5), F.lit(1.0), rng.uniform(42, 1, 7)).first()
    assert tuple(a) == pytest.approx(tuple(b)) and a.u == 0.7576901714783162
    assert [r.segment for r in spark.sql("SELECT * FROM segments('One two, 3')").orderBy("i").collect()] == ["One", " ", "two", ", 3"]
    assert spark.sql("SELECT d, s.sentence FROM VALUES ('A b. C!') t(d), LATERAL sentences_of(d) s WHERE s.i = 1").first().sentence == " C!"
    assert spark.sql("SELECT count(*) n FROM words").first().n == 51997
    assert spark.sql("SELECT count(*) n FROM lemma_ranks WHERE before * 10 < total * 9").first().n == 7370
    assert spark.sql("SELECT count(*) n FROM answers").first().n == fx.answers(spark, smoke).count()


def test_readers_and_sinks(spark, tmp_path):
    from embedvocab.sources import tables

    (tmp_path / "lexicon.json").write_text('{"lemma": "bank", "target_lang": "de", "sense": 1, "target": "Ufer", "cues": ["river"]}\n')
    assert [(r.lemma, r.sense, r.cues) for r in tables.read_lexicon(spark, str(tmp_path / "lexicon.json")).collect()] == [("bank", 1, ["river"])]
    (tmp_path / "stop.txt").write_text("The\n of \n\nthe\n")
    assert sorted(r.lemma for r in tables.read_stopwords(spark, str(tmp_path / "stop.txt")).collect()) == ["of", "the"]
    (tmp_path / "clicks.tsv").write_text("A\tB\tlink\t3\nA\tB\tlink\t1\nA\tother\texternal\t5\n")
    assert sorted(((r.u, r.v, r.n) for r in tables.read_clicks(spark, str(tmp_path / "clicks.tsv")).collect()), key=str) == [("A", "B", 4), ("A", None, 5)]
    docs = spark.createDataFrame([(1, "en", "a"), (2, "de", "b")], "doc_id long, lang string, text string")
    tables.write_augmented(docs, str(tmp_path / "out"))
    assert (tmp_path / "out" / "lang=de").is_dir() and spark.read.parquet(str(tmp_path / "out")).count() == 2
    tables.write_json(docs, str(tmp_path / "json"))
    assert spark.read.json(str(tmp_path / "json")).count() == 2


def test_random_scores_are_uniform(spark):
    from embedvocab.operators import context

    runs = spark.range(4000).select(F.col("id").alias("doc_id"), F.lit(0).alias("pos"))
    row = context.random_scores(runs).agg(F.avg("g").alias("m"), F.min("g").alias("a"), F.max("g").alias("b")).first()
    assert abs(row.m - 0.5) < 0.03 and 0 <= row.a < 0.01 and 0.99 < row.b < 1
