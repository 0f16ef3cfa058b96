import pytest
from pyspark.sql import functions as F

from embedvocab.operators import browse, corpus, coverage, revisit


def words(spark, docs, block=None):
    df = spark.createDataFrame([(c, i, w.split()) for c, i, w in docs], "corpus_id string, doc_id long, words array<string>")
    return corpus.number_words(df, block=block)


@pytest.mark.parametrize("block", [1, 7, 10**9])
def test_positions_and_gaps_do_not_depend_on_blocks(spark, block):
    docs = [("x", i, t) for i, t in enumerate(["a b a", "", "c a b", "c", "a c c"])] + [("y", 9, "a a")]
    rows = words(spark, docs, F.floor(F.col("doc_id") / block))
    got = sorted((r.corpus_id, r.pos, r.lemma) for r in rows.collect())
    assert got == [("x", i, w) for i, w in enumerate("a b a c a b c a c c".split())] + [("y", 0, "a"), ("y", 1, "a")]
    gaps = sorted(map(tuple, revisit.gaps(corpus.occurrences(rows)).filter("corpus_id = 'x'").select("lemma", "gap").collect()))
    assert gaps == [("a", 2), ("a", 2), ("a", 3), ("b", 4), ("c", 1), ("c", 2), ("c", 3)]


def test_six_words(spark):
    """a b a c a b: gaps 2, 2 and 4; half is covered by a, four fifths by a and b."""
    found = corpus.occurrences(words(spark, [("x", 0, "a b a"), ("x", 1, "c a b")], F.col("doc_id")))
    ranked = coverage.ranks(coverage.frequencies(found))
    assert [r.lemma for r in coverage.lemma_set(ranked, 0.5).collect()] == ["a"]
    assert sorted(r.lemma for r in coverage.lemma_set(ranked, 0.8).collect()) == ["a", "b"]
    cell = revisit.analyse(found, (0.8,)).first()
    assert cell.vocab == 2 and cell.revisit_days * 36000 == pytest.approx(3.8)
    between = revisit.gaps(found, "between").collect()
    assert sorted(r.gap for r in between) == [1, 1, 3]


def test_speed_is_linear(spark):
    row = spark.range(1).select(revisit.rescale(F.lit(3.0), 100, 3).alias("half"), revisit.to_days(F.lit(36000)).alias("day")).first()
    assert row.half == 6.0 and row.day == 1.0


@pytest.mark.parametrize("alpha", [0, 1.2])
def test_coverage_bounds(spark, alpha):
    with pytest.raises(ValueError):
        coverage.covers(alpha)


def test_walks_follow_edges_and_sessions_cut(spark):
    """0 leads to 1 and 1 stops, so a session is 0, 1, 1, 1, ... until its words exceed the limit."""
    edges = spark.createDataFrame([(0, 1, 5), (1, None, 5)], "u int, v int, n long")
    moves = browse.transitions(edges)
    assert all(abs(r.s - 1) < 1e-12 for r in moves.groupBy("u").agg(F.sum(F.col("hi") - F.col("lo")).alias("s")).collect())
    begun = spark.range(8).select(F.lit(10).alias("corpus_id"), F.lit(0).alias("s"), F.col("id").cast("int").alias("w"), F.lit(0).alias("u"), F.lit(4).cast("long").alias("n"))
    walked = browse.walks(begun, moves.withColumn("n", F.lit(3).cast("long")))
    kept = browse.sessions(walked)
    assert [(r.w, r.step, r.u) for r in kept.orderBy("w", "step").collect()] == [(0, 0, 0), (0, 1, 1), (1, 1, 1), (2, 1, 1)]
    assert browse.short_sessions(kept).first().short == 0


def test_a_start_that_always_stops_runs_short(spark):
    edges = spark.createDataFrame([(0, None, 1)], "u int, v int, n long")
    kept = browse.browse(edges, spark.createDataFrame([(0, 4)], "u int, n int"), (10,), 12)
    assert kept.count() == 3 and browse.short_sessions(kept).first().short == 3


def test_long_walks_and_sessions_are_whole(spark):
    """A ring that is left once in 40 pages: walks go on beyond any number of steps planned, and so do sessions."""
    n = 10
    edges = spark.createDataFrame([(i, (i + 1) % n, 39) for i in range(n)] + [(i, None, 1) for i in range(n)], "u int, v int, n long")
    kept = browse.browse(edges, spark.createDataFrame([(i, 1) for i in range(n)], "u int, n int"), (150,), 400).collect()
    sizes = [sum(r.s == s for r in kept) for s in {r.s for r in kept}]
    assert all(x == 151 for x in sizes) and 400 <= len(kept) <= 550 and max(r.step for r in kept) > 30


def test_topics_come_back_later_when_sessions_are_short(spark):
    """Two clusters with words of their own: a reader who switches often sees a cluster's words after longer pauses."""
    def history(run):
        order = [("p" if (i // run) % 2 == 0 else "q") for i in range(240)]
        found = corpus.occurrences(words(spark, [("x", i, f"{c}1 {c}2 {c}3") for i, c in enumerate(order)], F.floor(F.col("doc_id") / 16)))
        return revisit.analyse(found, (0.9,)).first().revisit_days

    assert history(2) > history(60)


def test_plan_has_no_single_task_over_words(spark, smoke):
    from embedvocab.plans import queries

    plan = queries.QUERIES["corpus_revisit_en"](spark, smoke)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BatchEvalPython" not in plan and "ArrowEvalPython" not in plan
    assert "PushedFilters: [IsNotNull(lang), EqualTo(lang,en)]" in plan
