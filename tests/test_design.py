import pytest
from pyspark.sql import functions as F

from embedvocab.operators import design
from embedvocab.plans import fixtures as fx
from embedvocab.plans.queries import QUERIES


def test_everybody_meets_every_word_once(spark, smoke):
    cells = fx.study_cells(spark, smoke)
    per = cells.groupBy("participant").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("word").alias("w")).collect()
    assert len(per) == 58 and all((r.n, r.w) == (78, 78) for r in per)
    assert all(r["count"] == 26 for r in cells.groupBy("participant", "condition").count().collect())
    assert cells.groupBy("word").agg(F.countDistinct("condition").alias("c")).filter("c <> 3").count() == 0
    sizes = [r["count"] for r in fx.participants(spark, smoke).groupBy("pgroup").count().collect()]
    assert max(sizes) - min(sizes) <= 1 and len(sizes) == 6


def test_multiple_choice_items(spark, smoke):
    items = design.mc_items(fx.participants(spark, smoke).filter("participant < 3"), fx.study_words(spark, smoke))
    per = items.groupBy("participant", "word").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("is_answer").cast("int")).alias("a"), F.countDistinct("option").alias("o"), F.max(F.when(F.col("slot") == 0, F.col("option"))).alias("first"))
    assert all((r.n, r.a, r.o, r.first) == (6, 1, 6, "don't know") for r in per.collect())
    again = design.retest(items)
    assert again.filter("slot = 0").select("option").distinct().count() == 1 and again.join(items, ["participant", "word", "option", "slot"]).count() < items.count()


def test_a_third_is_asked_as_gaps(spark, smoke):
    gaps = design.ftg_items(fx.study_cells(spark, smoke))
    assert all(r["count"] == 24 for r in gaps.groupBy("participant").count().collect())


def test_cover_is_greedy_whatever_is_held(spark):
    texts = {1: "x x y", 2: "x y y z", 3: "z", 4: "z z x", 5: "q"}
    pool = spark.createDataFrame([(d, t.split()) for d, t in texts.items()], "doc_id long, words array<string>")
    words = spark.createDataFrame([(w, 0) for w in "xyz"], "lemma string, wgroup int")
    need, want = dict.fromkeys("xyz", 3), []
    while any(need.values()):
        gain = {d: sum(min(t.split().count(w), n) for w, n in need.items()) for d, t in texts.items() if d not in [c[2] for c in want]}
        best = min(gain, key=lambda d: (-gain[d], d)) if gain else None
        if best is None or not gain[best]:
            break
        want.append((0, len(want) + 1, best, gain[best]))
        need = {w: max(0, n - texts[best].split().count(w)) for w, n in need.items()}
    for held in (1, 2, 1000):
        assert sorted(map(tuple, design.cover(pool, words, quota=3, held=held).collect())) == want


def test_sections_and_pages(spark, smoke):
    rows = design.sections(fx.participants(spark, smoke), design.assignment(spark)).collect()
    assert len(rows) == 3 * 58 and all(r.section == {"pre_table": 1, "embedded": 2, "post_table": 3}[r.condition] for r in rows)
    chosen = spark.createDataFrame([(g, 100 * g + i) for g in range(3) for i in range(42)], "wgroup int, doc_id long")
    pool = spark.range(1000).select(F.col("id").alias("doc_id"), F.lit(200).alias("n_words"))
    pages = design.study_pages(chosen, pool).collect()
    for g in range(3):
        own = [p for p in pages if p.wgroup == g]
        sizes = [sum(p.page == i for p in own) for i in range(1, 7)]
        assert sizes == [10, 10, 10, 10, 2, 5] and [p.treated for p in own if p.page == 6] == [False] * 5


def test_each_word_is_used_seven_times(spark):
    scored = spark.range(400).select((F.col("id") % 7).alias("doc_id"), F.col("id").cast("int").alias("pos"), F.concat(F.lit("w"), F.col("id") % 4).alias("w"), (F.col("id") % 13 / 13).alias("g"))
    groups = spark.createDataFrame([(f"w{i}", 0, ("easy", "random")[i % 2]) for i in range(4)], "lemma string, wgroup int, arm string")
    got = design.instances(scored, groups).collect()
    assert len(got) == 28 and {(r.lemma, r.arm) for r in got} == {(f"w{i}", ("easy", "random")[i % 2]) for i in range(4)}


def test_reverse_items_ask_for_the_translation(spark, smoke):
    items = design.mc_items(fx.participants(spark, smoke).filter("participant < 2"), fx.study_words(spark, smoke))
    words = spark.range(78).select(F.col("id").cast("int").alias("word"), F.concat(F.lit("en"), "id").alias("lemma"))
    lexicon = words.select("lemma", F.concat(F.lit("de"), "word").alias("target"))
    got = design.reverse_items(items, lexicon, words)
    assert got.count() == items.count() and got.filter("is_answer").filter("substr(prompt, 3) <> substr(option, 3)").count() == 0
    assert got.filter((F.col("slot") == 0) & (F.col("option") != "don't know")).count() == 0


@pytest.mark.parametrize(("name", "tables"), [
    ("participant_groups", ["customer"]), ("study_sections", ["customer"]), ("design_balance", ["customer", "part"]), ("ftg_items", ["customer", "part"]), ("mc_items", ["customer", "part"]),
    ("mc_retest", ["customer", "part"]), ("chance_baseline", ["customer", "part"]), ("tutor_free_schedule", ["events"]), ("density_ramp", ["events"])])
def test_study_is_made_of_given_tables(spark, smoke, name, tables):
    read = QUERIES[name](spark, smoke).inputFiles()
    assert sorted(f.rsplit("/", 1)[1] for f in read) == [f"{t}.parquet" for t in tables]
