"""Memory, context, selection, translation and rendering."""

import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from embedvocab.functions import memory, stats
from embedvocab.functions import text as txt
from embedvocab.functions.memory import Boost
from embedvocab.operators import context, corpus, guess, measure, render, select, translate, tutor


def one(spark, c):
    return spark.range(1).select(c.alias("x")).first().x


def exposures(spark, rows):
    df = spark.createDataFrame([(i, u, m, float(d), ok) for i, (u, m, d, ok) in enumerate(rows)], "event_id long, user_id long, lemma_id int, d double, success boolean")
    return df.withColumn("ts", F.timestamp_micros((F.col("d") * 86_400_000_000).cast("long"))).drop("d")


def test_memory_values(spark):
    assert one(spark, memory.recall(F.lit(3.0), F.lit(3.0))) == 0.5
    assert one(spark, memory.boost(F.lit(1.0), F.lit(1.0))) == 2
    assert one(spark, memory.boost(F.lit(32.0), F.lit(0.5))) == pytest.approx(1.707107, abs=1e-6)
    p = memory.understanding(F.lit(0.5), F.lit(0.5))
    assert one(spark, p) == 0.75 and one(spark, memory.priority(p, F.lit(2.0))) == 1.5
    with pytest.raises(ValueError):
        Boost(c=1.0)


def test_three_exposures(spark):
    state = tutor.replay(exposures(spark, [(1, 1, 0, True), (1, 1, 1, True), (1, 1, 3, True)])).first()
    assert state.exposures == 3 and state.half_life == pytest.approx(5.154, abs=1e-3)
    history = [r.half_life for r in tutor.history(exposures(spark, [(1, 1, 0, True), (1, 1, 1, True)])).orderBy("ts").collect()]
    assert history == pytest.approx([1, 2.414214], abs=1e-6)


@pytest.mark.parametrize(("lapse", "h"), [("keep", 1.0), ("reset", 1.0), ("shrink", 0.5)])
def test_lapses(spark, lapse, h):
    rows = exposures(spark, [(1, 1, 0, True), (1, 1, 1, False)])
    assert tutor.replay(rows, feedback="explicit", lapse=lapse).first().half_life == h


def test_never_seen_lemma_has_no_recall(spark):
    e = exposures(spark, [(1, 1, 5, True)])
    reads = exposures(spark, [(1, 1, 4, True), (1, 1, 6, True), (1, 2, 6, True)])
    got = {(r.lemma_id, r.t_days): r.r for r in tutor.state_asof(tutor.history(e), reads).collect()}
    assert got == {(1, None): 0.0, (1, 1.0): 0.5, (2, None): 0.0}


def test_free_schedule_is_due_at_the_target(spark):
    rows = tutor.free_schedule(spark.range(1).select(F.col("id").cast("int").alias("lemma_id"))).orderBy("revision").collect()
    for a, b in zip(rows, rows[1:]):
        assert 2 ** (-(b.day - a.day) / a.half_life) == pytest.approx(0.9)
        assert b.half_life > a.half_life


def test_stream_equals_batch(spark, smoke):
    from embedvocab.plans.queries import QUERIES

    a, b = (sorted(map(tuple, QUERIES[n](spark, smoke).collect())) for n in ("stream_tutor", "tutor_replay"))
    assert a == b


def test_stream_counts_late_rows_and_forgets(spark, tmp_path):
    from embedvocab.streaming import tutor_stream

    e = exposures(spark, [(1, 1, 5, True), (1, 2, 9, True), (1, 1, 3, True)]).withColumn("value", F.lit(1.0))
    for i in range(3):
        e.filter(F.col("event_id") == i).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = lambda: spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).option("latestFirst", "false").parquet(str(tmp_path / "in"))
    rows = tutor_stream.drained(tutor_stream.replay(stream())).filter("lemma_id = 1").collect()
    last = max(rows, key=lambda r: r.exposures)
    assert (last.exposures, last.late, last.last_day) == (2, 1, 5.0)
    kept = tutor_stream.drained(tutor_stream.replay(stream(), forget_days=2.0)).filter("lemma_id = 1").collect()
    assert max(r.exposures for r in kept) == 1 and len(kept) == 2


def test_language_models_sum_to_one(spark):
    docs = spark.createDataFrame([(1, "a b a b c a b".split()), (2, "c c a".split())], "doc_id long, words array<string>")
    runs = context.trigrams(docs)
    vocab = [r.w for r in runs.select("w").distinct().collect()]
    asked = spark.createDataFrame([(1, i, "a", "b", w) for i, w in enumerate(vocab)], "doc_id long, pos int, a string, b string, w string")
    for smoothing in ("interpolated", "kneser_ney", "kneser_ney_3"):
        total = context.NgramModel(runs, smoothing=smoothing).score(asked).agg(F.sum("g")).first()[0]
        assert total == pytest.approx(1.0), smoothing
    assert all(0 < r.g <= 1 for r in context.NgramModel(runs, smoothing="stupid_backoff").score(runs).collect())


def test_neural_adapter(spark):
    docs = spark.createDataFrame([(1, ["a", "b"]), (2, [])], "doc_id long, words array<string>")
    got = context.neural_scores(docs, lambda: lambda words: [1 / (i + 2) for i in range(len(words))]).collect()
    assert [(r.w, r.g) for r in got] == [("a", 0.5), ("b", 1 / 3)]


def test_top_k(spark):
    rows = spark.createDataFrame([(1, 0, "a", 2.0), (1, 1, "b", 3.0), (1, 2, "a", 2.0), (1, 3, "b", 1.0)], "doc_id long, pos int, lemma string, priority double")
    k = spark.createDataFrame([(1, 2), (2, 5)], "doc_id long, k int")
    pos = lambda df: sorted(r.pos for r in df.collect())
    assert pos(select.top_k(rows, k)) == [0, 1]
    assert pos(select.top_k(rows, k, per_lemma=1)) == [0, 1]
    assert pos(select.top_k(rows, k, per_lemma="all")) == [0, 1, 2, 3]
    assert pos(select.top_k(rows, k.withColumn("k", F.lit(9)))) == [0, 1, 2, 3]


def test_top_k_of_a_very_long_document(spark):
    rows = spark.range(12000).select(F.lit(1).cast("long").alias("doc_id"), F.col("id").cast("int").alias("pos"), F.concat(F.lit("w"), F.col("id") % 9000).alias("lemma"), (F.col("id") % 7).cast("double").alias("priority"))
    k = spark.createDataFrame([(1, 10000)], "doc_id long, k int")
    best = [p for _, p in sorted((-(p % 7), p) for p in range(12000))]
    assert sorted(r.pos for r in select.top_k(rows, k).collect()) == sorted(best[:10000])
    assert select.top_k(rows, k, per_lemma=1).count() == 9000


def test_rescoring_turns_to_other_lemmas(spark):
    rows = spark.createDataFrame([(1, 0, "a", 0.0, 0.6, None), (1, 1, "a", 0.0, 0.59, None), (1, 2, "b", 0.0, 0.1, None)], "doc_id long, pos int, lemma string, r double, g double, half_life double")
    k = spark.createDataFrame([(1, 2)], "doc_id long, k int")
    assert [r.pos for r in select.rescored(rows, k).orderBy("rank").collect()] == [0, 1]


def test_rescoring_equals_plain_greedy(spark):
    r = random.Random(2)
    items = [(1, i, r.choice("abcde"), r.choice([0.0, 0.3, 0.8]), round(r.random(), 2), r.choice([None, 2.0, 9.0])) for i in range(60)]
    df = spark.createDataFrame(items, "doc_id long, pos int, lemma string, r double, g double, half_life double")
    b, shown, left, want = Boost(), {}, list(items), []

    def worth(x):
        _, pos, lemma, recall, g, h = x
        h, gamma = h or b.initial, lambda h, recall: b.a * h**-b.b * b.c**-recall + b.d
        if lemma in shown:
            h, recall = h * gamma(h, recall), 1.0 if pos > shown[lemma] else recall
        return round((recall + g - recall * g) * gamma(h, recall), 9)

    for rank in range(1, 26):
        best = max(left, key=lambda x: (worth(x), -x[1]))
        want.append((best[1], worth(best), rank))
        left.remove(best)
        shown[best[2]] = min(best[1], shown.get(best[2], best[1]))
    got = select.rescored(df, spark.createDataFrame([(1, 25)], "doc_id long, k int")).orderBy("rank").collect()
    assert [(x.pos, x.priority, x.rank) for x in got] == want


def test_next_best_takes_the_place_of_words_without_translation(spark):
    from embedvocab.plans import pipeline

    docs = spark.createDataFrame([(1, "alpha beta gamma")], "doc_id long, text string")
    cands = spark.createDataFrame([(1, 0, "alpha", 0.0, 0.9, None), (1, 1, "beta", 0.0, 0.5, None), (1, 2, "gamma", 0.0, 0.1, None)], "doc_id long, pos int, lemma string, r double, g double, half_life double")
    k = spark.createDataFrame([(1, 1)], "doc_id long, k int")
    backend = translate.LexiconBackend(spark.createDataFrame([("beta", "de", 1, "B", []), ("gamma", "de", 1, "C", [])], "lemma string, target_lang string, sense int, target string, cues array<string>"))
    text = lambda **more: pipeline.augment(docs, cands, k, backend, **more).first().text
    assert text() == "alpha beta gamma" and text(promote=True) == text(spare=1) == "alpha B gamma"


def test_quizzes_are_explicit_feedback(spark):
    asked = exposures(spark, [(1, 1, 0, True), (1, 1, 1, True)])
    items = tutor.quiz_items(asked)
    assert items.filter("slot between 1 and 5").count() == 2
    right, wrong = (tutor.replay(tutor.quiz_feedback(items, c), feedback="explicit", lapse="shrink").first().half_life for c in (F.col("slot"), F.lit(0)))
    assert right > 2 and wrong == 0.25


def test_dictionary_lemmas(spark):
    words = spark.createDataFrame([(1, 0, "mice"), (1, 1, "mouse"), (1, 2, "cat")], "doc_id long, pos long, lemma string")
    dictionary = spark.createDataFrame([("mice", "mouse")], "word string, lemma string")
    assert [r.lemma for r in txt.lemmatize_by(words, dictionary).orderBy("pos").collect()] == ["mouse", "mouse", "cat"]


def test_three_word_units(spark):
    docs = spark.createDataFrame([(i, "x birds of a feather y".split()) for i in range(6)] + [(9, "a of birds".split())], "doc_id long, words array<string>")
    got = {(r.w1, r.w2, r.w3): r.n for r in select.collocations_3(context.trigrams(docs)).collect()}
    assert got["birds", "of", "a"] == 6 and ("a", "of", "birds") not in got


def test_segments_and_rewriting(spark):
    texts = ["One two, three.", " leading", "", "12 34", "ÀÉ l'été", None]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    parts = docs.select("text", F.array_join(txt.segments(F.col("text")), "").alias("back")).collect()
    assert all(r.text == r.back for r in parts)
    none = spark.createDataFrame([], "doc_id long, pos int, target string")
    assert {r.doc_id: r.text for r in render.rewrite(docs, none).collect()} == dict(enumerate(texts))
    chosen = spark.createDataFrame([(0, 1, "zwei"), (1, 0, "vorn"), (4, 2, "<sommer>")], "doc_id long, pos int, target string")
    got = {r.doc_id: r.text for r in render.rewrite(docs, chosen).collect()}
    assert got[0] == "One zwei, three." and got[1] == " vorn" and got[4] == "ÀÉ l'<sommer>" and got[5] is None
    marked = {r.doc_id: r.text for r in render.rewrite(docs, chosen, style="marked").collect()}
    assert marked[4] == "ÀÉ l'<mark data-original=\"été\">&lt;sommer&gt;</mark>"
    assert "original" not in render.rewrite(docs, chosen, style="marked", reveal=False).filter("doc_id = 0").first().text


def test_translation_follows_the_alignment(spark):
    lex = spark.createDataFrame([("bank", "de", 1, "Ufer", ["river"]), ("bank", "de", 2, "Geld", ["money", "loan"]), ("the", "de", 1, "die", [])], "lemma string, target_lang string, sense int, target string, cues array<string>")
    docs = spark.createDataFrame([(1, "The bank gave a loan for money. The bank."), (2, "nothing here")], "doc_id long, text string")
    chosen = spark.createDataFrame([(1, 1, "bank"), (1, 8, "bank"), (2, 0, "nothing")], "doc_id long, pos int, lemma string")
    plain = {(r.doc_id, r.pos): r.target for r in translate.in_context(chosen, docs, translate.LexiconBackend(lex)).collect()}
    assert plain == {(1, 1): "Ufer", (1, 8): "Ufer"}
    senses = {(r.doc_id, r.pos): r.target for r in translate.in_context(chosen, docs, translate.LexiconBackend(lex, senses=True)).collect()}
    assert senses == {(1, 1): "Geld", (1, 8): "Ufer"}


def test_service_backend(spark):
    docs = spark.createDataFrame([(1, "One two. One two.")], "doc_id long, text string")
    chosen = spark.createDataFrame([(1, 0, "one"), (1, 2, "one")], "doc_id long, pos int, lemma string")
    backend = translate.ServiceBackend(lambda: lambda batch: [(["deux", "un", "e"], [(0, 1), (0, 2), (1, 0)]) for _ in batch])
    assert [r.target for r in translate.in_context(chosen, docs, backend).collect()] == ["un e", "un e"]


def test_alignment_learns_a_swap(spark):
    pairs = spark.createDataFrame([(1, ["red", "house"], ["maison", "rouge"]), (2, ["house"], ["maison"]), (3, ["red"], ["rouge"]), (4, ["house", "red"], ["rouge", "maison"])], "pair_id long, src array<string>, tgt array<string>")
    t = {(r.e, r.f): r.t for r in translate.fit_alignment(pairs, 6).collect()}
    assert t["house", "maison"] > 0.9 and t["red", "rouge"] > 0.9


def test_alignment_reads_whole_turns(spark, tmp_path):
    from embedvocab.plans.queries import QUERIES

    r = random.Random(3)
    sides = [[[r.choice("abcdefghij") * 3 for _ in range(r.randint(9, 30))] for _ in range(2)] for _ in range(6)]
    rows = [(c, n, ("user", "assistant")[n], " ".join(words) + ".") for c, pair in enumerate(sides) for n, words in enumerate(pair)]
    spark.createDataFrame(rows, "conv_id long, turn int, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    t: dict = {}
    for _ in range(5):
        c, total = {}, {}
        for src, tgt in sides:
            for f in tgt:
                every = [None, *src]
                z = sum(t.get((e, f), 1.0 if not t else 0.0) for e in every)
                for e in every:
                    share = t.get((e, f), 1.0 if not t else 0.0) / z
                    c[e, f] = c.get((e, f), 0) + share
                    total[e] = total.get(e, 0) + share
        t = {(e, f): v / total[e] for (e, f), v in c.items()}
    got = {(x.e, x.f): x.t for x in QUERIES["word_alignment"](spark, str(tmp_path)).collect()}
    want = {k: v for k, v in t.items() if k[0] is not None}
    assert set(got) == set(want) and all(got[k] == pytest.approx(want[k], abs=2e-6) for k in want)


def learned(pairs, rounds):
    """Translation probabilities of (src, tgt) lists of words, cell by cell."""
    t = {(e, f): 1.0 for src, tgt in pairs for e in [None, *src] for f in tgt}
    for _ in range(rounds):
        c, total = dict.fromkeys(t, 0.0), {}
        for src, tgt in pairs:
            for f in tgt:
                z = sum(t[e, f] for e in [None, *src])
                for e in [None, *src]:
                    c[e, f] += t[e, f] / z
                    total[e] = total.get(e, 0) + t[e, f] / z
        t = {(e, f): v / total[e] for (e, f), v in c.items()}
    return t


def test_alignment_sends_no_pairs_of_words(spark):
    r = random.Random(8)
    sides = [[[r.choice("abcde") + r.choice("klmno") * r.randint(1, 9) for _ in range(60)] for _ in range(2)] for _ in range(30)]
    pairs = spark.createDataFrame([(i, *x) for i, x in enumerate(sides)], "pair_id long, src array<string>, tgt array<string>")
    store, none = spark.sparkContext._jsc.sc().statusStore(), spark._jvm.java.util.ArrayList()

    def sent():
        spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
        stages = store.stageList(none, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), none)
        return {stages.apply(i).stageId(): stages.apply(i).shuffleWriteRecords() for i in range(stages.size())}

    before = sent()
    got = {(x.e, x.f): x.t for x in translate.fit_alignment(pairs).collect()}
    want = learned(sides, 5)
    assert set(got) == set(want) and all(got[k] == pytest.approx(want[k], rel=1e-9) for k in want)
    cells = sum((1 + len(set(src))) * len(set(tgt)) for src, tgt in sides)
    rows = [n for stage, n in sent().items() if stage not in before]
    assert rows and sum(rows) < cells / 10, (sum(rows), cells)


def test_alignment_of_odd_pairs(spark):
    rows = [(1, ["a", "b"], ["x", "y", "x"]), (1, ["a", "c"], ["y"]), (2, None, ["x"]), (3, ["b"], None), (4, ["d"], []), (5, [], ["y", None]), (None, ["a"], ["x"])]
    pairs = spark.createDataFrame(rows, "pair_id long, src array<string>, tgt array<string>")
    # rows of one id are one pair, whose bag has the empty word twice; no source is the empty word alone
    whole = [([None, "a", "b", "a", "c"], ["x", "y", "x", "y"]), ([], ["x"]), ([], ["y"])]
    for rounds in (0, 1, 2, 6):
        got, want = {(x.e, x.f): x.t for x in translate.fit_alignment(pairs, rounds).collect()}, learned(whole, rounds)
        assert set(got) == set(want) and all(got[k] == pytest.approx(want[k], rel=1e-9) for k in want)
    assert translate.fit_alignment(pairs.limit(0)).collect() == []


def test_alignment_of_turns_without_text(spark, tmp_path):
    from embedvocab.plans.queries import QUERIES

    turns = [(1, 0, "user", "a b"), (1, 1, "assistant", "x y"), (2, 0, "user", None), (2, 1, "assistant", "x"), (3, 0, "user", "a"), (3, 1, "assistant", None)]
    spark.createDataFrame(turns, "conv_id long, turn int, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    want = {k: v for k, v in learned([(["a", "b"], ["x", "y"]), ([], ["x"])], 5).items() if k[0] is not None}
    got = {(x.e, x.f): x.t for x in QUERIES["word_alignment"](spark, str(tmp_path)).collect()}
    assert set(got) == set(want) and all(got[k] == pytest.approx(want[k], abs=2e-6) for k in want)


def test_alignment_of_a_word_in_many_pairs(monkeypatch):
    import pyarrow as pa

    from embedvocab.operators import alignment

    r = random.Random(9)
    sides = [([r.choice("abcdefgh") for _ in range(r.randint(0, 9))], ["the", *r.choices("klmnopqr", k=r.randint(0, 9))]) for _ in range(50)]
    known = pa.array([None, *"hgfedcba"])
    sums = [np.array([sum([None, *src].count(e) * len(tgt) / (1 + len(src)) for src, tgt in sides) for e in known.to_pylist()])]
    parts: dict = {}
    for half in (sides[:20], sides[20:]):
        for g, x in alignment._parts(pa.array([[None, *s] for s, _ in half]), pa.array([t for _, t in half]), known, 3):
            parts.setdefault(g, []).append(alignment._unpacked(x))
    want = learned(sides, 2)
    for batch in (1, 20, 100, 1 << 20):  # below 400 the pairs of "the" are formed in turns
        monkeypatch.setattr(alignment, "BATCH", batch)
        got: dict = {}
        for blocks in parts.values():
            block = alignment._merged(blocks)
            for e, f, c in alignment._expected(block, sums, len(known)):
                got |= {(known[int(a)].as_py(), block["words"][int(b)].as_py()): x for a, b, x in zip(e, f, c)}
        assert set(got) == set(want)
        whole = {e: sum(v for (x, _), v in got.items() if x == e) for e, _ in want}
        assert all(got[k] / whole[k[0]] == pytest.approx(want[k], rel=1e-9) for k in want)


def test_cognates_fold_first(spark):
    own = spark.createDataFrame([("philosopher",), ("house",)], "lemma string")
    other = spark.createDataFrame([("filosofi",), ("chambre",)], "lemma string")
    assert one(spark, txt.fold(F.lit("philosopher"))) == "filosofer"
    assert [r.lemma for r in txt.cognates(own, other).collect()] == ["philosopher"]


def test_cognates_are_compared_completely(spark):
    r = random.Random(4)
    words = sorted({"".join(r.choice("abeos") for _ in range(r.randint(3, 9))) for _ in range(160)})
    own, other = words[::2], words[1::2]

    def distance(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a):
            new = [i + 1]
            for j, y in enumerate(b):
                new.append(min(row[j] + (x != y), row[j + 1] + 1, new[j] + 1))
            row = new
        return row[-1]

    want = {a for a in own if any(distance(a, b) < 0.4 * max(len(a), len(b)) for b in other)}
    frame = lambda ws: spark.createDataFrame([(w,) for w in ws], "lemma string")
    assert {x.lemma for x in txt.cognates(frame(own), frame(other)).collect()} == want
    assert [x.lemma for x in txt.cognates(frame(["special"]), frame(["especial"])).collect()] == ["special"]


def test_stems(spark):
    words = {"cities": "city", "houses": "house", "cats": "cat", "bus": "bus", "glass": "glass"}
    for w, s in words.items():
        assert one(spark, txt.lemmatize(F.lit(w), "s_stem")) == s


def test_published_p_values(spark):
    """t and df as published, the p that belongs to them."""
    for t, df, p in [(4.5, 57, 3.40e-5), (4.4, 57, 4.80e-5), (3.8, 57, 3.54e-4), (0.52, 31, 0.607), (-0.19, 31, 0.851), (1.2, 28, 0.240), (2.0, 28, 0.0553), (6.5, 57, 2.16e-8)]:
        assert one(spark, stats.two_sided_p(F.lit(t), F.lit(df))) == pytest.approx(p, rel=5e-3)


def test_paired_t(spark):
    df = spark.createDataFrame([("x", 2.0, 1.0), ("x", 4.0, 2.0), ("x", 6.0, 3.0), ("y", 1.0, 1.0)], "g string, a double, b double")
    got = {r.g: r for r in stats.paired_t(df, ["g"], "a", "b").collect()}
    assert (got["x"].t, got["x"].df, got["x"].p) == (pytest.approx(3.464102, abs=1e-6), 2, pytest.approx(0.074180, abs=1e-6))
    assert got["y"].t is None and got["y"].p is None


def given(spark, flip):
    rows = []
    for u in range(30):
        for w in range(12):
            condition = ("embedded", "pre_table", "post_table")[(u + w) % 3]
            draw = zlib.crc32(f"{u}-{w}".encode()) % 100
            ok = draw < (80 if flip and condition == "embedded" else 30)
            rows.append((u, w, condition, "correct" if ok else ("unknown", "incorrect")[w % 2], "short"))
    return spark.createDataFrame(rows, "participant int, word int, condition string, outcome string, phase string")


def test_planted_effect_is_found_and_none_is_not(spark):
    found = measure.within(given(spark, True), "participant", ["phase"]).collect()
    assert all(r.t > 3 and r.p < 0.01 for r in found) and len(found) == 2
    assert all(r.p > 0.01 for r in measure.within(given(spark, False), "participant", ["phase"]).collect())


def test_retention_counts_unknown(spark):
    df = spark.createDataFrame([(1, o) for o in ("correct", "correct", "incorrect", "unknown")], "participant int, outcome string")
    assert measure.retention(df, ["participant"]).first().rate == 0.5


def test_grading_gaps(spark):
    asked = spark.createDataFrame([(1, " House "), (2, "hous"), (3, "home"), (4, ""), (5, "car")], "item int, answer string")
    keys = spark.createDataFrame([(i, "house") for i in range(1, 6)], "item int, key string")
    synonyms = spark.createDataFrame([("house", "home")], "word string, synonym string")
    got = {r.item: r.outcome for r in measure.grade_gaps(asked, keys, synonyms).collect()}
    assert got == {1: "correct", 2: "correct", 3: "correct", 4: "unknown", 5: "incorrect"}
    plural = spark.createDataFrame([(1, "cities"), (2, "towns")], "item int, answer string")
    assert {r.outcome for r in measure.grade_gaps(plural, spark.createDataFrame([(1, "city"), (2, "village")], "item int, key string"), spark.createDataFrame([("village", "town")], "word string, synonym string")).collect()} == {"correct"}


def test_share_never_clicked(spark):
    cells = spark.createDataFrame([(1, w, 0 if w else 2) for w in range(4)], "participant int, word int, clicks long")
    assert {r.clicks: r.share for r in measure.click_histogram(cells).collect()} == {0: 0.75, 2: 0.25}


def test_slowdown_and_overhead_differ(spark):
    speeds = spark.createDataFrame([(False, 199.0), (True, 163.0)], "treated boolean, wpm double")
    row = measure.overhead(measure.speed_summary(speeds)).first()
    assert row.slowdown == pytest.approx(0.181, abs=1e-3) and row.overhead == pytest.approx(0.221, abs=1e-3)


def test_regression_recovers_coefficients(spark):
    df = spark.range(200).select(F.col("id").cast("double").alias("a"), ((F.col("id") * 7) % 11).cast("double").alias("b")).withColumn("y", 2 * F.col("a") - 3 * F.col("b") + 5)
    beta = guess.fit(df, ["a", "b"], "y")
    assert (beta["_one"], beta["a"], beta["b"]) == pytest.approx((5, 2, -3))
    assert [r.feature for r in guess.rank_predictors(df, ["a", "b"], "y").collect()] == ["a", "b"]


def test_no_word_carries_its_sentence(spark):
    """Every word or chosen ones: the same translations, and texts are sent by document, at most once, never by sentence and word."""
    docs = spark.createDataFrame([(1, "One two. Three one two!"), (2, "One two."), (3, None), (4, "7 ?")], "doc_id long, text string")
    lex = spark.createDataFrame([("one", "de", 1, "eins", []), ("two", "de", 1, "zwei", [])], "lemma string, target_lang string, sense int, target string, cues array<string>")
    every = translate.in_context(None, docs, translate.LexiconBackend(lex))
    words = corpus.documents(docs, F.lit("en")).select("doc_id", F.posexplode("words").alias("pos", "lemma"))
    chosen = translate.in_context(words, docs, translate.LexiconBackend(lex))
    want = [(1, 0, "one", 0, "eins"), (1, 1, "two", 0, "zwei"), (1, 3, "one", 1, "eins"), (1, 4, "two", 1, "zwei"), (2, 0, "one", 0, "eins"), (2, 1, "two", 0, "zwei")]
    assert sorted(map(tuple, every.collect())) == sorted(map(tuple, chosen.collect())) == want
    assert "hashpartitioning" not in every._jdf.queryExecution().executedPlan().toString()
    assert "sent_key" not in chosen._jdf.queryExecution().optimizedPlan().toString()
    assert tuple(translate.cost(words, docs).first()) == (7, 2, len("one two") + len("three one two"))


def test_text_is_sent_no_more_often_than_needed(spark):
    """Runs that a model has counted are not looked up again, held-out bits come from distinct runs, and the same numbers come out."""
    docs = spark.createDataFrame([(i, [f"w{(i * j) % 7}" for j in range(i)]) for i in range(1, 30)], "doc_id long, words array<string>")
    runs = context.trigrams(docs)
    joins = lambda df: df._jdf.queryExecution().optimizedPlan().toString().count("Join ")
    for smoothing in ("interpolated", "kneser_ney", "kneser_ney_3", "stupid_backoff"):
        model = context.NgramModel(runs, smoothing=smoothing)
        own, other = model.score(runs), model.score(runs.select("*"))
        assert joins(own) < joins(other) and sorted(map(repr, own.collect())) == sorted(map(repr, other.collect()))
    model = context.NgramModel(runs.filter("doc_id % 2 <> 0"), smoothing="kneser_ney_3")
    plain = model.score(runs.filter("doc_id % 2 = 0"))
    want = plain.agg(F.count(F.lit(1)), F.sum((F.col("g") <= 0).cast("int")), F.avg(F.when(F.col("g") > 0, -F.log2("g")))).first()
    held = context.held_out(runs)
    got = held.filter("fold = 0").first()
    assert (got.words, got.unknown, got.bits) == (want[0], want[1], pytest.approx(want[2])) and joins(held) < 2 * joins(plain)


def test_runs_of_three_words_are_sent_packed(spark, monkeypatch):
    """Counted text is scored in blocks without a join: as joins score it, for any cut into blocks, buckets and parts, odd rows included."""
    from pyspark import cloudpickle

    from embedvocab.operators import packed

    texts = [(i, [f"w{(i * j) % 7}" for j in range(i)]) for i in range(1, 30)] + [(-3, ["w1", "only", "w1"]), (None, ["w2", "w1", "ß", ""]), (31, []), (32, None), (4, ["w1"])]
    runs = context.trigrams(spark.createDataFrame(texts, "doc_id long, words array<string>").coalesce(2))
    odd = runs.withColumn("more", F.when(F.col("pos") > 1, F.struct("w", "pos"))).withColumn("w", F.when(F.col("w") != "only", F.col("w"))).withColumn("day", F.when(F.col("pos") > 0, F.col("pos")))
    models = {smoothing: context.NgramModel(odd, smoothing=smoothing) for smoothing in ("interpolated", "kneser_ney_3")}
    joined = {smoothing: sorted(map(repr, model.score(odd.select("*")).collect())) for smoothing, model in models.items()}
    cloudpickle.register_pickle_by_value(packed)  # what the test sets holds on the workers too
    try:
        for block, words, parts in ((1 << 20, (1 << 21) - 2, (16, 1)), (100, 5, (3, 2)), (300, 8, (1, 1))):
            for name, value in (("BLOCK", block), ("WORDS", words), ("BATCH", 11), ("buckets", lambda _, parts=parts: parts)):
                monkeypatch.setattr(packed, name, value)
            for smoothing, model in models.items():
                own = model.score(odd)
                plan = own._jdf.queryExecution().optimizedPlan().toString()
                assert "Join " not in plan and "Aggregate" not in plan
                assert sorted(map(repr, own.collect())) == joined[smoothing]
        held = {r.fold: r for r in context.held_out(runs, folds=3).collect()}
    finally:
        cloudpickle.unregister_pickle_by_value(packed)
    for fold in range(3):
        scored = context.NgramModel(runs.filter(F.col("doc_id") % 3 != fold), smoothing="kneser_ney_3").score(runs.filter(F.col("doc_id") % 3 == fold))
        want = scored.agg(F.count(F.lit(1)), F.sum((F.col("g") <= 0).cast("int")), F.avg(F.when(F.col("g") > 0, -F.log2("g")))).first()
        assert (held[fold].words, held[fold].unknown, held[fold].bits) == (want[0], want[1], pytest.approx(want[2]))
    none = context.NgramModel(runs.filter("false"), smoothing="kneser_ney_3")
    assert none.score(none.runs).count() == 0 and [tuple(r) for r in context.held_out(none.runs).orderBy("fold").collect()] == [(0, 0, 0, None), (1, 0, 0, None)]
