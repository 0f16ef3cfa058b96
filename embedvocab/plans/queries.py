"""One query for each method, variant, baseline, measure and workload on the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from embedvocab.functions import memory, rng, stats
from embedvocab.functions import text as txt
from embedvocab.operators import browse, context, corpus, coverage, design, guess, measure, render, revisit, select, translate, tutor
from embedvocab.plans import fixtures as fx
from embedvocab.plans import pipeline
from embedvocab.sources.shared import stored
from embedvocab.sources.tables import exposures, table
from embedvocab.streaming import tutor_stream

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}


def query(f: Query) -> Query:
    QUERIES[f.__name__] = f
    return f


def rounded(df: DataFrame, *columns: str) -> DataFrame:
    """Columns rounded to six places, zero without a sign."""
    return df.withColumns({c: F.round(F.col(c), 6) + F.lit(0.0) for c in columns})


# ---------------------------------------------------------------- corpora

def _english(spark: SparkSession, sf_dir: str) -> DataFrame:
    return corpus.occurrences(corpus.number_words(fx.english_words(spark, sf_dir)))


@query
def corpus_revisit_en(spark, sf_dir):
    return rounded(revisit.analyse(_english(spark, sf_dir), (0.5, 0.7, 0.8, 0.9)), "revisit_days")


@query
def corpus_revisit_by_lang(spark, sf_dir):
    return rounded(revisit.analyse(corpus.occurrences(corpus.number_words(fx.by_language(spark, sf_dir))), fx.ALPHAS), "revisit_days")


@query
def corpus_revisit_s_stem(spark, sf_dir):
    """English with the plural endings off."""
    words = corpus.documents(fx.english(spark, sf_dir), F.lit("en"), "s_stem")
    return rounded(revisit.analyse(corpus.occurrences(corpus.number_words(words)), (0.5, 0.7, 0.8, 0.9)), "revisit_days")


@query
def corpus_revisit_dictionary(spark, sf_dir):
    """English lemmatized by a dictionary: forms whose stem is a word of the collection too."""
    words = corpus.number_words(fx.english_words(spark, sf_dir))
    return rounded(revisit.analyse(corpus.occurrences(txt.lemmatize_by(words, fx.form_dictionary(spark, sf_dir))), (0.5, 0.7, 0.8, 0.9)), "revisit_days")


@query
def lemma_revisit_top(spark, sf_dir):
    found = _english(spark, sf_dir)
    top = coverage.ranks(coverage.frequencies(found)).filter("rank <= 100").select("corpus_id", "lemma", "n", "rank")
    days = revisit.per_lemma(revisit.histogram(revisit.gaps(found.join(top.select("lemma"), "lemma", "left_semi").select(found.columns))))
    return rounded(top.join(days, ["corpus_id", "lemma"], "left").select("lemma", "n", "rank", F.col("days").alias("revisit_days")), "revisit_days")


@query
def corpus_revisit_sketched(spark, sf_dir):
    """Whether the sketched revisitation times lie within a tenth of the exact ones."""
    found = stored(_english(spark, sf_dir))
    exact, near = (revisit.analyse(found, (0.5, 0.9), estimator=e).select("corpus_id", "alpha", F.col("revisit_days").alias(e)) for e in ("exact", "kll"))
    both = exact.join(near, ["corpus_id", "alpha"])
    return rounded(both.select("corpus_id", "alpha", F.col("exact").alias("revisit_days"), (F.abs(F.col("kll") - F.col("exact")) <= 0.1 * F.col("exact")).alias("near")), "revisit_days")


@query
def vocabulary_sketched(spark, sf_dir):
    """Distinct lemmas of each language, and whether a HyperLogLog sketch counts them within a twentieth."""
    words = fx.by_language(spark, sf_dir).select("corpus_id", F.explode("words").alias("lemma"))
    sketched = words.groupBy("corpus_id").agg(F.hll_sketch_estimate(F.hll_sketch_agg("lemma", 14)).alias("_e"), F.countDistinct("lemma").alias("vocab"))
    return sketched.select("corpus_id", "vocab", (F.abs(F.col("_e") - F.col("vocab")) <= 0.05 * F.col("vocab")).alias("near"))


@query
def lemma_top_sketched(spark, sf_dir):
    """How many of the 20 most common lemmas of each language are among the 20 of an approximate top-k sketch: all but a few."""
    words = fx.by_language(spark, sf_dir).select("corpus_id", F.explode("words").alias("lemma"))
    sketched = words.groupBy("corpus_id").agg(F.expr("transform(approx_top_k(lemma, 20, 20000), x -> x.item)").alias("_top"))
    best = coverage.ranks(coverage.frequencies(corpus.occurrences(corpus.number_words(fx.by_language(spark, sf_dir))))).filter("rank <= 20")
    found = best.join(sketched, "corpus_id").groupBy("corpus_id").agg(F.sum(F.array_contains("_top", F.col("lemma")).cast("int")).alias("_n"), F.sum("n").alias("uses"))
    return found.select("corpus_id", "uses", (F.col("_n") >= 18).alias("near"))


@query
def corpus_gap_histogram(spark, sf_dir):
    hist = revisit.histogram(revisit.gaps(_english(spark, sf_dir)))
    return hist.groupBy(F.floor(revisit.to_days(F.col("gap"))).cast("int").alias("day_bucket")).agg(F.sum("count").alias("gaps"))


@query
def corpus_gaps_between(spark, sf_dir):
    hist = revisit.histogram(revisit.gaps(_english(spark, sf_dir), counting="between"))
    return hist.groupBy("corpus_id").agg(F.sum("count").alias("gaps"), F.sum(F.col("gap") * F.col("count")).alias("words_between"))


@query
def revisit_speed_sensitivity(spark, sf_dir):
    base = corpus_revisit_unrounded(spark, sf_dir)
    grid = spark.createDataFrame([(w, h) for w in (100, 200, 300, 400) for h in (1, 3, 5)], "wpm int, hours int")
    return rounded(base.crossJoin(F.broadcast(grid)).select("wpm", "hours", (F.col("revisit_days") * F.lit(600.0) / (F.col("wpm") * F.col("hours"))).alias("revisit_days")), "revisit_days")


def corpus_revisit_unrounded(spark, sf_dir):
    return revisit.analyse(_english(spark, sf_dir), (0.9,)).select("revisit_days")


def _books(spark, sf_dir):
    docs = fx.books(spark, sf_dir)
    return docs, revisit.analyse(corpus.occurrences(corpus.number_words(docs)), (0.9,))


@query
def book_revisit(spark, sf_dir):
    docs, found = _books(spark, sf_dir)
    joined = docs.select("corpus_id", "author", F.size("words").alias("n_words")).join(found, "corpus_id")
    return rounded(joined.select(F.col("corpus_id").alias("doc_id"), "author", "n_words", "vocab", "revisit_days"), "revisit_days")


@query
def book_vocab(spark, sf_dir):
    return book_revisit(spark, sf_dir).select("doc_id", "author", "n_words", "vocab")


@query
def book_revisit_summary(spark, sf_dir):
    docs, found = _books(spark, sf_dir)
    authors = docs.agg(F.countDistinct("author").alias("n_authors"))
    return rounded(revisit.summary(found, "revisit_days").withColumnRenamed("n", "n_books").crossJoin(authors), "q1", "median", "q3")


@query
def book_length_stats(spark, sf_dir):
    docs = fx.books(spark, sf_dir).select("author", F.size("words").alias("n_words"))
    return rounded(revisit.summary(docs, "n_words").withColumnRenamed("n", "n_books").crossJoin(docs.agg(F.countDistinct("author").alias("n_authors"))), "q1", "median", "q3")


@query
def author_revisit(spark, sf_dir):
    """Each source's English documents as one book."""
    docs = fx.english(spark, sf_dir)
    return rounded(revisit.analyse(corpus.occurrences(corpus.number_words(corpus.documents(docs, F.col("source")))), (0.9,)), "revisit_days")


# ---------------------------------------------------------------- browsing

def _grid(spark, sf_dir, limits=fx.LIMITS):
    return revisit.analyse(corpus.occurrences(fx.browsing_words(spark, sf_dir, limits)), fx.ALPHAS)


@query
def browse_revisit_grid(spark, sf_dir):
    return rounded(_grid(spark, sf_dir).withColumnRenamed("corpus_id", "session_words"), "revisit_days")


@query
def browse_vocab_by_alpha(spark, sf_dir):
    ranked = coverage.ranks(coverage.frequencies(corpus.occurrences(fx.browsing_words(spark, sf_dir))))
    return coverage.vocab_size(ranked, fx.ALPHAS).withColumnRenamed("corpus_id", "session_words")


@query
def daily_review_load(spark, sf_dir):
    grid = _grid(spark, sf_dir)
    return rounded(grid.select(F.col("corpus_id").alias("session_words"), "alpha", revisit.daily_load(F.col("vocab"), F.col("revisit_days")).alias("words_per_day")), "words_per_day")


@query
def browse_revisit_n100_a90(spark, sf_dir):
    read = stored(fx.browsing(spark, sf_dir, (100,)))
    cell = revisit.analyse(corpus.occurrences(fx.words_read(spark, sf_dir, read)), (0.9,))
    size = read.groupBy("corpus_id").agg(F.countDistinct("s").alias("sessions"), F.count(F.lit(1)).alias("page_views"), F.sum("n").alias("words"))
    out = size.join(cell, "corpus_id").withColumn("words_per_day", revisit.daily_load(F.col("vocab"), F.col("revisit_days")))
    return rounded(out.select("sessions", "page_views", "words", "vocab", "revisit_days", "words_per_day"), "revisit_days", "words_per_day")


@query
def browse_sessions(spark, sf_dir):
    return fx.browsing(spark, sf_dir).select(F.col("corpus_id").alias("session_words"), "s", "w", "step", "u", "n")


@query
def browse_short_sessions(spark, sf_dir):
    """Sessions that could not pass their limit, as their start is always followed by a stop."""
    return browse.short_sessions(fx.browsing(spark, sf_dir)).withColumnRenamed("corpus_id", "session_words")


@query
def browse_revisit_s_stem(spark, sf_dir):
    """The grid for lemmas in place of word forms."""
    words = fx.words_read(spark, sf_dir, fx.browsing(spark, sf_dir, (100, 10000)), "s_stem")
    return rounded(revisit.analyse(corpus.occurrences(words), fx.ALPHAS).withColumnRenamed("corpus_id", "session_words"), "revisit_days")


@query
def click_transitions(spark, sf_dir):
    return rounded(browse.transitions(browse.click_edges(exposures(spark, sf_dir), fx.page_count(spark, sf_dir))), "lo", "hi")


@query
def click_starts(spark, sf_dir):
    return rounded(browse.starts(browse.click_edges(exposures(spark, sf_dir), fx.page_count(spark, sf_dir))), "lo", "hi")


# ---------------------------------------------------------------- memory

@query
def tutor_replay(spark, sf_dir):
    return rounded(tutor.replay(exposures(spark, sf_dir)), "half_life", "last_day")


@query
def tutor_feedback(spark, sf_dir):
    return rounded(tutor.replay(exposures(spark, sf_dir), feedback="explicit", lapse="shrink"), "half_life", "last_day")


@query
def tutor_feedback_keep(spark, sf_dir):
    return rounded(tutor.replay(exposures(spark, sf_dir), feedback="explicit", lapse="keep"), "half_life", "last_day")


@query
def tutor_feedback_reset(spark, sf_dir):
    return rounded(tutor.replay(exposures(spark, sf_dir), feedback="explicit", lapse="reset"), "half_life", "last_day")


@query
def tutor_first_boost(spark, sf_dir):
    return rounded(tutor.replay(exposures(spark, sf_dir), first="boost"), "half_life", "last_day")


@query
def tutor_quiz(spark, sf_dir):
    """Purchases stand for embedded quizzes, whose answers are explicit feedback; all other events are exposures that succeed."""
    e = exposures(spark, sf_dir)
    quizzes = tutor.quiz_items(e.filter("event_type = 'purchase'"))
    graded = tutor.quiz_feedback(quizzes, 1 + F.floor(rng.uniform(42, F.lit("picked"), F.col("event_id")) * 5).cast("int"))
    shown = e.filter("event_type <> 'purchase'").withColumn("success", F.lit(True)).select(graded.columns)
    return rounded(tutor.replay(shown.unionByName(graded), feedback="explicit", lapse="shrink"), "half_life", "last_day")


@query
def tutor_recall_now(spark, sf_dir):
    states, now = fx.reader_states(spark, sf_dir)
    return rounded(tutor.recall_now(states.crossJoin(F.broadcast(now)), F.col("now")), "r", "gamma", "due_day")


@query
def tutor_due(spark, sf_dir):
    states, now = fx.reader_states(spark, sf_dir)
    return rounded(tutor.due(states.crossJoin(F.broadcast(now)), F.col("now")), "overdue_days")


@query
def tutor_asof(spark, sf_dir):
    e = exposures(spark, sf_dir)
    seen = tutor.history(e.filter("event_type <> 'view'"))
    return rounded(tutor.state_asof(seen, e.filter("event_type = 'view'")).select("event_id", "user_id", "lemma_id", "t_days", "r"), "t_days", "r")


@query
def tutor_free_schedule(spark, sf_dir):
    """The schedule of every lemma that readers have met."""
    return rounded(tutor.free_schedule(exposures(spark, sf_dir).select("lemma_id").filter("lemma_id is not null").distinct()), "day", "half_life")


@query
def tutor_slack(spark, sf_dir):
    return rounded(tutor.slack(exposures(spark, sf_dir)), "mean_delay")


@query
def stream_tutor(spark, sf_dir):
    got = tutor_stream.drained(tutor_stream.replay(tutor_stream.stream_of(spark, f"{sf_dir}/events.parquet")))
    # the last row of each pair is its state
    return rounded(got.groupBy("user_id", "lemma_id").agg(F.max("exposures").alias("exposures"), F.max_by("half_life", "exposures").alias("half_life"), F.max("last_day").alias("last_day")), "half_life", "last_day")


@query
def stream_clicks(spark, sf_dir):
    # the last count of a window is its largest
    got = tutor_stream.drained(tutor_stream.clicks(tutor_stream.stream_of(spark, f"{sf_dir}/events.parquet")))
    return got.groupBy("window_start", "user_id").agg(F.max("clicks").alias("clicks"))


@query
def reading_sessions(spark, sf_dir):
    return rounded(tutor_stream.reading_sessions(exposures(spark, sf_dir)), "hours")


@query
def clicks_sliding(spark, sf_dir):
    """Clicks of each reader in windows of a day, twice a day."""
    return tutor_stream.clicks(exposures(spark, sf_dir), slide="12 hours")


# ---------------------------------------------------------------- context

def _runs(spark, sf_dir):
    return context.trigrams(fx.english_words(spark, sf_dir))


def _pool(spark, sf_dir):
    return design.word_pool(fx.english(spark, sf_dir), fx.vocabulary(spark, sf_dir))


@query
def lm_bigram(spark, sf_dir):
    return rounded(context.bigrams(_runs(spark, sf_dir), 5), "p")


@query
def lm_trigram_score(spark, sf_dir):
    runs = _runs(spark, sf_dir)
    return rounded(context.NgramModel(runs).score(runs).select("doc_id", "pos", F.col("w").alias("lemma"), "g"), "g")


@query
def lm_kneser_ney(spark, sf_dir):
    runs = _runs(spark, sf_dir)
    return rounded(context.NgramModel(runs, smoothing="kneser_ney").score(runs).select("doc_id", "pos", F.col("w").alias("lemma"), "g"), "g")


@query
def lm_kneser_ney_trigram(spark, sf_dir):
    runs = _runs(spark, sf_dir)
    return rounded(context.NgramModel(runs, smoothing="kneser_ney_3").score(runs).select("doc_id", "pos", F.col("w").alias("lemma"), "g"), "g")


@query
def lm_held_out(spark, sf_dir):
    """Each half of the documents scored by the model of the other half."""
    return rounded(context.held_out(_runs(spark, sf_dir)), "bits")


@query
def lm_backoff(spark, sf_dir):
    runs = _runs(spark, sf_dir)
    return rounded(context.NgramModel(runs, smoothing="stupid_backoff").score(runs).select("doc_id", "pos", F.col("w").alias("lemma"), "g"), "g")


@query
def lm_frequency(spark, sf_dir):
    runs = _runs(spark, sf_dir)
    total = runs.agg(F.count(F.lit(1)).alias("_n"))
    return rounded(runs.groupBy(F.col("w").alias("lemma")).agg(F.count(F.lit(1)).alias("f_corpus")).crossJoin(F.broadcast(total)).select("lemma", "f_corpus", (F.col("f_corpus") / F.col("_n")).alias("g")), "g")


@query
def frequency_in_text(spark, sf_dir):
    return rounded(context.frequency_scores(_runs(spark, sf_dir), "both").select("doc_id", "pos", F.col("w").alias("lemma"), "g"), "g")


def _scored_words(spark, sf_dir):
    return fx.bigram_scores(fx.english_words(spark, sf_dir)).withColumnRenamed("lemma", "w").withColumn("g", F.round("g", 9))


@query
def easy_contexts(spark, sf_dir):
    return rounded(context.pick_contexts(_scored_words(spark, sf_dir), _pool(spark, sf_dir), mode="easy"), "g")


@query
def random_contexts(spark, sf_dir):
    return rounded(context.pick_contexts(_scored_words(spark, sf_dir), _pool(spark, sf_dir), mode="random"), "g")


# ---------------------------------------------------------------- selection

def _selected(spark, sf_dir, per_lemma=None, ablate=None):
    rows = select.scored(fx.candidates(spark, sf_dir), ablate=ablate)
    return select.top_k(rows, fx.budgets(spark, sf_dir), per_lemma)


def _shown(df):
    return rounded(df.select("doc_id", "pos", "lemma", "r", "g", "p", "gamma", "priority", "rank"), "r", "g", "p", "gamma", "priority")


@query
def select_topk(spark, sf_dir):
    return _shown(_selected(spark, sf_dir))


@query
def select_topk_lemma(spark, sf_dir):
    return _shown(_selected(spark, sf_dir, per_lemma=1))


@query
def select_tutor_only(spark, sf_dir):
    return _shown(_selected(spark, sf_dir, ablate="tutor_only"))


@query
def select_context_only(spark, sf_dir):
    return _shown(_selected(spark, sf_dir, ablate="context_only"))


@query
def select_random(spark, sf_dir):
    return _shown(_selected(spark, sf_dir, ablate="random"))


@query
def select_lookahead(spark, sf_dir):
    """The priority of words that come up again within the horizon grows with their coming uses."""
    ahead = select.lookahead(corpus.number_words(fx.english_words(spark, sf_dir))).select("doc_id", F.col("pos").alias("_at"), "lemma", "upcoming")
    first = corpus.number_words(fx.english_words(spark, sf_dir)).groupBy("doc_id").agg(F.min("pos").alias("_first"))
    local = ahead.join(first, "doc_id").select("doc_id", (F.col("_at") - F.col("_first")).cast("int").alias("pos"), "lemma", "upcoming")
    rows = select.scored(fx.candidates(spark, sf_dir).join(local, ["doc_id", "pos", "lemma"], "left"), ahead=0.25)
    return _shown(select.top_k(rows, fx.budgets(spark, sf_dir)))


@query
def select_topk_all(spark, sf_dir):
    """Every occurrence of the lemmas chosen by their best one."""
    return _shown(_selected(spark, sf_dir, per_lemma="all"))


@query
def select_rescored(spark, sf_dir):
    return rounded(select.rescored(fx.candidates(spark, sf_dir), fx.budgets(spark, sf_dir, 0.02)), "priority")


@query
def lookahead_weights(spark, sf_dir):
    return select.lookahead(corpus.number_words(fx.english_words(spark, sf_dir)))


@query
def collocations(spark, sf_dir):
    return rounded(select.collocations(_runs(spark, sf_dir)), "npmi")


@query
def collocations_llr(spark, sf_dir):
    return rounded(select.collocations(_runs(spark, sf_dir), score="llr"), "llr")


@query
def collocations_3(spark, sf_dir):
    return rounded(select.collocations_3(_runs(spark, sf_dir)), "npmi")


@query
def density_ramp(spark, sf_dir):
    """Where each reader stands on the ramp on each day of reading, counted from the reader's first."""
    density, direction = memory.schedule(F.col("day"))
    days = exposures(spark, sf_dir).select("user_id", F.to_date("ts").alias("_on")).distinct()
    first = days.groupBy(F.col("user_id").alias("_u")).agg(F.min("_on").alias("_first"))
    each = days.join(first, F.col("user_id").eqNullSafe(F.col("_u"))).select("user_id", F.date_diff("_on", "_first").alias("day"))
    return rounded(each.select("user_id", "day", density.alias("density"), direction.alias("direction")), "density")


# ---------------------------------------------------------------- translation

def _lexicon(spark, sf_dir, target="de"):
    return translate.lexicon(fx.vocabulary(spark, sf_dir), "en", target)


def _chosen(spark, sf_dir):
    return _selected(spark, sf_dir).select("doc_id", "pos", "lemma")


@query
def lexicon_de(spark, sf_dir):
    return _lexicon(spark, sf_dir).select("lemma", "target_lang", "sense", "target", F.array_join("cues", " ").alias("cues"))


@query
def translate_in_context(spark, sf_dir):
    return translate.in_context(_chosen(spark, sf_dir), fx.english(spark, sf_dir), translate.LexiconBackend(_lexicon(spark, sf_dir)))


@query
def translate_senses(spark, sf_dir):
    return translate.in_context(_chosen(spark, sf_dir), fx.english(spark, sf_dir), translate.LexiconBackend(_lexicon(spark, sf_dir), senses=True))


@query
def translate_reverse(spark, sf_dir):
    """Every word of the German documents that has an entry, in English."""
    docs = table(spark, sf_dir, "documents").filter("lang = 'de'")
    return translate.in_context(None, docs, translate.LexiconBackend(translate.reverse(_lexicon(spark, sf_dir).filter("sense = 1"))))


@query
def render_marked(spark, sf_dir):
    return render.rewrite(fx.english(spark, sf_dir), translate_in_context(spark, sf_dir), style="marked")


@query
def translate_cost(spark, sf_dir):
    return translate.cost(_chosen(spark, sf_dir), fx.english(spark, sf_dir))


@query
def augment_documents(spark, sf_dir):
    return pipeline.augment(fx.english(spark, sf_dir), fx.candidates(spark, sf_dir), fx.budgets(spark, sf_dir), translate.LexiconBackend(_lexicon(spark, sf_dir)))


@query
def augment_promoted(spark, sf_dir):
    """Only occurrences with a translation compete, so the next best takes the place of one without."""
    return pipeline.augment(fx.english(spark, sf_dir), fx.candidates(spark, sf_dir), fx.budgets(spark, sf_dir), translate.LexiconBackend(_lexicon(spark, sf_dir).filter("sense = 1 and rank <= 400")), promote=True)


@query
def converted_documents(spark, sf_dir):
    """The far end of the ramp: at density one every word with a translation is converted, in its sentence."""
    return pipeline.rendered(fx.english(spark, sf_dir), translate.in_context(None, fx.english(spark, sf_dir), translate.LexiconBackend(_lexicon(spark, sf_dir))))


@query
def word_alignment(spark, sf_dir):
    """Alignment learned from question and answer turns, whole, as parallel sentences."""
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    a, b = turns.filter("role = 'user'"), turns.filter("role = 'assistant'").select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("text").alias("answer"))
    # texts are joined, as words take several times their place in a row
    pairs = a.join(b, ["conv_id", "turn"]).select((F.col("conv_id") * 1000 + F.col("turn")).alias("pair_id"), txt.tokenize(F.col("text")).alias("src"), txt.tokenize(F.col("answer")).alias("tgt"))
    return rounded(translate.fit_alignment(pairs).filter("e is not null"), "t")


# ---------------------------------------------------------------- design

@query
def word_pool(spark, sf_dir):
    return _pool(spark, sf_dir)


@query
def word_groups(spark, sf_dir):
    return design.word_groups(_pool(spark, sf_dir))


@query
def participant_groups(spark, sf_dir):
    return fx.participants(spark, sf_dir)


@query
def design_balance(spark, sf_dir):
    return design.balance(fx.study_cells(spark, sf_dir))


@query
def snippet_pool(spark, sf_dir):
    return design.snippets(fx.english(spark, sf_dir)).select("doc_id", "n_words")


@query
def snippet_cover(spark, sf_dir):
    return design.cover(design.snippets(fx.english(spark, sf_dir)), design.word_groups(_pool(spark, sf_dir)).select("lemma", "wgroup"))


@query
def embedded_instances(spark, sf_dir):
    """The 7 uses of each word that the embedded section shows, 182 a group."""
    return rounded(design.instances(_scored_words(spark, sf_dir), design.word_groups(_pool(spark, sf_dir))), "g")


@query
def study_pages(spark, sf_dir):
    pool = design.snippets(fx.english(spark, sf_dir)).select("doc_id", "n_words")
    return design.study_pages(snippet_cover(spark, sf_dir).select("wgroup", "doc_id"), pool)


@query
def study_sections(spark, sf_dir):
    return design.sections(fx.participants(spark, sf_dir), design.assignment(spark))


@query
def control_page(spark, sf_dir):
    return design.control_page(design.snippets(fx.english(spark, sf_dir)).select("doc_id", "n_words"))


@query
def mc_items(spark, sf_dir):
    return design.mc_items(fx.participants(spark, sf_dir), fx.study_words(spark, sf_dir))


@query
def mc_retest(spark, sf_dir):
    return design.retest(design.mc_items(fx.participants(spark, sf_dir), fx.study_words(spark, sf_dir)))


@query
def mc_items_reverse(spark, sf_dir):
    """The items asked from the base language to the other: what active knowledge needs."""
    words = _pool(spark, sf_dir).select((F.col("rank") - 1).cast("int").alias("word"), "lemma")
    return design.reverse_items(design.mc_items(fx.participants(spark, sf_dir), fx.study_words(spark, sf_dir)), _lexicon(spark, sf_dir).filter("sense = 1"), words)


@query
def ftg_graded(spark, sf_dir):
    """Gap answers with inflections, typing errors, synonyms and other words, graded."""
    given, keys, synonyms = fx.gap_answers(_pool(spark, sf_dir), fx.vocabulary(spark, sf_dir))
    return measure.grade_gaps(given, keys, synonyms)


@query
def ftg_items(spark, sf_dir):
    return design.ftg_items(fx.study_cells(spark, sf_dir))


@query
def chance_baseline(spark, sf_dir):
    """What guessing among the five candidates gives: one in five, and drawn once for each item."""
    items = design.mc_items(fx.participants(spark, sf_dir), fx.study_words(spark, sf_dir)).filter("slot > 0")
    pick = 1 + F.floor(rng.uniform(42, F.lit("guess"), F.col("participant"), F.col("word")) * 5)
    return rounded(items.filter(F.col("slot") == pick).agg(F.count(F.lit(1)).alias("items"), F.lit(0.2).alias("expected"), F.avg(F.col("is_answer").cast("double")).alias("simulated")), "simulated")


@query
def participant_profile(spark, sf_dir):
    people = table(spark, sf_dir, "customer").join(F.broadcast(table(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select(F.col("c_acctbal").alias("balance"), F.col("n_name").alias("nation"), F.col("c_mktsegment").alias("segment"))
    return rounded(design.describe(people, "balance", ["nation", "segment"]), "share", "mean", "sd")


# ---------------------------------------------------------------- measures

BY = ["component", "phase"]


@query
def rq1_retention(spark, sf_dir):
    return rounded(measure.mean_over_users(fx.answers(spark, sf_dir), [*BY, "condition"]), "mean", "lo", "hi")


@query
def rq1_totals(spark, sf_dir):
    """Answers and correct ones by component, phase and condition, with subtotals; null stands for all."""
    return fx.answers(spark, sf_dir).rollup("component", "phase", "condition").agg(F.count(F.lit(1)).alias("answers"), F.sum(measure.correct()).cast("long").alias("correct"))


@query
def rq1_answer_mix(spark, sf_dir):
    return rounded(measure.answer_mix(fx.answers(spark, sf_dir), [*BY, "condition"]), "share", "lo", "hi")


@query
def rq1_ttests(spark, sf_dir):
    return rounded(measure.within(fx.answers(spark, sf_dir), "participant", BY), "mean_diff", "t", "p")


@query
def rq1_within_user(spark, sf_dir):
    return rounded(measure.within(fx.answers(spark, sf_dir), "participant", ["phase"]), "mean_diff", "t", "p")


@query
def rq1_within_word(spark, sf_dir):
    return rounded(measure.within(fx.answers(spark, sf_dir), "word", ["phase"]), "mean_diff", "t", "p")


@query
def rq1_boxplot(spark, sf_dir):
    given = fx.answers(spark, sf_dir)
    both = None
    for unit in ("participant", "word"):
        rows = stats.box(measure.differences(given, unit, ["phase"]).withColumn("diff", F.round("diff", 9)), ["phase", "versus"], "diff").withColumn("unit", F.lit(unit))
        both = rows if both is None else both.unionByName(rows)
    return rounded(both.select("unit", "phase", "versus", "lo_whisker", "q1", "median", "q3", "hi_whisker", "outliers"), "lo_whisker", "q1", "median", "q3", "hi_whisker")


@query
def rq2_click_histogram(spark, sf_dir):
    return rounded(measure.click_histogram(fx.cell_clicks(spark, sf_dir)), "share")


@query
def rq2_easiness_by_clicks(spark, sf_dir):
    easy = measure.easiness(fx.answers(spark, sf_dir).filter("component = 'mc'"))
    return rounded(stats.mean_ci(fx.cell_clicks(spark, sf_dir).join(easy, "word"), ["clicks"], "easiness", "cells"), "mean", "lo", "hi")


@query
def rq2_retention_by_clicks(spark, sf_dir):
    given = fx.answers(spark, sf_dir).filter("component = 'mc' and condition = 'embedded'").drop("arm")
    rows = given.join(fx.cell_clicks(spark, sf_dir), ["participant", "word"]).withColumn("ok", measure.correct())
    return rounded(stats.mean_ci(rows, ["clicks", "phase"], "ok", "cells"), "mean", "lo", "hi")


@query
def rq3_speed(spark, sf_dir):
    return rounded(measure.speed_summary(measure.speed(fx.page_times(spark, sf_dir))), "median_wpm", "q1", "q3")


@query
def rq3_overhead(spark, sf_dir):
    times = fx.page_times(spark, sf_dir)
    both = measure.overhead(measure.speed_summary(measure.speed(times)))
    return rounded(both.crossJoin(design.overhead_time(times).agg(F.avg("delta_minutes").alias("delta_minutes"))), "slowdown", "overhead", "delta_minutes")


def _by_context(given):
    rates = measure.retention(given, ["phase", "arm", "participant"])
    wide = rates.groupBy("phase", "participant").pivot("arm", ["easy", "random"]).agg(F.first("rate"))
    test = stats.paired_t(wide, ["phase"], "easy", "random").select("phase", "t", "p")
    return rounded(stats.mean_ci(rates, ["phase", "arm"], "rate").join(test, "phase"), "mean", "lo", "hi", "t", "p")


@query
def rq4_context_effect(spark, sf_dir):
    return _by_context(fx.answers(spark, sf_dir).filter("component = 'mc' and condition = 'embedded'"))


@query
def rq4_never_clicked(spark, sf_dir):
    never = fx.cell_clicks(spark, sf_dir).filter("clicks = 0").select("participant", "word")
    return _by_context(fx.answers(spark, sf_dir).filter("component = 'mc' and condition = 'embedded'").join(never, ["participant", "word"], "left_semi"))


@query
def rq5_mnemonics(spark, sf_dir):
    return rounded(measure.mnemonics(fx.codes(spark, sf_dir)), "share")


@query
def rq5_ratio(spark, sf_dir):
    return rounded(measure.conservative_ratio(measure.mnemonics(fx.codes(spark, sf_dir))), "ratio")


@query
def guess_moments(spark, sf_dir):
    return guess.moments(fx.guess_rows(spark, sf_dir), ["log_corpus", "log_text", "log_g", "y"]).withColumn("sum_xy", F.round("sum_xy", 4))


@query
def guess_rank(spark, sf_dir):
    return rounded(guess.rank_predictors(stored(fx.guess_rows(spark, sf_dir)), ["log_corpus", "log_text", "log_g"], "y"), "beta_std")
