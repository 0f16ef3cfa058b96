"""The study's and the corpora's inputs on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from embedvocab.functions import rng
from embedvocab.functions import text as txt
from embedvocab.operators import browse, context, corpus, coverage, design, tutor
from embedvocab.sources.tables import exposures, table

ALPHAS = (0.5, 0.6, 0.7, 0.8, 0.9)
#: Words after which a simulated session ends.
LIMITS = (100, 1000, 10000, 100000)
PARTICIPANTS, BOOK_WORDS = 58, 1000


def english(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").filter("lang = 'en'")


def by_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(corpus_id, doc_id, words): the collection of each language as one reading history."""
    return corpus.documents(table(spark, sf_dir, "documents"), F.col("lang"))


def english_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return corpus.documents(english(spark, sf_dir), F.lit("en"))


def vocabulary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(corpus_id, lemma, n, rank) of every language."""
    counts = by_language(spark, sf_dir).select("corpus_id", F.explode("words").alias("lemma")).groupBy("corpus_id", "lemma").agg(F.count(F.lit(1)).alias("n"))
    return coverage.ranks(counts).select("corpus_id", "lemma", "n", "rank")


def form_dictionary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(word, lemma): English forms whose stem occurs as a word by itself."""
    words = english_words(spark, sf_dir).select(F.explode("words").alias("word")).distinct()
    stemmed = words.withColumn("lemma", txt.lemmatize(F.col("word"), "s_stem")).filter("word <> lemma")
    return stemmed.join(words.select(F.col("word").alias("lemma")), "lemma", "left_semi").select("word", "lemma")


def gap_answers(pool: DataFrame, vocab: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Answers (item, answer), keys (item, key) and synonyms (word, synonym) over the word pool.

    In turn an answer is the key, its plural, the key with its second letter twice, its synonym, the next key, blank, or nothing. The
    synonym of a key is the English word of twice its rank plus 500.
    """
    keys = pool.select((F.col("rank") - 1).cast("int").alias("item"), F.col("lemma").alias("key"))
    others = vocab.filter("corpus_id = 'en'").select(F.col("rank").alias("_r"), F.col("lemma").alias("synonym"))
    synonyms = keys.withColumn("_r", F.col("item") * 2 + 502).join(others, "_r").select(F.col("key").alias("word"), "synonym")
    after = keys.select((F.col("item") - 1).alias("item"), F.col("key").alias("_next"))
    rows = keys.join(after, "item", "left").join(synonyms, F.col("key") == F.col("word"), "left")
    doubled = F.concat(F.substring("key", 1, 2), F.col("key").substr(F.lit(2), F.length("key")))
    kinds = [F.initcap("key"), F.concat("key", F.lit("s")), doubled, F.col("synonym"), F.col("_next"), F.lit("  "), F.lit(None).cast("string")]
    answer = F.element_at(F.array(*kinds), (F.col("item") % len(kinds) + 1).cast("int"))
    return rows.select("item", answer.alias("answer")), keys, synonyms


def books(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(corpus_id, author, doc_id, words): English documents long enough to count as books, each its own corpus."""
    docs = english(spark, sf_dir).select(F.col("doc_id").alias("corpus_id"), F.col("source").alias("author"), "doc_id", txt.tokenize(F.col("text")).alias("words"))
    return docs.filter(F.size("words") >= BOOK_WORDS)


def page_count(spark: SparkSession, sf_dir: str) -> int:
    return table(spark, sf_dir, "pages").count()


def page_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(u, words) of each page's article."""
    return table(spark, sf_dir, "pages").select(F.col("page_id").cast("int").alias("u"), txt.tokenize(txt.article_text(F.col("html"))).alias("words"))


def browsing(spark: SparkSession, sf_dir: str, limits: tuple[int, ...] = LIMITS, total: int | None = None) -> DataFrame:
    """(corpus_id, s, w, step, u, n): one corpus of sessions for each limit, of as many words as 800 a page in all (two million over 2,500 pages) or the total."""
    pages = page_count(spark, sf_dir)
    lengths = page_words(spark, sf_dir).select("u", F.size("words").alias("n"))
    return browse.browse(browse.click_edges(exposures(spark, sf_dir), pages), lengths, limits, 800 * pages if total is None else total)


def browsing_words(spark: SparkSession, sf_dir: str, limits: tuple[int, ...] = LIMITS) -> DataFrame:
    """(corpus_id, block, doc_id, pos, lemma) of the browsed corpora."""
    return words_read(spark, sf_dir, browsing(spark, sf_dir, limits))


def words_read(spark: SparkSession, sf_dir: str, read: DataFrame, method: str = "identity") -> DataFrame:
    """The words of browsed pages as positions, lemmatized by the method."""
    words = page_words(spark, sf_dir).withColumn("words", F.transform("words", lambda w: txt.lemmatize(w, method)))
    return corpus.number_words(read.join(words, "u").withColumnRenamed("s", "doc_id"), ["doc_id", "w", "step"], F.floor(F.col("doc_id") / 256))


def reader_states(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Every reader's replayed state, and the (day) of the last event."""
    e = exposures(spark, sf_dir)
    return tutor.replay(e), e.agg(F.max(tutor.in_days(F.col("ts"))).alias("now"))


def bigram_scores(docs: DataFrame) -> DataFrame:
    """(doc_id, pos, lemma, g): each word after its left neighbour, mixed with its share of all words."""
    runs = context.trigrams(docs)
    return context.NgramModel(runs, (0.0, 0.7, 0.3)).score(runs).select("doc_id", "pos", F.col("w").alias("lemma"), F.col("g"))


def candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, user_id, pos, lemma, r, g, half_life): each English document read by one reader; lemmas of rank up to 100 may be known."""
    docs = english_words(spark, sf_dir)
    users = table(spark, sf_dir, "events").agg(F.countDistinct("user_id").alias("_users"))
    known = vocabulary(spark, sf_dir).filter("corpus_id = 'en' and rank <= 100").select("lemma", (F.col("rank") - 1).cast("int").alias("lemma_id"))
    states, now = reader_states(spark, sf_dir)
    current = states.crossJoin(F.broadcast(now)).select("user_id", "lemma_id", tutor.recall(F.col("now") - F.col("last_day"), F.col("half_life")).alias("_r"), F.col("half_life").alias("_h"))
    words = bigram_scores(docs).crossJoin(F.broadcast(users)).withColumn("user_id", F.col("doc_id") % F.col("_users"))
    rows = words.join(F.broadcast(known), "lemma", "left").join(current, ["user_id", "lemma_id"], "left")
    rows = rows.filter((F.length("lemma") >= 3) & ~F.col("lemma").isin(txt.STOPWORDS))
    return rows.select("doc_id", "user_id", "pos", "lemma", F.coalesce("_r", F.lit(0.0)).alias("r"), "g", F.col("_h").alias("half_life"))


def budgets(spark: SparkSession, sf_dir: str, density: float = 0.05) -> DataFrame:
    """(doc_id, k)."""
    from embedvocab.functions.memory import budget

    return english_words(spark, sf_dir).select("doc_id", budget(F.size("words"), density).alias("k"))


# ---------------------------------------------------------------- the study

def participants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(participant, pgroup): customers by number, who are dealt to so many participants."""
    people = table(spark, sf_dir, "customer").filter("c_custkey is not null").select((F.col("c_custkey") % PARTICIPANTS).cast("int").alias("participant")).distinct()
    return design.participant_groups(people)


def study_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(word, wgroup, arm): parts by number, which are dealt to so many words; each group of 26 has 13 easy and 13 random ones."""
    w = table(spark, sf_dir, "part").filter("p_partkey is not null").select((F.col("p_partkey") % design.PICK).cast("int").alias("word")).distinct()
    return w.select("word", (F.col("word") % 3).alias("wgroup"), F.when(F.floor(F.col("word") / 3) % 2 == 0, "easy").otherwise("random").alias("arm"))


def study_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    return design.cells(participants(spark, sf_dir), study_words(spark, sf_dir), design.assignment(spark))


def answers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(participant, word, condition, arm, component, phase, outcome): the first line of each cell and status as a test answer."""
    lines, orders = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "orders")
    rows = lines.join(orders.select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).select(
        (F.col("o_custkey") % PARTICIPANTS).cast("int").alias("participant"), (F.col("l_partkey") % design.PICK).cast("int").alias("word"), "l_linestatus", "l_returnflag",
        F.struct("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_returnflag").alias("_first"))
    first = rows.groupBy("participant", "word", "l_linestatus").agg(F.min("_first")["l_returnflag"].alias("flag"))
    answered = first.select("participant", "word", F.when(F.col("l_linestatus") == "F", "short").otherwise("long").alias("phase"),
                            F.when(F.col("flag") == "R", "correct").when(F.col("flag") == "A", "incorrect").otherwise("unknown").alias("outcome"))
    every = study_cells(spark, sf_dir)
    gaps = design.ftg_items(every)
    both = every.withColumn("component", F.lit("mc")).unionByName(every.join(gaps, ["participant", "word"], "left_semi").withColumn("component", F.lit("ftg")))
    # who came back for the long-term test: 32 for multiple choice, 29 for gaps
    back = F.row_number().over(Window.orderBy(rng.order(42, F.lit("back"), F.col("participant")), "participant"))
    returned = participants(spark, sf_dir).select("participant", back.alias("_turn"))
    joined = answered.join(both, ["participant", "word"]).join(F.broadcast(returned), "participant")
    kept = joined.filter((F.col("phase") == "short") | (F.col("_turn") <= F.when(F.col("component") == "mc", 32).otherwise(29)))
    return kept.select("participant", "word", "condition", "arm", "component", "phase", "outcome")


def cell_clicks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(participant, word, arm, clicks) of all embedded cells, those without clicks included."""
    clicks = exposures(spark, sf_dir).filter("event_type = 'click'").groupBy((F.col("user_id") % PARTICIPANTS).cast("int").alias("participant"), (F.col("lemma_id") % design.PICK).alias("word")).agg(F.count(F.lit(1)).alias("clicks"))
    return study_cells(spark, sf_dir).filter("condition = 'embedded'").join(clicks, ["participant", "word"], "left").select("participant", "word", "arm", F.coalesce("clicks", F.lit(0)).alias("clicks"))


def page_times(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(participant, words, minutes, treated): views are untreated pages, clicks treated ones."""
    pages = page_count(spark, sf_dir)
    e = exposures(spark, sf_dir).filter("event_type in ('view', 'click') and value > 0").select((F.col("user_id") % PARTICIPANTS).cast("int").alias("participant"), browse.page_state(pages).alias("u"), (F.col("value") / 60).alias("minutes"), (F.col("event_type") == "click").alias("treated"))
    return e.join(page_words(spark, sf_dir).select("u", F.size("words").alias("words")), "u").select("participant", "words", "minutes", "treated")


def codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(arm, broad, narrow): two codings of the labelled rows."""
    return table(spark, sf_dir, "labels").select(F.when(F.col("doc_id") % 2 == 0, "embedded").otherwise("table").alias("arm"),
                                                 ((F.col("quality") == 1) | (F.col("toxic") == 1)).cast("double").alias("broad"), ((F.col("quality") == 1) & (F.col("toxic") == 1)).cast("double").alias("narrow"))


def guess_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, y, log_corpus, log_text, log_g): one fixed random word of each labelled English document, and how good the document is."""
    docs = english_words(spark, sf_dir)
    marked = table(spark, sf_dir, "labels").select("doc_id", F.col("quality").cast("double").alias("y"))
    counts = docs.select(F.explode("words").alias("lemma")).groupBy("lemma").agg(F.count(F.lit(1)).alias("n"))
    # the word is picked inside its text, before anything is sent; the model counts all words and scores the picked ones
    places = F.transform("words", lambda _, i: F.struct(rng.order(42, F.col("doc_id"), i).alias("o"), i.alias("pos")))
    at = docs.filter(F.size("words") > 0).withColumn("pos", F.array_min(places)["pos"])
    w = lambda i: F.get("words", F.col("pos") - i)
    own = F.size(F.filter("words", lambda x: x == w(0))) / F.size("words")
    picked = at.select("doc_id", w(1).alias("b"), w(0).alias("w"), own.alias("_own")).join(marked, "doc_id")
    scored = context.NgramModel(context.trigrams(docs), (0.0, 0.7, 0.3)).score(picked)
    rows = scored.join(counts, F.col("w") == F.col("lemma"))
    return rows.select("doc_id", "y", F.ln("n").alias("log_corpus"), F.ln("_own").alias("log_text"), F.ln("g").alias("log_g"))
