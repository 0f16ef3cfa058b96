"""The study: word pool, groups, assignment, texts and test items."""

from __future__ import annotations

from itertools import permutations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from embedvocab.functions import rng
from embedvocab.functions import text as txt
from embedvocab.operators import context

CONDITIONS = ("embedded", "pre_table", "post_table")
PICK, GROUPS, PER_WORD = 78, 3, 7


def word_pool(docs: DataFrame, vocab: DataFrame, base: str = "en", top: int = 500, pick: int = PICK, seed: int = 42) -> DataFrame:
    """(lemma, n, rank): a fixed random choice among the top lemmas that are no stopword, name, short word or cognate.

    vocab is (corpus_id, lemma, n, rank) of the base language and the others, docs the texts of the base language.
    """
    own = vocab.filter((F.col("corpus_id") == base) & (F.col("rank") <= top)).select("lemma", "n")
    own = txt.drop_stopwords(own).filter(F.length("lemma") >= 3)
    # at most ``top`` lemmas, and so are the names among them
    own = own.join(F.broadcast(txt.proper_nouns(docs, among=own)), "lemma", "left_anti")
    near = txt.cognates(own, vocab.filter((F.col("corpus_id") != base) & (F.col("rank") <= top)))
    left = own.join(near, "lemma", "left_anti")
    # at most 500 lemmas, so the order's window is small
    rank = F.row_number().over(Window.orderBy(rng.order(seed, F.col("lemma")), "lemma"))
    return left.withColumn("rank", rank).filter(F.col("rank") <= pick)


def word_groups(pool: DataFrame, groups: int = GROUPS) -> DataFrame:
    """(lemma, wgroup, arm): equal groups by rank; half of each learns from easy contexts, half from random ones."""
    return pool.select("lemma", ((F.col("rank") - 1) % groups).alias("wgroup"), F.when(F.floor((F.col("rank") - 1) / groups) % 2 == 0, "easy").otherwise("random").alias("arm"))


def assignment(spark) -> DataFrame:  # noqa: ANN001
    """(pgroup, wgroup, condition): one participant group for each way to give word groups to conditions."""
    rows = [(g, w, c) for g, order in enumerate(permutations(CONDITIONS)) for w, c in enumerate(order)]
    return spark.createDataFrame(rows, "pgroup int, wgroup int, condition string")


def participant_groups(people: DataFrame, seed: int = 42, groups: int = 6) -> DataFrame:
    """(participant, pgroup): sizes differ by one at most. A study has few participants, so one window orders them."""
    rank = F.row_number().over(Window.orderBy(rng.order(seed, F.lit("participant"), F.col("participant")), "participant"))
    return people.select("participant", ((rank - 1) % groups).cast("int").alias("pgroup"))


def cells(groups: DataFrame, words: DataFrame, table: DataFrame) -> DataFrame:
    """(participant, pgroup, word, wgroup, arm, condition): every participant meets every word once."""
    return groups.crossJoin(F.broadcast(words)).join(F.broadcast(table), ["pgroup", "wgroup"])


def balance(all_cells: DataFrame) -> DataFrame:
    """(condition, wgroup, pgroup, cells) over all combinations and totals; null stands for all."""
    return all_cells.cube("condition", "wgroup", "pgroup").agg(F.count(F.lit(1)).alias("cells"))


def snippets(docs: DataFrame, lo: int = 100, hi: int = 2500) -> DataFrame:
    """(doc_id, n_words, words) of (doc_id, text) with a length in the range."""
    return docs.select("doc_id", txt.tokenize(F.col("text")).alias("words")).withColumn("n_words", F.size("words")).filter(F.col("n_words").between(lo, hi))


def cover(pool: DataFrame, words: DataFrame, quota: int = PER_WORD, max_snippets: int = 47, held: int = 1000) -> DataFrame:
    """(wgroup, round, doc_id, gain): greedy snippets until each word of the group occurs its quota of times.

    A snippet's gain is the occurrences still needed that it brings; ties go to the lower id. Gains only shrink, so the
    driver holds the ``held`` snippets of largest gain and chooses among them for as long as the best still gains more
    than any snippet it does not hold could; then the gains are taken anew.
    """
    spark = pool.sparkSession
    found = pool.select("doc_id", F.explode("words").alias("lemma")).join(F.broadcast(words), "lemma").groupBy("wgroup", "doc_id", "lemma").agg(F.count(F.lit(1)).alias("n")).persist()
    lists: dict[int, list[str]] = {}
    for r in words.select("wgroup", "lemma").collect():
        lists.setdefault(r.wgroup, []).append(r.lemma)
    chosen: list[tuple] = []
    try:
        for group, lemmas in sorted(lists.items()):
            need, taken = dict.fromkeys(lemmas, quota), []

            def best_held() -> tuple[dict[int, dict[str, int]], int]:
                wanted = spark.createDataFrame([(w, n) for w, n in need.items() if n], "lemma string, need int")
                gains = found.filter((F.col("wgroup") == group) & ~F.col("doc_id").isin(taken)).join(F.broadcast(wanted), "lemma").groupBy("doc_id").agg(
                    F.sum(F.least("n", "need")).alias("gain"), F.map_from_entries(F.collect_list(F.struct("lemma", "n"))).alias("counts"))
                top = gains.orderBy(F.desc("gain"), "doc_id").limit(held + 1).collect()
                return {r.doc_id: r.counts for r in top[:held]}, top[held].gain if len(top) > held else 0

            snippets_held, bound = best_held()
            while any(need.values()) and len(taken) < max_snippets:
                gains = lambda: {d: sum(min(n, need[w]) for w, n in counts.items()) for d, counts in snippets_held.items()}
                gain = gains()
                if max(gain.values(), default=0) <= bound:
                    # one that is not held may gain as much and have a lower id
                    snippets_held, bound = best_held()
                    gain = gains()
                if not gain:
                    break
                best = min(gain, key=lambda d: (-gain[d], d))
                if not gain[best]:
                    break
                taken.append(best)
                chosen.append((group, len(taken), best, gain[best]))
                for w, n in snippets_held.pop(best).items():
                    need[w] = max(0, need[w] - n)
    finally:
        found.unpersist()
    return spark.createDataFrame(chosen, "wgroup int, round int, doc_id long, gain long")


def instances(scored: DataFrame, groups: DataFrame, per_word: int = PER_WORD) -> DataFrame:
    """(wgroup, arm, lemma, doc_id, pos, g, rank): the uses of each word that the embedded section shows, easy contexts for one arm, random ones for the other.

    A group of 26 words has 182 of them, which every participant who learns the group in this section reads.
    """
    picked = None
    for arm in ("easy", "random"):
        words = groups.filter(F.col("arm") == arm).select("wgroup", "arm", F.col("lemma").alias("_l"))
        rows = context.pick_contexts(scored, words.select(F.col("_l").alias("lemma")), per_word, arm).join(F.broadcast(words), F.col("lemma") == F.col("_l")).drop("_l")
        picked = rows if picked is None else picked.unionByName(rows)
    return picked.select("wgroup", "arm", "lemma", "doc_id", "pos", "g", "rank")


def sections(groups: DataFrame, table: DataFrame) -> DataFrame:
    """(participant, section, condition, wgroup): the embedded section lies between the two tables, which takes the first and the last place from it."""
    place = F.when(F.col("condition") == "pre_table", 1).when(F.col("condition") == "embedded", 2).otherwise(3)
    return groups.join(F.broadcast(table), "pgroup").select("participant", place.alias("section"), "condition", "wgroup")


def study_pages(chosen: DataFrame, pool: DataFrame, per_page: int = 10, control: int = 5) -> DataFrame:
    """(wgroup, page, doc_id, treated): each group's snippets, so many a page, then one page of unaltered ones that none of the groups has."""
    unaltered = control_page(pool.join(chosen.select("doc_id"), "doc_id", "left_anti"), control)
    pages = paginate(chosen, per_page).withColumn("treated", F.lit(True))
    last = pages.groupBy("wgroup").agg((F.max("page") + 1).alias("page"))
    return pages.select("wgroup", "page", "doc_id", "treated").unionByName(last.crossJoin(F.broadcast(unaltered.select("doc_id"))).select("wgroup", "page", "doc_id", F.lit(False).alias("treated")))


def paginate(chosen: DataFrame, per_page: int = 10, seed: int = 42) -> DataFrame:
    """(wgroup, doc_id, page): snippets in a fixed random order, so many a page."""
    turn = F.row_number().over(Window.partitionBy("wgroup").orderBy(rng.order(seed, F.col("doc_id")), "doc_id"))
    return chosen.select("wgroup", "doc_id", (F.floor((turn - 1) / per_page) + 1).cast("int").alias("page"))


def control_page(pool: DataFrame, n: int = 5, seed: int = 43) -> DataFrame:
    """The unaltered snippets of the control page."""
    return pool.orderBy(rng.order(seed, F.col("doc_id")), "doc_id").limit(n)


def mc_items(participants: DataFrame, words: DataFrame, k: int = 5, seed: int = 42) -> DataFrame:
    """(participant, word, slot, option, is_answer): "don't know" in slot 0, then the answer among k - 1 others in random order."""
    pairs = participants.select("participant").crossJoin(F.broadcast(words.select("word"))).crossJoin(F.broadcast(words.select(F.col("word").alias("option"))))
    wrong = F.row_number().over(Window.partitionBy("participant", "word").orderBy((F.col("word") != F.col("option")).cast("int"), rng.order(seed, F.col("participant"), F.col("word"), F.col("option")), "option"))
    options = pairs.withColumn("_r", wrong).filter(F.col("_r") <= k)
    slot = F.row_number().over(Window.partitionBy("participant", "word").orderBy(rng.order(seed, F.lit("slot"), F.col("participant"), F.col("word"), F.col("option")), "option"))
    answers = options.select("participant", "word", slot.cast("int").alias("slot"), F.col("option").cast("string").alias("option"), (F.col("word") == F.col("option")).alias("is_answer"))
    unknown = participants.select("participant").crossJoin(F.broadcast(words.select("word"))).select("participant", "word", F.lit(0).alias("slot"), F.lit("don't know").alias("option"), F.lit(False).alias("is_answer"))
    return unknown.unionByName(answers)


def ftg_items(all_cells: DataFrame, share: float = 1 / 3, seed: int = 42) -> DataFrame:
    """(participant, word): the share of each participant's words in each condition that are asked as gaps."""
    own = Window.partitionBy("participant", "condition")
    rank = F.row_number().over(own.orderBy(rng.order(seed, F.lit("gap"), F.col("participant"), F.col("word")), "word"))
    return all_cells.withColumn("_r", rank).withColumn("_n", F.count(F.lit(1)).over(own)).filter(F.col("_r") <= F.floor(F.col("_n") * share + 1e-9)).select("participant", "word")


def reverse_items(items: DataFrame, lexicon: DataFrame, words: DataFrame) -> DataFrame:
    """(participant, word, prompt, slot, option, is_answer): the same items asked the other way round: a base word is shown, its translation is looked for.

    items are of mc_items(); words (word, lemma) and lexicon (lemma, target) name the numbers. Words without a translation are not asked.
    """
    named = words.join(lexicon.select("lemma", "target"), "lemma").select("word", "lemma", "target")
    asked = items.join(F.broadcast(named.select("word", F.col("lemma").alias("prompt"))), "word")
    texts = asked.join(F.broadcast(named.select(F.col("word").cast("string").alias("_w"), F.col("target").alias("_t"))), F.col("option") == F.col("_w"), "left")
    return texts.select("participant", "word", "prompt", "slot", F.coalesce("_t", "option").alias("option"), "is_answer")


def retest(items: DataFrame, seed: int = 44) -> DataFrame:
    """The same items with their order drawn anew; slot 0 stays."""
    slot = F.row_number().over(Window.partitionBy("participant", "word").orderBy((F.col("slot") != 0).cast("int"), rng.order(seed, F.col("participant"), F.col("word"), F.col("option")), "option")) - 1
    return items.withColumn("slot", slot.cast("int"))


def overhead_time(page_times: DataFrame) -> DataFrame:
    """(participant, delta_minutes): what treated pages took beyond the reader's own speed on untreated ones."""
    s = lambda c, t: F.sum(F.when(F.col("treated") == t, F.col(c)))
    per = page_times.groupBy("participant").agg(s("minutes", True).alias("_tm"), s("words", True).alias("_tw"), s("minutes", False).alias("_cm"), s("words", False).alias("_cw"))
    return per.select("participant", (F.col("_tm") - F.col("_tw") * F.col("_cm") / F.col("_cw")).alias("delta_minutes"))


def describe(people: DataFrame, number: str, categories: list[str]) -> DataFrame:
    """(attribute, value, n, share, mean, sd): the number's mean and spread, and the share of each value of each category."""
    total = people.agg(F.count(F.lit(1)).alias("_t"))
    out = people.agg(F.count(number).alias("n"), F.avg(number).alias("mean"), F.stddev_samp(number).alias("sd")).select(
        F.lit(number).alias("attribute"), F.lit("all").alias("value"), "n", F.lit(1.0).alias("share"), "mean", "sd")
    values = people.select(F.explode(F.array(*(F.struct(F.lit(c).alias("attribute"), F.col(c).cast("string").alias("value")) for c in categories))).alias("x")).select("x.*")
    each = values.groupBy("attribute", "value").agg(F.count(F.lit(1)).alias("n")).crossJoin(F.broadcast(total)).select(
        "attribute", "value", "n", (F.col("n") / F.col("_t")).alias("share"), F.lit(None).cast("double").alias("mean"), F.lit(None).cast("double").alias("sd"))
    return out.unionByName(each)
