"""How well a word can be guessed from its left context: count-based language models and the scorers beside them."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from embedvocab.functions import rng
from embedvocab.operators import packed


def trigrams(docs: DataFrame) -> DataFrame:
    """(doc_id, pos, a, b, w) of (doc_id, words): each word with the two before it, null at the start; narrow."""
    at = lambda i: F.get("words", F.col("pos") - i)
    return docs.select("doc_id", "words", F.posexplode("words").alias("pos", "w")).select("doc_id", "pos", at(2).alias("a"), at(1).alias("b"), "w")


def bigrams(runs: DataFrame, least: int = 1) -> DataFrame:
    """(ctx, w, n, p): words after words, p their share after that context."""
    pairs = runs.filter("b is not null").groupBy("b", "w").agg(F.count(F.lit(1)).alias("n"))
    total = pairs.groupBy("b").agg(F.sum("n").alias("_t"))
    return pairs.join(total, "b").select(F.col("b").alias("ctx"), "w", "n", (F.col("n") / F.col("_t")).alias("p")).filter(F.col("n") >= least)


class NgramModel:
    """Counts of one to three words, interpolated or backed off; contexts unseen in training fall to the shorter ones.

    Everything is counted and joined by distinct runs of words, whose counts are added up before they are sent; the text itself takes
    part in one join only, on whole runs, of which none is nearly as common as a common word. Three words of the counted text itself
    are counted and scored in packed blocks, without a join.
    """

    def __init__(self, runs: DataFrame, lambdas: tuple[float, float, float] = (0.5, 0.3, 0.2), smoothing: str = "interpolated", discount: float = 0.75):
        self.lambdas, self.smoothing, self.discount = lambdas, smoothing, discount
        # two words suffice where three have no weight
        self.words = ["b", "w"] if smoothing == "kneser_ney" or (smoothing == "interpolated" and not lambdas[0]) else ["a", "b", "w"]
        self.runs, self.types = runs, runs.groupBy(*self.words).agg(F.count(F.lit(1)).alias("n_abw"))
        types = self.types
        self.uni = types.groupBy("w").agg(F.sum("n_abw").alias("n_w"))
        self.total = self.uni.agg(F.sum("n_w").alias("n_all"))
        follows = [F.count("a").alias("c_bw")] if "a" in self.words else []
        bi = types.filter("b is not null").groupBy("b", "w").agg(F.sum("n_abw").alias("n_bw"), *follows)
        continued = [F.sum("c_bw").alias("c_b"), F.sum(F.when(F.col("c_bw") > 0, 1).otherwise(0)).alias("e_b")] if follows else []
        self.bi, self.by_b = bi, bi.groupBy("b").agg(F.sum("n_bw").alias("n_b"), F.count(F.lit(1)).alias("d_b"), *continued)
        if "a" in self.words:
            self.tri = types.filter("a is not null")
            self.by_ab = self.tri.groupBy("a", "b").agg(F.sum("n_abw").alias("n_ab"), F.count(F.lit(1)).alias("d_ab"))
        # how many words a word follows: what continuation estimates count
        self.cont = bi.groupBy("w").agg(F.count(F.lit(1)).alias("c_w"))
        self.pairs = bi.agg(F.count(F.lit(1)).alias("c_all"))

    def score(self, runs: DataFrame) -> DataFrame:
        """runs with g, the probability of each word given what is left of it."""
        if runs is self.runs and packs(runs, self.words):
            return packed.counted(runs, self.smoothing == "kneser_ney_3").select(*runs.columns, self.probability().alias("g"))
        found = self.scored(self.types if runs is self.runs else runs.select(*self.words).distinct()).select(*(F.col(c).alias(f"_{c}") for c in self.words), "g")
        same = reduce(Column.__and__, (F.col(c).eqNullSafe(F.col(f"_{c}")) for c in self.words))
        return runs.join(found, same).select(*runs.columns, "g")

    def scored(self, types: DataFrame) -> DataFrame:
        """types, distinct runs of words, with g; those that were counted bring their counts and are not looked up again."""
        kept = [c for c in types.columns if c != "n_abw"]
        own, longest = types is self.types, "a" if "a" in self.words else "b"
        if own:
            types = types.withColumn("n_abw", F.when(F.col(longest).isNotNull(), F.col("n_abw")))
        types = types.join(self.uni, "w", "left").crossJoin(F.broadcast(self.total))
        types = types.withColumnRenamed("n_abw", "n_bw") if own and longest == "b" else types.join(self.bi, ["b", "w"], "left")
        types = types.join(self.by_b, "b", "left")
        if "a" in self.words:
            types = (types if own else types.join(self.tri, ["a", "b", "w"], "left")).join(self.by_ab, ["a", "b"], "left")
        if self.smoothing in ("kneser_ney", "kneser_ney_3"):
            types = types.join(self.cont, "w", "left").crossJoin(F.broadcast(self.pairs))
        return types.select(*kept, self.probability().alias("g"))

    def probability(self) -> Column:
        """g of the counts of a run and of its parts; null is none."""
        zero = lambda c: F.coalesce(c, F.lit(0.0))
        share = lambda n, of: zero(F.col(n) / F.col(of))
        if self.smoothing in ("interpolated", "stupid_backoff"):
            p1, p2, p3 = share("n_w", "n_all"), share("n_bw", "n_b"), share("n_abw", "n_ab") if "a" in self.words else F.lit(0.0)
            if self.smoothing == "stupid_backoff":
                return F.when(p3 > 0, p3).when(p2 > 0, 0.4 * p2).otherwise(0.16 * p1)
            x3, x2, x1 = self.lambdas
            return x3 * p3 + x2 * p2 + x1 * p1
        if self.smoothing not in ("kneser_ney", "kneser_ney_3"):
            raise ValueError(f"no smoothing {self.smoothing}")
        low = share("c_w", "c_all")

        def discounted(count: str, total: str, distinct: str, lower: Column) -> Column:
            rest = self.discount * F.col(distinct) / F.col(total) * lower
            return F.when(F.coalesce(F.col(total), F.lit(0)) == 0, lower).otherwise(F.greatest(zero(F.col(count).cast("double")) - self.discount, F.lit(0.0)) / F.col(total) + rest)

        # of two words the plain counts, or how many words the pair follows if three are in use
        return discounted("n_bw", "n_b", "d_b", low) if self.smoothing == "kneser_ney" else discounted("n_abw", "n_ab", "d_ab", discounted("c_bw", "c_b", "e_b", low))


def packs(runs: DataFrame, words: list[str]) -> bool:
    """Whether runs are of three words, as strings."""
    kinds = dict(runs.dtypes)
    return words == ["a", "b", "w"] and all(kinds.get(c) == "string" for c in words)


def held_out(runs: DataFrame, folds: int = 2, smoothing: str = "kneser_ney_3") -> DataFrame:
    """(fold, words, unknown, bits): each fold of documents scored by the model of the others; mean bits of the words they know.

    Distinct runs of a block are scored and weigh as often as they occur; one pass counts for all folds.
    """
    rows = runs.withColumn("_fold", (F.col("doc_id") % folds).cast("long")).filter("_fold is not null")
    model = NgramModel(runs, smoothing=smoothing)
    if packs(runs, model.words):
        scored = packed.counted(rows, smoothing == "kneser_ney_3", folds).select("_fold", "_uses", model.probability().alias("g"))
    else:
        scored = None
        for fold in range(folds):
            model = NgramModel(rows.filter(F.col("_fold") != fold).drop("_fold"), smoothing=smoothing)
            each = model.scored(rows.filter(F.col("_fold") == fold).groupBy(*model.words).agg(F.count(F.lit(1)).alias("_uses")))
            each = each.select(F.lit(fold).cast("long").alias("_fold"), "_uses", "g")
            scored = each if scored is None else scored.unionByName(each)
    uses, known = F.sum("_uses"), F.sum(F.when(F.col("g") > 0, F.col("_uses")))
    sums = scored.groupBy("_fold").agg(uses.alias("_n"), known.alias("_known"), F.sum(F.when(F.col("g") > 0, -F.log2("g") * F.col("_uses"))).alias("_bits"))
    every = runs.sparkSession.range(folds).join(F.broadcast(sums), F.col("id") == F.col("_fold"), "left")
    none = F.lit(0).cast("long")
    words, right = F.coalesce("_n", none), F.coalesce("_known", none)
    return every.select(F.col("id").cast("int").alias("fold"), words.alias("words"), (words - right).alias("unknown"), (F.col("_bits") / F.when(right > 0, right)).alias("bits"))


def frequency_scores(runs: DataFrame, scope: str = "corpus") -> DataFrame:
    """runs with g from counts alone: the word's share of the corpus, of its text, or the mean of both.

    Counts of a text's words are joined with the corpus, and the text's words with these, so no join key is as common as a word.
    """
    doc = runs.groupBy("doc_id", "w").agg(F.count(F.lit(1)).alias("_d"))
    own = doc.withColumn("_s", F.sum("_d").over(Window.partitionBy("doc_id")))
    corpus = doc.groupBy("w").agg(F.sum("_d").alias("_c")).crossJoin(F.broadcast(doc.agg(F.sum("_d").alias("_n"))))
    out = own.join(corpus, "w")
    share = {"corpus": lambda: F.col("_c") / F.col("_n"), "text": lambda: F.col("_d") / F.col("_s"), "both": lambda: (F.col("_c") / F.col("_n") + F.col("_d") / F.col("_s")) / 2}[scope]()
    return runs.join(out.select("doc_id", "w", share.alias("g")), ["doc_id", "w"]).select(*runs.columns, "g")


def random_scores(runs: DataFrame, seed: int = 42) -> DataFrame:
    return runs.withColumn("g", rng.uniform(seed, F.col("doc_id"), F.col("pos")))


def neural_scores(docs: DataFrame, load: Callable[[], Callable[[list[str]], list[float]]]) -> DataFrame:
    """(doc_id, pos, w, g) of (doc_id, words): ``load`` gives, once a worker, a function from a text's words to the probability of each."""
    schema = pa.schema([("doc_id", pa.int64()), ("pos", pa.int32()), ("w", pa.string()), ("g", pa.float64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = load()
        for b in batches:
            for doc_id, words in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                words = words or []
                yield pa.record_batch([pa.array([doc_id] * len(words), pa.int64()), pa.array(range(len(words)), pa.int32()), pa.array(words, pa.string()), pa.array(model(words), pa.float64())], schema=schema)

    return docs.select("doc_id", "words").mapInArrow(run, "doc_id long, pos int, w string, g double")


def pick_contexts(scored: DataFrame, lemmas: DataFrame, per_word: int = 7, mode: str = "easy", seed: int = 42) -> DataFrame:
    """(lemma, doc_id, pos, g, rank): each lemma's best occurrences, or random ones."""
    own = scored.withColumnRenamed("w", "lemma").join(F.broadcast(lemmas.select("lemma")), "lemma", "left_semi")
    first = F.desc("g") if mode == "easy" else rng.order(seed, F.col("lemma"), F.col("doc_id"), F.col("pos"))
    rank = F.row_number().over(Window.partitionBy("lemma").orderBy(first, "doc_id", "pos"))
    return own.withColumn("rank", rank).filter(F.col("rank") <= per_word).select("lemma", "doc_id", "pos", "g", "rank")
