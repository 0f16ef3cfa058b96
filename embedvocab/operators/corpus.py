"""Reading orders and word positions without a global sort.

Blocks are fixed ranges of the order key. Sums of blocks are few, so their running total is cheap; inside a block
a window adds what comes before each document. A block is bounded whatever the corpus.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from embedvocab.functions import text as txt

#: Documents of a block while words are numbered, and words of a block once they are.
BLOCK, WORDS = 4096, 1 << 20


def running_total(df: DataFrame, by: list[str], order: list[str], value: str, block: Column, out: str = "before") -> DataFrame:
    """df with the sum of ``value`` over the rows before each row, in two levels; ``block`` must grow with the order."""
    rows = df.withColumn("_block", block)
    sums = rows.groupBy(*by, "_block").agg(F.sum(value).alias("_n"))
    ahead = Window.partitionBy(*by).orderBy("_block").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.withColumn("_offset", F.coalesce(F.sum("_n").over(ahead), F.lit(0))).drop("_n")
    within = Window.partitionBy(*by, "_block").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    joined = rows.withColumn("_within", F.coalesce(F.sum(value).over(within), F.lit(0))).join(offsets, [*by, "_block"])
    return joined.withColumn(out, F.col("_offset") + F.col("_within")).drop("_block", "_offset", "_within")


def documents(docs: DataFrame, corpus: Column, method: str = "identity") -> DataFrame:
    """(corpus_id, doc_id, words) of a table with doc_id and text; null texts have no words."""
    words = F.coalesce(txt.tokenize(F.col("text")), F.array().cast("array<string>"))
    lemmas = words if method == "identity" else F.transform(words, lambda w: txt.lemmatize(w, method))
    return docs.select(corpus.alias("corpus_id"), "doc_id", lemmas.alias("words"))


def number_words(docs: DataFrame, order: list[str] | None = None, block: Column | None = None) -> DataFrame:
    """(corpus_id, block, doc_id, pos, lemma) of (corpus_id, doc_id, words): positions along the whole reading order."""
    order = order or ["doc_id"]
    block = F.floor(F.col("doc_id") / BLOCK) if block is None else block
    placed = running_total(docs.withColumn("_size", F.size("words").cast("long")).withColumn("block", block), ["corpus_id"], order, "_size", F.col("block"))
    each = placed.select("corpus_id", "block", "doc_id", "before", F.posexplode("words").alias("_i", "lemma"))
    return each.select("corpus_id", "block", "doc_id", (F.col("before") + F.col("_i")).alias("pos"), "lemma")


def occurrences(words: DataFrame) -> DataFrame:
    """(corpus_id, lemma, block, at): sorted positions of each lemma in each block of positions; bounded, however common the lemma and however long a document."""
    placed = words.withColumn("block", F.floor(F.col("pos") / WORDS))
    return placed.groupBy("corpus_id", "lemma", "block").agg(F.sort_array(F.collect_list("pos")).alias("at"))
