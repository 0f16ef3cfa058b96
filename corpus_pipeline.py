"""The corpus pipeline: toxic documents go, one of each group of near copies stays, repeated passages go, sources are
mixed to target weights, and what is left is packed into token sequences.

Each stage works on all that its predecessor kept. All but the last return the columns of ``documents``, and further columns
of the input, whatever their names. Null texts are empty: they are clean and near copies of each other, hold no passage, have no
words to mix and are packed as an end of text. Rows with null ids pass through all stages; rows that repeat id and text are
near copies. An empty table stays empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from embedvocab.llm import mixing, packing, quality_knn, simhash, substring_dedup, toxicity
from embedvocab.llm.common import table, written

#: Words of a shingle and least similarity of near copies.
SHINGLE, SIMILARITY = 5, 0.8
#: Words of a repeated passage.
WINDOW = 35
#: The column that holds a document's quality while sources are mixed.
WEIGHT = "_mixing_weight"


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the grammar, fitted on the labelled rows among them, scores at 0.3 or more go."""
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    return toxicity.keep_clean(docs, model, threshold=0.3)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the document with the least id stays."""
    return simhash.keep_one(docs, SHINGLE, SIMILARITY)


def drop_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Words that a repeated window covers go; a document of nothing else goes with them."""
    return substring_dedup.without_repeats(docs, WINDOW)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as their source's target takes them; how soon one is taken depends on its quality score."""
    model = quality_knn.fit(docs, table(spark, sf_dir, "labels"))
    scored = written(quality_knn.with_score(docs, model, WEIGHT))
    return mixing.materialise(mixing.mix(scored, weight=F.greatest(F.lit(0.05), F.col(WEIGHT))), docs.columns)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents in sequences of 1024 tokens."""
    return packing.pack(docs)


STAGES = [("toxicity", drop_toxic), ("simhash near-dedup", drop_near_copies), ("substring dedup", drop_repeats), ("source mixing", mix_sources), ("packing", pack_sequences)]

#: Fingerprints, models and packing are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = written(docs)
    return docs
