"""The smallest sets of most frequent lemmas that cover given shares of a corpus."""

from __future__ import annotations

from decimal import Decimal

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def frequencies(found: DataFrame) -> DataFrame:
    """(corpus_id, lemma, n) of occurrences()."""
    return found.groupBy("corpus_id", "lemma").agg(F.sum(F.size("at")).alias("n"))


def ranks(freqs: DataFrame) -> DataFrame:
    """(corpus_id, lemma, n, rank, before, total): rank by count, ties by lemma; ``before`` is the count of all above.

    Cumulates over distinct counts, of which a corpus of n words has at most the root of 2n; no window spans all lemmas.
    """
    sizes = freqs.groupBy("corpus_id", "n").agg(F.count(F.lit(1)).alias("_lemmas"))
    above = Window.partitionBy("corpus_id").orderBy(F.desc("n")).rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy("corpus_id")
    sizes = (sizes.withColumn("_rank", F.coalesce(F.sum("_lemmas").over(above), F.lit(0)))
             .withColumn("_before", F.coalesce(F.sum(F.col("n") * F.col("_lemmas")).over(above), F.lit(0)))
             .withColumn("total", F.sum(F.col("n") * F.col("_lemmas")).over(whole)).drop("_lemmas"))
    # lemmas that occur equally often, half of a vocabulary once, are ordered in slices by a lemma's first two letters: no task sees them all
    rows = freqs.withColumn("_slice", F.substring("lemma", 1, 2))
    within = F.row_number().over(Window.partitionBy("corpus_id", "n", "_slice").orderBy("lemma")) - 1
    slices = rows.groupBy("corpus_id", "n", "_slice").agg(F.count(F.lit(1)).alias("_k"))
    ahead = Window.partitionBy("corpus_id", "n").orderBy("_slice").rowsBetween(Window.unboundedPreceding, -1)
    offsets = slices.withColumn("_offset", F.coalesce(F.sum("_k").over(ahead), F.lit(0))).drop("_k")
    tie = F.col("_offset") + F.col("_within")
    return rows.withColumn("_within", within).join(offsets, ["corpus_id", "n", "_slice"]).join(sizes, ["corpus_id", "n"]).select(
        "corpus_id", "lemma", "n", (F.col("_rank") + tie + 1).alias("rank"), (F.col("_before") + F.col("n") * tie).alias("before"), "total")


def covers(alpha: float) -> F.Column:
    """Whether a ranked lemma is in the set of coverage alpha, compared without rounding."""
    a = Decimal(str(alpha))
    if not 0 < a <= 1:
        raise ValueError("coverage must be over 0 and at most 1")
    scale = 10 ** max(0, -a.as_tuple().exponent)
    return F.col("before") * F.lit(scale) < F.col("total") * F.lit(int(a * scale))


def lemma_set(ranked: DataFrame, alpha: float) -> DataFrame:
    return ranked.filter(covers(alpha))


def vocab_size(ranked: DataFrame, alphas: tuple[float, ...]) -> DataFrame:
    """(corpus_id, alpha, vocab) in one pass."""
    sums = ranked.groupBy("corpus_id").agg(*(F.sum(F.when(covers(a), 1).otherwise(0)).alias(str(a)) for a in alphas))
    return sums.unpivot("corpus_id", [F.col(f"`{a}`") for a in alphas], "alpha", "vocab").withColumn("alpha", F.col("alpha").cast("double"))
