"""How soon lemmas come back: gaps, their 90th percentiles in reading days, and the percentile of those over a lemma set."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from embedvocab.operators import coverage

#: Reading model: words a minute and hours a day.
WPM, HOURS = 200, 3


def to_days(words: Column, wpm: float = WPM, hours: float = HOURS) -> Column:
    return words / F.lit(float(wpm * 60 * hours))


def rescale(days: Column, wpm: float, hours: float) -> Column:
    """Days at another speed: half the speed doubles the time."""
    return days * F.lit(WPM * HOURS / (wpm * hours))


def gaps(found: DataFrame, counting: str = "distance") -> DataFrame:
    """(corpus_id, lemma, gap) of occurrences(): inside each block, then from each block's first to the last one before.

    ``between`` counts the words between, one less than the distance. Lemmas that occur once have no gap.
    """
    less = 1 if counting == "between" else 0
    inner = found.filter(F.size("at") > 1).select("corpus_id", "lemma", F.explode(F.zip_with(F.slice("at", F.lit(2), F.size("at") - 1), F.slice("at", F.lit(1), F.size("at") - 1), lambda b, a: b - a - less)).alias("gap"))
    ends = found.select("corpus_id", "lemma", "block", F.element_at("at", 1).alias("first"), F.element_at("at", -1).alias("last"))
    own = Window.partitionBy("corpus_id", "lemma").orderBy("block")
    seams = ends.withColumn("_prev", F.lag("last").over(own)).filter("_prev is not null").select("corpus_id", "lemma", (F.col("first") - F.col("_prev") - less).alias("gap"))
    return inner.unionByName(seams)


def histogram(gap_rows: DataFrame) -> DataFrame:
    """(corpus_id, lemma, gap, count): the gaps of a lemma sum to the corpus length at most, so few are distinct."""
    return gap_rows.groupBy("corpus_id", "lemma", "gap").agg(F.count(F.lit(1)).alias("count"))


def per_lemma(hist: DataFrame, q: float = 0.9, wpm: float = WPM, hours: float = HOURS) -> DataFrame:
    """(corpus_id, lemma, gaps, days): the exact percentile of each lemma's gaps, from counts."""
    out = hist.groupBy("corpus_id", "lemma").agg(F.sum("count").alias("gaps"), F.percentile("gap", q, F.col("count")).alias("_q"))
    return out.select("corpus_id", "lemma", "gaps", to_days(F.col("_q"), wpm, hours).alias("days"))


def per_lemma_sketched(gap_rows: DataFrame, q: float = 0.9, wpm: float = WPM, hours: float = HOURS) -> DataFrame:
    """The same from the gaps themselves by KLL sketches, which are small however many distinct gaps there are, with a bounded error of rank."""
    out = gap_rows.groupBy("corpus_id", "lemma").agg(F.count("gap").alias("gaps"), F.kll_sketch_get_quantile_bigint(F.kll_sketch_agg_bigint("gap"), F.lit(q)).cast("double").alias("_q"))
    return out.select("corpus_id", "lemma", "gaps", to_days(F.col("_q"), wpm, hours).alias("days"))


def per_corpus(days: DataFrame, ranked: DataFrame, alphas: tuple[float, ...], q: float = 0.9) -> DataFrame:
    """(corpus_id, alpha, vocab, lemmas_with_gap, revisit_days): all coverages in one pass over the ranked lemmas."""
    joined = ranked.join(days, ["corpus_id", "lemma"], "left")
    grid = joined.select("corpus_id", "days", F.explode(F.filter(F.array(*(F.when(coverage.covers(a), F.lit(a)) for a in alphas)), lambda x: x.isNotNull())).alias("alpha"))
    return grid.groupBy("corpus_id", "alpha").agg(F.count(F.lit(1)).alias("vocab"), F.count("days").alias("lemmas_with_gap"), F.percentile("days", q).alias("revisit_days"))


def analyse(found: DataFrame, alphas: tuple[float, ...], q: float = 0.9, wpm: float = WPM, hours: float = HOURS, estimator: str = "exact") -> DataFrame:
    """per_corpus of occurrences(), with gaps computed for the largest lemma set only; ``kll`` sketches the lemmas' percentiles."""
    if estimator not in ("exact", "kll"):
        raise ValueError(f"no estimator {estimator}")
    ranked = coverage.ranks(coverage.frequencies(found))
    kept = found.join(coverage.lemma_set(ranked, max(alphas)).select("corpus_id", "lemma"), ["corpus_id", "lemma"], "left_semi")
    days = per_lemma(histogram(gaps(kept)), q, wpm, hours) if estimator == "exact" else per_lemma_sketched(gaps(kept), q, wpm, hours)
    return per_corpus(days, ranked, alphas, q)


def summary(df: DataFrame, value: str, by: list[str] | None = None) -> DataFrame:
    """(n, q1, median, q3) of a column."""
    return df.groupBy(*(by or [])).agg(F.count(value).alias("n"), *(F.percentile(value, p).alias(n) for n, p in (("q1", 0.25), ("median", 0.5), ("q3", 0.75))))


def daily_load(vocab: Column, days: Column) -> Column:
    """Lemmas to review a day if each comes back in time."""
    return vocab / days
