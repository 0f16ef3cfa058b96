"""Accuracy and cost measures of the study."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from embedvocab.functions import stats
from embedvocab.functions import text as txt


def correct() -> Column:
    """1 for a correct answer; unknown answers count in the denominator."""
    return (F.col("outcome") == "correct").cast("double")


def retention(answers: DataFrame, by: list[str]) -> DataFrame:
    """(by, answers, rate)."""
    return answers.groupBy(*by).agg(F.count(F.lit(1)).alias("answers"), F.avg(correct()).alias("rate"))


def mean_over_users(answers: DataFrame, by: list[str]) -> DataFrame:
    """(by, users, mean, lo, hi): the mean of the users' own rates."""
    return stats.mean_ci(retention(answers, [*by, "participant"]), by, "rate")


def answer_mix(answers: DataFrame, by: list[str]) -> DataFrame:
    """(by, outcome, share, lo, hi): mean over users of each kind of answer's share."""
    kinds = ("correct", "incorrect", "unknown")
    per = answers.groupBy(*by, "participant").agg(*(F.avg((F.col("outcome") == k).cast("double")).alias(k) for k in kinds))
    long = per.unpivot([*by, "participant"], list(kinds), "outcome", "share")
    return stats.mean_ci(long, [*by, "outcome"], "share").withColumnRenamed("mean", "share").drop("users")


def differences(answers: DataFrame, unit: str, by: list[str]) -> DataFrame:
    """(by, unit, versus, diff, embedded, other): how a unit's rate in the embedded condition exceeds that in each table condition."""
    wide = retention(answers, [*by, unit, "condition"]).groupBy(*by, unit).pivot("condition", ["embedded", "pre_table", "post_table"]).agg(F.first("rate"))
    long = wide.unpivot([*by, unit, "embedded"], ["pre_table", "post_table"], "versus", "other")
    return long.filter("embedded is not null and other is not null").withColumn("diff", F.col("embedded") - F.col("other"))


def within(answers: DataFrame, unit: str, by: list[str]) -> DataFrame:
    """(by, versus, n, mean_diff, t, df, p): paired t tests over users or words."""
    return stats.paired_t(differences(answers, unit, by), [*by, "versus"], "embedded", "other")


def grade_gaps(given: DataFrame, keys: DataFrame, synonyms: DataFrame, max_edit: int = 1) -> DataFrame:
    """given (item, answer) with the outcome: right if it is the key or a synonym, inflected or not, or within so many edits of either."""
    right = keys.select("item", F.lower("key").alias("_k")).unionByName(keys.join(synonyms, F.lower(keys["key"]) == F.lower(synonyms["word"])).select("item", F.lower("synonym").alias("_k")))
    said, stem = F.lower(F.trim("answer")), lambda c: txt.lemmatize(c, "s_stem")
    near = given.join(right, "item", "left").withColumn("_ok", (stem(said) == stem(F.col("_k"))) | (F.levenshtein(said, F.col("_k")) <= max_edit))
    empty = F.coalesce(F.trim("answer"), F.lit("")) == ""
    return near.groupBy("item", "answer").agg(F.max(F.coalesce("_ok", F.lit(False))).alias("_ok")).select("item", "answer", F.when(empty, "unknown").when(F.col("_ok"), "correct").otherwise("incorrect").alias("outcome"))


def click_histogram(cell_clicks: DataFrame) -> DataFrame:
    """(clicks, share): mean over users of the share of their words clicked so often; cells without clicks count as zero."""
    per = cell_clicks.groupBy("participant", "clicks").agg(F.count(F.lit(1)).alias("n"))
    total = cell_clicks.groupBy("participant").agg(F.count(F.lit(1)).alias("t"))
    users = total.agg(F.count(F.lit(1)).alias("u"))
    return per.join(total, "participant").groupBy("clicks").agg(F.sum(F.col("n") / F.col("t")).alias("s")).crossJoin(F.broadcast(users)).select("clicks", (F.col("s") / F.col("u")).alias("share"))


def easiness(answers: DataFrame) -> DataFrame:
    """(word, easiness): share of users with the word in a table condition who got it right at once."""
    return retention(answers.filter("condition <> 'embedded' and phase = 'short'"), ["word"]).select("word", F.col("rate").alias("easiness"))


def speed(page_times: DataFrame) -> DataFrame:
    """(participant, treated, wpm): words read over minutes taken."""
    return page_times.groupBy("participant", "treated").agg((F.sum("words") / F.sum("minutes")).alias("wpm"))


def speed_summary(speeds: DataFrame) -> DataFrame:
    """(treated, users, median_wpm, q1, q3)."""
    return speeds.groupBy("treated").agg(F.count(F.lit(1)).alias("users"), F.percentile("wpm", 0.5).alias("median_wpm"), F.percentile("wpm", 0.25).alias("q1"), F.percentile("wpm", 0.75).alias("q3"))


def overhead(summary: DataFrame) -> DataFrame:
    """(slowdown, overhead): the share of speed lost, and the share of time gained, which is larger."""
    m = lambda t: F.max(F.when(F.col("treated") == t, F.col("median_wpm")))
    return summary.agg(m(True).alias("a"), m(False).alias("b")).select((1 - F.col("a") / F.col("b")).alias("slowdown"), (F.col("b") / F.col("a") - 1).alias("overhead"))


def mnemonics(codes: DataFrame) -> DataFrame:
    """(arm, coding, share) under both codings; codes has arm, broad and narrow."""
    per = codes.groupBy("arm").agg(F.avg("broad").alias("broad"), F.avg("narrow").alias("narrow"))
    return per.unpivot("arm", ["broad", "narrow"], "coding", "share")


def conservative_ratio(shares: DataFrame) -> DataFrame:
    """(ratio): the tables' share by the narrow coding over the embedded arm's by the broad one."""
    s = lambda arm, coding: F.max(F.when((F.col("arm") == arm) & (F.col("coding") == coding), F.col("share")))
    return shares.agg((s("table", "narrow") / s("embedded", "broad")).alias("ratio"))
