"""Paired t tests, intervals and box rows as aggregates and columns."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

Z95 = 1.959964


def two_sided_p(t: Column, df: Column) -> Column:
    """p of Student's t with whole degrees of freedom, by the finite trigonometric sum; 1 - A cancels below about 1e-12."""
    theta = F.atan(F.abs(t) / F.sqrt(df.cast("double")))
    c2 = F.pow(F.cos(theta), F.lit(2))
    odd = df % 2 == 1
    terms = F.when(odd, F.expr("1") * 0 + (df - 1) / 2).otherwise(df / 2).cast("int")

    def series(top: Column, low: Column) -> Column:
        # each term is the one before times top/low of its number and the squared cosine
        start = F.struct(F.lit(1.0).alias("term"), F.lit(0.0).alias("sum"))
        step = lambda s, k: F.struct((s["term"] * top(k) / low(k) * c2).alias("term"), (s["sum"] + s["term"]).alias("sum"))
        return F.aggregate(F.filter(F.sequence(F.lit(1), F.greatest(terms, F.lit(1))), lambda k: k <= terms), start, step, lambda s: s["sum"])

    a_odd = 2 / 3.141592653589793 * (theta + F.when(df > 1, F.sin(theta) * F.cos(theta) * series(lambda k: 2.0 * k, lambda k: 2.0 * k + 1)).otherwise(0.0))
    a_even = F.sin(theta) * series(lambda k: 2.0 * k - 1, lambda k: 2.0 * k)
    return 1 - F.when(odd, a_odd).otherwise(a_even)


def paired_t(df: DataFrame, by: list[str], a: str, b: str) -> DataFrame:
    """(by, n, mean_diff, t, df, p) of rows with both values; t is null for fewer than two rows or no spread."""
    diff = df.filter(F.col(a).isNotNull() & F.col(b).isNotNull()).withColumn("_d", F.col(a) - F.col(b))
    out = diff.groupBy(*by).agg(F.count("_d").alias("n"), F.avg("_d").alias("mean_diff"), F.stddev_samp("_d").alias("_s"))
    out = out.withColumn("t", F.when(F.col("_s") > 0, F.col("mean_diff") / (F.col("_s") / F.sqrt(F.col("n").cast("double"))))).withColumn("df", F.col("n") - 1)
    return out.withColumn("p", F.when(F.col("t").isNotNull(), two_sided_p(F.col("t"), F.col("df")))).drop("_s")


def mean_ci(df: DataFrame, by: list[str], value: str, units: str = "users") -> DataFrame:
    """(by, units, mean, lo, hi): mean and its 95 % interval by the normal quantile."""
    out = df.groupBy(*by).agg(F.count(value).alias(units), F.avg(value).alias("mean"), F.stddev_samp(value).alias("_s"))
    half = Z95 * F.coalesce(F.col("_s"), F.lit(0.0)) / F.sqrt(F.col(units).cast("double"))
    return out.withColumn("lo", F.col("mean") - half).withColumn("hi", F.col("mean") + half).drop("_s")


def box(df: DataFrame, by: list[str], value: str) -> DataFrame:
    """(by, lo_whisker, q1, median, q3, hi_whisker, outliers): whiskers end at the last value within 1.5 of the quartile range."""
    q = df.groupBy(*by).agg(*(F.percentile(value, p).alias(n) for n, p in (("q1", 0.25), ("median", 0.5), ("q3", 0.75))))
    both = df.join(q, by)
    reach = 1.5 * (F.col("q3") - F.col("q1"))
    inside = (F.col(value) >= F.col("q1") - reach) & (F.col(value) <= F.col("q3") + reach)
    return both.groupBy(*by, "q1", "median", "q3").agg(F.min(F.when(inside, F.col(value))).alias("lo_whisker"), F.max(F.when(inside, F.col(value))).alias("hi_whisker"), F.sum(F.when(inside, 0).otherwise(1)).alias("outliers"))
