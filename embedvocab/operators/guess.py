"""Which features predict how well a word is guessed: least squares from one aggregate."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def moments(df: DataFrame, columns: list[str]) -> DataFrame:
    """(i, j, sum_xy) for i <= j over 1 and the columns: all that least squares needs."""
    x = ["_one", *columns]
    rows = df.withColumn("_one", F.lit(1.0))
    pairs = [(i, j) for i in range(len(x)) for j in range(i, len(x))]
    sums = rows.agg(*(F.sum(F.col(x[i]) * F.col(x[j])).alias(f"{i}_{j}") for i, j in pairs))
    return sums.select(F.explode(F.array(*(F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.col(f"{i}_{j}").alias("sum_xy")) for i, j in pairs))).alias("m")).select("m.*")


def fit(df: DataFrame, features: list[str], y: str, ridge: float = 0.0) -> dict[str, float]:
    """Coefficients, with the constant under "_one"; the driver solves one system as wide as the features."""
    k = len(features) + 1
    m = np.zeros((k + 1, k + 1))
    for i, j, s in moments(df, [*features, y]).collect():
        m[i, j] = m[j, i] = s or 0.0
    beta = np.linalg.lstsq(m[:k, :k] + ridge * np.diag([0.0] + [1.0] * (k - 1)), m[:k, k], rcond=None)[0]
    return dict(zip(["_one", *features], beta.tolist(), strict=True))


def rank_predictors(df: DataFrame, features: list[str], y: str) -> DataFrame:
    """(feature, beta_std, rank): coefficients in standard deviations, largest first."""
    stats = df.agg(*(F.stddev_samp(c).alias(c) for c in [*features, y])).first()
    beta = fit(df, features, y)
    rows = sorted(((f, beta[f] * (stats[f] or 0.0) / (stats[y] or 1.0)) for f in features), key=lambda r: (-abs(r[1]), r[0]))
    return df.sparkSession.createDataFrame([(f, float(b), i + 1) for i, (f, b) in enumerate(rows)], "feature string, beta_std double, rank int")
