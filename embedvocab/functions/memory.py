"""The memory model and the scores that selection merges, as columns."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Boost:
    """Constants of the half-life's growth; all positive, and c over 1 so that growth falls with recall."""

    a: float = 2.0
    b: float = 0.2
    c: float = 2.0
    d: float = 1.0
    initial: float = 1.0

    def __post_init__(self) -> None:
        if min(self.a, self.b, self.d, self.initial) <= 0 or self.c <= 1:
            raise ValueError("a, b, d and the initial half-life must be positive and c over 1")


def recall(t_days: Column, h: Column) -> Column:
    """Probability of recall so long after the last revision: half at the half-life."""
    # not greatest(), which skips nulls: unknown stays unknown
    return F.pow(F.lit(2.0), -F.when(t_days < 0, 0.0).otherwise(t_days) / F.when(h < 1e-6, 1e-6).otherwise(h))


def boost(h: Column, r: Column, p: Boost = Boost()) -> Column:
    """What a successful revision multiplies the half-life by."""
    return p.a * F.pow(F.greatest(h, F.lit(1e-6)), F.lit(-p.b)) * F.pow(F.lit(p.c), -r) + p.d


def due_after(h: Column, target: float) -> Column:
    """Days until recall falls to the target."""
    return -h * F.log2(F.lit(target))


def understanding(r: Column, g: Column) -> Column:
    """Probability of understanding a word by memory or by context, taken as independent."""
    return r + g - r * g


def priority(p: Column, gamma: Column) -> Column:
    return p * gamma


def budget(n_words: Column, density: float, k_min: int = 0) -> Column:
    """How many words to replace for the reader's wished density."""
    return F.greatest(F.floor(n_words * density), F.lit(k_min)).cast("int")


def schedule(day: Column, start: float = 0.05, end: float = 1.0, days: int = 30, flip_at: float = 0.6) -> tuple[Column, Column]:
    """Density that grows to full conversion, and the direction, which flips once most words are converted."""
    share = F.least(F.lit(1.0), day / F.lit(float(days)))
    density = F.lit(start) + F.lit(end - start) * share
    return density, F.when(density < flip_at, F.lit("base_to_target")).otherwise(F.lit("target_to_base"))
