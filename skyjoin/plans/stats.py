"""Statistics on the fly from mini copies: counts with error bars, the distribution of right ascension, wedges."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Estimate:
    rows: float
    error: float  # one binomial standard deviation


def estimate(mini: DataFrame, rate: float, where: str | None = None) -> Estimate:
    """Rows of the full table that pass a filter, from its mini copy."""
    n = (mini.filter(where) if where else mini).count()
    return Estimate(n / rate, math.sqrt(max(n, 1) * (1 - rate)) / rate)


def histogram(df: DataFrame, bins: int, ra: str = "ra") -> DataFrame:
    """Rows by equal bins of right ascension."""
    return df.groupBy(F.least(F.lit(bins - 1), F.floor(F.col(ra) / 360.0 * bins)).cast("int").alias("bin")).agg(F.count("*").alias("n"))


def wedges(df: DataFrame, n: int, method: str = "count", ra: str = "ra", accuracy: int = 10_000) -> list[float]:
    """n + 1 boundaries from 0 to 360: of equal counts by approximate quantiles, or of equal width."""
    if n < 1:
        raise ValueError("at least one wedge")
    if method == "width" or n == 1:
        return [360.0 * k / n for k in range(n + 1)]
    found = df.agg(F.percentile_approx(ra, [k / n for k in range(1, n)], accuracy)).first()[0] or []
    return [0.0, *sorted(set(x for x in found if 0 < x < 360)), 360.0]


def wedge_of(ra: Column, bounds: list[float]) -> Column:
    """Number of the wedge that holds a right ascension."""
    out = F.lit(0)
    for b in bounds[1:-1]:
        out = out + (ra >= b).cast("int")
    return out


def partitions(df: DataFrame, multiple: int = 3) -> int:
    """A multiple of the workers: finer grains make recovery cheaper."""
    return multiple * df.sparkSession.sparkContext.defaultParallelism
