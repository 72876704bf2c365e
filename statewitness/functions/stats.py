"""Rates with lower limits under clustering, as column arithmetic."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed value: the two-sided 95 per cent point of the normal distribution.
Z = 1.959964


def wilson_lower(k: Column, n: Column, effective: Column | None = None) -> Column:
    """Lower limit of Wilson's interval for k of n, at an effective sample size; null without data."""
    size = n.cast("double") if effective is None else effective.cast("double")
    p = F.try_divide(k.cast("double"), n.cast("double"))
    z2 = Z * Z
    centre = p + F.try_divide(F.lit(z2), 2 * size)
    spread = Z * F.sqrt(F.try_divide(p * (1 - p), size) + F.try_divide(F.lit(z2), 4 * size * size))
    return F.when(n > 0, F.greatest(F.lit(0.0), F.try_divide(centre - spread, 1 + F.try_divide(F.lit(z2), size))))


def wilson_value(k: float, n: float, effective: float | None = None) -> float | None:
    """The same for two numbers."""
    size = n if effective is None else effective
    if not n or not size:
        return None
    p, z2 = k / n, Z * Z
    return max(0.0, (p + z2 / (2 * size) - Z * (p * (1 - p) / size + z2 / (4 * size * size)) ** 0.5) / (1 + z2 / size))


def clustering(df: DataFrame, cluster: str, y: str, groups: list[str] | None = None) -> DataFrame:
    """Per group: n, clusters, intra-class correlation (one-way analysis of variance), design effects, effective n.

    The correlation is clipped to [0, 1]; without any variance it is 0. Mean cluster size is the
    default effect; the size-weighted one is given beside it.
    """
    groups = groups or []
    value = F.col(y).cast("double")
    per = df.groupBy(*groups, cluster).agg(F.count("*").cast("double").alias("m"), F.sum(value).alias("s"), F.sum(value * value).alias("q"))
    agg = per.groupBy(*groups).agg(F.count("*").cast("double").alias("k"), F.sum("m").alias("n"), F.sum("s").alias("t"), F.sum("q").alias("q"), F.sum(F.col("s") * F.col("s") / F.col("m")).alias("b"), F.sum(F.col("m") * F.col("m")).alias("mm"))
    within = F.try_divide(F.col("q") - F.col("b"), F.col("n") - F.col("k"))
    between = F.try_divide(F.col("b") - F.try_divide(F.col("t") * F.col("t"), F.col("n")), F.col("k") - 1)
    m0 = F.try_divide(F.col("n") - F.try_divide(F.col("mm"), F.col("n")), F.col("k") - 1)
    raw = F.try_divide(between - within, between + (m0 - 1) * within)
    icc = F.least(F.lit(1.0), F.greatest(F.lit(0.0), F.coalesce(raw, F.lit(0.0))))
    out = agg.select(*groups, "n", "k", icc.alias("icc"), F.try_divide(F.col("n"), F.col("k")).alias("mean_size"), F.try_divide(F.col("mm"), F.col("n")).alias("weighted_size"))
    return out.select("*", (1 + (F.col("mean_size") - 1) * F.col("icc")).alias("deff_mean"), (1 + (F.col("weighted_size") - 1) * F.col("icc")).alias("deff_weighted")).select("*", F.try_divide(F.col("n"), F.col("deff_mean")).alias("n_effective"))
