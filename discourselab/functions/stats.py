"""Rank correlation with ties, its p-value, and ranks of columns too large for one window."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from discourselab.session import cut


def average_rank(value: str, by: list[str]) -> Column:
    """Rank of ``value`` within ``by``; tied values share the mean of their ranks."""
    order = Window.partitionBy(*by).orderBy(value)
    ties = Window.partitionBy(*by, value)
    return F.rank().over(order) + (F.count("*").over(ties) - 1) / 2.0


def spearman(df: DataFrame, x: str, y: str, by: list[str]) -> DataFrame:
    """(by..., n, r_s) of two columns; rows where either is null are left out, constants give null.

    Groups are series of days, so a group's window is small whatever the number of posts.
    """
    both = df.where(F.col(x).isNotNull() & F.col(y).isNotNull())
    ranked = both.select(*by, average_rank(x, by).alias("_x"), average_rank(y, by).alias("_y"))
    return ranked.groupBy(*by).agg(F.count("*").alias("n"), _corr("_x", "_y").alias("r_s"))


def _corr(x: str, y: str) -> Column:
    """Linear correlation; null, and no division by zero, where a column is constant."""
    return F.try_divide(F.covar_pop(x, y), F.stddev_pop(x) * F.stddev_pop(y))


def pearson(df: DataFrame, x: str, y: str, by: list[str]) -> DataFrame:
    return df.where(F.col(x).isNotNull() & F.col(y).isNotNull()).groupBy(*by).agg(F.count("*").alias("n"), _corr(x, y).alias("r"))


def distributed_rank(df: DataFrame, value: str) -> DataFrame:
    """(value, rank): average ranks over a whole column, without a window over all of its rows.

    Equal values are counted first; ranges of values are counted by partition, and each partition adds
    what lies below it. No task holds more than its range of different values.
    """
    counts = df.where(F.col(value).isNotNull()).groupBy(value).agg(F.count("*").alias("n"))
    held = cut(counts.repartitionByRange(value).withColumn("part", F.spark_partition_id()))
    below = held.groupBy("part").agg(F.sum("n").alias("size"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # a row for each partition
    offset = below.select("part", F.coalesce(F.sum("size").over(before), F.lit(0)).alias("offset"))
    within = F.coalesce(F.sum("n").over(Window.partitionBy("part").orderBy(value).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return (
        held.select(value, "n", "part", within.alias("within"))
        .join(F.broadcast(offset), "part")
        .select(value, (F.col("offset") + F.col("within") + (F.col("n") + 1) / 2.0).alias("rank"))
    )


def _fraction(a: float, b: float, x: float) -> float:
    """Continued fraction of the incomplete beta function, by the modified Lentz scheme."""
    tiny = 1e-300
    c, d = 1.0, 1.0 - (a + b) * x / (a + 1)
    d = 1 / (d if abs(d) > tiny else tiny)
    value = d
    for m in range(1, 500):
        for term in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 + term * d
            d = 1 / (d if abs(d) > tiny else tiny)
            c = 1 + term / c
            c = c if abs(c) > tiny else tiny
            value *= c * d
        if abs(c * d - 1) < 1e-15:
            break
    return value


def incomplete_beta(a: float, b: float, x: float) -> float:
    """Regularised incomplete beta function."""
    if x <= 0 or x >= 1:
        return float(x >= 1)
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x))
    if x < (a + 1) / (a + b + 2):
        return front * _fraction(a, b, x) / a
    return 1 - front * _fraction(b, a, 1 - x) / b


def p_value(r: float | None, n: int) -> float | None:
    """Two-sided p of a rank correlation by t on n - 2 degrees of freedom."""
    if r is None or r != r or n < 3:
        return None
    if abs(r) >= 1:
        return 0.0
    t2 = r * r * (n - 2) / (1 - r * r)
    return incomplete_beta((n - 2) / 2, 0.5, (n - 2) / (n - 2 + t2))


def p_column(r: Column, n: Column) -> Column:
    """``p_value`` as an Arrow UDF over a handful of rows."""

    def batch(rs: pd.Series, ns: pd.Series) -> pd.Series:
        return pd.Series([p_value(None if x is None or x != x else float(x), int(k)) for x, k in zip(rs, ns, strict=True)], dtype="float64")

    return F.pandas_udf(batch, "double")(r, n)


def describe(r: Column, p: Column) -> Column:
    """none / weak / moderate / strong, with sign, and whether it is significant at .05."""
    size = F.abs(r)
    strength = F.when(size < 0.1, "none").when(size < 0.4, "weak").when(size < 0.7, "moderate").otherwise("strong")
    return F.concat_ws(
        " ",
        strength,
        F.when(size >= 0.1, F.when(r > 0, "positive").otherwise("negative")),
        F.when(p < 0.05, "significant").otherwise("not significant"),
    )


def block_permutation_p(x: np.ndarray, y: np.ndarray, block: int = 30, rounds: int = 999, seed: int = 0) -> float:
    """p of a rank correlation of two series when whole blocks of days are shuffled; keeps serial dependence."""
    rank = lambda v: pd.Series(v).rank().to_numpy()
    rx, ry, rng = rank(x), rank(y), np.random.default_rng(seed)
    seen = abs(np.corrcoef(rx, ry)[0, 1])
    blocks = [ry[k : k + block] for k in range(0, len(ry), block)]
    hits = sum(abs(np.corrcoef(rx, np.concatenate([blocks[i] for i in rng.permutation(len(blocks))]))[0, 1]) >= seen for _ in range(rounds))
    return (hits + 1) / (rounds + 1)
