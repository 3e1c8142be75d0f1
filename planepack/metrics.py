"""Cost and accuracy measures over result rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def compression_ratio(df: DataFrame, *by: str) -> DataFrame:
    """Original over compressed bytes, of sums."""
    return df.groupBy(*by).agg((F.sum("raw") / F.sum("enc")).alias("cr"), (F.sum("raw") / F.sum("enc_with_header")).alias("cr_with_header"))


def gmean(c) -> Column:
    return F.exp(F.avg(F.log(c)))


def improvement(df: DataFrame, value: str, *by: str) -> DataFrame:
    """Clustered over standard of a measure: one row per key, by conditional sums rather than a self join."""
    side = lambda v: F.max(F.when(F.col("variant") == v, F.col(value)))
    return df.groupBy(*by).agg(side("clustered").alias(f"{value}_clustered"), side("standard").alias(f"{value}_standard"), (side("clustered") / side("standard")).alias(f"{value}_improvement"))


def average_rank(df: DataFrame, c: str, *by: str) -> DataFrame:
    """Ranks with ties averaged."""
    w = Window.partitionBy(*by).orderBy(c)
    return df.withColumn(f"rank_{c}", F.rank().over(w) + (F.count(F.lit(1)).over(Window.partitionBy(*by, c)) - 1) / 2)


def spearman(df: DataFrame, x: str, y: str, *by: str) -> DataFrame:
    r = average_rank(average_rank(df, x, *by), y, *by)
    return r.groupBy(*by).agg(F.corr(f"rank_{x}", f"rank_{y}").alias("rho"))


def win_rate(a: str, b: str) -> Column:
    return F.avg((F.col(a) > F.col(b)).cast("int"))


def cr_distribution(df: DataFrame, value: str, *by: str) -> DataFrame:
    q = lambda p: F.percentile(value, F.lit(p))
    return df.groupBy(*by).agg(q(0.0).alias("least"), q(0.25).alias("q1"), q(0.5).alias("q2"), q(0.75).alias("q3"), q(1.0).alias("most"), gmean(value).alias("gmean"))
