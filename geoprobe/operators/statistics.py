"""One-way analysis of variance from mergeable moments."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import workers_can_import


def anova_oneway(rows: DataFrame, value: str, group: str) -> DataFrame:
    """One row: groups, n, f. Counts, means and variances merge over partitions (no raw sums of squares); nulls are left out."""
    clean = rows.where(F.col(value).isNotNull() & F.col(group).isNotNull())
    parts = clean.groupBy(group).agg(F.count("*").alias("n"), F.avg(value).alias("mean"), F.coalesce(F.var_samp(value), F.lit(0.0)).alias("var"))
    total = parts.agg(F.count("*").alias("k"), F.sum("n").alias("total"), (F.sum(F.col("n") * F.col("mean")) / F.sum("n")).alias("grand"))
    sums = parts.crossJoin(total).agg(
        F.max("k").alias("groups"), F.max("total").alias("n"), F.sum(F.col("n") * F.pow(F.col("mean") - F.col("grand"), F.lit(2))).alias("between"), F.sum((F.col("n") - 1) * F.col("var")).alias("within")
    )
    return sums.select("groups", "n", F.expr("try_divide(between / (groups - 1), within / (n - groups))").alias("f"))


def anova_by(rows: DataFrame, value: str, group: str, by: str) -> DataFrame:
    """by, groups, n, f: one variance analysis for each value of `by`, all from one pass over the rows."""
    clean = rows.where(F.col(value).isNotNull() & F.col(group).isNotNull())
    parts = clean.groupBy(by, group).agg(F.count("*").alias("n"), F.avg(value).alias("mean"), F.coalesce(F.var_samp(value), F.lit(0.0)).alias("var"))
    whole = Window.partitionBy(by)  # a row per group
    parts = parts.withColumn("grand", F.sum(F.col("n") * F.col("mean")).over(whole) / F.sum("n").over(whole))
    sums = parts.groupBy(by).agg(F.count("*").alias("groups"), F.sum("n").alias("n"), F.sum(F.col("n") * F.pow(F.col("mean") - F.col("grand"), F.lit(2))).alias("between"), F.sum((F.col("n") - 1) * F.col("var")).alias("within"))
    return sums.select(by, "groups", "n", F.expr("try_divide(between / (groups - 1), within / (n - groups))").alias("f"))


def incomplete_beta(a: float, b: float, x: float) -> float:
    """Regularised incomplete beta function by its continued fraction."""
    if x <= 0 or x >= 1:
        return float(x >= 1)
    if x > (a + 1) / (a + b + 2):
        return 1 - incomplete_beta(b, a, 1 - x)
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x)) / a
    c, d = 1.0, 1 / max(1e-300, abs(1 - (a + b) * x / (a + 1))) * math.copysign(1, 1 - (a + b) * x / (a + 1))
    out = d
    for m in range(1, 500):
        for top in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 / (1 + top * d)
            c = 1 + top / c
            out *= c * d
        if abs(c * d - 1) < 1e-15:
            break
    return front * out


def f_tail(f: float, df1: int, df2: int) -> float:
    """Probability of a larger F."""
    return incomplete_beta(df2 / 2, df1 / 2, df2 / (df2 + df1 * f)) if f is not None and f >= 0 else float("nan")


def with_p(anova: DataFrame) -> DataFrame:
    """Adds p to the result of anova_oneway."""
    workers_can_import(anova.sparkSession)

    @F.pandas_udf("double")
    def tail(f: pd.Series, k: pd.Series, n: pd.Series) -> pd.Series:
        return pd.Series([f_tail(x, int(a) - 1, int(b) - int(a)) for x, a, b in zip(f, k, n, strict=True)])

    return anova.withColumn("p", tail("f", "groups", "n"))
