"""Statistical tests from one aggregate each."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def welch_t(df: DataFrame, group: str, value: str, a: str, b: str) -> DataFrame:
    """Welch's t and its degrees of freedom for two groups."""
    moments = [f(F.when(F.col(group) == g, F.col(value))).alias(f"{n}{i}") for i, g in enumerate((a, b)) for n, f in (("n", F.count), ("m", F.avg), ("v", F.var_samp))]
    s = df.where(F.col(group).isin(a, b)).agg(*moments)
    e0, e1 = F.col("v0") / F.col("n0"), F.col("v1") / F.col("n1")
    return s.select(F.round((F.col("m0") - F.col("m1")) / F.sqrt(e0 + e1), 6).alias("t"), F.round(F.pow(e0 + e1, 2) / (F.pow(e0, 2) / (F.col("n0") - 1) + F.pow(e1, 2) / (F.col("n1") - 1)), 4).alias("df"))


def chi2(df: DataFrame, a: str, b: str) -> DataFrame:
    """Pearson's statistic of independence; only counts of the categories are joined."""
    cells = df.groupBy(F.col(a).alias("a"), F.col(b).alias("b")).agg(F.count("*").cast("double").alias("n"))
    rows, cols, total = cells.groupBy("a").agg(F.sum("n").alias("ra")), cells.groupBy("b").agg(F.sum("n").alias("rb")), cells.agg(F.sum("n").alias("z"))
    grid = rows.crossJoin(F.broadcast(cols)).crossJoin(F.broadcast(total)).join(cells, ["a", "b"], "left")
    expected = F.col("ra") * F.col("rb") / F.col("z")
    return grid.agg(F.round(F.sum(F.pow(F.coalesce("n", F.lit(0.0)) - expected, 2) / expected), 6).alias("chi2"), ((F.countDistinct("a") - 1) * (F.countDistinct("b") - 1)).alias("df"))
