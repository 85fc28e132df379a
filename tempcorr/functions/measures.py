"""Measures as DataFrame expressions: discretisers, plug-in information, directions, correlations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def by_width(df: DataFrame, columns: list[str], bins: int, by: list[str] | None = None) -> DataFrame:
    """Adds b_<column>: equal-width bins between the smallest and largest value, of all rows or of each group."""
    w = Window.partitionBy(*by) if by else None
    if w is None:
        edges = df.agg(*[f(c).alias(f"_{n}_{c}") for c in columns for n, f in (("lo", F.min), ("hi", F.max))])
        df = df.crossJoin(F.broadcast(edges))  # one row
    else:
        df = df.select("*", *[f(c).over(w).alias(f"_{n}_{c}") for c in columns for n, f in (("lo", F.min), ("hi", F.max))])
    for c in columns:
        lo, hi = F.col(f"_lo_{c}"), F.col(f"_hi_{c}")
        df = df.withColumn(f"b_{c}", F.when(hi == lo, 0).otherwise(F.least(F.floor((F.col(c) - lo) / (hi - lo) * bins), F.lit(bins - 1))).cast("int")).drop(f"_lo_{c}", f"_hi_{c}")
    return df


def by_frequency(df: DataFrame, column: str, bins: int, by: list[str], order: list[str]) -> DataFrame:
    """Adds b_<column>: bins of equal counts within each group."""
    return df.withColumn(f"b_{column}", F.ntile(bins).over(Window.partitionBy(*by).orderBy(column, *order)) - 1)


def by_change(df: DataFrame, column: str, by: list[str], order: str) -> DataFrame:
    """Adds b_<column>: the sign of the step from the row before, null on the first."""
    return df.withColumn(f"b_{column}", F.signum(F.col(column) - F.lag(column).over(Window.partitionBy(*by).orderBy(order))).cast("int"))


def entropy(n: Column, total: Column) -> Column:
    return F.sum(-(n / total) * F.log(n / total))


def information(df: DataFrame, x: str, y: str, by: list[str]) -> DataFrame:
    """Per group: n, hx, hy, hxy and mi of two categorical columns, from counts of their cells; aggregates twice."""
    cells = df.where(F.col(x).isNotNull() & F.col(y).isNotNull()).groupBy(*by, x, y).agg(F.count("*").alias("c"))
    wx, wy, wt = (Window.partitionBy(*by, *c) for c in ([x], [y], []))
    cells = cells.select("*", F.sum("c").over(wx).alias("cx"), F.sum("c").over(wy).alias("cy"), F.sum("c").over(wt).alias("n"))
    p = F.col("c") / F.col("n")
    return cells.groupBy(*by, "n").agg(
        F.sum(-p * F.log(F.col("cx") / F.col("n"))).alias("hx"),
        F.sum(-p * F.log(F.col("cy") / F.col("n"))).alias("hy"),
        F.sum(-p * F.log(p)).alias("hxy"),
        F.sum(p * F.log(F.col("c") * F.col("n") / (F.col("cx") * F.col("cy")))).alias("mi"),
    )


def normalised(scores: DataFrame) -> DataFrame:
    """Adds the normalised entropy and both normalised informations."""
    log_n = F.when(F.col("n") > 1, F.log(F.col("n").cast("double")))
    return scores.select("*", (F.col("hxy") / log_n).alias("h_norm"), (F.col("mi") / log_n).alias("mi_norm1"), F.try_divide(F.col("mi"), F.when(F.col("hxy") > 0, F.col("hxy"))).alias("mi_norm2"))


def bounds_ok(tolerance: float = 1e-9) -> Column:
    """Information lies between zero and the smaller entropy; the joint entropy is at least the larger one."""
    return (F.col("mi") >= -tolerance) & (F.col("mi") <= F.least("hx", "hy") + tolerance) & (F.col("hxy") >= F.greatest("hx", "hy") - tolerance)


def digamma_int(c: Column) -> Column:
    return F.aggregate(F.sequence(F.lit(1), F.greatest(c - 1, F.lit(1)).cast("int")), F.lit(-0.5772156649015329), lambda a, j: a + F.when(c > 1, 1 / j).otherwise(F.lit(0.0)))


def directions(df: DataFrame, by: list[str], order: str = "idx") -> DataFrame:
    """Per group: steps in equal and in opposite direction, the degree mu, its label and confidences."""
    w = Window.partitionBy(*by).orderBy(order)
    step = F.signum(F.col("x") - F.lag("x").over(w)) * F.signum(F.col("y") - F.lag("y").over(w))
    out = df.withColumn("_t", step).groupBy(*by).agg(F.count("*").alias("n"), F.sum(F.when(F.col("_t") > 0, 1).otherwise(0)).alias("pp"), F.sum(F.when(F.col("_t") < 0, 1).otherwise(0)).alias("np"))
    pp, np_, steps = F.col("pp"), F.col("np"), F.col("n") - 1
    out = out.withColumn("mu", F.try_divide(pp - np_, F.when(steps > 0, steps)))
    sign = F.when(F.col("mu") > 0, "positive").when(F.col("mu") < 0, "negative").when(F.col("mu") == 0, "neither")
    out = out.withColumn("sign", sign)
    out = out.select("*", F.try_divide(pp - np_, F.when(pp > 0, pp)).alias("conf_p"), F.try_divide(np_ - pp, F.when(np_ > 0, np_)).alias("conf_n"), F.try_divide(steps - pp - np_, F.when(steps > 0, steps)).alias("conf_o"))
    return out.withColumn("conf", F.when(F.col("sign") == "positive", F.col("conf_p")).when(F.col("sign") == "negative", F.col("conf_n")).otherwise(F.col("conf_o")))


def linear(df: DataFrame, by: list[str]) -> DataFrame:
    """Per group: Pearson's coefficient and the sample covariance."""
    return df.groupBy(*by).agg(F.count("*").alias("n"), F.corr("x", "y").alias("pearson"), F.covar_samp("x", "y").alias("covariance"))
