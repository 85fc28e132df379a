"""Series with known relations: portable noise, single relations, several in a row, and relations planted in a table's series."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

KINDS = ("independent", "independent_outliers", "linear", "linear_outliers", "exponential", "quadratic", "diamond", "circle", "sine", "cross")


def noise(idx: Column, salt: str) -> Column:
    """Uniform on [0, 1), the same in any engine that has md5."""
    return F.conv(F.substring(F.md5(F.concat(idx.cast("string"), F.lit(salt))), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def shaped(kind: str, x: Column, u: Column, v: Column) -> Column:
    """y of a relation; u chooses a branch, v fills what is independent."""
    pi = 3.141592653589793
    branch = F.when(u < 0.5, 1.0).otherwise(-1.0)
    return {
        "independent": v,
        "independent_outliers": F.when(u < 0.1, x).otherwise(v),
        "linear": x,
        "linear_outliers": F.when(u < 0.1, v).otherwise(x),
        "exponential": F.exp(4 * x) / 54.598150033144236,
        "quadratic": F.pow(2 * x - 1, F.lit(2)),
        "diamond": 0.5 + branch * (0.5 - F.abs(x - 0.5)) * v,
        "circle": 0.5 + branch * F.sqrt(F.greatest(F.lit(0.0), 0.25 - F.pow(x - 0.5, F.lit(2)))),
        "sine": 0.5 + 0.5 * F.sin(4 * pi * x),
        "cross": F.when(u < 0.5, x).otherwise(1 - x),
    }[kind]


def relation(spark: SparkSession, kind: str, n: int, level: float = 0.02, salt: str = "r") -> DataFrame:
    """PAIRED rows of one relation, with noise of the given level on y."""
    i = F.col("id")
    x, u, v, e = (noise(i, salt + c) for c in "xuve")
    return spark.range(n).select(F.lit(kind).alias("pair_id"), i.alias("idx"), x.alias("x"), (shaped(kind, x, u, v) + level * e).alias("y"))


def plant(series: DataFrame, spans: list[tuple[int, int, str]], salt: str = "a", level: float = 0.02) -> DataFrame:
    """PAIRED: x is a value's rank in (0, 1]; y a function of x inside the spans, noise outside."""
    w = Window.partitionBy("var")
    ranked = series.withColumn("x", F.row_number().over(w.orderBy("v", "idx")) / F.count("*").over(w))
    idx, y = F.col("idx"), noise(F.col("idx"), salt)
    for s, e, kind in spans:
        f = (1 - F.col("x")) if kind == "negative" else shaped(kind, F.col("x"), noise(idx, "c"), noise(idx, "d"))
        y = F.when((idx >= s) & (idx < e), f + level * noise(idx, "b")).otherwise(y)
    return ranked.select(F.col("var").alias("pair_id"), "idx", "x", y.alias("y"))


def truth(spark: SparkSession, spans: list[tuple[int, int, str]], pair_id: str) -> DataFrame:
    return spark.createDataFrame([(pair_id, s, e, k) for s, e, k in spans], "pair_id string, s long, e long, relation string")
