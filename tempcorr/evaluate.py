"""Accuracy: which relations a measure identifies, which planted spans a search recovers, what thresholds do."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tempcorr.functions import kernel
from tempcorr.operators import windows as W
from tempcorr.operators.prep import overlaps


def identify_table(paired: DataFrame, alpha: float = 0.01, reps: int = 99) -> DataFrame:
    """(pair_id, metric, value, identified): a value is one where it exceeds what shuffled pairs reach."""
    import numpy as np

    metrics = {"knn_mi": kernel.knn_mi, "plugin_mi": lambda x, y: kernel.plugin(kernel.equal_width(x, 6), kernel.equal_width(y, 6))["mi"], "pearson": lambda x, y: abs(float(np.corrcoef(x, y)[0, 1])), "dcor": kernel.dcor}

    def run(df: pd.DataFrame) -> pd.DataFrame:
        df = df.sort_values("idx")
        x, y = df["x"].to_numpy(), df["y"].to_numpy()
        rows = [(df["pair_id"].iloc[0], m, v := f(x, y), v > kernel.permutation_quantile(x, y, f, alpha, reps)) for m, f in metrics.items()]
        return pd.DataFrame(rows, columns=["pair_id", "metric", "value", "identified"])

    return paired.groupBy("pair_id").applyInPandas(run, "pair_id string, metric string, value double, identified boolean")


def recovery(selected: DataFrame, truth: DataFrame, bucket: int = 64) -> DataFrame:
    """Per planted span: its best window, the intersection over union, and both ends' errors."""
    o = overlaps(selected, truth, bucket)
    best = o.groupBy("pair_id", "bs", "be").agg(F.max_by(F.struct("as", "ae", "iou"), F.struct("iou", -F.col("as"))).alias("w"))
    return truth.select("pair_id", F.col("s").alias("bs"), F.col("e").alias("be")).join(best, ["pair_id", "bs", "be"], "left").select("pair_id", F.col("bs").alias("s"), F.col("be").alias("e"), F.coalesce("w.iou", F.lit(0.0)).alias("iou"), (F.col("w.as") - F.col("bs")).alias("start_error"), (F.col("w.ae") - F.col("be")).alias("end_error"))


def threshold_effects(scores: DataFrame, truth: DataFrame, sigmas: list[float], by: str = "mi_norm2") -> DataFrame:
    """(sigma, total, meaningful): windows chosen at each threshold; meaningful ones lie half or more in a planted span."""
    grid = scores.sparkSession.createDataFrame([(s,) for s in sigmas], "sigma double")
    passing = scores.crossJoin(F.broadcast(grid)).where(F.col(by) >= F.col("sigma")).select("pair_id", "sigma", "s", "e")
    chosen = W.greedy(passing, ["pair_id", "sigma"])
    t = truth.select("pair_id", F.col("s").alias("ts"), F.col("e").alias("te"))
    near = chosen.join(F.broadcast(t), "pair_id", "left").withColumn("share", (F.least("e", "te") - F.greatest("s", "ts")) / (F.col("e") - F.col("s")))
    per = near.groupBy("pair_id", "sigma", "s").agg((F.max("share") >= 0.5).alias("hit"))
    got = per.groupBy("sigma").agg(F.count("*").alias("total"), F.sum(F.col("hit").cast("long")).alias("meaningful"))
    return grid.join(got, "sigma", "left").select("sigma", F.coalesce("total", F.lit(0)).alias("total"), F.coalesce("meaningful", F.lit(0)).alias("meaningful"))
