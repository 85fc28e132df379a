"""Plug-in scores of all grid windows from counts of panes: a pane is a step, and a window is size / step panes.

Cells are counted once for each pane and summed for each window, so that a point is not repeated for every window that
holds it. Bins are those of the whole series.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tempcorr.functions.measures import by_width, normalised


def scores(paired: DataFrame, size: int, step: int, bins: int, start: int = 0) -> DataFrame:
    """SCORE columns of every window [start + i step, + size) of each pair."""
    if size % step:
        raise ValueError("a grid needs a step that divides the size")
    rows = by_width(paired, ["x", "y"], bins, ["pair_id"]).where(F.col("idx") >= start)
    ends = rows.groupBy("pair_id").agg((F.max("idx") + 1).alias("n"))
    cells = rows.groupBy("pair_id", F.floor((F.col("idx") - start) / step).alias("pane"), "b_x", "b_y").agg(F.count("*").alias("c"))
    spread = cells.select("pair_id", "b_x", "b_y", "c", F.explode(F.sequence(F.col("pane") - (size // step - 1), F.col("pane"))).alias("g")).where("g >= 0")
    w = spread.groupBy("pair_id", "g", "b_x", "b_y").agg(F.sum("c").alias("c"))
    by = ["pair_id", "g"]
    w = w.select("*", F.sum("c").over(Window.partitionBy(*by, "b_x")).alias("cx"), F.sum("c").over(Window.partitionBy(*by, "b_y")).alias("cy"), F.sum("c").over(Window.partitionBy(*by)).alias("n"))
    p = F.col("c") / F.col("n")
    out = w.groupBy(*by, "n").agg(
        F.sum(-p * F.log(F.col("cx") / F.col("n"))).alias("hx"),
        F.sum(-p * F.log(F.col("cy") / F.col("n"))).alias("hy"),
        F.sum(-p * F.log(p)).alias("hxy"),
        F.sum(p * F.log(F.col("c") * F.col("n") / (F.col("cx") * F.col("cy")))).alias("mi"),
    )
    s = (F.lit(start) + F.col("g") * step).cast("long")
    out = out.withColumn("s", s).withColumn("e", F.col("s") + size).join(ends.withColumnRenamed("n", "end"), "pair_id").where("e <= end").drop("end", "g")
    return normalised(out)
