"""Connected components over a table of links, without bringing links or labels to the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from tempcorr.llm.common import dropped, written


def components(links: DataFrame, name: str = "cc") -> DataFrame:
    """(id, component): the smallest id that can be reached over links (a, b), for every id that has a link.

    Each round gives a node the smallest label among its own and its neighbours', and then that node's label (pointers are
    followed twice as far each round). Ends when a round changes nothing.
    """
    both = written(links.where("a <> b").select("a", "b").union(links.where("a <> b").select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), f"{name}-links")
    labels = written(both.groupBy("a").agg(F.least("a", F.min("b")).alias("label")).select(F.col("a").alias("id"), "label"), f"{name}-0")
    step = 0
    while True:
        step += 1
        near = both.join(labels.select(F.col("id").alias("b"), "label"), "b").groupBy("a").agg(F.min("label").alias("near"))
        lower = labels.join(near, F.col("id") == F.col("a")).select("id", F.least("label", "near").alias("label"), F.col("label").alias("old"))
        far = labels.select(F.col("id").alias("label"), F.col("label").alias("far"))
        jumped = lower.join(far, "label", "left").select("id", F.least("label", F.coalesce("far", "label")).alias("label"), "old")
        seen, before = Observation(), labels
        labels = written(jumped.observe(seen, F.count_if(F.col("label") < F.col("old")).alias("changed")).select("id", "label"), f"{name}-{step}")
        dropped(before)
        if not seen.get["changed"]:
            dropped(both)
            out = labels.select("id", F.col("label").alias("component"))
            out.tempcorr_path = labels.tempcorr_path
            return out
