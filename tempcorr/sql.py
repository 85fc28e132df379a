"""The engine from SQL: aggregates over columns and a table function over pairs."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from tempcorr.functions import kernel


def register(spark: SparkSession) -> None:
    """knn_mi_agg(x, y, k), dcor_agg(x, y), digamma_int(n) and correlation_windows(TABLE(...), size, step, sigma)."""

    @F.pandas_udf("double")
    def knn_mi_agg(x: pd.Series, y: pd.Series, k: pd.Series) -> float:
        return kernel.knn_mi(kernel.jitter(x.to_numpy(float), 1), kernel.jitter(y.to_numpy(float), 2), int(k.iloc[0])) if len(x) > int(k.iloc[0]) else None

    @F.pandas_udf("double")
    def dcor_agg(x: pd.Series, y: pd.Series) -> float:
        return kernel.dcor(x, y)

    @F.pandas_udf("double")
    def digamma_int(n: pd.Series) -> pd.Series:
        return pd.Series(kernel.digamma_int(n.to_numpy(int)))

    @F.udtf(returnType="pair_id string, s long, e long, mi double")
    class CorrelationWindows:
        def __init__(self):
            self.rows = []

        def eval(self, row, size: int, step: int, sigma: float):
            self.rows.append((row["idx"], row["x"], row["y"], row["pair_id"]))
            self.args = (size, step, sigma)

        def terminate(self):
            if self.rows:
                self.rows.sort()
                size, step, sigma = self.args
                x, y = ([r[j] for r in self.rows] for j in (1, 2))
                first, pair = self.rows[0][0], self.rows[0][3]
                for r in kernel.scan(x, y, 0, len(x), size, step, lambda q: q["mi"] is not None and q["mi"] >= sigma)[0]:
                    yield pair, r["s"] + first, r["e"] + first, r["mi"]

    for name, f in (("knn_mi_agg", knn_mi_agg), ("dcor_agg", dcor_agg), ("digamma_int", digamma_int)):
        spark.udf.register(name, f)
    spark.udtf.register("correlation_windows", CorrelationWindows)
