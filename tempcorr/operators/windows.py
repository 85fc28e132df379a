"""Windows: ladders, grids, greedy choice, left-out spans, merging, coverage, ranking."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

POINTS = {"1M": 1 / 60, "15M": 0.25, "1H": 1.0, "1D": 24.0}
HOURS = {"year": 8760, "month": 720, "week": 168, "day": 24, "hour": 1}


@dataclass(frozen=True)
class Layer:
    label: str
    size: int
    step: int
    sigma: float | None = None


@dataclass(frozen=True)
class Ladder:
    """Window sizes from coarse to fine, each with its step."""

    layers: tuple[Layer, ...]

    @classmethod
    def of(cls, *pairs: tuple[int, int]) -> Ladder:
        return cls(tuple(Layer(f"{size}", size, step) for size, step in pairs))

    @classmethod
    def single(cls, size: int, step: int) -> Ladder:
        return cls.of((size, step))

    @classmethod
    def calendar(cls, resolution: str, largest: str = "year", smallest: str = "hour", share: float = 0.25, least: int = 12) -> Ladder:
        """Year, month, week, day, hour in points of a resolution, as far as they have enough points."""
        names = list(HOURS)
        names = names[names.index(largest) : names.index(smallest) + 1]
        sizes = [(x, int(HOURS[x] / POINTS[resolution])) for x in names]
        return cls(tuple(Layer(x, n, max(1, int(n * share))) for x, n in sizes if n >= least))

    @classmethod
    def arithmetic(cls, largest: int, smallest: int, less: int, step: int) -> Ladder:
        return cls.of(*[(n, step) for n in range(largest, smallest - 1, -less)])


@dataclass(frozen=True)
class Absolute:
    sigma: float

    def column(self) -> Column:
        return F.col("mi") >= self.sigma

    def __call__(self, row: dict) -> bool:
        return row["mi"] is not None and row["mi"] >= self.sigma


@dataclass(frozen=True)
class TwoStep:
    """Enough normalised entropy first, then enough normalised information by either norm."""

    sigma_h: float = 0.2
    sigma_i: float = 0.2
    norm: str = "n2"

    def column(self) -> Column:
        one, two = F.col("mi_norm1") >= self.sigma_i, F.col("mi_norm2") >= self.sigma_i
        return (F.col("h_norm") >= self.sigma_h) & {"n1": one, "n2": two, "either": F.coalesce(one, F.lit(False)) | F.coalesce(two, F.lit(False))}[self.norm]

    def __call__(self, row: dict) -> bool:
        if row["h_norm"] is None or row["h_norm"] < self.sigma_h:
            return False
        one, two = ((row[c] is not None and row[c] >= self.sigma_i) for c in ("mi_norm1", "mi_norm2"))
        return {"n1": one, "n2": two, "either": one or two}[self.norm]


def whole(paired: DataFrame) -> DataFrame:
    """The first segments: each pair's whole range."""
    return paired.groupBy("pair_id").agg(F.min("idx").alias("s"), (F.max("idx") + 1).alias("e"))


def grid(segments: DataFrame, size: int, step: int) -> DataFrame:
    """All windows of a segment on its step grid."""
    return segments.where(F.col("e") - F.col("s") >= size).select("pair_id", F.col("s").alias("seg"), F.explode(F.sequence("s", F.col("e") - size, F.lit(step).cast("long"))).alias("s")).select("pair_id", "seg", "s", (F.col("s") + size).alias("e"))


#: Steps of a series whose windows are ordered in one task; what earlier ones reach is carried by a row for each.
STRETCH = 1 << 16


def _carried(df: DataFrame, keys: list[str], value: Column, name: str, include: bool) -> DataFrame:
    """Adds the largest value among the rows before (and with) each, by (s, e): within its stretch, and of all stretches before."""
    at = F.floor(F.col("s") / STRETCH)
    df = df.withColumn("_t", at).withColumn("_v", value)
    own = F.max("_v").over(Window.partitionBy(*keys, "_t").orderBy("s", "e").rowsBetween(Window.unboundedPreceding, 0 if include else -1))
    before = Window.partitionBy(*keys).orderBy("_t").rowsBetween(Window.unboundedPreceding, -1)
    carry = df.groupBy(*keys, "_t").agg(F.max("_v").alias("_m")).select(*keys, "_t", F.max("_m").over(before).alias("_m"))
    return df.withColumn("_o", own).join(carry, [*keys, "_t"]).withColumn(name, F.greatest("_o", "_m")).drop("_t", "_v", "_o", "_m")


def islands(df: DataFrame, keys: list[str]) -> DataFrame:
    """Adds _i: where the run of overlapping windows begins that a window is in. No task has a whole series."""
    out = _carried(df, keys, F.col("e"), "_before", False)
    new = F.col("_before").isNull() | (F.col("s") >= F.col("_before"))
    return _carried(out, keys, F.when(new, F.col("s")), "_i", True).drop("_before")


def _folded(df: DataFrame, keys: list[str], order, taken) -> DataFrame:
    """Of every island the windows that a fold over them, in an order, takes."""
    spans = islands(df, keys).groupBy(*keys, "_i").agg(order(F.collect_list(F.struct("s", "e"))).alias("all"))
    return spans.select(*keys, F.explode(taken("all")).alias("w")).select(*keys, "w.s", "w.e")


def greedy(passing: DataFrame, keys: list[str]) -> DataFrame:
    """The windows that a left-to-right scan takes. Islands of overlapping windows don't touch each other's choice."""

    def taken(column):
        return F.aggregate(
            column,
            F.struct(F.array().cast("array<struct<s:bigint,e:bigint>>").alias("t"), F.lit(-(1 << 62)).cast("long").alias("end")),
            lambda a, x: F.when(x["s"] >= a["end"], F.struct(F.concat(a["t"], F.array(F.struct(x["s"].alias("s"), x["e"].alias("e")))).alias("t"), x["e"].alias("end"))).otherwise(a),
            lambda a: a["t"],
        )

    return _folded(passing, keys, F.array_sort, taken)


def disjoint(selected: DataFrame) -> DataFrame:
    """(pair_id, s, e): of overlapping windows the larger, of equal ones the earlier; what is kept never overlaps."""
    larger = lambda a: F.transform(F.array_sort(F.transform(a, lambda w: F.struct((w["s"] - w["e"]).alias("n"), w["s"].alias("s"), w["e"].alias("e")))), lambda w: F.struct(w["s"].alias("s"), w["e"].alias("e")))

    def taken(column):
        none = F.array().cast("array<struct<s:bigint,e:bigint>>")
        return F.aggregate(column, none, lambda kept, x: F.when(F.exists(kept, lambda k: (k["s"] < x["e"]) & (x["s"] < k["e"])), kept).otherwise(F.concat(kept, F.array(x))))

    return _folded(selected.select("pair_id", "s", "e").distinct(), ["pair_id"], larger, taken)


def leftouts(segments: DataFrame, selected: DataFrame) -> DataFrame:
    """What the selected windows leave of the segments: heads, gaps and tails. Windows meet segments by stretches of time."""
    stretch = lambda s, e: F.explode(F.sequence(F.floor(F.col(s) / STRETCH), F.floor((F.col(e) - 1) / STRETCH)))
    seg = segments.select("pair_id", F.col("s").alias("gs"), F.col("e").alias("ge"))
    cut = seg.where("gs < ge").select("*", stretch("gs", "ge").alias("_t"))
    inside = cut.join(selected.select("pair_id", "s", "e", stretch("s", "e").alias("_t")), ["pair_id", "_t"]).where("s < ge and e > gs").drop("_t").distinct()
    keys = ["pair_id", "gs", "ge"]
    gaps = _carried(inside, keys, F.col("e"), "_before", False).withColumn("a", F.greatest("gs", F.coalesce("_before", F.col("gs")))).where("s > a").select("pair_id", F.col("a").alias("s"), F.col("s").alias("e"))
    tails = seg.join(inside.groupBy(*keys).agg(F.max("e").alias("last")), keys, "left").select("pair_id", F.greatest("gs", F.coalesce("last", "gs")).alias("s"), F.col("ge").alias("e")).where("s < e")
    return gaps.unionByName(tails)


def merge(selected: DataFrame, mode: str = "contained") -> DataFrame:
    """contained: drop windows inside a larger one; disjoint: of overlapping ones the larger; union: a span for each run."""
    if mode == "disjoint":
        return selected.join(disjoint(selected), ["pair_id", "s", "e"])
    if mode == "contained":  # of windows that begin together the longest comes first
        longest = selected.withColumn("_r", F.row_number().over(Window.partitionBy("pair_id", "s").orderBy(F.desc("e")))).where("_r = 1").drop("_r")
        return _carried(longest, ["pair_id"], F.col("e"), "_m", False).where("_m is null or e > _m").drop("_m")
    return islands(selected, ["pair_id"]).groupBy("pair_id", "_i").agg(F.min("s").alias("s"), F.max("e").alias("e"), F.array_sort(F.collect_list(F.struct("s", "e"))).alias("parts")).drop("_i")


def coverage(selected: DataFrame, sizes: DataFrame) -> DataFrame:
    """Samples in selected windows over all samples (pair_id, n)."""
    got = merge(selected.select("pair_id", "s", "e"), "union").groupBy("pair_id").agg(F.sum(F.col("e") - F.col("s")).alias("covered"))
    return sizes.join(got, "pair_id", "left").select("pair_id", (F.coalesce("covered", F.lit(0)) / F.col("n")).alias("coverage"))


def rank(selected: DataFrame, by: str = "mi", k: int = 10, per_pair: bool = False, method: str = "row_number") -> DataFrame:
    """The best windows; ties go to the earlier one, then to the smaller pair."""
    order = [F.desc(by), F.asc("s"), F.asc("pair_id")]
    if not per_pair:
        return selected.orderBy(*order).limit(k)
    f = F.ntile(k) if method == "ntile" else getattr(F, method)()
    ranked = selected.withColumn("rank", f.over(Window.partitionBy("pair_id").orderBy(*(order if method == "row_number" else order[:1]))))
    return ranked if method == "ntile" else ranked.where(F.col("rank") <= k)


def same(a: DataFrame, b: DataFrame) -> bool:
    columns = ["pair_id", "s", "e"]
    a, b = a.select(*columns), b.select(*columns)
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def rollup(selected: DataFrame) -> DataFrame:
    return selected.rollup("pair_id", "layer").agg(F.count("*").alias("windows"), F.max("mi").alias("best"))


def cube(selected: DataFrame) -> DataFrame:
    return selected.cube("pair_id", "layer", "sign").agg(F.count("*").alias("windows"), F.grouping_id().alias("grouping"))


def summary(selected: DataFrame) -> DataFrame:
    return selected.groupBy("pair_id").agg(F.count("*").alias("windows"), F.avg("mi").alias("mean"), F.variance("mi").alias("variance"), F.skewness("mi").alias("skewness"), F.percentile_approx("mi", 0.5).alias("median"))
