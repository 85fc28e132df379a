"""From raw rows to aligned series."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

ORIGIN = {"events": "2024-01-01", "orders": "1995-01-01", "lineitem": "1995-01-01"}
SECONDS = {"1M": 60, "15M": 900, "1H": 3600, "1D": 86400}


@dataclass(frozen=True)
class VariableSpec:
    """An aggregate of a source at a time resolution."""

    name: str
    ts: str
    value: Column
    resolution: str = "1H"
    origin: str = "2024-01-01"
    where: Column | None = None
    keys: tuple[str, ...] = field(default=())


def index_of(ts: Column, resolution: str, origin: str) -> Column:
    """The number of whole steps since the origin: arithmetic, so that no rows need a global order."""
    unit = {60: "MINUTE", 900: "MINUTE", 3600: "HOUR", 86400: "DAY"}[SECONDS[resolution]]
    steps = F.timestamp_diff(unit, F.lit(origin).cast("timestamp_ntz"), ts)
    return (F.floor(steps / 15) if resolution == "15M" else steps).cast("long")


def dedup(df: DataFrame, keys: list[str]) -> DataFrame:
    return df.dropDuplicates(keys)


def extract(df: DataFrame, spec: VariableSpec) -> DataFrame:
    """SERIES (var, idx, v) of a variable: filter, then a partial and a final aggregate."""
    rows = df if spec.where is None else df.where(spec.where)
    return rows.groupBy(*spec.keys, index_of(F.col(spec.ts), spec.resolution, spec.origin).alias("idx")).agg(spec.value.cast("double").alias("v")).select(F.lit(spec.name).alias("var"), *spec.keys, "idx", "v")


def spine(series: DataFrame, low: int, high: int, fill: float | None = None) -> DataFrame:
    """Every index of [low, high) for every variable; counts take `fill`, measured values stay null."""
    names = series.select("var").distinct()
    grid = names.select("var", F.explode(F.sequence(F.lit(low).cast("long"), F.lit(high - 1).cast("long"))).alias("idx"))
    out = grid.join(series, ["var", "idx"], "left").withColumn("imputed", F.col("v").isNull())
    return out if fill is None else out.withColumn("v", F.coalesce("v", F.lit(fill)))


def interpolate(series: DataFrame, chunk: int = 1 << 20, hold: bool = True) -> DataFrame:
    """Linear between known neighbours; at the ends the nearest known value is held, or the point dropped.

    Works by (var, chunk): a small table of each chunk's first and last known points carries values over chunk edges.
    """
    s = series.withColumn("chunk", F.floor(F.col("idx") / chunk))
    point = F.when(F.col("v").isNotNull(), F.struct("idx", "v"))
    s = s.withColumn("p", point)
    edges = s.groupBy("var", "chunk").agg(F.min("p").alias("first"), F.max("p").alias("last"))
    w = Window.partitionBy("var").orderBy("chunk")
    edges = edges.select("var", "chunk", F.last("last", True).over(w.rowsBetween(Window.unboundedPreceding, -1)).alias("carry_a"), F.first("first", True).over(w.rowsBetween(1, Window.unboundedFollowing)).alias("carry_b"))
    v = Window.partitionBy("var", "chunk").orderBy("idx")
    s = s.select("*", F.last("p", True).over(v.rowsBetween(Window.unboundedPreceding, 0)).alias("a"), F.first("p", True).over(v.rowsBetween(0, Window.unboundedFollowing)).alias("b"))
    s = s.join(edges, ["var", "chunk"]).withColumn("a", F.coalesce("a", "carry_a")).withColumn("b", F.coalesce("b", "carry_b"))
    between = F.col("a.v") + (F.col("b.v") - F.col("a.v")) * (F.col("idx") - F.col("a.idx")) / F.when(F.col("b.idx") > F.col("a.idx"), F.col("b.idx") - F.col("a.idx"))
    known = F.coalesce("v", between)
    out = s.withColumn("v", F.coalesce(known, F.col("a.v"), F.col("b.v")) if hold else known)
    return out.where("v is not null").select("var", "idx", "v", "imputed")


def align(a: DataFrame, b: DataFrame, pair_id: str) -> DataFrame:
    """PAIRED rows of two series of one resolution."""
    return a.select("idx", F.col("v").alias("x")).join(b.select("idx", F.col("v").alias("y")), "idx").select(F.lit(pair_id).alias("pair_id"), "idx", "x", "y")


def coarser(series: DataFrame, factor: int, how: str = "avg") -> DataFrame:
    return series.groupBy("var", F.floor(F.col("idx") / factor).cast("long").alias("idx")).agg(getattr(F, how)("v").alias("v"))


def finer(series: DataFrame, factor: int) -> DataFrame:
    return series.select("var", F.explode(F.sequence(F.col("idx") * factor, F.col("idx") * factor + factor - 1)).alias("idx"), "v")


def lagged(paired: DataFrame, tau: int) -> DataFrame:
    """y moved by tau steps against x."""
    return paired.select("pair_id", "idx", "x").join(paired.select("pair_id", (F.col("idx") + tau).alias("idx"), "y"), ["pair_id", "idx"])


def asof(left: DataFrame, right: DataFrame, tolerance: int | None = None) -> DataFrame:
    """For every left point the latest right value at or before it."""
    both = left.select("var", "idx", F.col("v").alias("x"), F.lit(1).alias("side"), F.lit(None).cast("struct<idx:bigint,v:double>").alias("r")).unionByName(right.select("var", "idx", F.lit(None).cast("double").alias("x"), F.lit(0).alias("side"), F.struct("idx", "v").alias("r")))
    w = Window.partitionBy("var").orderBy("idx", "side").rowsBetween(Window.unboundedPreceding, 0)
    out = both.withColumn("r", F.last("r", True).over(w)).where("side = 1")
    y = F.col("r.v") if tolerance is None else F.when(F.col("idx") - F.col("r.idx") <= tolerance, F.col("r.v"))
    return out.select("var", "idx", "x", y.alias("y"))


def enumerate_pairs(names: DataFrame) -> DataFrame:
    """Every pair of variables once; names are metadata, whose size a caller budgets."""
    a, b = names.select(F.col("var").alias("a")), names.select(F.col("var").alias("b"))
    return a.join(F.broadcast(b), F.col("a") < F.col("b"))


def pack(series: DataFrame, chunk: int) -> DataFrame:
    """BLOCK rows: a chunk of a series as one sorted array."""
    return series.groupBy("var", F.floor(F.col("idx") / chunk).cast("long").alias("chunk")).agg(F.array_sort(F.collect_list(F.struct("idx", "v"))).alias("p")).select("var", "chunk", F.element_at("p", 1)["idx"].alias("s"), (F.element_at("p", -1)["idx"] + 1).alias("e"), F.transform("p", lambda q: q["v"]).alias("v"))


def unpack(blocks: DataFrame) -> DataFrame:
    return blocks.select("var", "s", F.posexplode("v").alias("i", "v")).select("var", (F.col("s") + F.col("i")).alias("idx"), "v")


def all_pairs(series: DataFrame, chunk: int, tiles: int = 8) -> DataFrame:
    """Pairs of packed series, by tiles of variables: a block is shipped to the tiles it meets, not once for each pair."""
    b = pack(series, chunk).withColumn("tile", F.pmod(F.xxhash64("var"), F.lit(tiles)).cast("int"))
    to = F.explode(F.transform(F.sequence(F.lit(0), F.lit(tiles - 1)), lambda t: F.struct(F.least("tile", t).alias("lo"), F.greatest("tile", t).alias("hi"))))
    sent = b.select("*", to.alias("cell"))
    x = sent.select("cell", "chunk", F.col("var").alias("a"), "tile", "s", F.col("v").alias("xs"))
    y = sent.select("cell", "chunk", F.col("var").alias("b"), F.col("tile").alias("tile2"), F.col("s").alias("s2"), F.col("v").alias("ys"))
    own = F.col("cell") == F.struct(F.least("tile", "tile2").alias("lo"), F.greatest("tile", "tile2").alias("hi"))
    return x.join(y, ["cell", "chunk"]).where(own & (F.col("a") < F.col("b")) & (F.col("s") == F.col("s2"))).select(F.concat_ws("|", "a", "b").alias("pair_id"), F.explode(F.arrays_zip("xs", "ys")).alias("p"), "s", "chunk").select("pair_id", F.col("p.xs").alias("x"), F.col("p.ys").alias("y"))


def props_value(df: DataFrame, key: str) -> Column:
    return F.from_json(F.col("props"), "map<string,double>")[key]


def embedding_component(df: DataFrame, i: int) -> DataFrame:
    return df.select(F.lit(f"e{i}").alias("var"), F.col("vec_id").alias("idx"), F.element_at("embedding", i + 1).cast("double").alias("v"))


def assign_points(points: DataFrame, windows: DataFrame, bucket: int) -> DataFrame:
    """Points of each window: an equi join on index buckets, then the exact bounds."""
    w = windows.select("*", F.explode(F.sequence(F.floor(F.col("s") / bucket), F.floor((F.col("e") - 1) / bucket))).alias("_b"))
    return points.withColumn("_b", F.floor(F.col("idx") / bucket)).join(w, ["pair_id", "_b"]).where("idx >= s and idx < e").drop("_b")


def inside(points: DataFrame, windows: DataFrame, bucket: int, keep: bool = True) -> DataFrame:
    """The points that some window holds, or those that none does: a semi or an anti join on buckets of time."""
    w = windows.select(F.col("pair_id").alias("_p"), "s", "e", F.explode(F.sequence(F.floor(F.col("s") / bucket), F.floor((F.col("e") - 1) / bucket))).alias("_w"))
    held = (F.col("pair_id") == F.col("_p")) & (F.floor(F.col("idx") / bucket) == F.col("_w")) & (F.col("idx") >= F.col("s")) & (F.col("idx") < F.col("e"))
    return points.join(w, held, "left_semi" if keep else "left_anti")


def profile(series: DataFrame) -> DataFrame:
    """Per variable: points, steps without one, distinct values, smallest, largest and mean value."""
    out = series.groupBy("var").agg(F.count("v").alias("n"), (F.max("idx") - F.min("idx") + 1 - F.count("v")).alias("missing"), F.count_distinct("v").alias("values"), F.min("v").alias("low"), F.max("v").alias("high"), F.avg("v").alias("mean"))
    return out


def horizon(series: DataFrame) -> tuple[int, int]:
    """The first step of a series and the one after its last: two numbers."""
    r = series.agg(F.min("idx").alias("a"), F.max("idx").alias("b")).first()
    return (0, 0) if r["a"] is None else (r["a"], r["b"] + 1)


def even(series: DataFrame, fill: float | None = None) -> DataFrame:
    """Series without gaps: interpolated, each from its first to its last step; or all over one range, with `fill`."""
    if fill is not None:
        return spine(series, *horizon(series), fill)
    ends = series.groupBy("var").agg(F.min("idx").alias("a"), F.max("idx").alias("b"))
    steps = ends.select("var", F.explode(F.sequence("a", "b")).alias("idx"))
    return interpolate(steps.join(series.select("var", "idx", "v"), ["var", "idx"], "left").withColumn("imputed", F.col("v").isNull()))


def overlaps(a: DataFrame, b: DataFrame, bucket: int) -> DataFrame:
    """Pairs of overlapping spans with their intersection over union."""
    cut = lambda df, p: df.select("pair_id", F.col("s").alias(f"{p}s"), F.col("e").alias(f"{p}e"), F.explode(F.sequence(F.floor(F.col("s") / bucket), F.floor((F.col("e") - 1) / bucket))).alias("_b"))
    common = F.least("ae", "be") - F.greatest("as", "bs")
    return cut(a, "a").join(cut(b, "b"), ["pair_id", "_b"]).where(common > 0).select("pair_id", "as", "ae", "bs", "be", common.alias("common"), (common / (F.greatest("ae", "be") - F.least("as", "bs"))).alias("iou")).distinct()
