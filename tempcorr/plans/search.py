"""Searches over pairs: layer by layer, by one of three executors, and what is built from them."""

from __future__ import annotations

import tempfile
import uuid

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tempcorr.functions import kernel
from tempcorr.operators import prep
from tempcorr.operators import windows as W
from tempcorr.sources.synth import noise

SCORE = "n long, mi double, hx double, hy double, hxy double, h_norm double, mi_norm1 double, mi_norm2 double, pp long, np long, mu double, sign string, conf double"
FOUND = f"pair_id string, kind string, number long, s long, e long, {SCORE}, windows long, added long, removed long, researched long, recounted long, untouched long, rebuilt long"
NAMES = [c.split()[0] for c in SCORE.split(", ")]
COUNTERS = ["windows", "added", "removed", "researched", "recounted", "untouched", "rebuilt"]


def cut(df: DataFrame) -> DataFrame:
    """Cuts the lineage between layers: a table in the shared folder, which survives lost executors.

    Only a local session that names no folder (tests) gets a temporary one.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark).rstrip('/')}/tempcorr-search-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def shared_folder(spark) -> str:
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder is None:
        kept = spark.sparkContext._jsc.sc().getCheckpointDir()
        if kept.isDefined():
            return kept.get()
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = tempfile.mkdtemp(prefix="tempcorr-")
        spark.sparkContext.setCheckpointDir(folder)
    return folder


def untied(paired: DataFrame, share: float = 1e-6) -> DataFrame:
    """Breaks ties by noise of a millionth of a pair's spread. It depends on idx alone: every slice has the same values."""
    spread = paired.groupBy("pair_id").agg(*[F.coalesce(F.nullif(F.stddev_pop(c), F.lit(0.0)), F.lit(1.0)).alias(f"_{c}") for c in "xy"])
    moved = [(F.col(c) + share * F.col(f"_{c}") * (noise(F.col("idx"), f"tie{c}") - 0.5)).alias(c) for c in "xy"]
    return paired.join(spread, "pair_id").select("pair_id", "idx", *moved)


def _rows(pair, kind, spans):
    return [{"pair_id": pair, "kind": kind, "s": s, "e": e} for s, e in spans]


def _frame(rows) -> pd.DataFrame:
    out = pd.DataFrame(rows, columns=[c.split()[0] for c in FOUND.split(", ")]).astype({c: "Int64" for c in ("number", "s", "e", "n", "pp", "np", *COUNTERS)})
    for c in ("pair_id", "kind", "sign"):  # plain objects: strings and nulls in one array
        out[c] = [None if v is None or v != v else str(v) for v in out[c]]
        out[c] = out[c].astype(object)
    return out


def scan_segments(paired: DataFrame, segments: DataFrame, layers: list[tuple[W.Layer, object]], options: dict) -> DataFrame:
    """For each segment one task's scan by the given (layer, rule) pairs, coarse to fine: rows of FOUND.

    kind is selected, left, or counters; a row's number is its layer's place in `layers`.
    """
    inside = prep.assign_points(paired, segments.select("pair_id", "s", "e"), max(layers[0][0].size, 1024))
    sizes, rules = [(x.size, x.step) for x, _ in layers], [r for _, r in layers]

    def run(df: pd.DataFrame) -> pd.DataFrame:
        df = df.sort_values("idx")
        pair, s, e = df["pair_id"].iloc[0], int(df["s"].iloc[0]), int(df["e"].iloc[0])
        if len(df) != e - s:
            raise ValueError("a series has gaps: fill its spine first")
        chosen, left, tallies = kernel.top_down(df["x"].to_numpy(), df["y"].to_numpy(), 0, e - s, sizes, rules.__getitem__, **options)
        rows = [{"pair_id": pair, "kind": "selected", "number": i, **r, "s": r["s"] + s, "e": r["e"] + s} for i, r in chosen]
        rows += _rows(pair, "left", [(a + s, b + s) for a, b in left])
        rows += [{"pair_id": pair, "kind": "counters", "number": i, "s": s, "e": e, **c} for i, c in enumerate(tallies)]
        return _frame(rows)

    return inside.groupBy("pair_id", "s", "e").applyInPandas(run, FOUND)


def score_windows(paired: DataFrame, wanted: DataFrame, size: int, options: dict) -> DataFrame:
    """SCORE rows of given windows of one size. Points go to chunks with the next `size` points as a halo: a window is a slice."""
    chunk = 16 * size
    at = F.floor(F.col("idx") / chunk)
    halo = F.when((F.col("idx") % chunk < size) & (at > 0), F.array(at - 1, at)).otherwise(F.array(at))
    points = paired.select("pair_id", "idx", "x", "y", F.explode(halo).alias("chunk"))
    starts = wanted.select(F.col("pair_id").alias("pair"), F.col("s").alias("start"), F.floor(F.col("s") / chunk).alias("part"))

    def run(key, p: pd.DataFrame, w: pd.DataFrame) -> pd.DataFrame:
        p = p.sort_values("idx")
        idx, x, y = (p[c].to_numpy() for c in ("idx", "x", "y"))
        rows = []
        for s in np.sort(w["start"].to_numpy()):
            a, b = np.searchsorted(idx, [s, s + size])
            if b - a == size:
                rows.append({"pair_id": key[0], "s": int(s), "e": int(s) + size, **kernel.score(x[a:b], y[a:b], **options)})
        return pd.DataFrame(rows, columns=["pair_id", "s", "e", *NAMES]).astype({c: "Int64" for c in ("s", "e", "n", "pp", "np")})

    return points.groupBy("pair_id", "chunk").cogroup(starts.groupBy("pair", "part")).applyInPandas(run, f"pair_id string, s long, e long, {SCORE}")


def chunk_bounds(n: int, largest: int, m: int) -> list[tuple[int, int]]:
    """Overlapping chunks: each begins one largest window before its own part."""
    width = m * largest
    return [(max(0, r * width - largest), min(n, (r + 1) * width)) for r in range(-(-n // width))]


def _chunked(segments: DataFrame, largest: int, m: int) -> DataFrame:
    width = m * largest
    r = F.explode(F.sequence(F.floor(F.col("s") / width), F.floor((F.col("e") - 1) / width)))
    return segments.select("pair_id", "s", "e", r.alias("r")).select("pair_id", F.greatest("s", F.col("r") * width - largest).alias("s"), F.least("e", (F.col("r") + 1) * width).alias("e"))


def layered_search(paired: DataFrame, ladder: W.Ladder, criterion, executor: str = "sequential", windows_per_chunk: int = 4, independent_layers: bool = False, **options):
    """(selected, left out, counters). Finer layers search only what coarser ones left.

    executor 'sequential' scans each series in a task, all layers one after the other; 'grid' scores all grid windows at once and then takes greedily,
    which equals the scan where the step divides the size. 'chunked' scans overlapping chunks of bounded size, layer by
    layer; 'recursive' runs the whole ladder inside each chunk. Both then keep of overlapping windows the larger, then the
    earlier, deal what the others have covered to new tasks of bounded size, and end when nothing more is left.
    """
    options = {"estimator": "knn", "k": 6, "tie": "jitter", **options}
    if options["estimator"] != "plugin" and options["tie"] == "jitter":
        paired, options["tie"] = cut(untied(paired)), None
    rules = [criterion if x.sigma is None else W.Absolute(x.sigma) for x in ladder.layers]
    layers = list(zip(ladder.layers, rules, strict=True))
    whole = cut(W.whole(paired))
    if executor == "recursive":
        return _in_chunks(paired, whole, layers, list(range(len(layers))), windows_per_chunk, options)
    if executor == "sequential" and not independent_layers:
        rows = cut(scan_segments(paired, whole, layers, options))
        numbers = list(range(len(layers)))
        return _selected(rows, numbers, [x.size for x, _ in layers]), rows.where("kind = 'left'").select("pair_id", "s", "e"), _tallies(rows, numbers)
    segments, found, tallies, left = whole, [], [], whole
    for i, (layer, rule) in enumerate(layers):
        if executor == "grid" and layer.size % layer.step == 0:
            wanted = W.grid(segments, layer.size, layer.step)
            kept = {k: v for k, v in options.items() if k in ("estimator", "k", "bins", "tie")}
            scores = cut(score_windows(paired, wanted, layer.size, kept))
            passing = scores.where(rule.column()).select("pair_id", "s", "e").join(wanted, ["pair_id", "s", "e"])
            selected = W.greedy(passing, ["pair_id", "seg"]).select("pair_id", "s", "e").join(scores, ["pair_id", "s", "e"])
            selected = cut(selected.withColumn("layer", F.lit(i)).withColumn("g", F.lit(layer.size).cast("long")))
            left = cut(W.leftouts(segments, selected))
            tally = scores.groupBy("pair_id").agg(F.count("*").alias("windows"), *[F.lit(0).cast("long").alias(c) for c in COUNTERS[1:]]).withColumn("layer", F.lit(i))
        elif executor == "chunked":
            selected, left, tally = _in_chunks(paired, segments, [(layer, rule)], [i], windows_per_chunk, options, ladder.layers[0].size)
        else:
            rows = cut(scan_segments(paired, segments, [(layer, rule)], options))
            selected = _selected(rows, [i], [layer.size])
            left = rows.where("kind = 'left'").select("pair_id", "s", "e")
            tally = _tallies(rows, [i])
        found.append(selected)
        tallies.append(tally)
        segments = whole if independent_layers else left
        if segments.isEmpty():
            break
    return _union(found), left, _union(tallies)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _numbered(values: list[int], kind: str):
    return F.array(*[F.lit(v) for v in values])[F.col("number").cast("int")].cast(kind)


def _selected(rows: DataFrame, numbers: list[int], sizes: list[int]) -> DataFrame:
    return rows.where("kind = 'selected'").select("pair_id", "s", "e", *NAMES, _numbered(numbers, "int").alias("layer"), _numbered(sizes, "long").alias("g"))


def _tallies(rows: DataFrame, numbers: list[int]) -> DataFrame:
    return rows.where("kind = 'counters'").groupBy("pair_id", _numbered(numbers, "int").alias("layer")).agg(*[F.sum(c).alias(c) for c in COUNTERS]).select("pair_id", *COUNTERS, "layer")


def _in_chunks(paired, segments, layers, numbers, windows_per_chunk, options, largest=None):
    """Scans of overlapping chunks, their windows merged, and what the merging has freed dealt anew until nothing is."""
    largest, sizes = largest or layers[0][0].size, [x.size for x, _ in layers]
    finest, found, tallies, waiting = min(sizes), None, [], segments
    while True:
        rows = cut(scan_segments(paired, _chunked(waiting, largest, windows_per_chunk), layers, options))
        scanned = _selected(rows, numbers, sizes).dropDuplicates(["pair_id", "s", "e"])
        tallies.append(_tallies(rows, numbers))
        new = cut(W.merge(scanned, "disjoint"))
        found = new if found is None else found.unionByName(new)
        left = cut(W.leftouts(segments, found))
        dropped = scanned.join(new.select("pair_id", "s", "e"), ["pair_id", "s", "e"], "left_anti")
        free = prep.overlaps(left.where(F.col("e") - F.col("s") >= finest), dropped, W.STRETCH).select("pair_id", F.col("as").alias("s"), F.col("ae").alias("e")).distinct()
        waiting = cut(free)  # only where a window has gone that another one overlapped can there be something new
        if waiting.isEmpty():
            return found, left, _union(tallies).groupBy("pair_id", "layer").agg(*[F.sum(c).alias(c) for c in COUNTERS]).select("pair_id", *COUNTERS, "layer")


def choose_executor(segments: int, longest_share: float, divides: bool, cores: int) -> str:
    """Many segments of like length fill the cores by themselves; a few long ones need the grid, or chunks."""
    if segments >= 4 * cores and longest_share < 0.5:
        return "sequential"
    return "grid" if divides else "chunked"


def explain_search(n: int, ladder: W.Ladder, executor: str) -> str:
    lines = [f"executor {executor}, {n} points"]
    lines += [f"layer {i} {x.label}: size {x.size}, step {x.step}, at most {max(0, (n - x.size) // x.step + 1)} windows, {16 * n} bytes of points" for i, x in enumerate(ladder.layers)]
    return "\n".join(lines)


def exhaustive(paired: DataFrame, least: int, most: int, stride: int = 1, max_windows: int = 1_000_000, **options) -> DataFrame:
    """All windows of all sizes between two bounds."""
    n = W.whole(paired).agg(F.sum(F.col("e") - F.col("s")).alias("n")).first()["n"] or 0
    sizes = range(least, most + 1, stride)
    if n * len(sizes) > max_windows * stride:
        raise ValueError("too many windows: raise max_windows knowingly")
    parts = [score_windows(paired, W.grid(W.whole(paired), g, stride), g, options) for g in sizes]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def tune_k(paired: DataFrame, ks=range(1, 21), width: int = 3) -> DataFrame:
    """(pair_id, k, mi, spread): the estimate for every k and its variance over the ks around."""
    ks = list(ks)

    def run(df: pd.DataFrame) -> pd.DataFrame:
        df = df.sort_values("idx")
        x, y = kernel.jitter(df["x"].to_numpy(), 1), kernel.jitter(df["y"].to_numpy(), 2)
        mi = [kernel.knn_mi(x, y, k) for k in ks]
        spread = [float(np.var(mi[max(0, i - width // 2) : i + width // 2 + 1])) for i in range(len(ks))]
        return pd.DataFrame({"pair_id": df["pair_id"].iloc[0], "k": ks, "mi": mi, "spread": spread})

    return paired.groupBy("pair_id").applyInPandas(run, "pair_id string, k long, mi double, spread double")


def tune_sigma(scores: DataFrame, sizes: DataFrame, target: float, sigmas: list[float]) -> DataFrame:
    """(pair_id, sigma, coverage): of one scored layer, the threshold whose coverage is nearest to the target."""
    grid = scores.sparkSession.createDataFrame([(s,) for s in sigmas], "sigma double")
    passing = scores.crossJoin(F.broadcast(grid)).where("mi >= sigma").select("pair_id", "sigma", "s", "e")
    chosen = W.greedy(passing, ["pair_id", "sigma"]).groupBy("pair_id", "sigma").agg(F.sum(F.col("e") - F.col("s")).alias("covered"))
    every = sizes.crossJoin(F.broadcast(grid)).join(chosen, ["pair_id", "sigma"], "left").withColumn("coverage", F.coalesce("covered", F.lit(0)) / F.col("n"))
    return every.groupBy("pair_id").agg(F.min_by(F.struct("sigma", "coverage"), F.struct(F.abs(F.col("coverage") - target), "sigma")).alias("b")).select("pair_id", "b.sigma", "b.coverage")


def overall(paired: DataFrame, **options) -> DataFrame:
    """One window over all of each pair."""

    def run(df: pd.DataFrame) -> pd.DataFrame:
        df = df.sort_values("idx")
        row = kernel.score(df["x"].to_numpy(), df["y"].to_numpy(), **options) | {"dcor": kernel.dcor(df["x"].to_numpy(), df["y"].to_numpy())}
        return pd.DataFrame([{"pair_id": df["pair_id"].iloc[0], **row}])[["pair_id", *NAMES, "dcor"]]

    return paired.groupBy("pair_id").applyInPandas(run, f"pair_id string, {SCORE}, dcor double")


def knn_mi_distributed(paired: DataFrame, k: int = 6, cells: int | None = None) -> DataFrame:
    """(pair_id, mi) for windows too large for a task: neighbours by joins of grid cells, rings widened where needed.

    A point is settled when its k-th distance does not reach beyond the cells searched; the others go on with more rings.
    """
    from pyspark.sql import Window

    n = paired.groupBy("pair_id").agg(F.count("*").alias("n"), F.min("x").alias("lx"), F.max("x").alias("hx"), F.min("y").alias("ly"), F.max("y").alias("hy"))
    per = (F.lit(float(k)) / F.col("n")) if cells is None else F.lit(1.0 / cells)
    wide, high = F.col("hx") - F.col("lx"), F.col("hy") - F.col("ly")
    longest = F.greatest(wide, high)  # a series that is flat on one axis has a side all the same, a point cloud of one place too
    side = F.greatest(F.sqrt(wide * high * per), longest * per, F.when(longest == 0, F.lit(1.0)))
    points = cut(paired.join(n, "pair_id").withColumn("side", side).select("pair_id", "idx", "x", "y", "n", "side", F.floor((F.col("x") - F.col("lx")) / F.col("side")).alias("cx"), F.floor((F.col("y") - F.col("ly")) / F.col("side")).alias("cy")))
    if not points.where(F.col("n") <= k).isEmpty():
        raise ValueError("a pair needs more than k points")
    ends = points.agg(F.max(F.greatest("cx", "cy")).alias("m")).first()["m"]
    waiting, settled, ring = points, None, 1
    while ends is not None:
        around = F.explode(F.transform(F.sequence(F.lit(0), F.lit((2 * ring + 1) ** 2 - 1)), lambda j: F.struct((j % (2 * ring + 1) - ring).alias("u"), (F.floor(j / (2 * ring + 1)) - ring).alias("v"))))
        asked = waiting.select("*", around.alias("o")).select("pair_id", "idx", "x", "y", "side", "cx", "cy", (F.col("cx") + F.col("o.u")).alias("jx"), (F.col("cy") + F.col("o.v")).alias("jy"))
        other = points.select("pair_id", F.col("cx").alias("jx"), F.col("cy").alias("jy"), F.col("idx").alias("i2"), F.col("x").alias("x2"), F.col("y").alias("y2"))
        near = asked.join(other, ["pair_id", "jx", "jy"]).where("idx <> i2").withColumn("ax", F.abs(F.col("x") - F.col("x2"))).withColumn("ay", F.abs(F.col("y") - F.col("y2"))).withColumn("d", F.greatest("ax", "ay"))
        best = near.withColumn("r", F.row_number().over(Window.partitionBy("pair_id", "idx").orderBy("d", "i2"))).where(F.col("r") <= k)
        got = cut(best.groupBy("pair_id", "idx", "side").agg(F.count("*").alias("m"), F.max("d").alias("d"), F.max("ax").alias("dx"), F.max("ay").alias("dy")).where((F.col("m") == k) & ((F.col("d") < ring * F.col("side")) | F.lit(ring > ends))).select("pair_id", "idx", "dx", "dy"))
        settled = got if settled is None else settled.unionByName(got)
        waiting = cut(waiting.join(got.select("pair_id", "idx"), ["pair_id", "idx"], "left_anti"))
        if waiting.isEmpty():
            break
        ring *= 2
    both = points.join(settled, ["pair_id", "idx"])
    counts = None
    for v, reach in (("x", "dx"), ("y", "dy")):  # others within reach on one axis, by ranks in slices of the axis
        counted = _strip_counts(both, v, reach, k)
        counts = counted if counts is None else counts.join(counted, ["pair_id", "idx"])
    harmonic = lambda c: F.aggregate(F.sequence(F.lit(1), F.greatest(F.col(c) - 1, F.lit(1)).cast("int")), F.lit(0.0), lambda a, j: a + F.when(F.col(c) > 1, 1 / j).otherwise(F.lit(0.0))) - kernel.EULER
    total = counts.join(n.select("pair_id", "n"), "pair_id").withColumn("p", harmonic("nx") + harmonic("ny"))
    return total.groupBy("pair_id", "n").agg(F.avg("p").alias("m")).withColumn("psi_n", harmonic("n")).select("pair_id", (F.lit(float(kernel.digamma_int(np.array(k))) - 1 / k) - F.col("m") + F.col("psi_n")).alias("mi"))


def _strip_counts(points: DataFrame, v: str, reach: str, k: int) -> DataFrame:
    """How many others lie within reach on an axis: whole slices by their counts, the two at the ends point by point."""
    from pyspark.sql import Window

    edges = points.groupBy("pair_id").agg(F.min(v).alias("lo"), F.max(v).alias("hi"), F.sqrt(F.count("*") / 4).cast("int").alias("slices"))
    cell = lambda c: F.coalesce(F.floor(F.try_divide(c - F.col("lo"), F.col("hi") - F.col("lo")) * F.col("slices")), F.lit(0).cast("long"))
    p = points.join(edges, "pair_id").withColumn("a", F.col(v) - F.col(reach)).withColumn("b", F.col(v) + F.col(reach)).withColumn("slice", cell(F.col(v))).withColumn("sa", F.greatest(cell(F.col("a")), F.lit(-1))).withColumn("sb", F.least(cell(F.col("b")), F.col("slices") + 1))
    sizes = p.groupBy("pair_id", "slice").agg(F.count("*").alias("c"))
    upto = sizes.select("pair_id", "slice", F.sum("c").over(Window.partitionBy("pair_id").orderBy("slice")).alias("upto"))
    every = p.select("pair_id", "slices").distinct().select("pair_id", F.explode(F.sequence(F.lit(-1).cast("long"), F.col("slices").cast("long") + 1)).alias("slice"))
    filled = every.join(upto, ["pair_id", "slice"], "left").select("pair_id", "slice", F.coalesce(F.last("upto", True).over(Window.partitionBy("pair_id").orderBy("slice").rowsBetween(Window.unboundedPreceding, 0)), F.lit(0)).alias("upto"))
    inner = p.join(filled.select("pair_id", F.col("slice").alias("sa"), F.col("upto").alias("ua")), ["pair_id", "sa"]).join(filled.select("pair_id", (F.col("slice") + 1).alias("sb"), F.col("upto").alias("ub")), ["pair_id", "sb"], "left")
    inner = inner.withColumn("whole", F.when(F.col("sb") > F.col("sa"), F.coalesce("ub", F.lit(0)) - F.col("ua")).otherwise(0))
    ends = inner.select("pair_id", "idx", v, reach, F.explode(F.array_distinct(F.array("sa", "sb"))).alias("slice"))
    hits = ends.join(p.select("pair_id", "slice", F.col(v).alias("w")), ["pair_id", "slice"]).where(F.abs(F.col(v) - F.col("w")) <= F.col(reach)).groupBy("pair_id", "idx").agg(F.count("*").alias("c"))
    name = "n" + v
    return inner.join(hits, ["pair_id", "idx"], "left").select("pair_id", "idx", (F.col("whole") + F.coalesce("c", F.lit(0)) - 1).cast("long").alias(name))
