"""Series and searches over streams."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tempcorr.functions import kernel

SELECTED = "pair_id string, layer int, s long, e long, mi double, revision int, passes boolean"
STATE = "idx array<bigint>, x array<double>, y array<double>, free array<bigint>, pos array<bigint>, upto bigint, ends array<bigint>, picked array<bigint>"


def resample(stream: DataFrame, ts: str, step: str, watermark: str, *aggregates) -> DataFrame:
    return stream.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, watermark).groupBy(F.window(ts, step)).agg(*aggregates)


def sliding(stream: DataFrame, ts: str, size: str, step: str, watermark: str) -> DataFrame:
    """Pearson's coefficient of columns x and y over sliding windows."""
    return stream.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, watermark).groupBy(F.window(ts, size, step)).agg(F.count("*").alias("n"), F.corr("x", "y").alias("pearson"))


def sessions(stream: DataFrame, ts: str, gap: str, watermark: str, key: str) -> DataFrame:
    return stream.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, watermark).groupBy(key, F.session_window(ts, gap)).agg(F.count("*").alias("n"))


class Cascade:
    """The scans of all layers over a series that grows.

    A layer's scan is at `pos` in a left-out run that begins at `free`. What lies before `pos` is left for good, so that the
    next layer scans it, while the run may still grow; what a run's end leaves goes on when the run is closed. So every
    layer takes the windows that it would take with the whole series at hand.
    """

    def __init__(self, layers, accept, k):
        self.layers, self.accept, self.k = layers, accept, k
        self.free: list[int | None] = [None] * len(layers)
        self.pos: list[int | None] = [None] * len(layers)
        self.points: dict[int, tuple[float, float]] = {}
        self.found: list[tuple[int, int, int, float]] = []

    def score(self, s: int, e: int) -> dict:
        x, y = (np.array([self.points[i][j] for i in range(s, e)]) for j in (0, 1))
        return kernel.score(x, y, k=self.k, tie=None)

    def push(self, layer: int, start: int, upto: int, closed: bool) -> None:
        """The run from `start` is known up to `upto`, where it may end."""
        if layer == len(self.layers):
            return
        size, step = self.layers[layer]
        free, pos = (start, start) if self.free[layer] is None else (self.free[layer], self.pos[layer])
        while pos + size <= upto:
            row = self.score(pos, pos + size)
            if self.accept(row):
                self.found.append((layer, pos, pos + size, row["mi"]))
                if free < pos:
                    self.push(layer + 1, free, pos, True)
                free = pos = pos + size
            else:
                pos += step
        edge = upto if closed else min(pos, upto)
        if free < edge:
            self.push(layer + 1, free, edge, closed)
        self.free[layer], self.pos[layer] = (None, None) if closed else (free, pos)

    def needed(self, upto: int) -> int:
        """The first point that a window may still need."""
        return min([upto, *(p for p in self.pos if p is not None)])


def stream_search(paired: DataFrame, ladder, accept, k: int = 6, lateness: int = 0, remember: int = 0) -> DataFrame:
    """Selected windows of a stream of (pair_id, idx, x, y) as points arrive, in any order; of all layers, as in a batch.

    A missing point holds its pair up until points of an idx more than `lateness` steps later have come (0: for ever);
    then the run ends there, and the next begins after the gap. A row without x and y ends the series at its idx. A point
    that comes again with other values within the last `remember` steps gives its selected windows anew, with a higher
    revision and whether they still pass; points that come later than that are dropped. Ties are not broken here.
    """
    layers = [(x.size, x.step) for x in ladder.layers]

    def run(key, batches, state):
        scan = Cascade(layers, accept, k)
        upto, ends, picked = None, [], []
        if state.exists:
            idx, x, y, free, pos, upto, ends, flat = (list(v) if hasattr(v, "__len__") else v for v in state.get)
            scan.points = {int(i): (a, b) for i, a, b in zip(idx, x, y, strict=True)}
            scan.free, scan.pos = ([None if v < -(1 << 61) else int(v) for v in c] for c in (free, pos))
            upto, ends = None if upto is None else int(upto), [int(v) for v in ends]
            picked = [[int(v) for v in flat[i : i + 4]] for i in range(0, len(flat), 4)]
        again, newest = set(), max(scan.points, default=-(1 << 62))
        for df in batches:
            for i, a, b in zip(df["idx"], df["x"], df["y"], strict=True):
                i = int(i)
                if a is None or a != a:
                    ends.append(i)
                    continue
                newest = max(newest, i)
                if upto is not None and i < upto:  # passed already
                    if i in scan.points and scan.points[i] != (a, b):
                        scan.points[i] = (float(a), float(b))
                        again.add(i)
                elif i not in scan.points:
                    scan.points[i] = (float(a), float(b))
        out = []
        for p in picked:
            if any(p[1] <= i < p[2] for i in again) and all(i in scan.points for i in range(p[1], p[2])):
                p[3] += 1
                row = scan.score(p[1], p[2])
                out.append((key[0], p[0], p[1], p[2], row["mi"], p[3], bool(accept(row))))
        ahead = sorted(i for i in scan.points if upto is None or i >= upto)
        begin = upto
        for i in ahead:
            if upto is None:
                begin = upto = i
            if i > upto:  # a gap: wait, or end the run here
                if upto not in ends and not (lateness and newest - upto > lateness):
                    break
                scan.push(0, begin, upto, True)
                begin = i
            upto = i + 1
        if upto is not None:
            scan.push(0, begin if begin is not None else upto, upto, upto in ends)
        for layer, s, e, mi in scan.found:
            out.append((key[0], layer, s, e, mi, 0, True))
            picked.append([layer, s, e, 0])
        if upto is not None:
            picked = [p for p in picked if p[2] > upto - remember]
            keep = min([scan.needed(upto), upto - remember, *(p[1] for p in picked)])
            scan.points = {i: v for i, v in scan.points.items() if i >= keep}
            ends = [e for e in ends if e > upto]
        held = sorted(scan.points)
        none = -(1 << 62)
        state.update((held, [scan.points[i][0] for i in held], [scan.points[i][1] for i in held], [none if v is None else v for v in scan.free], [none if v is None else v for v in scan.pos], upto, ends, [v for p in picked for v in p]))
        yield pd.DataFrame(out, columns=[c.split()[0] for c in SELECTED.split(", ")])

    return paired.groupBy("pair_id").applyInPandasWithState(run, SELECTED, STATE, "append", "NoTimeout")
