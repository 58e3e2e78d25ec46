"""Centres of distributed party models (party_id, w array<double>[, weight]).

The result is (coord, g) in long form: one row for each coordinate, so that models wider than a row can be joined back.
Means and coordinate medians take one exchange by coordinate. The geometric median takes one scan of the models for each
step: tasks add up their own weighted vectors, and only those sums move.
"""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pandas as pd
from pyspark import StorageLevel
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from parley.functions.centres import Layout, clipped, solved
from parley.functions.prox import Regulariser
from parley.plans.choose import MEDIAN_ROWS, aggregator


def long_form(models: DataFrame, w: str = "w", *keep: str) -> DataFrame:
    """(party_id, ..., coord, value)."""
    return models.select("party_id", *keep, F.posexplode(w).alias("coord", "value"))


def mean(models: DataFrame) -> DataFrame:
    return long_form(models).groupBy("coord").agg(F.avg("value").alias("g"))


def weighted_mean(models: DataFrame, weight: str = "weight") -> DataFrame:
    return long_form(models, "w", weight).groupBy("coord").agg((F.sum(F.col(weight) * F.col("value")) / F.sum(weight)).alias("g"))


@contextmanager
def held(models: DataFrame):
    """Models that an iteration scans many times: made once, in memory or on disk, and made anew where an executor is lost."""
    own = models.select("w")
    if own.storageLevel.useMemory or own.storageLevel.useDisk:
        yield own
        return
    own.persist(StorageLevel.MEMORY_AND_DISK)
    try:
        yield own
    finally:
        own.unpersist()


def coordinate_median(models: DataFrame, parties: int | None = None, weight: str | None = None) -> DataFrame:
    """Exact; an even number of parties gives the middle of the two inner values. weight: the lower weighted median.

    Up to MEDIAN_ROWS parties a coordinate's values meet in one buffer; beyond, sketched bounds first leave the few values
    around the middle (the result is the same).
    """
    if weight:
        return _weighted_median(models, weight)
    if (models.count() if parties is None else parties) <= MEDIAN_ROWS:
        return long_form(models).groupBy("coord").agg(F.percentile("value", 0.5).alias("g"))
    return median_between_bounds(models)


def median_between_bounds(models: DataFrame, accuracy: int = 10_000) -> DataFrame:
    """The exact median from a mergeable sketch: values outside its bounds are only counted."""
    rows, e = long_form(models), 2.0 / accuracy
    sketch = rows.groupBy("coord").agg(F.percentile_approx("value", [max(0.0, 0.5 - e), 0.5 + e], accuracy).alias("q"))
    near = rows.join(sketch, "coord").withColumn("side", F.when(F.col("value") < F.col("q")[0], -1).when(F.col("value") > F.col("q")[1], 1).otherwise(0))
    counts = near.groupBy("coord").agg(F.count("*").alias("n"), F.sum((F.col("side") < 0).cast("long")).alias("below"))
    # equal values count as one row with their number, so that ties don't fill a task
    inner = near.where("side = 0").groupBy("coord", "value").agg(F.count("*").alias("k")).join(counts, "coord")
    upto = F.sum("k").over(Window.partitionBy("coord").orderBy("value")) + F.col("below")
    lower, upper = F.floor((F.col("n") + 1) / 2), F.floor(F.col("n") / 2) + 1
    placed = inner.withColumn("upto", upto).withColumn("from", F.col("upto") - F.col("k") + 1)
    at = lambda place: F.max(F.when((F.col("from") <= place) & (F.col("upto") >= place), F.col("value")))
    return placed.groupBy("coord").agg(((at(lower) + at(upper)) / 2).alias("g"))


def _weighted_median(models: DataFrame, weight: str) -> DataFrame:
    """Per coordinate the smallest value at which half of all weight is reached."""
    rows = long_form(models, "w", weight).groupBy("coord", "value").agg(F.sum(weight).alias("weight"))
    total = rows.groupBy("coord").agg(F.sum("weight").alias("total"))
    upto = F.sum("weight").over(Window.partitionBy("coord").orderBy("value"))
    return rows.withColumn("upto", upto).join(total, "coord").where(F.col("upto") >= F.col("total") / 2).groupBy("coord").agg(F.min("value").alias("g"))


def smoothed_coordinate_median(models: DataFrame, delta: float) -> DataFrame:
    """Exact centre of the summed Huber functions, in windows over each coordinate's bends.

    At a bend x the slope is the sum of clip(x - value, -delta, delta). Passing a lower bend value - delta adds one to the
    number of models pulling linearly, passing value + delta takes one away; a running sum gives every slope.
    """
    d = float(delta)
    rows = long_form(models)
    sums = rows.groupBy("coord").agg(F.count("*").alias("n"), F.avg("value").alias("m"))
    bends = rows.select("coord", F.explode(F.array(F.struct((F.col("value") - d).alias("x"), F.lit(1).alias("turn")), F.struct((F.col("value") + d).alias("x"), F.lit(-1).alias("turn")))).alias("b")).select("coord", "b.*")
    merged = bends.groupBy("coord", "x").agg(F.sum("turn").alias("turn"))
    w = Window.partitionBy("coord").orderBy("x")
    before = w.rowsBetween(Window.unboundedPreceding, -1)
    inner = F.coalesce(F.sum("turn").over(before), F.lit(0))
    shifted = merged.withColumn("inner", inner).withColumn("rise", F.col("inner") * (F.col("x") - F.coalesce(F.lag("x").over(w), F.col("x"))))
    slopes = shifted.withColumn("up", F.sum("rise").over(w)).join(sums, "coord").withColumn("slope", F.col("up") - d * F.col("n"))
    near = F.abs(F.col("slope")) <= 1e-12 * F.col("n")
    last = slopes.withColumns({"x0": F.lag("x").over(w), "s0": F.lag("slope").over(w)})
    cross = last.where(F.col("slope") > 0).where((F.col("s0") < 0) & ~near)
    touching = slopes.where(near).groupBy("coord").agg(F.min("x").alias("lo"), F.max("x").alias("hi"), F.first("m").alias("m"))
    met = touching.select("coord", F.least(F.greatest("m", "lo"), F.col("hi")).alias("g"))
    cut = cross.join(met, "coord", "left_anti").groupBy("coord").agg(F.min(F.struct("x", "x0", "s0", "slope")).alias("c")).select("coord", (F.col("c.x0") - F.col("c.s0") * (F.col("c.x") - F.col("c.x0")) / (F.col("c.slope") - F.col("c.s0"))).alias("g"))
    return met.unionByName(cut)


def plain_steps(models: DataFrame, kind: str, delta: float, steps: int) -> DataFrame:
    """A fixed number of the alternating iteration's steps, begun at the mean."""
    with held(models) as own:
        g = _start(own)
        for _ in range(steps):
            g = g + _mean_of(own, lambda w, g=g: clipped(w - g, kind, delta))
    return _long(models, g)


def _vector(g: DataFrame) -> np.ndarray:
    """A centre as an array: one number for each coordinate, bounded by the model's size."""
    return np.array([r.g for r in g.orderBy("coord").collect()])


def _long(models: DataFrame, g: np.ndarray) -> DataFrame:
    return models.sparkSession.createDataFrame(pd.DataFrame({"coord": np.arange(len(g), dtype=np.int32), "g": g}), "coord int, g double")


def _summed(models: DataFrame, part) -> tuple[np.ndarray, float]:
    """Sum over parties of part(w) -> (vectors, weights), added up in tasks before it moves."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total, weight = None, 0.0
        for frame in frames:
            if len(frame):
                v, s = part(np.stack(frame["w"].to_numpy()))
                total = v.sum(0) if total is None else total + v.sum(0)
                weight += float(np.sum(s))
        if total is not None:
            yield pd.DataFrame({"coord": np.arange(len(total) + 1, dtype=np.int32), "value": np.append(total, weight)})

    rows = models.select("w").mapInPandas(run, "coord int, value double").groupBy("coord").agg(F.sum("value").alias("g"))
    both = _vector(rows)
    return both[:-1], both[-1]


def _mean_of(models: DataFrame, f) -> np.ndarray:
    total, n = _summed(models, lambda w: (f(w), np.ones(len(w))))
    return total / n


def _start(models: DataFrame) -> np.ndarray:
    """The mean, from the same partial sums as every later step."""
    return _mean_of(models, lambda w: w)


def geometric_median(
    models: DataFrame, delta: float = 0.0, tol: float = 1e-10, limit: int = 500, start: np.ndarray | None = None, weight: str | None = None
) -> tuple[DataFrame, int]:
    """Smoothed (delta > 0) or exact geometric median by reweighting, weighted if a column says so; also the number of steps."""
    floor = max(float(delta), 1e-9)
    own = models if weight is None else models.select(F.concat(F.array(F.col(weight).cast("double")), "w").alias("w"))  # the weight travels before the vector

    def parted(w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return (w[:, 0], w[:, 1:]) if weight else (np.ones(len(w)), w)

    with held(own) as vectors:
        if start is None:
            total, weights = _summed(vectors, lambda w: (parted(w)[0][:, None] * parted(w)[1], parted(w)[0]))
            start = total / weights
        g = start
        for k in range(limit):

            def pull(w: np.ndarray, g: np.ndarray = g) -> tuple[np.ndarray, np.ndarray]:
                p, v = parted(w)
                share = p * np.minimum(1, floor / np.maximum(np.linalg.norm(v - g, axis=1), 1e-300))
                return share[:, None] * v, share

            total, weights = _summed(vectors, pull)
            new = total / weights
            moved = np.abs(new - g).max()
            g = new
            if moved <= tol * max(1.0, np.abs(g).max()):
                return _long(models, g), k + 1
    return _long(models, g), limit


def general_centre(models: DataFrame, reg: Regulariser, sigma: float, tol: float = 1e-10, limit: int = 500) -> tuple[DataFrame, int]:
    """The alternating iteration for any proximal map."""
    with held(models) as vectors:
        m = _start(vectors)
        g = m
        for k in range(limit):
            new = m - _mean_of(vectors, lambda w, g=g: reg.prox(w - g, sigma))
            moved = np.abs(new - g).max()
            g = new
            if moved <= tol:
                return _long(models, g), k + 1
    return _long(models, g), limit


def plain_centre(models: DataFrame, kind: str, delta: float, tol: float = 1e-10, limit: int = 100_000) -> tuple[DataFrame, int]:
    """The alternating iteration to its end."""
    with held(models) as vectors:
        g = _start(vectors)
        for k in range(limit):
            step = _mean_of(vectors, lambda w, g=g: clipped(w - g, kind, delta))
            g = g + step
            if np.abs(step).max() <= tol:
                return _long(models, g), k + 1
    return _long(models, g), limit


def hybrid(models: DataFrame, layout: Layout, sigma: float = 1.0, exact: bool = False, solver: str = "accelerated", parties: int | None = None) -> tuple[DataFrame, int]:
    """A regulariser for each block of coordinates [lo, hi); also the steps of all blocks."""
    out, steps = None, 0
    for lo, hi, reg in layout:
        block = models.select("party_id", F.slice("w", lo + 1, hi - lo).alias("w"))
        g, k = solve(block, reg, sigma, exact, solver, parties, hi - lo)
        part = g.select((F.col("coord") + lo).cast("int").alias("coord"), "g")
        out, steps = part if out is None else out.unionByName(part), steps + k
    return out, steps


def carried_forward(models: DataFrame, news: DataFrame) -> DataFrame:
    """All parties' models: the new one of an active party, the last one of an idle party."""
    return models.join(news.withColumnRenamed("w", "__new"), "party_id", "left").select("party_id", F.coalesce("__new", "w").alias("w"))


def solve(
    models: DataFrame, reg: Regulariser, sigma: float = 1.0, exact: bool = False, solver: str = "accelerated", parties: int | None = None, size: int | None = None
) -> tuple[DataFrame, int]:
    """(coord, g) by the form that the planner picks, and the steps it took."""
    if parties is None or size is None:
        got = models.agg(F.count("*").alias("n"), F.max(F.size("w")).alias("d")).first()
        parties, size = got["n"], got["d"] or 0
    form = aggregator(reg, parties, size).form
    if form == "mean":
        return mean(models), 1
    if form == "gathered":
        w = np.array([r.w for r in models.orderBy("party_id").select("w").collect()])
        g, steps = solved(w, reg, sigma, solver, exact)
        return _long(models, g), steps
    if solver == "plain" and not exact and reg.kind in ("l1", "l2"):
        return plain_centre(models, reg.kind, reg.delta)
    if form == "by_coordinate":
        return coordinate_median(models, parties) if exact or reg.delta <= 0 else smoothed_coordinate_median(models, reg.delta), 1
    if reg.kind == "l2":
        return geometric_median(models, 0.0 if exact else reg.delta)
    return general_centre(models, reg, sigma)


def aggregate(models: DataFrame, reg: Regulariser, sigma: float = 1.0, exact: bool = False, solver: str = "accelerated", parties: int | None = None, size: int | None = None) -> DataFrame:
    """(coord, g) by the form that the planner picks."""
    return solve(models, reg, sigma, exact, solver, parties, size)[0]


def residual(models: DataFrame, g: DataFrame, kind: str, delta: float) -> DataFrame:
    """Length of the mean clipped residual: 0 at a smoothed median."""
    v = _vector(g)
    r = _mean_of(models, lambda w: clipped(w - v, kind, delta))
    return models.sparkSession.createDataFrame([(float(np.linalg.norm(r)),)], "residual double")


def offsets(models: DataFrame, reg: Regulariser, sigma: float = 1.0) -> tuple[DataFrame, DataFrame]:
    """Joint minimiser of the objective for fixed models: (party_id, v) and (coord, g)."""
    g = aggregate(models, reg, sigma)
    at = _vector(g)

    def part(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            if len(frame):
                yield pd.DataFrame({"party_id": frame["party_id"], "v": list(reg.prox(np.stack(frame["w"].to_numpy()) - at, sigma))})

    return models.select("party_id", "w").mapInPandas(part, "party_id long, v array<double>"), g
