"""Closed forms, exact local steps and convergence measures.

Quadratic parties f(w) = a / 2 (w - c)^2 have exact local minimisers, so rounds are plain projections and fixed points are
known: with no tie each party's own c; with consensus the centre weighted by a sigma / (a + sigma); with the squared-norm
regulariser weights a / (a + s), s = sigma delta / (1 + delta), and parties at g + weight (c - g).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from parley.functions.prox import Regulariser
from parley.operators.aggregate import _vector, aggregate
from parley.operators.methods import Method, Rounds
from parley.operators.quadratic import statistics
from parley.operators.simulation import Federation, objective, simulate
from parley.sources.tables import Tables, load


def quadratic_parties(spark, sf_dir: str) -> DataFrame:
    """(party_id, a, c): nations; c is their customers' mean order price, a their share of orders (times the number of nations)."""
    o = load(spark, sf_dir, "orders").select("o_custkey", "o_totalprice")
    c = load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    per = o.join(c, o.o_custkey == c.c_custkey).groupBy(F.col("c_nationkey").cast("long").alias("party_id")).agg((F.avg("o_totalprice") / 1e5).alias("c"), F.count("*").alias("n"))
    total = per.agg(F.sum("n").alias("total"), F.count("*").alias("k"))
    return per.crossJoin(F.broadcast(total)).select("party_id", (F.col("n") * F.col("k") / F.col("total")).alias("a"), "c")  # one row


def _closed(parties: DataFrame, weight: Column) -> DataFrame:
    """(party_id, w-weight, c, g) with the weighted centre beside every party."""
    own = parties.withColumn("rho", weight)
    g = own.agg((F.sum(F.col("rho") * F.col("c")) / F.sum("rho")).alias("g"))
    return own.crossJoin(F.broadcast(g))  # one row


def fixed_point(parties: DataFrame, case: str, sigma: float, delta: float = 0.1) -> DataFrame:
    """(party_id, w, g) at the fixed point of case a (no tie), b (consensus) or c (squared norm)."""
    if case == "a":
        return _closed(parties, F.lit(1.0)).select("party_id", F.col("c").alias("w"), F.lit(None).cast("double").alias("g"))
    if case == "b":
        at = _closed(parties, F.col("a") * sigma / (F.col("a") + sigma))
        return at.select("party_id", ((F.col("a") * F.col("c") + sigma * F.col("g")) / (F.col("a") + sigma)).alias("w"), "g")
    s = sigma * delta / (1 + delta)
    return _closed(parties, F.col("a") / (F.col("a") + s)).select("party_id", (F.col("g") + F.col("rho") * (F.col("c") - F.col("g"))).alias("w"), "g")


def offset(kind: str, r: Column, delta: float) -> Column:
    """A scalar residual's proximal map."""
    return {"sq": r / (1 + delta), "l1": F.signum(r) * F.greatest(F.abs(r) - delta, F.lit(0.0)), "consensus": F.lit(0.0), "free": r}[kind]


def quadratic_path(
    parties: DataFrame, kind: str, sigma: float, delta: float, rounds: int, eta: float | None = None, steps: int = 0, lam: float = 0.0
) -> Iterator[tuple[DataFrame, float]]:
    """((party_id, a, c, w), g) after each round of exact local minimisation, or of `steps` fused steps of length eta; all parties active, begun at 0.

    The centre is one number; the plan of a round is a projection over the parties, written every fourth round.
    """
    tables = Tables(parties.sparkSession)
    base = now = tables.keep(parties.withColumn("w", F.lit(0.0)), "quadratic")
    g, kappa = 0.0, 1 / (1 + (eta or 0) * sigma)
    for t in range(rounds):
        z = g + offset(kind, F.col("w") - g, delta)
        if steps:
            new = (1 - lam) * F.col("w") + lam * g
            anchor = z if sigma else F.lit(0.0)
            for _ in range(steps):
                new = kappa * (new - eta * F.col("a") * (new - F.col("c"))) + (1 - kappa) * anchor
        else:
            new = (F.col("a") * F.col("c") + sigma * z) / (F.col("a") + sigma)
        now = now.select("party_id", "a", "c", new.alias("w"))
        if t % 4 == 3:
            before, base = base, tables.keep(now, "quadratic")
            now = base
            tables.drop(before)
        reg = Regulariser(kind if kind in ("l1", "l2") else "consensus", delta)
        found = _vector(aggregate(now.select("party_id", F.array("w").alias("w")), reg, sigma))
        g = float(found[0]) if len(found) else g
        yield now, g


def quadratic_rounds(parties: DataFrame, kind: str, sigma: float, delta: float, rounds: int, eta: float | None = None, steps: int = 0, lam: float = 0.0) -> DataFrame:
    """(party_id, w, g) after so many rounds."""
    now, g = parties.withColumn("w", F.lit(0.0)), 0.0
    for now, g in quadratic_path(parties, kind, sigma, delta, rounds, eta, steps, lam):  # noqa: B007
        pass
    return now.select("party_id", "w", F.lit(g).alias("g"))


def residuals(parties: DataFrame, at: DataFrame, kind: str, sigma: float, delta: float = 0.1) -> DataFrame:
    """Fixed-point conditions: mean envelope gradient, and the largest miss of a party's relation to it."""
    z = F.col("g") + offset(kind, F.col("w") - F.col("g"), delta)
    slope = F.col("a") * sigma / (F.col("a") + sigma) * (z - F.col("c"))  # of the loss's Moreau envelope at z
    both = parties.join(at, "party_id").select(slope.alias("slope"), F.abs(F.col("w") - (z - slope / sigma)).alias("miss"))
    return both.agg(F.abs(F.avg("slope")).alias("mean_slope"), F.max("miss").alias("worst_miss"))


def vector_residuals(stats: DataFrame, models: DataFrame, g: np.ndarray, reg: Regulariser, sigma: float) -> DataFrame:
    """Fixed-point conditions of linear parties: (coord, mean_slope) and the worst miss, in one row a coordinate.

    stats: (party_id, gram, cross); at a fixed point the envelope gradients at z = g + offset average to 0, and every
    party's model is the minimiser at its z.
    """
    size = len(g)

    def part(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for row in frame.itertuples():
                w = np.array(row.w)
                z = g + reg.prox(w - g, sigma)
                best = np.linalg.solve(np.array(row.gram).reshape(size, size) + sigma * np.eye(size), np.array(row.cross) + sigma * z)
                out += [(j, sigma * (z[j] - best[j]), float(np.abs(w - best).max())) for j in range(size)]
            yield pd.DataFrame(out, columns=["coord", "slope", "miss"])

    rows = stats.select("party_id", "gram", "cross").join(models.select("party_id", "w"), "party_id").mapInPandas(part, "coord int, slope double, miss double")
    return rows.groupBy("coord").agg(F.avg("slope").alias("mean_slope"), F.max("miss").alias("worst_miss"))


def loss_envelopes(examples: DataFrame, features: int, z: list[float], sigma: float) -> DataFrame:
    """(party_id, envelope, slope): the Moreau envelope of each party's linear loss at z, and its gradient, from one scan."""
    st = statistics(examples, features).join(examples.groupBy("party_id").agg(F.avg(F.col("y") * F.col("y")).alias("yy")), "party_id")
    at = np.array(z, float)

    def part(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for row in frame.itertuples():
                gram, cross = np.array(row.gram).reshape(features, features), np.array(row.cross)
                best = np.linalg.solve(gram + sigma * np.eye(features), cross + sigma * at)  # the exact inner minimiser
                f = 0.5 * (best @ gram @ best - 2 * cross @ best + row.yy)
                out.append((row.party_id, f + sigma / 2 * ((best - at) ** 2).sum(), sigma * (at - best)))
            yield pd.DataFrame(out, columns=["party_id", "envelope", "slope"])

    return st.mapInPandas(part, "party_id long, envelope double, slope array<double>")


def condensed(examples: DataFrame, features: int) -> Federation:
    """Parties of features + 1 rows each on which linear losses, and their gradients are those on all of a party's rows; from one scan."""
    z, m = F.concat("x", F.array("y")), features + 1
    second = [F.avg(z[i] * z[j]).alias(f"m{i}_{j}") for i in range(m) for j in range(m)]
    found = examples.where("party_id IS NOT NULL AND y IS NOT NULL").groupBy("party_id").agg(*second).orderBy("party_id").collect()  # a few numbers a party
    xs, ys = [], []
    for r in found:
        values, vectors = np.linalg.eigh(np.array(r[1:], float).reshape(m, m))
        root = np.sqrt(m * np.maximum(values, 0))[:, None] * vectors.T
        xs.append(root[:, :features])
        ys.append(root[:, features])
    return Federation(xs, ys, [x[:0] for x in xs], [y[:0] for y in ys], np.array([r[0] for r in found], np.int64))


def rate(values: list[float]) -> float:
    """Slope of log gap against log round: -1 or less for a 1/t rate."""
    gap = np.array(values[:-1]) - min(values)
    t = np.arange(1, len(gap) + 1)
    keep = (gap > 1e-14) & (t > 2)
    return float(np.polyfit(np.log(t[keep]), np.log(gap[keep]), 1)[0]) if keep.sum() > 2 else -np.inf


def descent(loss, fed: Federation, method: Method, cfg: Rounds) -> list[dict]:
    """A row for each round of full-gradient training: joint objective, sum of squared gradients, and whether the promised decrease held."""
    lip, rows = loss.lipschitz(fed.x), []

    def penal(w: np.ndarray, z: np.ndarray, k: int) -> tuple[float, float]:
        f = loss.value(w[None], fed.x[k][None], fed.y[k][None])[0] + cfg.sigma / 2 * ((w - z) ** 2).sum()
        d = loss.grad(w[None], fed.x[k][None], fed.y[k][None])[0] + cfg.sigma * (w - z)
        return f, float((d * d).sum())

    before = {"w": np.zeros((len(fed.x), loss.size))}

    def watch(t: int, state: dict, g: np.ndarray, g_new: np.ndarray, active: np.ndarray) -> None:
        old, new, held, squares = before["w"], state["w"].copy(), True, 0.0
        for k in range(len(fed.x)):
            z = g + method.offset(old[k] - g, cfg.sigma)
            f0, q = penal(old[k], z, k)
            squares += q
            if k in active:
                held &= penal(new[k], z, k)[0] <= f0 - q / (2 * (lip + cfg.sigma)) + 1e-9
        rows.append({"round": t, "objective": objective(loss, method, cfg, new, g_new, fed), "squared_gradients": squares, "decrease_held": bool(held)})
        before["w"] = new

    simulate(loss, fed, method, cfg, watch=watch)
    return rows
