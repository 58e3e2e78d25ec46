"""Rounds of a linear loss from sufficient statistics: one scan of the rows, then training never reads them again."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from parley.operators.methods import Method, Rounds
from parley.operators.rounds import RunResult, run_rounds
from parley.plans.choose import sufficient_statistics
from parley.sources.tables import Tables


def statistics(examples: DataFrame, features: int) -> DataFrame:
    """(party_id, n, gram, cross): X'X / n row by row and X'y / n."""
    gram = [F.avg(F.get("x", F.lit(i)) * F.get("x", F.lit(j))) for i in range(features) for j in range(features)]
    cross = [F.avg(F.get("x", F.lit(i)) * F.col("y")) for i in range(features)]
    return examples.groupBy("party_id").agg(F.count("*").alias("n"), F.array(*gram).alias("gram"), F.array(*cross).alias("cross"))


class FromStatistics:
    """Half the squared error, of a party whose one row holds its Gram matrix (x) and cross products (y)."""

    task = "regression"

    def __init__(self, features: int):
        self.size = features

    def grad(self, w, x, y):
        return np.einsum("pij,pj->pi", x[:, 0].reshape(len(w), self.size, self.size), w) - y[:, 0]

    def solve(self, w, x, y, z, sigma):
        gram = x[:, 0].reshape(len(w), self.size, self.size) + sigma * np.eye(self.size)
        return np.linalg.solve(gram, (y[:, 0] + sigma * z)[..., None])[..., 0]


def rounds(stats: DataFrame, method: Method, cfg: Rounds) -> RunResult:
    """Full-gradient rounds by the distributed loop over one row a party; nothing but the centre comes to the driver."""
    if cfg.batch is not None:
        raise ValueError("sufficient statistics give full gradients only")
    features = stats.select(F.max(F.size("cross"))).first()[0] or 0
    rows = stats.select("party_id", F.lit(0).cast("long").alias("pos"), F.lit(1).cast("long").alias("n"), F.col("gram").alias("x"), F.col("cross").alias("y"))
    return run_rounds(rows, FromStatistics(features), method, cfg)


def train(examples: DataFrame, loss, method: Method, cfg: Rounds) -> RunResult:
    """Rounds on sufficient statistics where the planner finds that they do, else on the rows."""
    if not sufficient_statistics(type(loss).__name__, loss.size, cfg.batch is None):
        return run_rounds(examples, loss, method, cfg)
    tables = Tables(examples.sparkSession)
    held = tables.keep(statistics(examples, loss.size), "statistics")
    run = rounds(held, method, cfg)
    tables.drop(held)
    return run


def foreign_errors(stats: DataFrame, models: DataFrame) -> DataFrame:
    """(party_id, mse): each party's model on the rows of all others, from sums: no row meets a foreign party.

    stats: (party_id, n, gram, cross, yy) of the rows to score.
    """
    size = stats.select(F.max(F.size("cross"))).first()[0] or 0
    parts = [F.col("n") * F.col("yy"), *(F.col("n") * F.get("gram", F.lit(k)) for k in range(size * size)), *(F.col("n") * F.get("cross", F.lit(k)) for k in range(size))]
    own = stats.select("party_id", F.array(F.col("n").cast("double"), *parts).alias("s"))
    total = own.agg(*[F.sum(F.get("s", F.lit(k))).alias(f"t{k}") for k in range(len(parts) + 1)]).first()  # one row
    rest = own.select("party_id", F.zip_with(F.array(*[F.lit(float(t or 0)) for t in total]), "s", lambda a, b: a - b).alias("s"))
    at = lambda k: F.get("s", F.lit(k))
    w = lambda k: F.get("w", F.lit(k))
    square = sum((w(i) * w(j) * at(2 + i * size + j) for i in range(size) for j in range(size)), F.lit(0.0))
    cross = sum((w(i) * at(2 + size * size + i) for i in range(size)), F.lit(0.0))
    return rest.join(models.select("party_id", "w"), "party_id").select("party_id", ((square - 2 * cross + at(1)) / at(0)).alias("mse"))
