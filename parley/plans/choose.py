"""Planner choices made before a plan is built."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from parley.functions.prox import Regulariser

#: Models of one round that the driver may gather to find their centre; beyond it the distributed forms run.
GATHER_BYTES = 64 << 20
#: Ids that a round may send to every task; beyond it they are joined by exchange.
BROADCAST_BYTES = 8 << 20
#: Values of one coordinate that one buffer may hold.
MEDIAN_ROWS = 1_000_000
#: Bytes of a federation that one task may hold; beyond it the distributed loop runs the same rounds.
TASK_BYTES = 256 << 20


@dataclass(frozen=True)
class Choice:
    form: str  # mean, gathered, by_coordinate, by_norm
    why: str


def aggregator(reg: Regulariser, parties: int, size: int, limit: int = GATHER_BYTES) -> Choice:
    if reg.mean_centre or reg.kind == "free":
        return Choice("mean", "the mean is this regulariser's centre: one aggregation, no iteration")
    if parties * size * 8 <= limit:
        return Choice("gathered", f"{parties} x {size} numbers fit {limit} bytes")
    if reg.kind == "l1":
        return Choice("by_coordinate", "coordinates are independent: one exchange")
    return Choice("by_norm", "norms couple the coordinates: one scan for each iteration, models don't move")


def sufficient_statistics(loss_name: str, features: int, full_gradient: bool, most: int = 512) -> bool:
    """Quadratic losses with full gradients need one scan for all rounds."""
    return loss_name == "Linear" and full_gradient and features <= most


def few(df: DataFrame, rows: int, width: int = 8) -> DataFrame:
    """df marked for broadcast if its known number of rows is small."""
    return F.broadcast(df) if rows * width <= BROADCAST_BYTES else df
