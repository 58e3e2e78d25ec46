"""Streams of party updates: (party_id, round, event_time, w).

Rounds close by watermark: an update that comes later than the allowance is dropped, and its party keeps its last model,
as idle parties do. State is one model for each party, in a state store on disk (RocksDB) where all models don't fit memory.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from parley.functions.prox import Regulariser
from parley.operators.aggregate import _vector, aggregate
from parley.sources.tables import Tables, run_folder

UPDATES = "party_id long, round int, event_time timestamp, w double"


def stream_of(spark: SparkSession, path: str, schema, per_trigger: int = 1) -> DataFrame:
    """A folder of Parquet files as a stream."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def as_updates(events: DataFrame) -> DataFrame:
    """Events as party updates: a user's value is its model, an hour a round."""
    return events.select(F.col("user_id").alias("party_id"), F.hour("ts").alias("round"), F.col("ts").cast("timestamp").alias("event_time"), F.col("value").alias("w"))


def tumbling(updates: DataFrame, width: str = "6 hours", late: str = "2 hours") -> DataFrame:
    return updates.withWatermark("event_time", late).groupBy(F.window("event_time", width)).agg(F.count("*").alias("n"), F.sum("w").alias("w"))


def sliding(updates: DataFrame, width: str = "12 hours", step: str = "6 hours", late: str = "2 hours") -> DataFrame:
    return updates.withWatermark("event_time", late).groupBy(F.window("event_time", width, step)).agg(F.count("*").alias("n"), F.sum("w").alias("w"))


def sessions(updates: DataFrame, gap: str = "8 hours", late: str = "2 hours") -> DataFrame:
    return updates.withWatermark("event_time", late).groupBy(F.session_window("event_time", gap).alias("window"), "party_id").agg(F.count("*").alias("n"), F.sum("w").alias("w"))


def once_each(updates: DataFrame, late: str = "40 days") -> DataFrame:
    """The first update of each party and round."""
    return updates.withWatermark("event_time", late).dropDuplicatesWithinWatermark(["party_id", "round"])


def with_centre(updates: DataFrame, centres: DataFrame) -> DataFrame:
    """Each update beside the centre of its round (a static table)."""
    return updates.join(centres, "round")


def acknowledged(updates: DataFrame, acks: DataFrame, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Updates whose acknowledgement follows within an interval; both sides are streams."""
    a = updates.withWatermark("event_time", late)
    b = acks.select(F.col("party_id").alias("ack_party"), F.col("event_time").alias("ack_time")).withWatermark("ack_time", late)
    return a.join(b, (F.col("party_id") == F.col("ack_party")) & (F.col("ack_time") >= F.col("event_time")) & (F.col("ack_time") <= F.col("event_time") + F.expr(f"interval {within}")))


def party_models(updates: DataFrame, eta: float = 0.1) -> DataFrame:
    """A party's model follows its updates by gradient steps; state outlives micro-batches. Output: one row a party and batch."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        w, n = state.get if state.exists else (0.0, 0)
        rows = pd.concat(list(frames)).sort_values(["event_time", "w"])
        for target in rows["w"]:
            w, n = w - eta * (w - target), n + 1
        state.update((float(w), int(n)))
        yield pd.DataFrame({"party_id": [key[0]], "w": [w], "n": [n]})

    return updates.groupBy("party_id").applyInPandasWithState(step, "party_id long, w double, n long", "w double, n long", "update", GroupStateTimeout.NoTimeout)


class ModelKeeper(StatefulProcessor):
    """A party's model and its number of updates as a value state."""

    def __init__(self, eta: float):
        self.eta = eta

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.kept = handle.getValueState("model", "w double, n long")

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803 (Spark's names)
        w, n = self.kept.get() if self.kept.exists() else (0.0, 0)
        for target in pd.concat(list(rows)).sort_values(["event_time", "w"])["w"]:
            w, n = w - self.eta * (w - target), n + 1
        self.kept.update((float(w), int(n)))
        yield pd.DataFrame({"party_id": [key[0]], "w": [float(w)], "n": [int(n)]})

    def close(self) -> None:
        pass


#: The store that keeps states on disk; the state API below needs it.
ON_DISK = ("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")


def kept_models(updates: DataFrame, eta: float = 0.1) -> DataFrame:
    """As party_models, by the state API; the session's state store must be ON_DISK while it runs."""
    return updates.groupBy("party_id").transformWithStateInPandas(ModelKeeper(eta), "party_id long, w double, n long", "Update", "None")


def run_to_end(df: DataFrame, mode: str = "append", folder: str | None = None, each: Callable[[DataFrame, int], None] | None = None) -> DataFrame | None:
    """Run a stream over everything that has arrived. each: called with every micro-batch; else the result as a table."""
    spark = df.sparkSession
    base = folder or f"{run_folder(spark)}/stream-{uuid.uuid4().hex}"
    writer = df.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{base}/checkpoint")
    if each:
        writer.foreachBatch(each).start().awaitTermination()
        return None
    if mode == "append":
        writer.format("parquet").start(f"{base}/out").awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{base}/out")
    parts: list[str] = []

    def keep(batch: DataFrame, number: int) -> None:
        path = f"{base}/out-{number}"
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(path)
        parts.append(path)

    writer.foreachBatch(keep).start().awaitTermination()
    return spark.read.parquet(*(parts[-1:] if mode == "complete" else parts))  # each batch of a complete result replaces the one before


def close_rounds(updates: DataFrame, centres: list[tuple[int, float, int]], reg: Regulariser | None = None, folder: str | None = None) -> None:
    """Per micro-batch: the centre that reg implies (none: the mean) of parties' latest models so far, appended to centres as (batch, centre, parties)."""
    tables, latest = Tables(updates.sparkSession), []

    def close(batch: DataFrame, number: int) -> None:
        news = batch.groupBy("party_id").agg(F.max_by("w", "event_time").alias("w"))
        now = news if not latest else latest[0].join(news, "party_id", "left_anti").select("party_id", "w").unionByName(news)
        kept = tables.keep(now, "latest")
        tables.drop(*latest)
        latest[:] = [kept]
        n = kept.count()
        g = _vector(aggregate(kept.select("party_id", F.array("w").alias("w")), reg or Regulariser("consensus"), parties=n, size=1))
        centres.append((number, float(g[0]) if len(g) else float(np.nan), n))

    run_to_end(updates, folder=folder, each=close)
