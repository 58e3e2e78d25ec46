"""Party files, example stores, round stores, and a generator source."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StringType, StructField, StructType

from parley.operators.rounds import RunResult

EXAMPLES = "party_id long, pos long, n long, split string, x array<double>, y double"


def read_parties(spark: SparkSession, path: str, fmt: str, schema: str | StructType, corrupt: str | None = None) -> DataFrame:
    """Party files of a format. corrupt: a column for the whole text of CSV and JSON rows that don't parse (null for those that do)."""
    own = schema if isinstance(schema, StructType) else StructType.fromDDL(schema)
    if fmt == "text":
        return spark.read.text(path).withColumnRenamed("value", own.fieldNames()[0])
    if corrupt and fmt in ("csv", "json"):
        own = StructType([*own.fields, StructField(corrupt, StringType())])
    reader = spark.read.schema(own)
    if fmt in ("csv", "json"):
        reader = reader.option("mode", "PERMISSIVE")
        if corrupt:
            reader = reader.option("columnNameOfCorruptRecord", corrupt)
        return reader.option("header", True).csv(path) if fmt == "csv" else reader.json(path)
    return reader.format(fmt).load(path)


def write_parties(df: DataFrame, path: str, fmt: str) -> None:
    writer = df.write.mode("overwrite")
    (writer.option("header", True) if fmt == "csv" else writer).format(fmt).save(path)


def write_examples(df: DataFrame, path: str, buckets: int) -> None:
    """Examples in folders of party buckets, sorted by party and place: a round reads a few folders and row groups."""
    bucket = F.pmod(F.hash("party_id"), F.lit(buckets)).alias("party_bucket")
    df.select("*", bucket).repartition("party_bucket").sortWithinPartitions("party_id", "pos").write.mode("overwrite").partitionBy("party_bucket").parquet(path)


def bucketed(df: DataFrame, table: str, buckets: int, *sort: str) -> DataFrame:
    """A catalog table bucketed by party: joins and groups by party on such tables need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, "party_id").sortBy(*(sort or ("party_id",))).saveAsTable(table)
    return df.sparkSession.table(table)


class RunStore:
    """A run after each saved round below one path; a round counts once its manifest row is there."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def save(self, run: RunResult) -> None:
        t = run.rounds
        run.state.write.mode("overwrite").parquet(f"{self.path}/state/round={t}")
        lists = [None if a is None else [float(x) for x in a] for a in (run.g, run.control, run.before)]
        row = self.spark.createDataFrame([(t, json.dumps(lists))], "done int, vectors string")
        row.coalesce(1).write.mode("overwrite").parquet(f"{self.path}/manifest/round={t}")  # last: its presence says that the state is whole

    def rounds(self) -> list[int]:
        jvm = self.spark._jvm
        path = jvm.org.apache.hadoop.fs.Path(f"{self.path}/manifest/round=*/_SUCCESS")
        found = path.getFileSystem(self.spark._jsc.hadoopConfiguration()).globStatus(path)
        return sorted(int(s.getPath().getParent().getName().split("=")[1]) for s in found or [])

    def load(self, t: int) -> RunResult:
        vectors = json.loads(self.spark.read.parquet(f"{self.path}/manifest/round={t}").first()["vectors"])
        g, control, before = (None if a is None else np.array(a) for a in vectors)
        return RunResult(self.spark.read.parquet(f"{self.path}/state/round={t}"), g, [], control, t, before)


class FederationSource(DataSource):
    """spark.read.format("parley_synth"): planted regressions, a partition for each party. Options: parties, rows, features, seed, models (1: a row a party, its planted model as x)."""

    @classmethod
    def name(cls) -> str:
        return "parley_synth"

    def schema(self) -> str:
        return "party_id long, row_id long, x array<double>, y double"

    def reader(self, schema: StructType) -> DataSourceReader:
        return _FederationReader({k: int(self.options.get(k, v)) for k, v in (("parties", 10), ("rows", 100), ("features", 8), ("seed", 1), ("models", 0))})


class _FederationReader(DataSourceReader):
    def __init__(self, options: dict[str, int]):
        self.options = options

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(k) for k in range(self.options["parties"])]

    def read(self, partition: InputPartition):
        from parley.functions.draws import laplace_np, normal_np

        o, k = self.options, partition.value
        j = np.arange(o["features"])
        w = normal_np(o["seed"], 1 if k < o["parties"] - 1 else 2, j) * (2.2 if k < o["parties"] - 1 else 7.1) + 0.5 * laplace_np(o["seed"], 3, k, j)
        if o["models"]:
            yield k, 0, [float(a) for a in w], 0.0
            return
        for i in range(o["rows"]):
            x = normal_np(o["seed"], 5, k, i, j)
            yield k, i, [float(a) for a in x], float(x @ w + normal_np(o["seed"], 6, k, i))


def register_sources(spark: SparkSession) -> None:
    spark.dataSource.register(FederationSource)
