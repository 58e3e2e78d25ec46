"""Grouped aggregates and table functions over party models."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, LongType, StructType

from parley.functions import centres


def _grouped(f):
    @F.pandas_udf(ArrayType(DoubleType()))
    def centre(w: pd.Series) -> list[float]:
        return [float(a) for a in f(np.stack(w.to_numpy()))]

    return centre


#: For groups that fit one task; operators.aggregate has the distributed forms.
agg_mean = _grouped(lambda w: w.mean(0))
agg_geomed = _grouped(lambda w: centres.geometric(w, 0.1)[0])
agg_comed = _grouped(lambda w: centres.coordinate(w, 0.1))


@F.udtf(returnType=StructType().add("lam", DoubleType()).add("w", ArrayType(DoubleType())))
class LambdaPath:
    """Points on the way from a local to a global model."""

    def eval(self, w: list, g: list, steps: int):
        for k in range(steps + 1):
            lam = k / steps
            yield lam, [(1 - lam) * a + lam * b for a, b in zip(w, g, strict=True)]


@F.udtf(returnType=StructType().add("party_id", LongType()).add("rows", LongType()))
class PowerLawSizes:
    """Party sizes by a power law that add up to total."""

    def eval(self, parties: int, total: int, exponent: float):
        share = np.arange(1, parties + 1) ** -exponent
        size = np.floor(share / share.sum() * total).astype(int)
        size[0] += total - size.sum()
        for k, s in enumerate(size):
            yield k, int(s)


def register(spark: SparkSession) -> None:
    spark.udtf.register("lambda_path", LambdaPath)
    spark.udtf.register("power_law_sizes", PowerLawSizes)
    for name, f in (("agg_geomed", agg_geomed), ("agg_comed", agg_comed)):
        spark.udf.register(name, f)
