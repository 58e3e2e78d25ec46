"""Vector arithmetic over array columns, and the same names as SQL functions."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def sub(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x - y)


def scale(a: Column, k: Column | float) -> Column:
    k = k if isinstance(k, Column) else F.lit(float(k))
    return F.transform(a, lambda x: x * k)


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(F.aggregate(a, F.lit(0.0), lambda s, x: s + x * x))


def mix(a: Column, b: Column, share: Column | float) -> Column:
    """(1 - share) a + share b."""
    share = share if isinstance(share, Column) else F.lit(float(share))
    return F.zip_with(a, b, lambda x, y: (1 - share) * x + share * y)


def argmax(a: Column) -> Column:
    """Position of the greatest element, from 0; the first of equals."""
    return (F.array_position(a, F.array_max(a)) - 1).cast("int")


def rounded(a: Column, digits: int = 6) -> Column:
    """Rounded for comparison between engines; -0.0 becomes 0.0."""
    return F.transform(a, lambda x: F.round(x, digits) + F.lit(0.0))


#: SQL functions that Catalyst inlines.
SQL_FUNCTIONS = {
    "vec_add": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN zip_with(a, b, (x, y) -> x + y)",
    "vec_sub": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN zip_with(a, b, (x, y) -> x - y)",
    "vec_scale": "(a ARRAY<DOUBLE>, k DOUBLE) RETURNS ARRAY<DOUBLE> RETURN transform(a, x -> x * k)",
    "vec_dot": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "vec_norm": "(a ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt(aggregate(a, 0D, (s, x) -> s + x * x))",
    "prox_l1": "(a ARRAY<DOUBLE>, delta DOUBLE) RETURNS ARRAY<DOUBLE> RETURN transform(a, x -> signum(x) * greatest(abs(x) - delta, 0D))",
    "prox_sq": "(a ARRAY<DOUBLE>, delta DOUBLE) RETURNS ARRAY<DOUBLE> RETURN transform(a, x -> x / (1D + delta))",
    "fused_step": "(w ARRAY<DOUBLE>, grad ARRAY<DOUBLE>, anchor ARRAY<DOUBLE>, eta DOUBLE, sigma DOUBLE) RETURNS ARRAY<DOUBLE> RETURN zip_with(zip_with(w, grad, (x, d) -> (x - eta * d) / (1D + eta * sigma)), anchor, (x, z) -> x + z * (eta * sigma) / (1D + eta * sigma))",
}


def register(spark: SparkSession) -> list[str]:
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    return sorted(SQL_FUNCTIONS)
