"""Shared helpers of the text operators: table loading, shared-folder tables, byte-exact words."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator
from functools import wraps

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from parley.sources.tables import Tables, fresh_path, load, remove  # noqa: F401

#: The word alphabet of every contract: anything but blank and the five control blanks.
WORD_GAP = r"[\x20\x09-\x0D]+"


def one_of_each(df: DataFrame, repeated: DataFrame, copies: str, key: list[str]) -> DataFrame:
    """df with one row, any, of those that share a key and say copies > 1. repeated: such keys, if there are any."""
    if repeated.isEmpty():
        return df
    # rows with equal keys are added up before they move, so that no key is too large for a task
    picked = df.where(F.col(copies) > 1).groupBy(*key).agg(F.any_value(F.struct(*[F.col(f"`{c}`") for c in df.columns])).alias("row")).select("row.*")
    return df.where(F.coalesce(F.col(copies) <= 1, F.lit(True))).unionByName(picked)


def tidy(f: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], forget: Callable[[], None] | None = None) -> Callable:
    """f for mapInArrow, which at the end of its task gives memory back: workers live on and add to what an executor holds."""

    @wraps(f)
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from f(batches)
        finally:
            if forget:
                forget()
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except (AttributeError, OSError):  # another C library
                pass

    return run


def free_name(df: DataFrame, base: str) -> str:
    """A column name that df doesn't have, in any case."""
    taken, name = {c.lower() for c in df.columns}, base
    while name.lower() in taken:
        name += "_"
    return name


def tokenizer_path(name: str) -> str:
    """The place of a public vocabulary file; installed with its package on every machine."""
    import public_tokenizers

    return public_tokenizers.path(name)
