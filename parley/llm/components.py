"""Connected components of a distributed edge list, by local union-find and star contraction.

Neither the driver nor one task ever holds the graph: each partition first shrinks its own edges to a forest, then
rounds of large and small stars (grouped minima and joins, over which a hot node's rows are dealt by salt) pull every
node to the smallest id it can reach. Each round is a written table in the shared folder; the one before it goes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from parley.llm.common import Tables, tidy

CHUNK = 1 << 20
#: Tasks whose forests one task joins before the rounds begin.
FEWER = 16
#: Parts that the rows of a node are dealt in.
SALT = 32


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Union-find over id pairs: every id that isn't the smallest of its component, and that smallest id."""
    if not len(a):
        return a, b
    ids, code = np.unique(np.concatenate([a, b]), return_inverse=True)
    left, right = code[: len(a)], code[len(a) :]
    root = np.arange(len(ids))
    while True:  # hooking and pointer jumping, in whole arrays
        low = np.minimum(root[left], root[right])
        before = root.copy()
        np.minimum.at(root, root[left], low)
        np.minimum.at(root, root[right], low)
        np.minimum.at(root, left, low)
        np.minimum.at(root, right, low)
        root = root[root]
        while (deeper := root[root]).tobytes() != root.tobytes():
            root = deeper
        if np.array_equal(before, root):
            break
    moved = root != np.arange(len(ids))
    return ids[moved], ids[root[moved]]


def _contract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    a, b = np.empty(0, np.int64), np.empty(0, np.int64)
    for batch in batches:
        a, b = np.concatenate([a, batch.column(0).to_numpy()]), np.concatenate([b, batch.column(1).to_numpy()])
        if len(a) > CHUNK:
            a, b = forest(a, b)
            if len(a) > CHUNK // 2:  # a forest too large to carry along
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["v", "u"])
                a, b = a[:0], b[:0]
    a, b = forest(a, b)
    yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["v", "u"])


def _with_least(rows: DataFrame, itself: bool) -> DataFrame:
    """rows (v, u) with m, the least u of v's rows (itself: and of v): a node's rows are joined in up to SALT parts."""
    dealt = rows.withColumn("s", F.pmod(F.xxhash64("u"), F.lit(SALT)))
    part = dealt.groupBy("v", "s").agg(F.min("u").alias("m"))
    least = part.groupBy("v").agg(F.min("m").alias("m"), F.collect_list("s").alias("parts"))  # SALT at most
    m = F.least("v", "m") if itself else F.col("m")
    return dealt.join(least.select("v", m.alias("m"), F.explode("parts").alias("s")), ["v", "s"]).select("v", "u", "m")


def components(edges: DataFrame, tables: Tables | None = None, max_rounds: int = 40) -> DataFrame:
    """edges: two long columns. Returns (node, root) for every node that isn't its own component's smallest id."""
    names, tables = edges.columns, tables or Tables(edges.sparkSession)
    start = edges.select(F.col(names[0]).cast("long").alias("v"), F.col(names[1]).cast("long").alias("u")).where("v IS NOT NULL AND u IS NOT NULL AND v != u")
    # written first: a task that makes edges in Python and contracts them too would keep two workers, for good
    raw = tables.keep(start, "edges")
    first = tables.keep(raw.mapInArrow(tidy(_contract), "v long, u long"), "forests")
    tables.drop(raw)
    fewer = max(1, len(first.inputFiles()) // FEWER)
    now = tables.keep(first.coalesce(fewer).mapInArrow(tidy(_contract), "v long, u long"), "forest")
    tables.drop(first)
    mark = lambda: now.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("v", "u")).alias("x"), F.count_distinct("v").alias("d")).first()
    seen = mark()
    for _ in range(max_rounds if seen["n"] else 0):
        both = now.select("v", "u").unionByName(now.select(F.col("u").alias("v"), F.col("v").alias("u")))
        large = _with_least(both, True).where("u > v").select(F.col("u").alias("v"), F.col("m").alias("u"))  # v's larger neighbours go to v's least
        small = _with_least(large, False).select(F.explode(F.array(F.struct("v", F.col("m").alias("u")), F.struct(F.col("u").alias("v"), F.col("m").alias("u")))).alias("e")).select("e.*").where("v != u").distinct()
        before, now = now, tables.keep(small, "stars")
        tables.drop(before)
        last, seen = seen, mark()
        if last == seen and seen["n"] == seen["d"]:
            break
    else:
        if seen["n"]:
            raise RuntimeError(f"no convergence in {max_rounds} rounds")
    return now.select(F.col("v").alias("node"), F.col("u").alias("root"))
