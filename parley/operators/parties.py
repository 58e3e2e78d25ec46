"""Party builders, exact splits, batch places, active draws, corruptions: columns over any table, by integer draws."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from parley.functions.draws import P, laplace, mixed, uniform


def by_hash(df: DataFrame, n: int, seed: int, key: str) -> DataFrame:
    return df.withColumn("party_id", F.pmod(mixed(seed, F.col(key)), F.lit(n)))


def equal(df: DataFrame, n: int, seed: int, key: str, buckets: int = 64) -> DataFrame:
    """Parties whose sizes differ by one at most within each of `buckets` hashed slices: no global sort."""
    slice_ = F.pmod(mixed(seed, 7, F.col(key)), F.lit(buckets))
    place = F.row_number().over(Window.partitionBy(slice_).orderBy(mixed(seed, F.col(key)), key))
    return df.withColumn("party_id", F.pmod(place - 1 + slice_, F.lit(n)).cast("long"))


def one_label(df: DataFrame, n: int, seed: int, key: str, label: str, classes: int) -> DataFrame:
    """Each party has rows of one label; a label's rows go to its parties by a power law."""
    per = n // classes
    return df.withColumn("party_id", power_law_place(uniform(seed, F.col(key)), per) * classes + F.col(label))


def some_labels(df: DataFrame, n: int, seed: int, key: str, label: str, classes: int, each: int) -> DataFrame:
    """Each party has rows of `each` neighbouring labels, from a start of its own."""
    step = F.pmod(mixed(seed, F.col(key)), F.lit(n * each // classes))
    flat = step * classes + F.pmod(F.col(label), F.lit(classes))  # a row's place among the pairs (party, label)
    k = F.pmod(mixed(seed, 3, F.col(key)), F.lit(each))
    start = F.pmod(F.col(label) - k, F.lit(classes))
    return df.withColumn("party_id", (F.floor(F.pmod(flat, F.lit(n)) / classes) * classes + start).cast("long"))


def power_law_place(u: Column, n: int, exponent: float = 2.0) -> Column:
    """0..n-1 with earlier places far likelier."""
    return F.least(F.floor(F.pow(u, F.lit(exponent)) * n), F.lit(n - 1)).cast("long")


def power_law(df: DataFrame, n: int, seed: int, key: str) -> DataFrame:
    return df.withColumn("party_id", power_law_place(uniform(seed, F.col(key)), n))


def split(df: DataFrame, share: float, seed: int, key: str, slices: int = 256) -> DataFrame:
    """Exactly ceil(share x rows) training rows in each party; adds split, n and pos, a row's place in its party's seeded order.

    A party is ranked in slices of that order, each begun where the one before ends, so that no party is too large for a task.
    Rows without a party belong to no split and are left out.
    """
    order = mixed(seed, 11, F.col(key))
    rows = df.withColumns({"_order": order, "_slice": F.floor(order * slices / P)})
    sizes = rows.groupBy("party_id", "_slice").agg(F.count("*").alias("_size"))
    w = Window.partitionBy("party_id")
    ahead = F.coalesce(F.sum("_size").over(w.orderBy("_slice").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    begins = sizes.select("party_id", "_slice", ahead.alias("_ahead"), F.sum("_size").over(w).alias("n"))  # at most `slices` rows a party
    place = F.row_number().over(Window.partitionBy("party_id", "_slice").orderBy("_order", key))
    placed = rows.join(begins, ["party_id", "_slice"]).withColumn("pos", place - 1 + F.col("_ahead")).drop("_order", "_slice", "_ahead")
    return placed.withColumn("split", F.when(F.col("pos") < F.ceil(F.col("n") * share), "train").otherwise("test"))


def batches(df: DataFrame, size: int) -> DataFrame:
    """batch_no of each training row, from its place."""
    return df.withColumn("batch_no", F.floor(F.col("pos") / size).cast("int"))


def draw_active(parties: DataFrame, k: int, t: int, seed: int) -> DataFrame:
    return parties.select("party_id").orderBy(mixed(seed, 101, t, F.col("party_id")), "party_id").limit(k)


def schedule(parties: DataFrame, t: int, steps: int, stragglers: float, seed: int) -> DataFrame:
    late = uniform(seed, 202, t, F.col("party_id")) < stragglers
    return parties.select("party_id", F.when(late, 1 + F.pmod(mixed(seed, 303, t, F.col("party_id")), F.lit(steps))).otherwise(F.lit(steps)).cast("int").alias("steps"))


def negate(df: DataFrame, share: float, n: int, x: str = "x") -> DataFrame:
    """Inputs of the first share x n parties with their sign turned."""
    return df.withColumn(x, F.when(F.col("party_id") < int(round(share * n)), F.transform(x, lambda a: -a)).otherwise(F.col(x)))


def outlier(df: DataFrame, party: int, far: float = 8.0, y: str = "y") -> DataFrame:
    """One party's targets moved far out, as if its model came from another centre."""
    return df.withColumn(y, F.when(F.col("party_id") == party, F.col(y) * far).otherwise(F.col(y)))


def noisy_classes(df: DataFrame, seed: int, key: str, classes: int = 10, per_party: int = 2, scale: float = 0.3, x: str = "x", label: str = "y") -> DataFrame:
    """Laplace noise on the inputs of per_party neighbouring classes of each party."""
    first = F.pmod(mixed(seed, 5, F.col("party_id")), F.lit(classes))
    hit = F.pmod(F.col(label).cast("long") - first, F.lit(classes)) < per_party
    return df.withColumn(x, F.when(hit, F.transform(x, lambda a, i: a + scale * laplace(seed, F.col(key), i))).otherwise(F.col(x)))


def heterogeneity(df: DataFrame, label: str) -> DataFrame:
    """Per party: total variation and Kullback-Leibler distance of its label mix from that of all rows."""
    own = df.groupBy("party_id", label).agg(F.count("*").alias("k"))
    size = own.groupBy("party_id").agg(F.sum("k").alias("n"))
    world = own.groupBy(label).agg(F.sum("k").alias("a"))
    total = world.agg(F.sum("a").alias("total"))
    full = size.crossJoin(F.broadcast(world)).crossJoin(F.broadcast(total)).join(own, ["party_id", label], "left")  # labels are few
    p, q = F.coalesce("k", F.lit(0)) / F.col("n"), F.col("a") / F.col("total")
    return full.groupBy("party_id").agg((F.sum(F.abs(p - q)) / 2).alias("tv"), F.sum(F.when(p > 0, p * F.log(p / q)).otherwise(0.0)).alias("kl"))
