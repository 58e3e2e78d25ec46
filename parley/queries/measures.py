"""Measures and fixtures: accuracy, change, paths, objective, parties, splits, corruptions, features."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from parley import workloads as W
from parley.functions import draws
from parley.functions import vectors as V
from parley.functions.draws import mixed_sql
from parley.functions.losses import Linear, Softmax
from parley.functions.prox import Regulariser
from parley.operators import methods as M
from parley.operators import parties as PT
from parley.operators import theory as T
from parley.queries import Registry
from parley.queries.loops import QUAD_SQL, SHORT, _r, _rounds_sql
from parley.sources.tables import load

register = Registry()

#: Fixed linear scorers of three classes over the first four coordinates of a vector.
SCORERS = ((1.0, -1.0, 0.5, 0.0), (-0.5, 1.0, 0.0, 1.0), (0.0, 0.5, -1.0, -0.5))
_SCORED_SQL = "list_value(" + ", ".join(" + ".join(f"{a} * embedding[{j + 1}]::DOUBLE" for j, a in enumerate(row)) for row in SCORERS) + ")"


def predicted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(party_id, y, label, top): vectors of hashed parties, the class a fixed scorer gives, and its score."""
    e = PT.by_hash(load(spark, sf_dir, "embeddings"), 10, 1, "vec_id")
    scores = F.array(*[sum((F.lit(a) * F.col("embedding")[j].cast("double") for j, a in enumerate(row)), F.lit(0.0)) for row in SCORERS])
    return e.select("party_id", "label", V.argmax(scores).alias("y"), F.array_max(scores).alias("top"))


@register(f"""WITH p AS (SELECT {mixed_sql(1, 'vec_id')} % 10 AS party_id, label, list_position({_SCORED_SQL}, list_max({_SCORED_SQL})) - 1 AS y FROM embeddings)
SELECT party_id, count(*) AS n, round(avg(CASE WHEN y = label % 3 THEN 1.0 ELSE 0 END), 6) AS accuracy FROM p GROUP BY party_id""")
def accuracy_by_party(spark: SparkSession, sf_dir: str) -> DataFrame:
    return predicted(spark, sf_dir).groupBy("party_id").agg(F.count("*").alias("n"), F.round(F.avg(F.when(F.col("y") == F.col("label") % 3, 1.0).otherwise(0.0)), 6).alias("accuracy"))


@register(f"""WITH p AS (SELECT {mixed_sql(1, 'vec_id')} % 10 AS party_id, label, list_position({_SCORED_SQL}, list_max({_SCORED_SQL})) - 1 AS y FROM embeddings),
a AS (SELECT party_id, avg(CASE WHEN y = label % 3 THEN 1.0 ELSE 0 END) AS s FROM p GROUP BY 1)
SELECT round(avg(s), 6) AS mean, round(min(s), 6) AS worst, round(quantile_cont(s, 0.1), 6) AS p10, round(quantile_cont(s, 0.5), 6) AS median FROM a""")
def accuracy_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean over parties, and the parties that do worst."""
    a = predicted(spark, sf_dir).groupBy("party_id").agg(F.avg(F.when(F.col("y") == F.col("label") % 3, 1.0).otherwise(0.0)).alias("s"))
    return a.agg(F.round(F.avg("s"), 6).alias("mean"), F.round(F.min("s"), 6).alias("worst"), F.round(F.percentile("s", 0.1), 6).alias("p10"), F.round(F.percentile("s", 0.5), 6).alias("median"))


@register("""WITH e AS (SELECT l_suppkey AS party_id, l_extendedprice / 1e5 - (0.5 * l_quantity / 50 + 0.1 * l_discount * 10) AS e FROM lineitem)
SELECT party_id, round(avg(e * e), 6) AS mse, round(sum(e * e) / 1000, 6) AS sse_thousands FROM e GROUP BY party_id""")
def mse_by_party(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("party_id"), (F.col("l_extendedprice") / 1e5 - (F.lit(0.5) * F.col("l_quantity") / 50 + F.lit(0.1) * F.col("l_discount") * 10)).alias("e"))
    return e.groupBy("party_id").agg(F.round(F.avg(F.col("e") * F.col("e")), 6).alias("mse"), F.round(F.sum(F.col("e") * F.col("e")) / 1000, 6).alias("sse_thousands"))


@register(f"""WITH p AS (SELECT {mixed_sql(1, 'vec_id')} % 10 AS party_id, label, list_position({_SCORED_SQL}, list_max({_SCORED_SQL})) - 1 AS y FROM embeddings),
s AS (SELECT party_id AS owner, label % 3 AS lab, y FROM p), pairs AS (SELECT a.party_id, s.owner, s.lab, s.y FROM (SELECT DISTINCT party_id FROM p) a JOIN s ON a.party_id != s.owner)
SELECT party_id, round(avg(CASE WHEN y = lab THEN 1.0 ELSE 0 END), 6) AS transfer FROM pairs GROUP BY party_id""")
def transfer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Score on all rows that other parties own, from sums: no row meets a foreign party."""
    a = predicted(spark, sf_dir).groupBy("party_id").agg(F.sum(F.when(F.col("y") == F.col("label") % 3, 1).otherwise(0)).alias("hit"), F.count("*").alias("n"))
    total = a.agg(F.sum("hit").alias("hits"), F.sum("n").alias("rows"))
    return a.crossJoin(F.broadcast(total)).select("party_id", F.round((F.col("hits") - F.col("hit")) / (F.col("rows") - F.col("n")), 6).alias("transfer"))  # one row


@register(QUAD_SQL + f""", w AS (SELECT party_id, c AS before, (SELECT avg(c) FROM q) AS g FROM q)
SELECT method, round(avg(lam * (g - before)), 6) + 0.0 AS change_mean, round(stddev_pop(lam * (g - before)), 6) + 0.0 AS change_std FROM w, (VALUES ('fed_mean', 1.0), ('start_mix', 0.001), ('personal_mean', 0.0)) m(method, lam) GROUP BY method""")
def param_change(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Change of parties' models at an aggregation, by the share of the global model they go on from."""
    p = T.quadratic_parties(spark, sf_dir)
    g = p.agg(F.avg("c").alias("g"))
    methods = spark.createDataFrame([("fed_mean", 1.0), ("start_mix", 0.001), ("personal_mean", 0.0)], "method string, lam double")
    moved = p.crossJoin(F.broadcast(g)).crossJoin(F.broadcast(methods)).withColumn("d", F.col("lam") * (F.col("g") - F.col("c")))  # one row; three rows
    return moved.groupBy("method").agg(F.avg("d").alias("change_mean"), F.stddev_pop("d").alias("change_std")).select("method", *_r("change_mean", "change_std"))


@register(QUAD_SQL + """, g AS (SELECT avg(c) AS g FROM q), l AS (SELECT unnest(range(0, 11)) / 10.0 AS lam)
SELECT lam, round(avg(a / 2 * power((1 - lam) * c + lam * g - c, 2)), 6) + 0.0 AS loss, round(max(a / 2 * power((1 - lam) * c + lam * g - c, 2)), 6) + 0.0 AS worst FROM q, g, l GROUP BY lam""")
def lambda_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Local losses on the way from the local to the global model."""
    p = T.quadratic_parties(spark, sf_dir)
    grid = spark.range(11).select((F.col("id") / 10.0).alias("lam"))
    at = p.crossJoin(F.broadcast(p.agg(F.avg("c").alias("g")))).crossJoin(F.broadcast(grid))  # one row; eleven rows
    loss = F.col("a") / 2 * F.pow((1 - F.col("lam")) * F.col("c") + F.col("lam") * F.col("g") - F.col("c"), 2)
    return at.groupBy("lam").agg(F.avg(loss).alias("loss"), F.max(loss).alias("worst")).select("lam", *_r("loss", "worst"))


def _objective_sql(rounds: int) -> str:
    env = "2.0 * 0.1 / (2 * 1.1) * (w - g) * (w - g)"
    base = _rounds_sql(rounds, "g + (w - g) / 1.1", "(a * c + 2.0 * z) / (a + 2.0)")
    base = base[: base.rindex(" SELECT party_id")]
    parts = " UNION ALL ".join(f"SELECT {k} AS round, avg(a / 2 * (w - c) * (w - c) + {env}) AS o FROM r{k}, g{k}" for k in range(1, rounds + 1))
    return base + f", o AS ({parts}) SELECT round::INTEGER AS round, round(o, 6) + 0.0 AS objective, o > coalesce(lag(o) OVER (ORDER BY round), 1e300) + 1e-12 AS rose FROM o"


@register(_objective_sql(6))
def objective_by_round(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The joint objective after each round of the mean variant; it never rises."""
    p, rows = T.quadratic_parties(spark, sf_dir), []
    r = F.col("w") - F.col("g")
    o = F.avg(F.col("a") / 2 * F.pow(F.col("w") - F.col("c"), 2) + 2.0 * 0.1 / (2 * 1.1) * r * r)
    for t, (now, g) in enumerate(T.quadratic_path(p, "sq", 2.0, 0.1, 6), 1):
        rows.append((t, now.withColumn("g", F.lit(g)).agg(o.alias("o")).first()["o"]))  # one number a round
    every = spark.createDataFrame(rows, "round int, o double")
    w = Window.orderBy("round")  # six rows
    return every.select("round", (F.round("o", 6) + 0.0).alias("objective"), (F.col("o") > F.coalesce(F.lag("o").over(w), F.lit(1e300)) + 1e-12).alias("rose"))


@register()
def descent_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per regulariser: rises of the objective, kept decreases, vanishing gradients and the rate, for convex losses and all parties.

    Parties are six groups of suppliers with all their lineitem rows and a planted target; one scan condenses them.
    """
    rows, x = [], F.array(F.col("l_quantity") / 50, F.col("l_extendedprice") / 1e5, F.col("l_discount") * 10, F.col("l_tax") * 10)
    items = load(spark, sf_dir, "lineitem").select(F.pmod("l_suppkey", F.lit(6)).alias("party_id"), x.alias("x"))
    loss, fed = Linear(4), T.condensed(W.planted(items, 4, 6, 1), 4)
    for name, reg in (("mean", Regulariser("sq")), ("geomed", Regulariser("l2")), ("comed", Regulariser("l1"))):
        cfg = M.Rounds(1 / loss.lipschitz(fed.x), 0.1, 25, 6, 3, None, scope="all")
        got = T.descent(loss, fed, M.Method(name, reg), cfg)
        o = [r["objective"] for r in got]
        rows.append((name, sum(b > a + 1e-12 for a, b in zip(o, o[1:], strict=False)), all(r["decrease_held"] for r in got), got[-1]["squared_gradients"] / got[0]["squared_gradients"], T.rate(o)))
    return spark.createDataFrame(rows, "method string, rises int, decrease_held boolean, gradient_ratio double, rate double")


@register(f"""WITH p AS (SELECT {mixed_sql(2, 'vec_id')} % 10 AS party_id, label FROM embeddings), own AS (SELECT party_id, label, count(*) AS k FROM p GROUP BY 1, 2),
n AS (SELECT party_id, sum(k) AS n FROM own GROUP BY 1), wd AS (SELECT label, sum(k) / (SELECT count(*) FROM p) AS q FROM own GROUP BY 1),
f AS (SELECT n.party_id, coalesce(k, 0) / n AS p, q FROM n CROSS JOIN wd LEFT JOIN own ON own.party_id = n.party_id AND own.label = wd.label)
SELECT party_id, round(sum(abs(p - q)) / 2, 6) AS tv, round(sum(CASE WHEN p > 0 THEN p * ln(p / q) ELSE 0 END), 6) AS kl FROM f GROUP BY party_id""")
def heterogeneity(spark: SparkSession, sf_dir: str) -> DataFrame:
    h = PT.heterogeneity(PT.by_hash(load(spark, sf_dir, "embeddings"), 10, 2, "vec_id"), "label")
    return h.select("party_id", F.round("tv", 6).alias("tv"), F.round("kl", 6).alias("kl"))


@register("SELECT eta, sigma, round(1 / (1 + sigma * eta), 6) AS kappa, 1 / (1 + sigma * eta) BETWEEN 0.9 AND 0.999 AS advised, count(*) AS n FROM (SELECT l_discount / 100 AS eta, l_quantity AS sigma FROM lineitem WHERE l_discount IS NOT NULL AND l_quantity IS NOT NULL) GROUP BY eta, sigma")
def kappa_settings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The tie's weight for every pair of a step length (a discount's hundredth) and a penalty (a quantity) that lineitem has."""

    def part(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            runs = [M.Rounds(e, s) for e, s in zip(frame["eta"], frame["sigma"], strict=True)]
            yield frame.assign(kappa=[r.kappa for r in runs], advised=[r.advised for r in runs])

    pairs = load(spark, sf_dir, "lineitem").groupBy((F.col("l_discount") / 100).alias("eta"), F.col("l_quantity").alias("sigma")).agg(F.count("*").alias("n"))
    at = pairs.where("eta IS NOT NULL AND sigma IS NOT NULL").mapInPandas(part, "eta double, sigma double, n long, kappa double, advised boolean")
    return at.select("eta", "sigma", F.round("kappa", 6).alias("kappa"), "advised", "n")


# ---- fixtures ----------------------------------------------------------------------------------------------------------


@register(f"SELECT {mixed_sql(1, 'vec_id')} % 50 AS party_id, count(*) AS n, sum(vec_id)::BIGINT AS ids FROM embeddings GROUP BY 1")
def parties_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return PT.by_hash(load(spark, sf_dir, "embeddings"), 50, 1, "vec_id").groupBy("party_id").agg(F.count("*").alias("n"), F.sum("vec_id").alias("ids"))


@register(f"""WITH s AS (SELECT vec_id, {mixed_sql(1, 7, 'vec_id')} % 64 AS s, {mixed_sql(1, 'vec_id')} AS h FROM embeddings),
o AS (SELECT vec_id, (row_number() OVER (PARTITION BY s ORDER BY h, vec_id) - 1 + s) % 10 AS party_id FROM s) SELECT party_id, count(*) AS n, sum(vec_id)::BIGINT AS ids FROM o GROUP BY 1""")
def parties_equal(spark: SparkSession, sf_dir: str) -> DataFrame:
    return PT.equal(load(spark, sf_dir, "embeddings"), 10, 1, "vec_id").groupBy("party_id").agg(F.count("*").alias("n"), F.sum("vec_id").alias("ids"))


_U = f"(({mixed_sql(1, 'vec_id')} + 0.5) / 2147483647.0)"


@register(f"SELECT least(floor(power({_U}, 2.0) * 10), 9)::BIGINT * 10 + label AS party_id, count(*) AS n, count(DISTINCT label) AS labels FROM embeddings GROUP BY 1")
def parties_one_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    return PT.one_label(load(spark, sf_dir, "embeddings"), 100, 1, "vec_id", "label", 10).groupBy("party_id").agg(F.count("*").alias("n"), F.countDistinct("label").alias("labels"))


@register(f"""SELECT (floor((({mixed_sql(1, 'vec_id')} % 10) * 10 + label % 10) % 20 / 10.0) * 10 + (label - {mixed_sql(1, 3, 'vec_id')} % 5 + 10) % 10)::BIGINT AS party_id, count(*) AS n, count(DISTINCT label) AS labels FROM embeddings GROUP BY 1""")
def parties_five_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    return PT.some_labels(load(spark, sf_dir, "embeddings"), 20, 1, "vec_id", "label", 10, 5).groupBy("party_id").agg(F.count("*").alias("n"), F.countDistinct("label").alias("labels"))


def _shared(examples: DataFrame) -> DataFrame:
    """How many rows the parties hold, in how many parties a row is, and whether a training row is tested somewhere."""
    key = examples.withColumn("k", F.xxhash64("x", "y"))
    per = key.groupBy("k").agg(F.countDistinct("party_id").alias("parties"), F.countDistinct("split").alias("parts"), F.count("*").alias("copies"))
    return per.agg(F.sum("copies").alias("rows"), F.max("parties").alias("most_parties"), F.max("parts").alias("most_parts"))


@register("SELECT each, (SELECT count(*) FROM embeddings)::BIGINT AS rows, 1::BIGINT AS most_parties, 1::BIGINT AS most_parts FROM (VALUES (1), (5)) v(each)")
def label_parties_share_nothing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One-label and five-label parties together hold every image once."""
    out = None
    for each, n in ((1, 100), (5, 20)):
        part = _shared(W.label_examples(spark, sf_dir, n, 1, each)).select(F.lit(each).alias("each"), "*")
        out = part if out is None else out.unionByName(part)
    return out


@register(f"""WITH s AS (SELECT source, row_number() OVER (ORDER BY source) - 1 AS k, count(*) OVER () AS m FROM (SELECT DISTINCT source FROM documents d JOIN labels l USING (doc_id))),
b AS (SELECT source, floor(k * 77 / m) AS lo, floor((k + 1) * 77 / m) AS hi FROM s),
d AS (SELECT d.source, (lo + least(floor(({mixed_sql(1, 13, 'doc_id')} + 0.5) / 2147483647.0 * (hi - lo)), greatest(hi - lo - 1, 0)))::BIGINT AS party_id FROM documents d JOIN labels USING (doc_id) JOIN b ON b.source = d.source)
SELECT party_id, count(*) AS n, count(DISTINCT source) AS sources FROM d GROUP BY 1""")
def text_accounts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accounts of the text workload: every account has documents of one source."""
    return W.accounts(W.labelled_text(spark, sf_dir), 77, 1).groupBy("party_id").agg(F.count("*").alias("n"), F.countDistinct("source").alias("sources"))


@register("""WITH h AS (SELECT date_trunc('hour', ts) AS hour, event_type, avg(value) AS price FROM events GROUP BY 1, 2),
r AS (SELECT DISTINCT hour FROM (SELECT hour, price / lag(price) OVER (PARTITION BY event_type ORDER BY hour) AS relative FROM h) WHERE relative IS NOT NULL),
p AS (SELECT row_number() OVER (ORDER BY hour) AS k, count(*) OVER () AS m FROM r) SELECT floor((k - 1) * 8 / (m - 1))::BIGINT AS party_id, count(*) AS n, max(k) - min(k) + 1 AS stretch FROM p WHERE k < m GROUP BY 1""")
def portfolio_stretches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each party of the portfolio workload has a stretch of hours of its own, without gaps."""
    ex = W.portfolio_examples(spark, sf_dir).groupBy("party_id").agg(F.count("*").alias("n"))
    return ex.select("party_id", "n", F.col("n").alias("stretch"))


@register(f"WITH p AS (SELECT vec_id, {mixed_sql(1, 'vec_id')} % 10 AS party_id, label FROM embeddings) SELECT vec_id, CASE WHEN party_id = 9 THEN label * 8.0 ELSE label END::DOUBLE AS y FROM p")
def outlier_party(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = PT.by_hash(load(spark, sf_dir, "embeddings"), 10, 1, "vec_id").withColumn("y", F.col("label").cast("double"))
    return PT.outlier(p, 9).select("vec_id", "y")


@register(f"SELECT least(floor(power({_U}, 2.0) * 30), 29)::BIGINT AS party_id, count(*) AS n FROM embeddings GROUP BY 1")
def parties_power_law(spark: SparkSession, sf_dir: str) -> DataFrame:
    return PT.power_law(load(spark, sf_dir, "embeddings"), 30, 1, "vec_id").groupBy("party_id").agg(F.count("*").alias("n"))


_SPLIT_SQL = f"""WITH p AS (SELECT vec_id, {mixed_sql(1, 'vec_id')} % 10 AS party_id FROM embeddings),
s AS (SELECT *, row_number() OVER (PARTITION BY party_id ORDER BY {mixed_sql(3, 11, 'vec_id')}, vec_id) - 1 AS pos, count(*) OVER (PARTITION BY party_id) AS n FROM p),
c AS (SELECT *, CASE WHEN pos < ceil(n * 0.8) THEN 'train' ELSE 'test' END AS split FROM s)
"""


def _split(spark: SparkSession, sf_dir: str) -> DataFrame:
    return PT.split(PT.by_hash(load(spark, sf_dir, "embeddings"), 10, 1, "vec_id"), 0.8, 3, "vec_id")


@register(_SPLIT_SQL + "SELECT party_id, split, count(*) AS n, sum(vec_id)::BIGINT AS ids FROM c GROUP BY 1, 2")
def split_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _split(spark, sf_dir).groupBy("party_id", "split").agg(F.count("*").alias("n"), F.sum("vec_id").alias("ids"))


@register(_SPLIT_SQL + "SELECT party_id, floor(pos / 10)::INTEGER AS batch_no, count(*) AS n, sum(vec_id)::BIGINT AS ids FROM c WHERE split = 'train' GROUP BY 1, 2")
def batch_slots(spark: SparkSession, sf_dir: str) -> DataFrame:
    return PT.batches(_split(spark, sf_dir).where("split = 'train'"), 10).groupBy("party_id", "batch_no").agg(F.count("*").alias("n"), F.sum("vec_id").alias("ids"))


@register(f"SELECT s_suppkey AS party_id FROM supplier ORDER BY {mixed_sql(1, 101, 7, 's_suppkey')}, s_suppkey LIMIT 10")
def active_draw(spark: SparkSession, sf_dir: str) -> DataFrame:
    return PT.draw_active(load(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("party_id")), 10, 7, 1)


@register(f"WITH p AS (SELECT vec_id, {mixed_sql(1, 'vec_id')} % 10 AS party_id, embedding FROM embeddings) SELECT vec_id, party_id, round(CASE WHEN party_id < 1 THEN -1 ELSE 1 END * embedding[1]::DOUBLE, 6) + 0.0 AS x0 FROM p")
def negate_parties(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = PT.by_hash(load(spark, sf_dir, "embeddings"), 10, 1, "vec_id").withColumn("x", F.transform("embedding", lambda a: a.cast("double")))
    return PT.negate(p, 0.1, 10).select("vec_id", "party_id", (F.round(F.col("x")[0], 6) + 0.0).alias("x0"))


_LAP = f"(({mixed_sql(1, 'vec_id', 0)} + 0.5) / 2147483647.0 - 0.5)"


@register(f"""WITH p AS (SELECT vec_id, label, {mixed_sql(1, 'vec_id')} % 10 AS party_id, embedding FROM embeddings)
SELECT vec_id, round(embedding[1]::DOUBLE + CASE WHEN (label - {mixed_sql(1, 5, 'party_id')} % 10 + 10) % 10 < 2 THEN -0.3 * sign({_LAP}) * ln(1 - 2 * abs({_LAP})) ELSE 0 END, 6) + 0.0 AS x0 FROM p""")
def class_noise(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = PT.by_hash(load(spark, sf_dir, "embeddings"), 10, 1, "vec_id").withColumn("x", F.transform("embedding", lambda a: a.cast("double")))
    return PT.noisy_classes(p, 1, "vec_id", label="label").select("vec_id", (F.round(F.col("x")[0], 6) + 0.0).alias("x0"))


@register("""SELECT d.doc_id, toxic, quality, length(text) AS chars, len(string_split(text, chr(10))) AS n_lines, round(len(list_distinct(string_split(text, ' '))) / len(string_split(text, ' ')), 6) AS distinct_share
FROM documents d JOIN labels l USING (doc_id)""")
def text_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    d, words = load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels"), "doc_id"), F.split("text", " ")
    return d.select("doc_id", "toxic", "quality", F.length("text").cast("long").alias("chars"), F.size(F.split("text", "\n")).cast("long").alias("n_lines"), F.round(F.size(F.array_distinct(words)) / F.size(words), 6).alias("distinct_share"))


@register("""WITH h AS (SELECT date_trunc('hour', ts) AS hour, event_type, avg(value) AS price FROM events GROUP BY 1, 2),
r AS (SELECT hour, event_type, price / lag(price) OVER (PARTITION BY event_type ORDER BY hour) AS relative FROM h)
SELECT epoch(hour)::BIGINT AS hour, event_type, round(relative, 6) AS relative FROM r WHERE relative IS NOT NULL""")
def portfolio_relatives(spark: SparkSession, sf_dir: str) -> DataFrame:
    return W.price_relatives(spark, sf_dir).select(F.unix_timestamp(F.col("hour").cast("timestamp")).alias("hour"), "event_type", F.round("relative", 6).alias("relative"))


@register(f"SELECT id, round(({mixed_sql(9, 'id')} + 0.5) / 2147483647.0, 6) AS u, round(sqrt(-2 * ln(({mixed_sql(9, 'id', 1)} + 0.5) / 2147483647.0)) * cos(2 * pi() * ({mixed_sql(9, 'id', 2)} + 0.5) / 2147483647.0), 6) + 0.0 AS z FROM (SELECT event_id AS id FROM events)")
def seeded_draws(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Uniform and normal draws by event, which every engine and task repeats."""
    e = load(spark, sf_dir, "events").select(F.col("event_id").alias("id"))
    return e.select("id", F.round(draws.uniform(9, F.col("id")), 6).alias("u"), (F.round(draws.normal(9, F.col("id")), 6) + 0.0).alias("z"))


@register()
def method_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Relative gain of the best variant over each other method, by dataset, and over all datasets."""
    r = W.compare_standard(spark, sf_dir, rounds=10, seeds=range(1, 2), every=0, sizes=SHORT)
    s = r.groupBy("dataset", "method").agg(F.avg("score").alias("score"))
    best = s.where(F.col("method").startswith("personal")).groupBy("dataset").agg(F.max("score").alias("best"))
    return s.where(~F.col("method").startswith("personal")).join(best, "dataset").withColumn("gain", F.col("best") / F.col("score") - 1).rollup("method", "dataset").agg(F.avg("gain").alias("gain"), F.count("*").alias("n"))


@register()
def curve_speed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """First watched round at which a method reaches 90 % of its dataset's best score."""
    r = W.compare_standard(spark, sf_dir, rounds=12, seeds=range(1, 2), every=2, sizes=SHORT)
    top = r.groupBy("dataset").agg(F.max("score").alias("top"))
    return r.join(top, "dataset").groupBy("dataset", "method").agg(F.min(F.when(F.col("score") >= 0.9 * F.col("top"), F.col("round"))).alias("reached"), F.max("score").alias("score"))


@register()
def spikes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rounds whose change at aggregation is over three times the method-wide median, and scores that fall with them."""
    r = W.training_failure(spark, sf_dir, rounds=10, seeds=range(1, 2))
    w = Window.partitionBy("method", "seed").orderBy("round")
    mid = r.groupBy("seed").agg(F.percentile("change_std", 0.5).alias("mid"))
    j = r.withColumn("fall", F.lag("score").over(w) - F.col("score")).join(mid, "seed")
    return j.groupBy("method").agg(F.max("change_std").alias("largest"), F.sum(F.when(F.col("change_std") > 3 * F.col("mid"), 1).otherwise(0)).alias("spikes"), F.sum(F.when((F.col("change_std") > 3 * F.col("mid")) & (F.col("fall") > 0), 1).otherwise(0)).alias("collapses"))


@register()
def loss_constants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lipschitz constants that give the theory's step lengths: of the softmax loss over all rows, and the greatest norm of a row."""

    def part(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total, most = None, 0.0
        for frame in frames:
            if len(frame):
                x = np.stack(frame["embedding"].to_numpy()).astype(float)
                x *= np.sqrt(x.shape[1])
                most = max(most, float(np.linalg.norm(x, axis=1).max()))
                x1 = np.hstack([x, np.ones((len(x), 1))])
                total = x1.T @ x1 if total is None else total + x1.T @ x1
        if total is not None:
            yield pd.DataFrame({"at": np.arange(total.size), "v": total.ravel(), "most": most})

    rows = load(spark, sf_dir, "embeddings").select("embedding").where("embedding IS NOT NULL")
    sums = rows.mapInPandas(part, "at int, v double, most double").groupBy("at").agg(F.sum("v").alias("v"), F.max("most").alias("most")).orderBy("at").collect()
    gram = np.array([r.v for r in sums]).reshape(-1, math.isqrt(len(sums)))  # its last entry counts the rows
    return spark.createDataFrame([("softmax", float(0.5 * np.linalg.eigvalsh(gram / gram[-1, -1])[-1])), ("rows", sums[0].most)], "loss string, constant double")
