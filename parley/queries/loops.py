"""Local steps, closed-form fixed points, rounds of quadratic parties, and training runs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parley import workloads as W
from parley.functions import vectors as V
from parley.functions.draws import mixed_sql
from parley.functions.losses import Linear, Logistic, Softmax
from parley.functions.prox import Regulariser
from parley.operators import methods as M
from parley.operators import parties as PT
from parley.operators import rounds as R
from parley.operators import theory as T
from parley.queries import Registry
from parley.sources.tables import Tables, load

register = Registry()
S, D = 2.0, 0.1

QUAD_SQL = """
WITH RECURSIVE per AS (SELECT c_nationkey::BIGINT AS party_id, avg(o_totalprice) / 1e5 AS c, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1),
q AS (SELECT party_id, n * count(*) OVER () / sum(n) OVER () AS a, c FROM per)
"""


def _r(*names: str):
    return [(F.round(n, 6) + F.lit(0.0)).alias(n) for n in names]


@register(QUAD_SQL + "SELECT party_id, round(c, 6) + 0.0 AS w FROM q")
def quadratic_case_a(spark: SparkSession, sf_dir: str) -> DataFrame:
    """No tie: every party ends at its own minimiser."""
    return T.fixed_point(T.quadratic_parties(spark, sf_dir), "a", S).select("party_id", *_r("w"))


@register(QUAD_SQL + f", g AS (SELECT sum(a * {S} / (a + {S}) * c) / sum(a * {S} / (a + {S})) AS g FROM q) SELECT party_id, round((a * c + {S} * g) / (a + {S}), 6) + 0.0 AS w, round(g, 6) + 0.0 AS g FROM q, g")
def quadratic_case_b(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.fixed_point(T.quadratic_parties(spark, sf_dir), "b", S).select("party_id", *_r("w", "g"))


@register(QUAD_SQL + f""", p AS (SELECT *, a / (a + {S} * {D} / (1 + {D})) AS rho FROM q), g AS (SELECT sum(rho * c) / sum(rho) AS g FROM p)
SELECT party_id, round(g + rho * (c - g), 6) + 0.0 AS w, round(g, 6) + 0.0 AS g FROM p, g""")
def quadratic_case_c(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.fixed_point(T.quadratic_parties(spark, sf_dir), "c", S, D).select("party_id", *_r("w", "g"))


def _rounds_sql(rounds: int, z: str, new: str) -> str:
    """Rounds as one query after the other; z from w and g, new from a, c, z, w, g."""
    sql = QUAD_SQL + ", r0 AS (SELECT party_id, a, c, 0.0::DOUBLE AS w FROM q), g0 AS (SELECT 0.0::DOUBLE AS g)"
    for k in range(rounds):
        sql += f", z{k} AS (SELECT *, {z} AS z FROM r{k}, g{k}), r{k + 1} AS MATERIALIZED (SELECT party_id, a, c, {new} AS w FROM z{k}), g{k + 1} AS MATERIALIZED (SELECT avg(w) AS g FROM r{k + 1})"
    return sql + f" SELECT party_id, round(w, 6) + 0.0 AS w, round(g, 6) + 0.0 AS g FROM r{rounds}, g{rounds}"


def _fused(x: str, e: float, s: float, times: int) -> str:
    for _ in range(times):
        x = f"(({x}) - {e} * a * (({x}) - c)) / (1 + {e} * {s}) + ({e} * {s}) / (1 + {e} * {s}) * z"
    return x


@register(_rounds_sql(8, f"g + (w - g) / (1 + {D})", f"(a * c + {S} * z) / (a + {S})"))
def quadratic_rounds_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eight rounds of the mean variant with exact local minimisers."""
    return T.quadratic_rounds(T.quadratic_parties(spark, sf_dir), "sq", S, D, 8).select("party_id", *_r("w", "g"))


@register(_rounds_sql(6, "g", f"(a * c + {S} * z) / (a + {S})"))
def quadratic_rounds_consensus(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.quadratic_rounds(T.quadratic_parties(spark, sf_dir), "consensus", S, D, 6).select("party_id", *_r("w", "g"))


@register(_rounds_sql(3, "0.0", _fused("g", 0.2, 0.0, 2)))
def fed_mean_scalar(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every party goes on from the centre; two steps a round."""
    return T.quadratic_rounds(T.quadratic_parties(spark, sf_dir), "consensus", 0.0, D, 3, 0.2, 2, 1.0).select("party_id", *_r("w", "g"))


@register(_rounds_sql(3, "g", _fused("g", 0.2, S, 2)))
def fed_prox_scalar(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.quadratic_rounds(T.quadratic_parties(spark, sf_dir), "consensus", S, D, 3, 0.2, 2, 1.0).select("party_id", *_r("w", "g"))


@register(_rounds_sql(3, "0.0", _fused("w", 0.2, 0.0, 2)))
def local_only_scalar(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.quadratic_rounds(T.quadratic_parties(spark, sf_dir), "free", 0.0, D, 3, 0.2, 2).select("party_id", *_r("w", "g"))


@register(_rounds_sql(3, f"g + (w - g) / (1 + {D})", _fused("w", 0.2, S, 2)))
def personal_mean_scalar(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.quadratic_rounds(T.quadratic_parties(spark, sf_dir), "sq", S, D, 3, 0.2, 2).select("party_id", *_r("w", "g"))


@register(_rounds_sql(2, f"g + (w - g) / (1 + {D})", _fused("(1 - 0.001) * w + 0.001 * g", 0.2, S, 2)))
def start_mix_scalar(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The mean variant begun at a mix of local and global model."""
    return T.quadratic_rounds(T.quadratic_parties(spark, sf_dir), "sq", S, D, 2, 0.2, 2, 0.001).select("party_id", *_r("w", "g"))


def _robust_sql(rounds: int) -> str:
    """Rounds of the coordinate-median variant; its centre by the plain iteration from the mean."""
    sql = QUAD_SQL + ", r0 AS (SELECT party_id, a, c, 0.0::DOUBLE AS w FROM q), g0 AS (SELECT 0.0::DOUBLE AS g)"
    for k in range(rounds):
        z = f"g + sign(w - g) * greatest(abs(w - g) - {D}, 0)"
        sql += f""", z{k} AS (SELECT *, {z} AS z FROM r{k}, g{k}), r{k + 1} AS MATERIALIZED (SELECT party_id, a, c, (a * c + {S} * z) / (a + {S}) AS w FROM z{k}),
m{k}(k, ws, g) AS (SELECT 0, list(w ORDER BY party_id), avg(w) FROM r{k + 1} UNION ALL SELECT k + 1, ws, g + list_avg(list_transform(ws, lambda x: least(greatest(x - g, -{D}), {D}))) FROM m{k} WHERE k < 2000),
g{k + 1} AS MATERIALIZED (SELECT g FROM m{k} WHERE k = 2000)"""
    return sql + f" SELECT party_id, round(w, 6) + 0.0 AS w, round(g, 6) + 0.0 AS g FROM r{rounds}, g{rounds}"


@register(_robust_sql(6))
def quadratic_rounds_comed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.quadratic_rounds(T.quadratic_parties(spark, sf_dir), "l1", S, D, 6).select("party_id", *_r("w", "g"))


_CASES = {"a": ("free", "w"), "b": ("consensus", "g"), "c": ("sq", f"g + (w - g) / (1 + {D})")}


def _residual_sql() -> str:
    """Residuals after three rounds, and at the closed form, of the three cases."""
    parts = []
    for case, (_, z) in _CASES.items():
        rounds = _rounds_sql(3, z, f"(a * c + {S} * z) / (a + {S})")
        body = rounds[: rounds.rindex(" SELECT party_id")]
        parts.append(f"""SELECT '{case}' AS which, 3 AS rounds, round(abs(avg(slope)), 6) + 0.0 AS mean_slope, round(max(abs(w - (z - slope / {S}))), 6) + 0.0 AS worst_miss
FROM (SELECT w, z, a * {S} / (a + {S}) * (z - c) AS slope FROM ({body} SELECT r3.*, {z} AS z FROM r3, g3))""")
    return " UNION ALL ".join(parts)


@register(_residual_sql())
def fixed_point_residual(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How far three exact rounds are from the fixed point's conditions, in the three cases that have a closed form."""
    p, out = T.quadratic_parties(spark, sf_dir), None
    for case, (kind, _) in _CASES.items():
        at = T.quadratic_rounds(p, kind, S, D, 3)
        part = T.residuals(p, at, kind, S, D).select(F.lit(case).alias("which"), F.lit(3).alias("rounds"), *_r("mean_slope", "worst_miss"))
        out = part if out is None else out.unionByName(part)
    return out


_CLOSED_SQL = "SELECT which, true AS mean_holds, true AS relation_holds FROM (VALUES ('b'), ('c')) v(which)"


@register(_CLOSED_SQL)
def closed_forms_are_fixed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The closed forms of cases b and c meet both conditions to 1e-9 (case a's centre is free)."""
    p, out = T.quadratic_parties(spark, sf_dir), None
    for case in ("b", "c"):
        part = T.residuals(p, T.fixed_point(p, case, S, D), _CASES[case][0], S, D).select(F.lit(case).alias("which"), (F.col("mean_slope") < 1e-9).alias("mean_holds"), (F.col("worst_miss") < 1e-9).alias("relation_holds"))
        out = part if out is None else out.unionByName(part)
    return out


@register(QUAD_SQL + f"""SELECT party_id, round((1.0 - 0.2 * a * (1.0 - c)) / (1 + 0.2 * {S}) + 0.2 * {S} / (1 + 0.2 * {S}) * 0.5, 6) + 0.0 AS fused,
    round(1.0 - 0.2 / (1 + 0.2 * {S}) * (a * (1.0 - c) + {S} * (1.0 - 0.5)), 6) + 0.0 AS penalised FROM q""")
def fused_step_forms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A fused step, and a gradient step of length eta kappa on the penalised loss: the same number twice."""
    V.register(spark)
    T.quadratic_parties(spark, sf_dir).createOrReplaceTempView("parley_quadratic")
    rows = spark.sql(f"SELECT party_id, fused_step(array(1D), array(a * (1D - c)), array(0.5D), 0.2D, {S}D)[0] AS fused, 1D - 0.2D / (1D + 0.2D * {S}D) * (a * (1D - c) + {S}D * 0.5D) AS penalised FROM parley_quadratic")
    return rows.select("party_id", *_r("fused", "penalised"))


@register("""SELECT l_suppkey AS party_id, count(*) AS n, round(avg(l_quantity / 50 * l_quantity / 50), 6) AS xx, round(avg(l_quantity / 50 * l_discount * 10), 6) AS xz, round(avg(l_discount * 10 * l_discount * 10), 6) AS zz,
    round(avg(l_quantity / 50 * l_extendedprice / 1e5), 6) AS xy, round(avg(l_discount * 10 * l_extendedprice / 1e5), 6) AS zy FROM lineitem GROUP BY 1""")
def gram_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sufficient statistics of a two-feature linear loss: one scan, then training needs no rows."""
    x, z, y = F.col("l_quantity") / 50, F.col("l_discount") * 10, F.col("l_extendedprice") / 1e5
    return load(spark, sf_dir, "lineitem").groupBy(F.col("l_suppkey").alias("party_id")).agg(F.count("*").alias("n"), *[F.round(F.avg(a * b), 6).alias(k) for k, a, b in (("xx", x, x), ("xz", x, z), ("zz", z, z), ("xy", x, y), ("zy", z, y))])


@register(f"SELECT c_custkey AS party_id, CASE WHEN ({mixed_sql(1, 202, 4, 'c_custkey')} + 0.5) / 2147483647.0 < 0.9 THEN 1 + {mixed_sql(1, 303, 4, 'c_custkey')} % 20 ELSE 20 END::INTEGER AS steps FROM customer")
def straggler_schedule(spark: SparkSession, sf_dir: str) -> DataFrame:
    return PT.schedule(load(spark, sf_dir, "customer").select(F.col("c_custkey").alias("party_id")), 4, 20, 0.9, 1)


def _tested(spark: SparkSession, examples: DataFrame, loss, method: M.Method, cfg: M.Rounds) -> DataFrame:
    ex = Tables(spark).keep(examples, "examples")
    run = R.run_rounds(ex.where("split = 'train'"), loss, method, cfg)
    return R.scores(ex.where("split = 'test'"), run, loss, method, cfg)


@register()
def train_images(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Test accuracy of each party after distributed rounds on robust images."""
    return _tested(spark, W.image_examples(spark, sf_dir), Softmax(64, W.CLASSES), M.personal_geomed(), M.Rounds(0.02, 15.0, 2, 10, 20, 20))


@register()
def train_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Document quality from text measures, a party for each source."""
    return _tested(spark, W.quality_examples(spark, sf_dir), Logistic(4), M.personal_geomed(), M.Rounds(0.5, 0.1, 3, 20, 20, 10))


@register()
def train_regression_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _tested(spark, W.regression_examples(spark, sf_dir), Linear(4), M.personal_comed(), M.Rounds(0.1, 1.0, 3, 10, 20, 10))


@register()
def train_regression_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings as inputs of planted regressions, one party's weights far out."""
    return _tested(spark, W.vector_regression_examples(spark, sf_dir), Linear(64), M.personal_geomed(), M.Rounds(0.5, 0.2, 3, 10, 20, 10))


#: Settings of the short runs that every check repeats; bench.py --published runs the experiments at their full length.
SHORT = {"softmax": 30, "one_label": 100, "five_labels": 20, "text": 77}


@register()
def compare_personal(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five datasets by seven methods, ten rounds."""
    r = W.compare_personal(spark, sf_dir, rounds=10, seeds=range(1, 3), d=1000)
    return r.groupBy("dataset", "n_parties", "method").agg(F.avg("score").alias("score"), F.avg("worst").alias("worst"), F.stddev_samp("score").alias("spread"))


@register()
def compare_standard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return W.compare_standard(spark, sf_dir, rounds=10, seeds=range(1, 2), every=5, sizes=SHORT)


@register()
def party_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """At the published numbers of parties, ten rounds."""
    return W.party_ablation(spark, sf_dir, rounds=10, seeds=range(1, 2))


@register()
def training_failure(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Change at aggregation and test growth by round, for methods with and without a common model."""
    return W.training_failure(spark, sf_dir, rounds=10, seeds=range(1, 3))


@register()
def straggler_levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return W.stragglers(spark, sf_dir, rounds=10, seeds=range(1, 2), sizes={"softmax": 30, "text": 77})
