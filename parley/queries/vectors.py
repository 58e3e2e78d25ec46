"""Proximal maps, envelopes and centres over suppliers' mean vectors, some of them moved far out."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from parley.functions import prox as P
from parley.functions import vectors as V
from parley.functions.draws import mixed_sql
from parley.functions.prox import Regulariser
from parley.operators import aggregate as A
from parley.operators.parties import draw_active
from parley.queries import Registry
from parley.sources.tables import load

register = Registry()
D = 0.1
SIGMA = 2.0

MODELS_SQL = """
WITH v AS (SELECT l_suppkey AS party_id, avg(l_quantity) / 50 AS a, avg(l_extendedprice) / 1e5 AS b, avg(l_discount) * 10 AS c, avg(l_tax) * 10 AS d, count(*) AS weight
           FROM lineitem GROUP BY l_suppkey),
models AS (SELECT party_id, weight, CASE WHEN party_id % 10 = 0 THEN [a + 5, b - 5, c + 5, d + 3] ELSE [a, b, c, d] END AS w FROM v),
rows_ AS (SELECT party_id, weight, unnest(range(4)) AS coord, unnest(w) AS value FROM models),
mean_ AS (SELECT coord, avg(value) AS g FROM rows_ GROUP BY coord),
mvec AS (SELECT list(g ORDER BY coord) AS g FROM mean_),
res AS (SELECT party_id, list_transform(range(1, 5), lambda i: w[i] - g[i]) AS r FROM models, mvec),
nrm AS (SELECT party_id, r, sqrt(list_sum(list_transform(r, lambda x: x * x))) AS n FROM res)
"""


def models(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(party_id, weight, w): each supplier's mean quantity, price, discount and tax; every tenth far out."""
    li = load(spark, sf_dir, "lineitem").groupBy(F.col("l_suppkey").alias("party_id")).agg(F.array(F.avg("l_quantity") / 50, F.avg("l_extendedprice") / 1e5, F.avg("l_discount") * 10, F.avg("l_tax") * 10).alias("w"), F.count("*").alias("weight"))
    far = F.zip_with("w", F.array(*[F.lit(x) for x in (5.0, -5.0, 5.0, 3.0)]), lambda a, b: a + b)
    return li.select("party_id", "weight", F.when(F.col("party_id") % 10 == 0, far).otherwise(F.col("w")).alias("w"))


def residuals(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = models(spark, sf_dir)
    g = A.mean(m).agg(F.transform(F.sort_array(F.collect_list(F.struct("coord", "g"))), lambda e: e["g"]).alias("g"))
    return m.crossJoin(F.broadcast(g)).select("party_id", V.sub(F.col("w"), F.col("g")).alias("r"))  # one row


def coords(df: DataFrame, v: Column) -> DataFrame:
    """Long form with rounded values, for comparison between engines."""
    return df.select("party_id", F.posexplode(v).alias("coord", "value")).select("party_id", F.col("coord").cast("long").alias("coord"), (F.round("value", 6) + F.lit(0.0)).alias("value"))


def centre_rows(g: DataFrame) -> DataFrame:
    return g.select(F.col("coord").cast("long").alias("coord"), (F.round("g", 6) + F.lit(0.0)).alias("g"))


def _long_sql(expr: str) -> str:
    return MODELS_SQL + f", o AS (SELECT party_id, {expr} AS v FROM nrm) SELECT party_id, unnest(range(4)) AS coord, round(unnest(v), 6) + 0.0 AS value FROM o"


_PROX_SQL = {
    "sq": f"list_transform(r, lambda x: x / (1 + {D}))",
    "l2": f"list_transform(r, lambda x: x * CASE WHEN n > {D} THEN 1 - {D} / n ELSE 0 END)",
    "l1": f"list_transform(r, lambda x: sign(x) * greatest(abs(x) - {D}, 0))",
    "consensus": "list_transform(r, lambda x: 0.0 * x)",
    "free": "r",
}
for _kind, _expr in _PROX_SQL.items():

    @register(_long_sql(_expr), f"prox_{_kind}")
    def _prox(spark: SparkSession, sf_dir: str, kind: str = _kind) -> DataFrame:
        return coords(residuals(spark, sf_dir), P.prox(kind, F.col("r"), D))


@register(_long_sql(f"list_transform(r, lambda x: sign(x) * greatest(abs(x) - {1 / SIGMA}, 0))"))
def prox_unscaled_l1(spark: SparkSession, sf_dir: str) -> DataFrame:
    reg = P.unscaled("l1", SIGMA)
    return coords(residuals(spark, sf_dir), P.prox(reg.kind, F.col("r"), reg.delta))


@register(_long_sql(f"list_transform(r, lambda x: x * CASE WHEN n > {1 / SIGMA} THEN 1 - {1 / SIGMA} / n ELSE 0 END)"))
def prox_unscaled_l2(spark: SparkSession, sf_dir: str) -> DataFrame:
    reg = P.unscaled("l2", SIGMA)
    return coords(residuals(spark, sf_dir), P.prox(reg.kind, F.col("r"), reg.delta))


@register(_long_sql(f"list_transform(r, lambda x: x / (1 + {2 / SIGMA}))"))
def prox_unscaled_sq(spark: SparkSession, sf_dir: str) -> DataFrame:
    reg = P.unscaled("sq", SIGMA)
    return coords(residuals(spark, sf_dir), P.prox(reg.kind, F.col("r"), reg.delta))


@register(_long_sql(f"list_concat(list_transform(r[1:2], lambda x: x / (1 + {D})), list_transform(r[3:4], lambda x: sign(x) * greatest(abs(x) - {D}, 0)))"))
def prox_blockwise(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = residuals(spark, sf_dir)
    return coords(r, F.concat(P.prox("sq", F.slice("r", 1, 2), D), P.prox("l1", F.slice("r", 3, 2), D)))


@register(_long_sql(_PROX_SQL["l1"]))
def prox_sql_function(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The proximal map through SQL functions that Catalyst inlines."""
    V.register(spark)
    residuals(spark, sf_dir).createOrReplaceTempView("parley_residuals")
    return coords(spark.sql(f"SELECT party_id, prox_l1(r, {D}D) AS v FROM parley_residuals"), F.col("v"))


def _huber_sql(r: str) -> str:
    return f"CASE WHEN {r} <= {D} THEN {r} * {r} / 2 ELSE {D} * {r} - {D} * {D} / 2 END"


@register(MODELS_SQL + f"""SELECT party_id, round({SIGMA} * {D} / (2 * (1 + {D})) * n * n, 6) + 0.0 AS sq, round({SIGMA} * ({_huber_sql("n")}), 6) + 0.0 AS l2,
    round({SIGMA} * list_sum(list_transform(r, lambda x: {_huber_sql("abs(x)")})), 6) + 0.0 AS l1 FROM nrm""")
def envelopes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return residuals(spark, sf_dir).select("party_id", *[(F.round(P.envelope(k, F.col("r"), D, SIGMA), 6) + 0.0).alias(k) for k in ("sq", "l2", "l1")])


@register(MODELS_SQL + f"""SELECT party_id, round({SIGMA} * {D} / 2 * n * n, 6) + 0.0 AS sq, round({SIGMA} * {D} * n, 6) + 0.0 AS l2,
    round({SIGMA} * {D} * list_sum(list_transform(r, lambda x: abs(x))), 6) + 0.0 AS l1, CASE WHEN n > 0 THEN 'Infinity'::DOUBLE ELSE 0 END AS consensus FROM nrm""")
def psi_values(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = F.col("r")
    return residuals(spark, sf_dir).select("party_id", *[(F.round(P.value(k, r, D, SIGMA), 6) + 0.0).alias(k) for k in ("sq", "l2", "l1")], P.value("consensus", r, D, SIGMA).alias("consensus"))


@register(MODELS_SQL + "SELECT coord, round(g, 6) + 0.0 AS g FROM mean_")
def agg_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    return centre_rows(A.mean(models(spark, sf_dir)))


@register(MODELS_SQL + "SELECT coord, round(sum(weight * value) / sum(weight), 6) + 0.0 AS g FROM rows_ GROUP BY coord")
def agg_weighted_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    return centre_rows(A.weighted_mean(models(spark, sf_dir)))


@register(MODELS_SQL + "SELECT coord, round(quantile_cont(value, 0.5), 6) + 0.0 AS g FROM rows_ GROUP BY coord")
def agg_comed_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    return centre_rows(A.coordinate_median(models(spark, sf_dir)))


@register(MODELS_SQL + "SELECT coord, round(quantile_cont(value, 0.5), 6) + 0.0 AS g FROM rows_ GROUP BY coord")
def agg_comed_bounded(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The exact median of many parties: sketched bounds, then the values between them."""
    return centre_rows(A.median_between_bounds(models(spark, sf_dir), 20))


@register(MODELS_SQL + """, t AS (SELECT coord, sum(weight) AS total FROM rows_ GROUP BY 1),
u AS (SELECT coord, value, sum(weight) OVER (PARTITION BY coord ORDER BY value RANGE UNBOUNDED PRECEDING) AS upto FROM rows_) SELECT coord, round(min(value), 6) + 0.0 AS g FROM u JOIN t USING (coord) WHERE upto >= total / 2 GROUP BY coord""")
def agg_weighted_comed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return centre_rows(A.coordinate_median(models(spark, sf_dir), weight="weight"))


@register(MODELS_SQL + """SELECT coord, round(avg(value), 6) + 0.0 AS g FROM rows_ GROUP BY coord""")
def agg_mean_identity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The alternating iteration with the squared norm ends at the mean, which the planner therefore takes at once."""
    return centre_rows(A.general_centre(models(spark, sf_dir), Regulariser("sq", D), SIGMA)[0])


def _unrolled(kind: str, steps: int, reweighted: bool = False, delta: float = D) -> str:
    """Steps of a centre's iteration as one query after the other."""
    sql = MODELS_SQL + ", g0 AS (SELECT g FROM mvec)"
    for k in range(steps):
        n = f"sqrt(list_sum(list_transform(range(1, 5), lambda i: (w[i] - g[i]) * (w[i] - g[i]))))"
        if reweighted:
            sql += f""", d{k} AS (SELECT w, least(1, {delta} / greatest({n}, 1e-300)) AS s FROM models, g{k}),
g{k + 1} AS (SELECT [{", ".join(f"sum(s * w[{i}]) / sum(s)" for i in range(1, 5))}] AS g FROM d{k})"""
        elif kind == "l2":
            sql += f""", d{k} AS (SELECT w, g, least(1, {delta} / greatest({n}, 1e-300)) AS s FROM models, g{k}),
g{k + 1} AS (SELECT [{", ".join(f"any_value(g[{i}]) + avg(s * (w[{i}] - g[{i}]))" for i in range(1, 5))}] AS g FROM d{k})"""
        else:
            sql += f""", g{k + 1} AS (SELECT [{", ".join(f"any_value(g[{i}]) + avg(least(greatest(w[{i}] - g[{i}], -{delta}), {delta}))" for i in range(1, 5))}] AS g FROM models, g{k})"""
    return sql + f" SELECT unnest(range(4)) AS coord, round(unnest(g), 6) + 0.0 AS g FROM g{steps}"


@register(_unrolled("l2", 5))
def agg_geomed_plain(spark: SparkSession, sf_dir: str) -> DataFrame:
    return centre_rows(A.plain_steps(models(spark, sf_dir), "l2", D, 5))


@register(_unrolled("l1", 5))
def agg_comed_plain(spark: SparkSession, sf_dir: str) -> DataFrame:
    return centre_rows(A.plain_steps(models(spark, sf_dir), "l1", D, 5))


@register(_unrolled("l2", 40, True))
def agg_geomed_smoothed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """By reweighting to convergence."""
    return centre_rows(A.geometric_median(models(spark, sf_dir), D)[0])


def _weighted_sql(steps: int) -> str:
    """Weighted reweighting as a recursion over lists."""
    far = " + ".join(f"power(ws[i][{j}] - g[{j}], 2)" for j in range(1, 5))
    step = ", ".join(f"list_dot_product(s, list_transform(ws, lambda v: v[{j}])) / list_sum(s)" for j in range(1, 5))
    first = ", ".join(f"sum(weight * w[{j}]) / sum(weight)" for j in range(1, 5))
    return MODELS_SQL.replace("WITH v", "WITH RECURSIVE v", 1) + f""", l AS (SELECT list(w ORDER BY party_id) AS ws, list(weight::DOUBLE ORDER BY party_id) AS ps, [{first}] AS g FROM models),
go(k, ws, ps, g) AS (SELECT 0, ws, ps, g FROM l UNION ALL SELECT k + 1, ws, ps, [{step}] FROM (SELECT *, list_transform(range(1, len(ws) + 1), lambda i: ps[i] * least(1.0::DOUBLE, {D} / greatest(sqrt({far}), 1e-300))) AS s FROM go WHERE k < {steps}))
SELECT unnest(range(4)) AS coord, round(unnest(g), 6) + 0.0 AS g FROM go WHERE k = {steps}"""


@register(_weighted_sql(60))
def agg_weighted_geomed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parties weighed by their rows."""
    return centre_rows(A.geometric_median(models(spark, sf_dir), D, weight="weight")[0])


@register("SELECT kind, true AS at_optimum FROM (VALUES ('l1'), ('l2')) v(kind)")
def agg_residual(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The mean clipped residual vanishes at both smoothed medians."""
    m, out = models(spark, sf_dir), None
    for kind, g in (("l1", A.smoothed_coordinate_median(m, D)), ("l2", A.geometric_median(m, D)[0])):
        part = A.residual(m, g, kind, D).select(F.lit(kind).alias("kind"), (F.col("residual") < 1e-8).alias("at_optimum"))
        out = part if out is None else out.unionByName(part)
    return out


@register(_unrolled("l2", 60, True, 1e-9))
def agg_geomed_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    return centre_rows(A.geometric_median(models(spark, sf_dir))[0])


#: At every bend the slope of the summed Huber functions, in quadratic time; the centre by interpolation.
COMED_SQL = MODELS_SQL + f""", bends AS (SELECT DISTINCT coord, x FROM (SELECT coord, value - {D} AS x FROM rows_ UNION ALL SELECT coord, value + {D} FROM rows_)),
slopes AS (SELECT b.coord, b.x, sum(least(greatest(b.x - r.value, -{D}), {D})) AS s FROM bends b JOIN rows_ r USING (coord) GROUP BY b.coord, b.x),
steps_ AS (SELECT *, lag(x) OVER w AS x0, lag(s) OVER w AS s0 FROM slopes WINDOW w AS (PARTITION BY coord ORDER BY x)),
flat AS (SELECT s.coord, least(greatest(any_value(m.g), min(x)), max(x)) AS g FROM slopes s JOIN mean_ m USING (coord) WHERE abs(s) <= 1e-9 GROUP BY s.coord),
cut AS (SELECT coord, x0 - s0 * (x - x0) / (s - s0) AS g FROM steps_ WHERE s > 1e-9 AND s0 < -1e-9 AND coord NOT IN (SELECT coord FROM flat))
"""


@register(COMED_SQL + "SELECT coord, round(g, 6) + 0.0 AS g FROM (SELECT * FROM flat UNION ALL SELECT * FROM cut)")
def agg_comed_smoothed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return centre_rows(A.smoothed_coordinate_median(models(spark, sf_dir), D))


@register(COMED_SQL + "SELECT coord, round(g, 6) + 0.0 AS g FROM mean_ WHERE coord < 2 UNION ALL SELECT coord, round(g, 6) + 0.0 FROM (SELECT * FROM flat UNION ALL SELECT * FROM cut) WHERE coord >= 2")
def agg_hybrid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The mean for the first two coordinates, the smoothed coordinate median for the others."""
    return centre_rows(A.hybrid(models(spark, sf_dir), [(0, 2, Regulariser("sq", D)), (2, 4, Regulariser("l1", D))])[0])


@register(
    COMED_SQL
    + f""", c AS (SELECT list(g ORDER BY coord) AS g FROM (SELECT * FROM flat UNION ALL SELECT * FROM cut)), o AS (SELECT party_id, list_transform(range(1, 5), lambda i: sign(w[i] - g[i]) * greatest(abs(w[i] - g[i]) - {D}, 0)) AS v FROM models, c)
SELECT party_id, unnest(range(4)) AS coord, round(unnest(v), 6) + 0.0 AS value FROM o"""
)
def offsets_at_optimum(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Offsets and centre that minimise the objective together, for given models."""
    return coords(A.offsets(models(spark, sf_dir), Regulariser("l1", D), SIGMA)[0], F.col("v"))


@register(_unrolled("l2", 40, True))
def agg_general(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A user's proximal map (here the norm's), by the alternating iteration."""
    reg = Regulariser("user", user_prox=lambda x, sigma: P.prox_np("l2", x, D))
    return centre_rows(A.general_centre(models(spark, sf_dir), reg, SIGMA, limit=400)[0])


@register(MODELS_SQL + f""", act AS (SELECT party_id FROM models ORDER BY {mixed_sql(1, 101, 3, "party_id")}, party_id LIMIT 5),
news AS (SELECT party_id, list_transform(w, lambda x: x + 1) AS w FROM models WHERE party_id IN (SELECT party_id FROM act)),
now_ AS (SELECT m.party_id, coalesce(n.w, m.w) AS w FROM models m LEFT JOIN news n USING (party_id)),
sides AS (SELECT 'all' AS scope, w FROM now_ UNION ALL SELECT 'active', w FROM news),
lng AS (SELECT scope, unnest(range(4)) AS coord, unnest(w) AS value FROM sides)
SELECT scope, coord, round(avg(value), 6) + 0.0 AS g FROM lng GROUP BY scope, coord""")
def agg_scopes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Centres over all parties, idle ones carried forward, and over the active ones."""
    m = models(spark, sf_dir)
    news = m.join(F.broadcast(draw_active(m, 5, 3, 1)), "party_id", "left_semi").select("party_id", F.transform("w", lambda x: x + 1).alias("w"))
    both = A.mean(A.carried_forward(m.select("party_id", "w"), news)).withColumn("scope", F.lit("all")).unionByName(A.mean(news).withColumn("scope", F.lit("active")))
    return both.select("scope", F.col("coord").cast("long").alias("coord"), (F.round("g", 6) + 0.0).alias("g"))
