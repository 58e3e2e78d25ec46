"""Relational operators around the methods, sources and sinks, and streams, each against SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from parley.functions.draws import mixed_sql, normal
from parley.functions.prox import Regulariser
from parley.operators.parties import by_hash
from parley.queries import Registry
from parley.sources import stores
from parley.sources.tables import load, run_folder
from parley.streaming import updates as U

register = Registry()


def _round(name: str, digits: int = 4):
    return (F.round(name, digits) + F.lit(0.0)).alias(name)


@register("SELECT l_suppkey AS party_id, round(l_extendedprice * (1 - l_discount), 4) AS net, year(l_shipdate)::INTEGER AS y FROM lineitem WHERE l_quantity BETWEEN 10 AND 12 AND l_returnflag IN ('A', 'R') AND l_tax < 0.05")
def project_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = load(spark, sf_dir, "lineitem").where(F.col("l_quantity").between(10, 12) & F.col("l_returnflag").isin("A", "R") & (F.col("l_tax") < 0.05))
    return li.select(F.col("l_suppkey").alias("party_id"), F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"), F.year("l_shipdate").alias("y"))


@register("SELECT p_partkey, upper(p_brand) AS brand FROM part WHERE p_name LIKE '%a%' AND regexp_matches(p_type, '^[A-Z]') AND p_size IS DISTINCT FROM 1")
def pattern_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = load(spark, sf_dir, "part").where(F.col("p_name").like("%a%") & F.col("p_type").rlike("^[A-Z]") & ~F.col("p_size").eqNullSafe(1))
    return p.select("p_partkey", F.upper("p_brand").alias("brand"))


@register("SELECT n_name, r_name, count(c_custkey) AS customers FROM nation JOIN region ON n_regionkey = r_regionkey LEFT JOIN customer ON c_nationkey = n_nationkey GROUP BY 1, 2")
def join_inner_left(spark: SparkSession, sf_dir: str) -> DataFrame:
    n, r, c = (load(spark, sf_dir, t) for t in ("nation", "region", "customer"))
    return n.join(r, n.n_regionkey == r.r_regionkey).join(c, c.c_nationkey == n.n_nationkey, "left").groupBy("n_name", "r_name").agg(F.count("c_custkey").alias("customers"))


@register("WITH u AS (SELECT user_id, count(*) AS n FROM events GROUP BY 1) SELECT coalesce(u.user_id, s.s_suppkey) AS party_id, coalesce(n, 0)::BIGINT AS events, coalesce(s_name, 'none') AS supplier FROM u FULL JOIN supplier s ON u.user_id = s.s_suppkey + 20")
def join_full(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two sides of which each has rows that the other lacks."""
    u = load(spark, sf_dir, "events").groupBy("user_id").agg(F.count("*").alias("n"))
    s = load(spark, sf_dir, "supplier").select("s_suppkey", "s_name")
    both = u.join(s, u.user_id == s.s_suppkey + 20, "full")
    return both.select(F.coalesce("user_id", "s_suppkey").alias("party_id"), F.coalesce("n", F.lit(0)).cast("long").alias("events"), F.coalesce("s_name", F.lit("none")).alias("supplier"))


@register("SELECT doc_id, EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id) AS labelled FROM documents d")
def semi_anti(spark: SparkSession, sf_dir: str) -> DataFrame:
    d, lab = load(spark, sf_dir, "documents").select("doc_id"), load(spark, sf_dir, "labels")
    return d.join(lab, "doc_id", "left_semi").withColumn("labelled", F.lit(True)).unionByName(d.join(lab, "doc_id", "left_anti").withColumn("labelled", F.lit(False)))


@register("SELECT s_suppkey, band FROM supplier JOIN (VALUES (0, -2000.0, 0.0), (1, 0.0, 3000.0), (2, 3000.0, 100000.0)) b(band, lo, hi) ON s_acctbal >= lo AND s_acctbal < hi")
def band_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = spark.createDataFrame([(0, -2000.0, 0.0), (1, 0.0, 3000.0), (2, 3000.0, 100000.0)], "band int, lo double, hi double")
    s = load(spark, sf_dir, "supplier")
    return s.join(F.broadcast(b), (s.s_acctbal >= b.lo) & (s.s_acctbal < b.hi)).select("s_suppkey", "band")  # three rows


@register("""WITH g AS (SELECT date_trunc('hour', ts) + INTERVAL 1 HOUR AS g_time, avg(value) AS g FROM events GROUP BY 1)
SELECT event_id, round(g, 4) AS g FROM events e ASOF LEFT JOIN g ON e.ts >= g.g_time""")
def asof_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each update beside the latest centre at or before its time (an hour's centre is known when it ends): tasks work on days apart."""
    e = load(spark, sf_dir, "events")
    g = e.groupBy((F.date_trunc("hour", "ts") + F.expr("interval 1 hour")).alias("t")).agg(F.avg("value").alias("g"))
    both = e.select(F.col("ts").alias("t"), "event_id", F.lit(None).cast("double").alias("g")).unionByName(g.select("t", F.lit(None).cast("long").alias("event_id"), "g"))
    day = both.withColumn("day", F.to_date("t"))
    ends = day.groupBy("day").agg(F.max_by("g", F.when(F.col("g").isNotNull(), F.col("t"))).alias("last"))
    carry = ends.select("day", F.last("last", True).over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)).alias("carried"))  # a row a day
    w = Window.partitionBy("day").orderBy("t", F.col("event_id").isNotNull()).rowsBetween(Window.unboundedPreceding, 0)
    at = day.withColumn("seen", F.last("g", True).over(w)).join(carry, "day")
    return at.where("event_id IS NOT NULL").select("event_id", F.round(F.coalesce("seen", "carried"), 4).alias("g"))


@register("""WITH w AS (SELECT user_id, min(ts) AS lo, min(ts) + INTERVAL 3 DAY AS hi FROM events GROUP BY 1)
SELECT e.user_id, count(*) AS n FROM events e JOIN w ON e.user_id = w.user_id AND e.ts BETWEEN lo AND hi GROUP BY 1""")
def interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events").select("user_id", "ts")
    w = e.groupBy("user_id").agg(F.min("ts").alias("lo"))
    return e.join(w, "user_id").where(F.col("ts").between(F.col("lo"), F.col("lo") + F.expr("interval 3 days"))).groupBy("user_id").agg(F.count("*").alias("n"))


@register("SELECT n_nationkey, lam, method FROM nation, (SELECT unnest(range(0, 5)) / 4.0 AS lam), (VALUES ('a'), ('b')) m(method)")
def cross_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    grid = spark.range(5).select((F.col("id") / 4.0).alias("lam")).crossJoin(spark.createDataFrame([("a",), ("b",)], "method string"))  # ten rows
    return load(spark, sf_dir, "nation").select("n_nationkey").crossJoin(F.broadcast(grid))


@register("SELECT l_suppkey AS party_id, rn, price FROM (SELECT l_suppkey, l_extendedprice AS price, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_extendedprice DESC) AS rn FROM lineitem) WHERE rn <= 3")
def top_of_party(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("l_suppkey").orderBy(F.desc("l_extendedprice"))
    return load(spark, sf_dir, "lineitem").withColumn("rn", F.row_number().over(w).cast("long")).where("rn <= 3").select(F.col("l_suppkey").alias("party_id"), "rn", F.col("l_extendedprice").alias("price"))


@register("SELECT l_suppkey AS party_id, i::INTEGER AS at, x FROM (SELECT l_suppkey, unnest(range(4)) AS i, unnest([min(l_quantity), max(l_quantity), min(l_tax), max(l_tax)]) AS x FROM lineitem GROUP BY l_suppkey)")
def lateral_explode(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = load(spark, sf_dir, "lineitem").groupBy(F.col("l_suppkey").alias("party_id")).agg(F.array(F.min("l_quantity"), F.max("l_quantity"), F.min("l_tax"), F.max("l_tax")).alias("v"))
    return a.select("party_id", F.posexplode("v").alias("at", "x"))


@register("""SELECT l_suppkey AS party_id, count(*) AS n, round(avg(l_quantity), 4) AS mean, round(var_samp(l_quantity), 4) AS var, round(covar_pop(l_quantity, l_extendedprice), 2) AS cov, round(corr(l_quantity, l_extendedprice), 4) AS corr,
round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, min(l_extendedprice) AS lo, max(l_extendedprice) AS hi FROM lineitem GROUP BY 1""")
def party_statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    q, p = "l_quantity", "l_extendedprice"
    return load(spark, sf_dir, "lineitem").groupBy(F.col("l_suppkey").alias("party_id")).agg(F.count("*").alias("n"), F.round(F.avg(q), 4).alias("mean"), F.round(F.var_samp(q), 4).alias("var"), F.round(F.covar_pop(q, p), 2).alias("cov"), F.round(F.corr(q, p), 4).alias("corr"), F.round(F.regr_slope(p, q), 4).alias("slope"), F.min(p).alias("lo"), F.max(p).alias("hi"))


@register("SELECT source AS party, count(DISTINCT lang) AS langs, count(DISTINCT text) AS texts FROM documents GROUP BY 1")
def distinct_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents").groupBy(F.col("source").alias("party")).agg(F.countDistinct("lang").alias("langs"), F.countDistinct("text").alias("texts"))


@register("SELECT user_id AS party_id, round(quantile_cont(value, 0.5), 4) AS p50, round(quantile_cont(value, 0.9), 4) AS p90 FROM events GROUP BY 1")
def party_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").groupBy(F.col("user_id").alias("party_id")).agg(F.round(F.percentile("value", 0.5), 4).alias("p50"), F.round(F.percentile("value", 0.9), 4).alias("p90"))


@register("SELECT coalesce(n_regionkey, -1) AS region, coalesce(c_mktsegment, 'all') AS segment, grouping(n_regionkey, c_mktsegment) AS level, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, c_mktsegment)")
def rollup_results(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, n = load(spark, sf_dir, "customer"), load(spark, sf_dir, "nation")
    j = c.join(n, c.c_nationkey == n.n_nationkey).select(F.col("n_regionkey").alias("region"), F.col("c_mktsegment").alias("segment"))
    return j.rollup("region", "segment").agg(F.grouping_id().alias("level"), F.count("*").alias("n")).select(F.coalesce("region", F.lit(-1)).alias("region"), F.coalesce("segment", F.lit("all")).alias("segment"), "level", "n")


@register("SELECT coalesce(l_returnflag, 'all') AS flag, coalesce(l_linestatus, 'all') AS status, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def cube_results(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "lineitem").select(F.col("l_returnflag").alias("flag"), F.col("l_linestatus").alias("status")).cube("flag", "status").agg(F.count("*").alias("n")).select(F.coalesce("flag", F.lit("all")).alias("flag"), F.coalesce("status", F.lit("all")).alias("status"), "n")


@register("SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY 1")
def pivot_results(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = load(spark, sf_dir, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).count()
    return p.select("user_id", F.coalesce("click", F.lit(0)).alias("click"), F.coalesce("view", F.lit(0)).alias("view"))


@register("SELECT s_suppkey, 'balance' AS measure, s_acctbal AS v FROM supplier UNION ALL SELECT s_suppkey, 'nation', s_nationkey::DOUBLE FROM supplier")
def unpivot_results(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = load(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_acctbal").alias("balance"), F.col("s_nationkey").cast("double").alias("nation"))
    return s.unpivot("s_suppkey", ["balance", "nation"], "measure", "v")


@register("SELECT s_suppkey, rank() OVER w AS r, dense_rank() OVER w AS d, ntile(4) OVER (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey) AS q, round(percent_rank() OVER w, 4) AS p FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal)")
def ranking_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("s_nationkey").orderBy("s_acctbal")
    wide = Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")
    return load(spark, sf_dir, "supplier").select("s_suppkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.ntile(4).over(wide).alias("q"), F.round(F.percent_rank().over(w), 4).alias("p"))


@register("""SELECT event_id, round(value - coalesce(lag(value) OVER w, value), 4) + 0.0 AS change, round(min(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 4) AS least,
count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS day_n FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""")
def analytic_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    second = F.rint(F.unix_micros(F.col("ts").cast("timestamp")) / 1e6).cast("long")  # the nearest one, as the SQL's cast takes it
    day = Window.partitionBy("user_id").orderBy(second).rangeBetween(-86400, 0)
    return load(spark, sf_dir, "events").select("event_id", (F.round(F.col("value") - F.coalesce(F.lag("value").over(w), F.col("value")), 4) + 0.0).alias("change"), F.round(F.min("value").over(w.rowsBetween(Window.unboundedPreceding, 0)), 4).alias("least"), F.count("*").over(day).alias("day_n"))


@register("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@register("""SELECT 'both' AS kind, count(*) AS n FROM (SELECT c_nationkey FROM customer INTERSECT SELECT s_nationkey FROM supplier) UNION ALL
SELECT 'rest', count(*) FROM (SELECT c_nationkey FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier) UNION ALL SELECT 'all', count(*) FROM (SELECT c_nationkey FROM customer UNION SELECT s_nationkey FROM supplier)""")
def set_operations(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, s = load(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")), load(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k"))
    count = lambda kind, df: df.agg(F.count("*").alias("n")).select(F.lit(kind).alias("kind"), "n")
    return count("both", c.intersect(s)).unionByName(count("rest", c.exceptAll(s))).unionByName(count("all", c.union(s).distinct()))


@register("SELECT l_suppkey AS party_id, round(sum((l_quantity - m) / s), 3) + 0.0 AS total, round(max((l_quantity - m) / s), 4) AS top FROM (SELECT l_suppkey, l_quantity, avg(l_quantity) OVER w AS m, stddev_samp(l_quantity) OVER w AS s FROM lineitem WINDOW w AS (PARTITION BY l_suppkey)) GROUP BY 1")
def standardise(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Features scaled within each party, from its statistics: rows aren't sorted."""
    li = load(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("party_id"), "l_quantity")
    st = li.groupBy("party_id").agg(F.avg("l_quantity").alias("m"), F.stddev_samp("l_quantity").alias("s"))
    z = li.join(st, "party_id").select("party_id", ((F.col("l_quantity") - F.col("m")) / F.col("s")).alias("z"))
    return z.groupBy("party_id").agg((F.round(F.sum("z"), 3) + 0.0).alias("total"), F.round(F.max("z"), 4).alias("top"))


@register("SELECT event_type, round(avg((props->>'k')::DOUBLE), 4) AS k FROM events GROUP BY 1")
def json_props(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").groupBy("event_type").agg(F.round(F.avg(F.get_json_object("props", "$.k").cast("double")), 4).alias("k"))


def _scratch(spark: SparkSession) -> str:
    return f"{run_folder(spark)}/files-{uuid.uuid4().hex}"


for _fmt in ("csv", "json", "orc", "parquet"):

    @register("SELECT s_suppkey, s_name, s_acctbal FROM supplier", f"round_trip_{_fmt}")
    def _round_trip(spark: SparkSession, sf_dir: str, fmt: str = _fmt) -> DataFrame:
        df, path = load(spark, sf_dir, "supplier").select("s_suppkey", "s_name", "s_acctbal"), _scratch(spark)
        stores.write_parties(df, path, fmt)
        return stores.read_parties(spark, path, fmt, df.schema)


@register("SELECT l_suppkey AS party_id, count(*) AS n FROM lineitem WHERE l_suppkey IN (3, 5) GROUP BY 1")
def example_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two parties out of a store by party buckets: the filter prunes folders."""
    path = _scratch(spark)
    stores.write_examples(load(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("party_id"), F.col("l_orderkey").alias("pos")), path, 8)
    wanted = spark.createDataFrame([(3,), (5,)], "party_id long")
    buckets = [r[0] for r in wanted.select(F.pmod(F.hash("party_id"), F.lit(8))).collect()]
    return spark.read.parquet(path).where(F.col("party_bucket").isin(buckets) & F.col("party_id").isin(3, 5)).groupBy("party_id").agg(F.count("*").alias("n"))


@register("SELECT s_suppkey, s_name, s_acctbal, CASE WHEN s_suppkey % 7 = 0 THEN 'bad ' || s_suppkey::VARCHAR || ',x' END AS broken FROM supplier")
def corrupt_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of a text file that don't parse keep their whole text; the others their columns."""
    s, path = load(spark, sf_dir, "supplier"), _scratch(spark)
    line = F.concat_ws(",", F.col("s_suppkey").cast("string"), "s_name", F.col("s_acctbal").cast("string"))
    bad = F.concat(F.lit("bad "), F.col("s_suppkey").cast("string"), F.lit(",x"))
    s.select(F.when(F.col("s_suppkey") % 7 == 0, F.concat(bad, F.lit(","))).otherwise(line).alias("value")).write.text(path)
    rows = spark.read.schema("s_suppkey long, s_name string, s_acctbal double, broken string").option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "broken").csv(path)
    key = F.coalesce("s_suppkey", F.regexp_extract("broken", r"(\d+)", 1).cast("long")).alias("s_suppkey")
    names = s.select(F.col("s_suppkey").alias("k"), F.col("s_name").alias("name"), F.col("s_acctbal").alias("bal"))
    read = rows.select(key, F.regexp_replace("broken", ",$", "").alias("broken"))
    return read.join(names, F.col("s_suppkey") == F.col("k")).select("s_suppkey", F.col("name").alias("s_name"), F.col("bal").alias("s_acctbal"), "broken")


@register("SELECT n_name AS line FROM nation")
def round_trip_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = _scratch(spark)
    load(spark, sf_dir, "nation").select("n_name").write.text(path)
    return stores.read_parties(spark, path, "text", "line string")


def _drawn(*keys: str | int) -> str:
    """SQL of a normal draw."""
    u = lambda last: f"(({mixed_sql(*keys, last)} + 0.5) / 2147483647.0)"
    return f"(sqrt(-2 * ln({u(1)})) * cos(2 * pi() * {u(2)}))"


_FLAT = f"(({mixed_sql(1, 3, 'k', 'j')} + 0.5) / 2147483647.0 - 0.5)"


@register(f"""WITH w AS (SELECT k, j, CASE WHEN k < 4 THEN {_drawn(1, 1, 'j')} * 2.2 ELSE {_drawn(1, 2, 'j')} * 7.1 END + 0.5 * (-sign({_FLAT}) * ln(1 - 2 * abs({_FLAT}))) AS w FROM range(5) a(k), range(8) b(j)),
e AS (SELECT {mixed_sql(1, 'vec_id')} % 5 AS k, vec_id AS i, embedding FROM embeddings),
x AS (SELECT k, i, j, 8 * embedding[j + 1]::DOUBLE AS x FROM e, range(8) b(j)),
y AS (SELECT k, i, sum(x * w) + any_value({_drawn(1, 6, 'k', 'i')}) AS y, sum(x) AS total FROM x JOIN w USING (k, j) GROUP BY k, i)
SELECT k AS party_id, count(*) AS n, round(avg(y), 5) + 0.0 AS y, round(sum(total), 5) + 0.0 AS x FROM y GROUP BY k""")
def generator_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Regressions over the given vectors, planted by the models of a data source of our own; every drawn value is a seeded one."""
    stores.register_sources(spark)
    planted = spark.read.format("parley_synth").options(parties=5, models=1).load().select("party_id", F.col("x").alias("w"))  # five rows
    e = by_hash(load(spark, sf_dir, "embeddings"), 5, 1, "vec_id").select("party_id", "vec_id", F.transform(F.slice("embedding", 1, 8), lambda a: a.cast("double") * 8).alias("x"))
    summed = lambda v: F.aggregate(v, F.lit(0.0), lambda s, a: s + a)
    y = summed(F.zip_with("x", "w", lambda a, b: a * b)) + normal(1, 6, F.col("party_id"), F.col("vec_id"))
    rows = e.join(F.broadcast(planted), "party_id").select("party_id", y.alias("y"), summed("x").alias("total"))
    return rows.groupBy("party_id").agg(F.count("*").alias("n"), (F.round(F.avg("y"), 5) + 0.0).alias("y"), (F.round(F.sum("total"), 5) + 0.0).alias("x"))


# ---- streams: four files that come one after the other, some of their rows late and some twice, against the same in SQL ----

#: part: the file that a row comes in, by its day; every tenth row a file late, every seventeenth once more in the next file.
_PART = "least(3, (day(ts) - 1) // 8 + CASE WHEN event_id % 10 = 0 THEN 1 ELSE 0 END)"
_UPDATES_SQL = f"""WITH RECURSIVE e AS (SELECT *, {_PART} AS part FROM events),
u AS (SELECT user_id AS party_id, hour(ts)::INTEGER AS round, ts AS event_time, value AS w, part FROM e
UNION ALL SELECT user_id, hour(ts)::INTEGER, ts, value, least(3, part + 1) FROM e WHERE event_id % 17 = 0)"""


def _arrived(spark: SparkSession, sf_dir: str) -> tuple[str, DataFrame]:
    """The folder in which the files have come in order."""
    e, path = load(spark, sf_dir, "events"), _scratch(spark)
    part = F.least(F.lit(3), F.floor((F.dayofmonth("ts") - 1) / 8) + F.when(F.col("event_id") % 10 == 0, 1).otherwise(0))
    first = e.withColumn("part", part)
    every = first.unionByName(first.where("event_id % 17 = 0").withColumn("part", F.least(F.lit(3), F.col("part") + 1)))
    for k in range(4):
        every.where(F.col("part") == k).drop("part").coalesce(1).write.mode("append").parquet(path)
    return path, e


def _updates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream of files."""
    path, events = _arrived(spark, sf_dir)
    return U.as_updates(U.stream_of(spark, path, events.schema))


def _flat(df: DataFrame) -> DataFrame:
    return df.select(F.unix_timestamp("window.start").alias("start_s"), *[c for c in df.columns if c not in ("window", "w", "batch")], F.round("w", 3).alias("w"))


@register(_UPDATES_SQL + " SELECT epoch(time_bucket(INTERVAL 6 HOUR, event_time))::BIGINT AS start_s, count(*) AS n, round(sum(w), 3) AS w FROM u GROUP BY 1")
def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _flat(U.run_to_end(U.tumbling(_updates(spark, sf_dir)), "complete"))


#: What a watermark of two hours lets in and closes: a file's rows are judged by the times seen before the file ahead of it.
_LATE_SQL = _UPDATES_SQL + """, seen AS (SELECT p AS part, (SELECT max(event_time) FROM u WHERE u.part < p - LATE_LAG) - INTERVAL 2 HOUR AS mark FROM range(4) t(p)),
win AS (SELECT time_bucket(INTERVAL 6 HOUR, event_time) AS start, u.* FROM u),
kept AS (SELECT win.* FROM win JOIN seen USING (part) WHERE mark IS NULL OR start + INTERVAL 6 HOUR > mark),
over AS (SELECT max(event_time) - INTERVAL 2 HOUR AS mark FROM u)
SELECT epoch(start)::BIGINT AS start_s, count(*) AS n, round(sum(w), 3) AS w FROM kept, over WHERE start + INTERVAL 6 HOUR <= over.mark GROUP BY 1""".replace("LATE_LAG", "1")


@register(_LATE_SQL)
def stream_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Closed windows, as they are given once: what comes after the watermark is dropped."""
    return _flat(U.run_to_end(U.tumbling(_updates(spark, sf_dir))))


@register(_UPDATES_SQL + """, s AS (SELECT time_bucket(INTERVAL 6 HOUR, event_time) - k * INTERVAL 6 HOUR AS start, w FROM u, range(2) t(k)) SELECT epoch(start)::BIGINT AS start_s, count(*) AS n, round(sum(w), 3) AS w FROM s GROUP BY 1""")
def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _flat(U.run_to_end(U.sliding(_updates(spark, sf_dir)), "complete"))


@register(_UPDATES_SQL + """, m AS (SELECT *, CASE WHEN event_time - lag(event_time) OVER p <= INTERVAL 8 HOUR THEN 0 ELSE 1 END AS new FROM u WINDOW p AS (PARTITION BY party_id ORDER BY event_time)),
g AS (SELECT *, sum(new) OVER (PARTITION BY party_id ORDER BY event_time, w ROWS UNBOUNDED PRECEDING) AS s FROM m) SELECT floor(epoch(min(event_time)))::BIGINT AS start_s, party_id, count(*) AS n, round(sum(w), 3) AS w FROM g GROUP BY party_id, s""")
def stream_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _flat(U.run_to_end(U.sessions(_updates(spark, sf_dir), late="40 days"), "complete"))


@register(_UPDATES_SQL + " SELECT DISTINCT party_id, round FROM u")
def stream_once_each(spark: SparkSession, sf_dir: str) -> DataFrame:
    return U.run_to_end(U.once_each(_updates(spark, sf_dir))).select("party_id", "round")


@register(_UPDATES_SQL + ", g AS (SELECT hour(ts)::INTEGER AS round, avg(value) AS g FROM events GROUP BY 1) SELECT round, count(*) AS n, round(sum(w - g), 3) + 0.0 AS pull FROM u JOIN g USING (round) GROUP BY round")
def stream_with_centre(spark: SparkSession, sf_dir: str) -> DataFrame:
    centres = U.as_updates(load(spark, sf_dir, "events")).groupBy("round").agg(F.avg("w").alias("g"))
    j = U.run_to_end(U.with_centre(_updates(spark, sf_dir), centres))
    return j.groupBy("round").agg(F.count("*").alias("n"), (F.round(F.sum(F.col("w") - F.col("g")), 3) + 0.0).alias("pull"))


@register(_UPDATES_SQL + " SELECT a.party_id, count(*) AS n FROM u a JOIN (SELECT * FROM u WHERE round < 12) b ON a.party_id = b.party_id AND b.event_time BETWEEN a.event_time AND a.event_time + INTERVAL 1 HOUR GROUP BY 1")
def stream_acknowledged(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Morning updates acknowledge what came in the hour before; the allowance is long enough for late ones."""
    path, events = _arrived(spark, sf_dir)
    one, two = (U.as_updates(U.stream_of(spark, path, events.schema)) for _ in range(2))
    return U.run_to_end(U.acknowledged(one, two.where("round < 12"), late="40 days")).groupBy("party_id").agg(F.count("*").alias("n"))


_MODELS_SQL = _UPDATES_SQL + """, o AS (SELECT *, count(*) OVER (PARTITION BY party_id) - row_number() OVER (PARTITION BY party_id ORDER BY part, event_time, w) AS after FROM u)
SELECT party_id, count(*) AS n, round(sum(0.1 * power(0.9, after) * w), 4) AS w FROM o GROUP BY 1"""


def _last(m: DataFrame) -> DataFrame:
    return m.groupBy("party_id").agg(F.max_by("w", "n").alias("w"), F.max("n").alias("n")).select("party_id", "n", F.round("w", 4).alias("w"))


@register(_MODELS_SQL)
def stream_party_models(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Models kept in state, as they stand after the last micro-batch."""
    return _last(U.run_to_end(U.party_models(_updates(spark, sf_dir)), "update"))


@register(_MODELS_SQL)
def stream_kept_models(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same by the state API, with states on disk."""
    before = spark.conf.get(U.ON_DISK[0], None)
    spark.conf.set(*U.ON_DISK)
    try:
        return _last(U.run_to_end(U.kept_models(_updates(spark, sf_dir)), "update"))
    finally:
        spark.conf.set(U.ON_DISK[0], before) if before else spark.conf.unset(U.ON_DISK[0])


_NEAR = 5.0


@register(_UPDATES_SQL + f""", l AS (SELECT p AS batch, party_id, arg_max(w, {{'a': part, 'b': event_time}}) AS w FROM u, range(4) t(p) WHERE part <= p GROUP BY 1, 2),
m AS (SELECT batch, list(w) AS ws, avg(w) AS m FROM l GROUP BY 1),
go(k, batch, ws, g) AS (SELECT 0, batch, ws, m FROM m UNION ALL SELECT k + 1, batch, ws, g + list_avg(list_transform(ws, lambda z: least(greatest(z - g, -{_NEAR}), {_NEAR}))) FROM go WHERE k < 3000)
SELECT 'consensus' AS kind, batch::INTEGER AS batch, round(m, 4) AS g, len(ws)::BIGINT AS n FROM m UNION ALL SELECT kind, batch::INTEGER, round(g, 4), len(ws)::BIGINT FROM go, (VALUES ('l1'), ('l2')) v(kind) WHERE k = 3000""")
def stream_close_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The centre after each micro-batch, for three regularisers (of one number, both medians are the same)."""
    path, events = _arrived(spark, sf_dir)
    rows = []
    for kind in ("consensus", "l1", "l2"):
        centres: list[tuple[int, float, int]] = []
        U.close_rounds(U.as_updates(U.stream_of(spark, path, events.schema)), centres, Regulariser(kind, _NEAR))
        rows += [(kind, b, g, n) for b, g, n in centres]
    return spark.createDataFrame(rows, "kind string, batch int, g double, n long").select("kind", "batch", F.round("g", 4).alias("g"), "n")
