"""Every query with SQL against DuckDB on the smallest tables; the others run."""

import math
from decimal import Decimal

import pytest
from conftest import SF

from parley.queries import loops, measures, relational, training, variants, vectors

SUBJECTS = [vectors.register, loops.register, training.register, measures.register, relational.register, variants.register]
WITH_SQL = {k: (r.queries[k], s) for r in SUBJECTS for k, s in r.sql.items()}
#: Short ones among those without SQL; the longer runs are in the bench and in test_methods.
WITHOUT = ["training_failure", "compare_standard", "text_sequences", "layer_hybrid", "straggler_levels", "party_ablation"]


def canonical(rows):
    def one(v):
        if v is None or (isinstance(v, float) and math.isnan(v)):
            return ""
        return repr(float(v)) if isinstance(v, (float, Decimal)) else str(v)

    return sorted(tuple(map(one, r)) for r in rows)


@pytest.mark.parametrize("name", sorted(WITH_SQL))
def test_query_matches_sql(spark, duck, name):
    query, sql = WITH_SQL[name]
    df = query(spark, SF)
    cols = sorted(df.columns)
    want = duck.execute(sql)
    names = [d[0] for d in want.description]
    assert cols == sorted(names)
    order = [names.index(c) for c in cols]
    assert canonical(df.select(cols).collect()) == canonical([[r[i] for i in order] for r in want.fetchall()])


@pytest.mark.parametrize("name", WITHOUT)
def test_query_runs(spark, name):
    df = next(r.queries[name] for r in SUBJECTS if name in r.queries)(spark, SF)
    assert df.count() > 0


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())


def test_loss_constants_are_of_all_rows(spark):
    import numpy as np

    x = np.array([r[0] for r in spark.read.parquet(f"{SF}/embeddings.parquet").select("embedding").collect()], float)
    x = np.append(x, [8 * x[-1]], axis=0)  # a long row that no prefix shows
    frame = spark.createDataFrame([(k, row.tolist()) for k, row in enumerate(x)], "vec_id long, embedding array<double>").repartition(3)
    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(measures, "load", lambda *_: frame)
        patch.setattr(measures.W, "load", lambda *_: frame)
        got = {r.loss: r.constant for r in measures.loss_constants(spark, SF).collect()}
    x *= np.sqrt(x.shape[1])
    assert got == {"softmax": pytest.approx(measures.Softmax(64, 10).lipschitz([x])), "rows": pytest.approx(np.linalg.norm(x, axis=1).max())}


def test_day_windows_take_the_nearest_second(spark, tmp_path):
    """Rows that truncated seconds would bring within a day of each other, or part."""
    import duckdb

    times = ("2024-01-01 00:00:00.6", "2024-01-02 00:00:01.4", "2024-01-02 00:00:01.6", "2024-01-03 00:00:00.5", "2024-01-03 00:00:01.5")
    path = f"{tmp_path}/events.parquet"
    con = duckdb.connect()
    con.execute(f"COPY (SELECT k - 1 AS event_id, 7 AS user_id, ({list(times)})[k]::TIMESTAMP AS ts, k / 2.0 AS value FROM range(1, 6) t(k)) TO '{path}'")
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{path}'")
    query, sql = WITH_SQL["analytic_windows"]
    want = con.execute(f"SELECT event_id, change, least, day_n FROM ({sql})").fetchall()
    assert canonical(query(spark, str(tmp_path)).select("event_id", "change", "least", "day_n").collect()) == canonical(want)
    assert dict((r[0], r[3]) for r in want)[1] == 2  # 00:00:01 to the second, as the row a day before


def test_descent_check_reads_all_rows(spark):
    """Losses and gradients of condensed parties are those on all of their rows; the decreases hold on them."""
    import numpy as np
    from pyspark.sql import functions as F

    from parley.functions.losses import Linear
    from parley.operators.theory import condensed

    li = spark.read.parquet(f"{SF}/lineitem.parquet")
    rows = li.select(F.pmod("l_suppkey", F.lit(3)).alias("party_id"), F.array(F.col("l_quantity") / 50, F.col("l_tax") * 10).alias("x"), (F.col("l_extendedprice") / 1e5).alias("y"))
    fed, loss, w = condensed(rows, 2), Linear(2), np.array([[0.3, -0.7]])
    every = rows.toPandas()
    assert sum(len(own) for _, own in every.groupby("party_id")) == li.count() and fed.ids.tolist() == [0, 1, 2]
    for k, own in every.groupby("party_id"):
        x, y = np.stack(own["x"])[None], own["y"].to_numpy()[None]
        assert loss.value(w, fed.x[k][None], fed.y[k][None]) == pytest.approx(loss.value(w, x, y))
        assert loss.grad(w, fed.x[k][None], fed.y[k][None]) == pytest.approx(loss.grad(w, x, y))
    got = measures.descent_check(spark, SF).collect()
    assert len(got) == 3 and all(r.rises == 0 and r.decrease_held and r.gradient_ratio < 1 for r in got)


def test_generator_source_is_over_the_given_vectors(spark):
    """Every vector is in one party; the source's models are those that plant its own rows."""
    import numpy as np

    n = spark.read.parquet(f"{SF}/embeddings.parquet").count()
    assert sum(r.n for r in relational.generator_source(spark, SF).collect()) == n
    source = spark.read.format("parley_synth").options(parties=3, rows=200)
    models = {r.party_id: np.array(r.x) for r in source.option("models", 1).load().collect()}
    for k, own in source.option("models", 0).load().toPandas().groupby("party_id"):
        assert np.std(own["y"] - np.stack(own["x"]) @ models[k]) < 1.3  # what the model leaves is noise of variance 1


def test_kappa_settings_cover_all_rows(spark):
    got = measures.kappa_settings(spark, SF).collect()
    assert sum(r.n for r in got) == spark.read.parquet(f"{SF}/lineitem.parquet").count()
    assert {r.advised for r in got} == {True, False}


def test_seeded_draws_are_of_every_event(spark):
    ids = [r[0] for r in spark.read.parquet(f"{SF}/events.parquet").select("event_id").collect()]
    assert sorted(r.id for r in measures.seeded_draws(spark, SF).collect()) == sorted(ids)


def test_sensitivity_follows_the_given_vectors(spark, tmp_path):
    """Other vectors give other errors; each setting has one."""
    import math

    from pyspark.sql import functions as F

    e = spark.read.parquet(f"{SF}/embeddings.parquet")
    e.withColumn("embedding", F.transform("embedding", lambda a: a * 2)).write.parquet(f"{tmp_path}/embeddings.parquet")
    one, two = ({r.dataset: r.score for r in variants.sensitivity(spark, d).collect()} for d in (SF, str(tmp_path)))
    assert len(one) == 15 and all(math.isfinite(x) for x in one.values()) and all(one[k] != two[k] for k in one)


def test_power_law_sizes_add_up_to_the_customers(spark):
    got = variants.udtf_power_law(spark, SF).collect()
    assert sum(r.total for r in got) == spark.read.parquet(f"{SF}/customer.parquet").count()
    assert all(0 < r.largest <= r.total for r in got)
