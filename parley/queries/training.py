"""Distributed training of every method, each beside the same rounds unrolled in SQL.

Parties are nations, rows their customers' orders (price against the day of the year), the loss is linear. Eight of the
parties take part in a round, half of them late; batches follow seeded places, so that both engines touch the same rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parley import workloads as W
from parley.functions.draws import mixed_sql
from parley.functions.losses import Linear
from parley.functions.prox import Regulariser, prox_np
from parley.operators import methods as M
from parley.operators import quadratic
from parley.operators import rounds as R
from parley.operators import theory as T
from parley.operators.quadratic import statistics
from parley.queries import Registry
from parley.sources.tables import Tables

register = Registry()
CFG = M.Rounds(0.3, 1.0, 3, 8, 3, 10, seed=1, stragglers=0.5)
D = 0.1
LOSS = Linear(2)

ROWS_SQL = f"""
WITH RECURSIVE raw AS (SELECT c_nationkey::BIGINT AS party_id, o_orderkey AS k, dayofyear(o_orderdate) / 366.0 AS x, o_totalprice / 1e5 AS y FROM orders JOIN customer ON o_custkey = c_custkey),
placed AS (SELECT *, row_number() OVER (PARTITION BY party_id ORDER BY {mixed_sql(1, 11, "k")}, k) - 1 AS pos, count(*) OVER (PARTITION BY party_id) AS m FROM raw),
tr AS MATERIALIZED (SELECT party_id, pos, ceil(m * 0.8)::BIGINT AS n, x::DOUBLE AS x, y::DOUBLE AS y FROM placed WHERE pos < ceil(m * 0.8)),
te AS MATERIALIZED (SELECT party_id, x::DOUBLE AS x, y::DOUBLE AS y FROM placed WHERE pos >= ceil(m * 0.8)),
parts AS MATERIALIZED (SELECT DISTINCT party_id FROM tr),
whole AS MATERIALIZED (SELECT party_id, 1.0::DOUBLE AS a, avg(x) AS b, avg(x * x) AS c, avg(y) AS p, avg(x * y) AS q FROM tr GROUP BY 1)
"""


def stats_sql(cfg: M.Rounds) -> str:
    """Means over the batch of each step: of 1, x, x*x, y and x*y, a row counted as often as the batch goes round."""
    if cfg.batch is None:
        return f", st AS MATERIALIZED (SELECT t, i, whole.* FROM whole, range({cfg.rounds}) u(t), range({cfg.steps + 1}) v(i))"
    b = cfg.batch
    return f""", hit AS (SELECT t, i, tr.*, (((pos - (t * {cfg.steps} + i) * {b}) % n) + n) % n AS d FROM tr, range({cfg.rounds}) u(t), range({cfg.steps + 1}) v(i)),
st AS MATERIALIZED (SELECT t, i, party_id, sum(w) / {b} AS a, sum(w * x) / {b} AS b, sum(w * x * x) / {b} AS c, sum(w * y) / {b} AS p, sum(w * x * y) / {b} AS q
FROM (SELECT *, floor(({b} - 1 - d) / n) + 1 AS w FROM hit WHERE d < {b}) GROUP BY 1, 2, 3)"""


def _grad(u: str, v: str, s: str = "st") -> tuple[str, str]:
    return f"({s}.a * {u} + {s}.b * {v} - {s}.p)", f"({s}.b * {u} + {s}.c * {v} - {s}.q)"


def _best_sql(s: float) -> tuple[str, str]:
    """The minimiser of a party's loss with penalty s around (z0, z1), from its means a, b, c, p, q."""
    det = f"((a + {s}) * (c + {s}) - b * b)"
    return f"((c + {s}) * (p + {s} * z0) - b * (q + {s} * z1)) / {det}", f"((a + {s}) * (q + {s} * z1) - b * (p + {s} * z0)) / {det}"


def _offset_sql(reg: Regulariser, lo: int, hi: int) -> list[str]:
    """Offsets of the coordinates lo..hi-1, from r0, r1."""
    if reg.kind == "sq":
        return [f"r{j} / (1 + {reg.delta})" for j in range(lo, hi)]
    if reg.kind == "l1":
        return [f"sign(r{j}) * greatest(abs(r{j}) - {reg.delta}, 0)" for j in range(lo, hi)]
    if reg.kind in ("l2", "user"):
        n = "sqrt(" + " + ".join(f"r{j} * r{j}" for j in range(lo, hi)) + ")"
        return [f"r{j} * CASE WHEN {n} > {D} THEN 1 - {D} / {n} ELSE 0 END" for j in range(lo, hi)]
    return [("0.0" if reg.kind == "consensus" else f"r{j}") for j in range(lo, hi)]


def _centre_sql(t: int, pool: str, method: M.Method) -> str:
    """centre{t}: (m0, m1) of the pool's models u0, u1."""
    mean = f", mean{t} AS MATERIALIZED (SELECT list(u0 ORDER BY party_id) AS p, list(u1 ORDER BY party_id) AS q, avg(u0) AS m0, avg(u1) AS m1, median(u0) AS d0, median(u1) AS d1 FROM {pool})"
    kinds = [reg.kind for _, _, reg in method.layout] or [method.reg.kind] * 2
    if kinds[0] in ("l2", "user"):
        floor, times = (1e-9, 600) if method.exact else (D, 600)
        far = "sqrt((p[i] - m0) * (p[i] - m0) + (q[i] - m1) * (q[i] - m1))"
        return mean + f""", go{t}(k, m0, m1, p, q) AS (SELECT 0, m0, m1, p, q FROM mean{t} UNION ALL SELECT k + 1, list_dot_product(s, p) / list_sum(s), list_dot_product(s, q) / list_sum(s), p, q
FROM (SELECT *, list_transform(range(1, len(p) + 1), lambda i: least(1.0::DOUBLE, {floor} / greatest({far}, 1e-300))) AS s FROM go{t} WHERE k < {times})),
centre{t} AS MATERIALIZED (SELECT m0, m1 FROM go{t} WHERE k = {times})"""
    if "l1" in kinds and not method.exact:
        pull = lambda c, m: f"{m} + list_avg(list_transform({c}, lambda z: least(greatest(z - {m}, -{D}), {D})))"
        own = [pull(c, m) if kind == "l1" else m for c, m, kind in zip("pq", ("m0", "m1"), kinds, strict=True)]
        return mean + f""", go{t}(k, m0, m1, p, q) AS (SELECT 0, m0, m1, p, q FROM mean{t} UNION ALL SELECT k + 1, {own[0]}, {own[1]}, p, q FROM go{t} WHERE k < 1500),
centre{t} AS MATERIALIZED (SELECT m0, m1 FROM go{t} WHERE k = 1500)"""
    if kinds[0] == "l1":
        return mean + f", centre{t} AS (SELECT d0 AS m0, d1 AS m1 FROM mean{t})"
    return mean + f", centre{t} AS (SELECT m0, m1 FROM mean{t})"


def _step_sql(name: str, before: str, t: int, i: int, method: M.Method, cfg: M.Rounds) -> str:
    """One local step of all active parties: u, and what else the method moves (e0, e1, al)."""
    eta, e = cfg.eta, method.extra
    on = lambda new, old: f"CASE WHEN {i} < steps THEN {new} ELSE {old} END"
    join = f"FROM {before} b JOIN st ON st.t = {t} AND st.i = {i} AND st.party_id = b.party_id"
    keep = "b.party_id, w0, w1, g0, g1, k0, k1, z0, z1, s0, s1, steps"
    g = _grad("u0", "u1")
    if method.kind == "loop" and cfg.local == "exact":
        best = _best_sql(cfg.sigma if method.tied else 0.0)
        return f", {name} AS MATERIALIZED (SELECT {keep}, {best[0]} AS u0, {best[1]} AS u1, e0, e1, al {join})"
    if method.kind == "loop":
        kappa = 1 / (1 + eta * (cfg.sigma if method.tied else 0.0))
        new = [f"{kappa!r} * (u{j} - {eta} * {g[j]}) + (1 - {kappa!r}) * z{j}" for j in range(2)]
        return f", {name} AS MATERIALIZED (SELECT {keep}, {on(new[0], 'u0')} AS u0, {on(new[1], 'u1')} AS u1, e0, e1, al {join})"
    if method.kind == "control":
        new = [f"u{j} - {eta} * ({g[j]} - e{j} + k{j})" for j in range(2)]
        return f", {name} AS MATERIALIZED (SELECT {keep}, {on(new[0], 'u0')} AS u0, {on(new[1], 'u1')} AS u1, e0, e1, al {join})"
    if method.kind == "envelope":
        sql, last = f", {name}i0 AS (SELECT {keep}, u0, u1, u0 AS h0, u1 AS h1, e0, e1, al, st.a, st.b, st.c, st.p, st.q {join})", f"{name}i0"
        for j in range(e["inner"]):
            h = _grad("h0", "h1", "b")
            own = [f"h{k} - {eta} * ({h[k]} + {e['lam_p']} * (h{k} - u{k})) AS h{k}" for k in range(2)]
            sql += f", {name}i{j + 1} AS MATERIALIZED (SELECT * EXCLUDE (h0, h1), {', '.join(own)} FROM {last} b)"
            last = f"{name}i{j + 1}"
        new = [f"u{k} - {eta} * {e['lam_p']} * (u{k} - h{k})" for k in range(2)]
        return sql + f", {name} AS MATERIALIZED (SELECT {keep}, {on(new[0], 'u0')} AS u0, {on(new[1], 'u1')} AS u1, {on('h0', 'e0')} AS e0, {on('h1', 'e1')} AS e1, al FROM {last} b)"
    if method.kind == "meta":
        sql = f", {name}i AS (SELECT {keep}, u0, u1, e0, e1, al, u0 - {eta} * {g[0]} AS h0, u1 - {eta} * {g[1]} AS h1, st.a, st.b, st.c {join})"
        n = _grad("h0", "h1")
        inner = f", {name}j AS (SELECT b.*, {n[0]} AS n0, {n[1]} AS n1 FROM {name}i b JOIN st ON st.t = {t} AND st.i = {i + 1} AND st.party_id = b.party_id)"
        push = [f"(n0 - {eta} * (a * n0 + b * n1))", f"(n1 - {eta} * (b * n0 + c * n1))"] if e["mode"] == "hvp" else ["n0", "n1"]
        new = [f"u{j} - {eta} * {push[j]}" for j in range(2)]
        # the step's own columns a, b, c stand beside those of the joined batch only within this part
        return sql + inner.replace("b.*", f"{keep.replace('b.party_id', 'b.party_id')}, u0, u1, e0, e1, al, b.a, b.b, b.c") + f", {name} AS MATERIALIZED (SELECT {keep}, {on(new[0], 'u0')} AS u0, {on(new[1], 'u1')} AS u1, e0, e1, al FROM {name}j b)"
    mixed = [f"(al * e{j} + (1 - al) * u{j})" for j in range(2)]
    gm = _grad(*mixed)
    sql = f", {name}i AS (SELECT {keep}, u0, u1, e0, e1, al, {gm[0]} AS n0, {gm[1]} AS n1, {g[0]} AS o0, {g[1]} AS o1 {join})"
    al = f"least(greatest(al - {eta} * (n0 * (e0 - u0) + n1 * (e1 - u1)), 0), 1)" if e["adapt"] and i == 0 else "al"
    sql += f", {name}j AS (SELECT * EXCLUDE (al), {al} AS al FROM {name}i)"
    return sql + f", {name} AS MATERIALIZED (SELECT {keep}, {on(f'u0 - {eta} * o0', 'u0')} AS u0, {on(f'u1 - {eta} * o1', 'u1')} AS u1, {on(f'e0 - {eta} * al * n0', 'e0')} AS e0, {on(f'e1 - {eta} * al * n1', 'e1')} AS e1, al FROM {name}j b)"


def rounds_sql(method: M.Method, cfg: M.Rounds = CFG) -> str:
    """Common table expressions of all rounds: r{t}, every party's state, and g{t}, the centre, after t rounds."""
    al = method.extra.get("alpha0", 0.5)
    sql = ROWS_SQL + stats_sql(cfg) + f", r0 AS (SELECT party_id, 0.0::DOUBLE AS w0, 0.0::DOUBLE AS w1, 0.0::DOUBLE AS e0, 0.0::DOUBLE AS e1, {al}::DOUBLE AS al FROM parts)"
    sql += ", g0 AS (SELECT 0.0::DOUBLE AS g0, 0.0::DOUBLE AS g1, 0.0::DOUBLE AS k0, 0.0::DOUBLE AS k1)"
    lam = method.lam
    offsets = [o for lo, hi, reg in method.layout for o in _offset_sql(reg, lo, hi)] or _offset_sql(method.reg, 0, 2)
    for t in range(cfg.rounds):
        late = f"CASE WHEN ({mixed_sql(cfg.seed, 202, t, 'r.party_id')} + 0.5) / 2147483647.0 < {cfg.stragglers} THEN 1 + {mixed_sql(cfg.seed, 303, t, 'r.party_id')} % {cfg.steps} ELSE {cfg.steps} END"
        z = [f"g{j} + {offsets[j]}" if method.tied else "0.0" for j in range(2)]
        sql += f""", act{t} AS MATERIALIZED (SELECT party_id FROM parts ORDER BY {mixed_sql(cfg.seed, 101, t, 'party_id')}, party_id LIMIT {cfg.active}),
a{t} AS (SELECT r.*, g{t}.*, w0 - g0 AS r0, w1 - g1 AS r1, {late} AS steps FROM r{t} r, g{t} WHERE party_id IN (SELECT party_id FROM act{t})),
b{t}_0 AS MATERIALIZED (SELECT party_id, w0, w1, g0, g1, k0, k1, {z[0]} AS z0, {z[1]} AS z1, {1 - lam} * w0 + {lam} * g0 AS s0, {1 - lam} * w1 + {lam} * g1 AS s1, steps,
{1 - lam} * w0 + {lam} * g0 AS u0, {1 - lam} * w1 + {lam} * g1 AS u1, e0, e1, al FROM a{t})"""
        for i in range(cfg.steps):
            sql += _step_sql(f"b{t}_{i + 1}", f"b{t}_{i}", t, i, method, cfg)
        done = f"b{t}_{cfg.steps}"
        extra = [f"e{j} - k{j} + (s{j} - u{j}) / ({cfg.eta} * steps)" if method.kind == "control" else f"e{j}" for j in range(2)]
        sql += f", n{t} AS MATERIALIZED (SELECT party_id, u0, u1, {extra[0]} AS e0, {extra[1]} AS e1, al FROM {done})"
        sql += f", r{t + 1} AS MATERIALIZED (SELECT r.party_id, coalesce(u0, w0) AS w0, coalesce(u1, w1) AS w1, coalesce(n.e0, r.e0) AS e0, coalesce(n.e1, r.e1) AS e1, coalesce(n.al, r.al) AS al FROM r{t} r LEFT JOIN n{t} n ON n.party_id = r.party_id)"
        if not method.aggregates:
            sql += f", g{t + 1} AS (SELECT * FROM g{t})"
            continue
        pool = f"n{t}" if cfg.scope == "active" else f"(SELECT party_id, w0 AS u0, w1 AS u1 FROM r{t + 1})"
        sql += _centre_sql(t, pool, method)
        if method.kind == "control":
            moved = [f"k{j} + (SELECT count(*) FROM act{t}) / (SELECT count(*) FROM parts)::DOUBLE * ((SELECT avg(e{j}) FROM n{t}) - (SELECT avg(e{j}) FROM r{t} WHERE party_id IN (SELECT party_id FROM act{t})))" for j in range(2)]
            sql += f", g{t + 1} AS MATERIALIZED (SELECT g0 + {method.extra['eta_g']} * (m0 - g0) AS g0, g1 + {method.extra['eta_g']} * (m1 - g1) AS g1, {moved[0]} AS k0, {moved[1]} AS k1 FROM g{t}, centre{t})"
        else:
            beta = method.extra.get("beta", 1.0)
            sql += f", g{t + 1} AS MATERIALIZED (SELECT {1 - beta} * g0 + {beta} * m0 AS g0, {1 - beta} * g1 + {beta} * m1 AS g1, k0, k1 FROM g{t}, centre{t})"
    return sql


def training_sql(method: M.Method, cfg: M.Rounds = CFG) -> str:
    own = {"own": ("w0", "w1"), "global": ("g0", "g1"), "theta": ("e0", "e1"), "mixture": ("al * e0 + (1 - al) * w0", "al * e1 + (1 - al) * w1")}
    t = cfg.rounds
    if method.score == "adapted":
        g = _grad("g0", "g1", "whole")
        judged = f"SELECT r.*, g.*, g0 - {cfg.eta} * {g[0]} AS o0, g1 - {cfg.eta} * {g[1]} AS o1 FROM r{t} r JOIN whole ON whole.party_id = r.party_id, g{t} g"
    else:
        judged = f"SELECT r.*, g.*, {own[method.score][0]} AS o0, {own[method.score][1]} AS o1 FROM r{t} r, g{t} g"
    return rounds_sql(method, cfg) + f""", judged AS ({judged})
SELECT j.party_id, round(any_value(w0), 6) + 0.0 AS w0, round(any_value(w1), 6) + 0.0 AS w1, round(any_value(g0), 6) + 0.0 AS g0, round(any_value(g1), 6) + 0.0 AS g1,
round(any_value(o0), 6) + 0.0 AS own0, round(any_value(o1), 6) + 0.0 AS own1, round(avg((o0 + o1 * x - y) * (o0 + o1 * x - y)), 5) + 0.0 AS mse FROM judged j JOIN te ON te.party_id = j.party_id GROUP BY j.party_id"""


def trained(spark: SparkSession, sf_dir: str, method: M.Method, cfg: M.Rounds = CFG) -> DataFrame:
    """(party_id, w, g, own, mse): models, centre, the parameters a party is judged with, and their error on its test rows."""
    ex = W.order_examples(spark, sf_dir)
    tables = Tables(spark)
    ex = tables.keep(ex, "examples")
    run = R.run_rounds(ex.where("split = 'train'"), LOSS, method, cfg)
    judged = R.judged_models(run, LOSS, method, cfg)
    mse = R.scored(ex.where("split = 'test'"), judged, LOSS).select("party_id", F.round("score", 5).alias("mse"))
    six = lambda c, name: (F.round(c, 6) + 0.0).alias(name)
    g = [(F.round(F.lit(float(a)), 6) + 0.0).alias(f"g{j}") for j, a in enumerate(run.g)]
    own = judged.select("party_id", *[six(F.get("w", F.lit(j)), f"own{j}") for j in range(2)])
    return run.state.select("party_id", *[six(F.get("w", F.lit(j)), f"w{j}") for j in range(2)], *g).join(own, "party_id").join(mse, "party_id")


GENERAL = M.personal_general(lambda x, sigma: prox_np("l2", x, D))
METHODS = {
    "personal_mean": M.personal_mean(D),
    "personal_geomed": M.personal_geomed(D),
    "personal_comed": M.personal_comed(D),
    "personal_hybrid": M.personal_hybrid([(0, 1, Regulariser("sq", D)), (1, 2, Regulariser("l1", D))]),
    "personal_general": GENERAL,
    "start_mix_mean": M.personal_mean(D, 0.001),
    "start_mix_geomed": M.personal_geomed(D, 0.001),
    "start_mix_comed": M.personal_comed(D, 0.001),
    "untied": M.untied(),
    "local_only": M.local_only(),
    "fed_mean": M.fed_mean(),
    "fed_geomed": M.fed_geomed(),
    "fed_geomed_smoothed": M.fed_geomed(D),
    "fed_comed": M.fed_comed(),
    "fed_comed_smoothed": M.fed_comed(D),
    "fed_prox_mean": M.fed_prox_mean(),
    "control_variate_mean": M.control_variate_mean(),
    "envelope_personal": M.envelope_personal(1.5, 2, 0.8),
    "meta_init_personal": M.meta_init_personal(),
    "meta_init_hessian": M.meta_init_personal(mode="hvp"),
    "adaptive_mix_personal": M.adaptive_mix_personal(),
    "fixed_mix_personal": M.adaptive_mix_personal(0.3, False),
}
for _name, _method in METHODS.items():

    @register(training_sql(_method), f"train_{_name}")
    def _train(spark: SparkSession, sf_dir: str, method: M.Method = _method) -> DataFrame:
        return trained(spark, sf_dir, method)


ALL = M.Rounds(0.3, 1.0, 3, 8, 3, 10, seed=2, scope="all", stragglers=0.5)
FULL = M.Rounds(0.3, 1.0, 3, 8, 3, None, seed=1)


@register(training_sql(METHODS["personal_geomed"], ALL))
def train_scope_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The centre over all parties' models, idle ones included."""
    return trained(spark, sf_dir, METHODS["personal_geomed"], ALL)


EXACT = M.Rounds(0.3, 1.0, 4, 25, 1, None, seed=1, local="exact")
for _name in ("personal_mean", "personal_geomed", "personal_comed"):

    @register(training_sql(METHODS[_name], EXACT), f"train_exact_{_name}")
    def _train_exact(spark: SparkSession, sf_dir: str, method: M.Method = METHODS[_name]) -> DataFrame:
        """Every party minimises its penalised loss exactly, as the fixed points assume."""
        return trained(spark, sf_dir, method, EXACT)


def _fixed_sql(method: M.Method) -> str:
    t, offsets, best = EXACT.rounds, _offset_sql(method.reg, 0, 2), _best_sql(EXACT.sigma)
    return rounds_sql(method, EXACT) + f""", fo AS (SELECT r.*, g.*, w0 - g0 AS r0, w1 - g1 AS r1 FROM r{t} r, g{t} g), fz AS (SELECT *, g0 + {offsets[0]} AS z0, g1 + {offsets[1]} AS z1 FROM fo),
fm AS (SELECT fz.*, {best[0]} AS m0, {best[1]} AS m1 FROM fz JOIN whole ON whole.party_id = fz.party_id),
fs AS (SELECT {EXACT.sigma} * (z0 - m0) AS s0, {EXACT.sigma} * (z1 - m1) AS s1, greatest(abs(w0 - m0), abs(w1 - m1)) AS miss FROM fm)
SELECT 0 AS coord, round(avg(s0), 6) + 0.0 AS mean_slope, round(max(miss), 6) + 0.0 AS worst_miss FROM fs UNION ALL SELECT 1, round(avg(s1), 6) + 0.0, round(max(miss), 6) + 0.0 FROM fs"""


for _name in ("personal_mean", "personal_geomed", "personal_comed", "untied"):

    @register(_fixed_sql(METHODS[_name]), f"fixed_point_{_name}")
    def _fixed(spark: SparkSession, sf_dir: str, method: M.Method = METHODS[_name]) -> DataFrame:
        """How far four exact rounds are from the fixed point: the mean envelope gradient, and the worst party's miss of its relation."""
        train = Tables(spark).keep(W.order_examples(spark, sf_dir).where("split = 'train'"), "examples")
        run = R.run_rounds(train, LOSS, method, EXACT)
        got = T.vector_residuals(statistics(train, 2), run.state, run.g, method.reg, EXACT.sigma)
        return got.withColumns({c: F.round(c, 6) + 0.0 for c in ("mean_slope", "worst_miss")})


@register(training_sql(METHODS["personal_comed"], FULL))
def train_full_gradients(spark: SparkSession, sf_dir: str) -> DataFrame:
    return trained(spark, sf_dir, METHODS["personal_comed"], FULL)


def _log_sql(method: M.Method, cfg: M.Rounds) -> str:
    kappa = cfg.advised
    rows = " UNION ALL ".join(
        f"""SELECT {t} AS round, (SELECT count(*) FROM act{t}) AS active, (SELECT sum(steps) FROM b{t}_0)::BIGINT AS local_steps, (SELECT sum(steps) * {cfg.batch} FROM b{t}_0)::BIGINT AS gradient_rows,
(SELECT count(*) * 4 FROM act{t})::BIGINT AS numbers_moved, 1::BIGINT AS aggregator_steps, round(avg({method.lam} * d), 6) + 0.0 AS change_mean, round(stddev_pop({method.lam} * d), 6) + 0.0 AS change_std, {str(kappa).lower()} AS kappa_in_advice
FROM (SELECT g0 - u0 AS d FROM n{t}, g{t + 1} UNION ALL SELECT g1 - u1 FROM n{t}, g{t + 1})"""
        for t in range(cfg.rounds)
    )
    return rounds_sql(method, cfg) + " SELECT round::INTEGER AS round, * EXCLUDE (round) FROM (" + rows + ")"


@register(_log_sql(METHODS["fed_mean"], CFG))
def run_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What each round moved, computed and changed (without its seconds)."""
    ex = W.order_examples(spark, sf_dir).where("split = 'train'")
    log = R.run_rounds(Tables(spark).keep(ex, "examples"), LOSS, METHODS["fed_mean"], CFG).log_table()
    return log.drop("seconds").withColumns({c: F.round(c, 6) + 0.0 for c in ("change_mean", "change_std")})


def _path_sql(method: M.Method, cfg: M.Rounds) -> str:
    """Loss on test rows along the way from own model to centre, before (own models and old centre) and after the last aggregation."""
    t, sides = cfg.rounds, []
    for side, g in (("before", f"g{cfg.rounds - 1}"), ("after", f"g{cfg.rounds}")):
        at = [f"((1 - k / 5.0) * w{j} + k / 5.0 * g{j})" for j in range(2)]
        sides.append(f"SELECT '{side}' AS side, k / 5.0 AS lam, r.party_id, avg(({at[0]} + {at[1]} * x - y) * ({at[0]} + {at[1]} * x - y)) / 2 AS f FROM r{t} r JOIN te ON te.party_id = r.party_id, {g}, range(6) u(k) GROUP BY 1, 2, 3")
    return rounds_sql(method, cfg) + f" SELECT side, lam::DOUBLE AS lam, round(avg(f), 6) + 0.0 AS loss, round(max(f), 6) + 0.0 AS worst FROM ({' UNION ALL '.join(sides)}) GROUP BY 1, 2"


@register(_path_sql(METHODS["personal_mean"], CFG))
def trained_lambda_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Loss of a trained run's parties on the way to the centre, the one before and the one after the last aggregation."""
    ex = Tables(spark).keep(W.order_examples(spark, sf_dir), "examples")
    run = R.run_rounds(ex.where("split = 'train'"), LOSS, METHODS["personal_mean"], CFG)
    old = R.RunResult(run.state, run.before, run.log)
    both = [R.lambda_path(ex.where("split = 'test'"), r, LOSS).select(F.lit(side).alias("side"), "*") for side, r in (("before", old), ("after", run))]
    return both[0].unionByName(both[1]).withColumns({c: F.round(c, 6) + 0.0 for c in ("loss", "worst")})


@register(
    ROWS_SQL
    + """, grid AS (SELECT whole.*, 1.0::DOUBLE AS z0, -0.5::DOUBLE AS z1, 2.0::DOUBLE AS s FROM whole),
best AS (SELECT *, ((c + s) * (p + s * z0) - b * (q + s * z1)) / ((a + s) * (c + s) - b * b) AS m0, ((a + s) * (q + s * z1) - b * (p + s * z0)) / ((a + s) * (c + s) - b * b) AS m1 FROM grid),
y2 AS (SELECT party_id, avg(y * y) AS yy FROM tr GROUP BY 1)
SELECT party_id, round((a * m0 * m0 + 2 * b * m0 * m1 + c * m1 * m1 - 2 * p * m0 - 2 * q * m1 + yy) / 2 + s / 2 * ((m0 - z0) * (m0 - z0) + (m1 - z1) * (m1 - z1)), 6) + 0.0 AS envelope,
round(s * (z0 - m0), 6) + 0.0 AS slope0, round(s * (z1 - m1), 6) + 0.0 AS slope1 FROM best JOIN y2 USING (party_id)"""
)
def loss_envelopes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The Moreau envelope of each party's linear loss at one point, and its gradient there."""
    train = W.order_examples(spark, sf_dir).where("split = 'train'")
    at = T.loss_envelopes(train, 2, [1.0, -0.5], 2.0)
    return at.select("party_id", (F.round("envelope", 6) + 0.0).alias("envelope"), *[(F.round(F.get("slope", F.lit(j)), 6) + 0.0).alias(f"slope{j}") for j in range(2)])


@register(
    rounds_sql(METHODS["personal_mean"], FULL)
    + f" SELECT party_id, round(w0, 6) + 0.0 AS w0, round(w1, 6) + 0.0 AS w1 FROM r{FULL.rounds}"
)
def gram_training(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Full-gradient rounds from sufficient statistics: one scan, then a row a party."""
    run = quadratic.train(W.order_examples(spark, sf_dir).where("split = 'train'"), LOSS, METHODS["personal_mean"], FULL)
    return run.state.select("party_id", *[(F.round(F.get("w", F.lit(j)), 6) + 0.0).alias(f"w{j}") for j in range(2)])


def _foreign_sql(method: M.Method) -> str:
    return rounds_sql(method) + f" SELECT r.party_id, round(avg((w0 + w1 * x - y) * (w0 + w1 * x - y)), 5) + 0.0 AS mse FROM r{CFG.rounds} r JOIN te ON te.party_id != r.party_id GROUP BY r.party_id"


@register(_foreign_sql(METHODS["personal_geomed"]))
def trained_transfer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trained models on the test rows of all other parties."""
    ex = Tables(spark).keep(W.order_examples(spark, sf_dir), "examples")
    run, test = R.run_rounds(ex.where("split = 'train'"), LOSS, METHODS["personal_geomed"], CFG), ex.where("split = 'test'")
    yy = test.groupBy("party_id").agg(F.avg(F.col("y") * F.col("y")).alias("yy"))
    got = quadratic.foreign_errors(statistics(test, 2).join(yy, "party_id"), run.state)
    return got.select("party_id", (F.round("mse", 5) + 0.0).alias("mse"))


@register(training_sql(METHODS["personal_comed"]).replace("SELECT j.party_id, round(any_value(w0)", "SELECT * FROM (SELECT j.party_id, round(any_value(w0)", 1).replace("GROUP BY j.party_id", "GROUP BY j.party_id)", 1).replace("SELECT * FROM (", "SELECT round(avg(mse), 4) AS mean, round(max(mse), 4) AS worst, round(quantile_cont(mse, 0.9), 4) AS p90 FROM (", 1))
def trained_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean, worst and ninth decile of the parties' errors after training."""
    t = trained(spark, sf_dir, METHODS["personal_comed"])
    return t.agg(F.round(F.avg("mse"), 4).alias("mean"), F.round(F.max("mse"), 4).alias("worst"), F.round(F.percentile("mse", 0.9), 4).alias("p90"))
