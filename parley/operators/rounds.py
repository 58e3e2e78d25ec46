"""The distributed round loop.

Examples are (party_id, pos, n, x array<double>, y double or array<double>), best in a table bucketed by party (see
sources.stores.bucketed: then no exchange moves them). A round reads the rows of its active parties that its steps need,
so with batches a party's group never exceeds (steps + 1) x batch rows; full gradients need a party's rows in one task.
Local steps run as one grouped function over rows and model together. A round writes the models of its active parties
only, beside the table of all parties' models; every FOLD rounds they are folded into it, and what has been replaced is
deleted. The driver holds the ids of the active parties and the centre (one vector).
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from parley.operators.aggregate import _vector, hybrid, solve
from parley.operators.methods import Method, Rounds, initial, judged, party_round, steps_of
from parley.operators.parties import draw_active
from parley.plans.choose import few
from parley.sources.tables import Tables

STATE = "party_id long, w array<double>, c array<double>, theta array<double>, v array<double>, alpha double"
_FIELDS = ("w", "c", "theta", "v", "alpha")
LOG = (
    "round int, active long, local_steps long, gradient_rows long, numbers_moved long, aggregator_steps long, "
    "change_mean double, change_std double, kappa_in_advice boolean, seconds double"
)
#: Rounds whose models stand beside the table of all.
FOLD = 8
#: Test rows that one task scores together.
SHARD_ROWS = 4096


@dataclass
class RunResult:
    """state: every party's models; control: the server's variate; rounds: how many are done. Any run can go on from one."""

    state: DataFrame
    g: np.ndarray
    log: list[tuple]
    control: np.ndarray | None = None
    rounds: int = 0
    before: np.ndarray | None = field(default=None, repr=False)  # the centre that the last round began with

    def log_table(self) -> DataFrame:
        return self.state.sparkSession.createDataFrame(self.log, LOG)


def _row(party: int, state: dict[str, np.ndarray]) -> dict:
    out = {"party_id": party}
    for f in _FIELDS:
        v = state[f][0] if f in state else None
        out[f] = float(v) if f == "alpha" and v is not None else v
    return out


def _state_of(row) -> dict[str, np.ndarray]:
    return {f: np.array([row[f]]) for f in _FIELDS if row[f] is not None and not (f == "alpha" and np.isnan(row[f]))}


class States:
    """Every party's latest state: a table of all, and the rows that later rounds wrote."""

    def __init__(self, base: DataFrame, tables: Tables):
        self.base, self.tables, self.news = base, tables, []

    def latest(self, only: DataFrame | None = None, rows: int = 0) -> DataFrame:
        """only: parties that are asked for, so many rows."""
        pick = (lambda df: df) if only is None else (lambda df: df.join(few(only, rows), "party_id", "left_semi"))
        if not self.news:
            return pick(self.base)
        late = None
        for at, (news, _) in enumerate(self.news):
            part = pick(news).withColumn("at", F.lit(at))
            late = part if late is None else late.unionByName(part)
        newest = late.groupBy("party_id").agg(F.max_by(F.struct(*_FIELDS), "at").alias("s")).select("party_id", "s.*")
        known = sum(n for _, n in self.news)
        return pick(self.base).join(few(newest.select("party_id"), known), "party_id", "left_anti").unionByName(newest)

    def add(self, news: DataFrame, rows: int) -> None:
        self.news.append((news, rows))

    def settle(self) -> None:
        """At a round's end, when nothing is to read its tables any more."""
        if len(self.news) >= FOLD:
            self.fold()

    def fold(self) -> DataFrame:
        if self.news:
            old = [self.base, *(n for n, _ in self.news)]
            self.base = self.tables.keep(self.latest(), "state")
            self.news = []
            self.tables.drop(*old)
        return self.base


def needed_rows(examples: DataFrame, cfg: Rounds, t: int) -> DataFrame:
    """Rows that round t's steps touch; all of them for full gradients."""
    if cfg.batch is None:
        return examples
    span = (cfg.steps + 1) * cfg.batch  # one batch more, for methods that look ahead
    return examples.where(F.pmod(F.col("pos") - F.lit(t * cfg.steps * cfg.batch), F.col("n")) < span)


def _solver(loss, method: Method, cfg: Rounds, g: np.ndarray, t: int, control: np.ndarray):
    """One party's local steps: its needed rows on the left, its state on the right."""

    def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not len(left) or not len(right):  # no rows that this round needs, or no such party
            return pd.DataFrame(columns=["party_id", *_FIELDS])
        row = right.iloc[0]
        party, n = int(row["party_id"]), int(left["n"].iloc[0])
        place = {int(p): k for k, p in enumerate(left["pos"])}
        xs, ys = np.stack(left["x"].to_numpy()), np.stack(left["y"].to_numpy())

        def batch(i: int):
            at = range(n) if cfg.batch is None else [((t * cfg.steps + i) * cfg.batch + j) % n for j in range(cfg.batch)]
            pick = [place[p] for p in at]
            return xs[None, pick], ys[None, pick]

        return pd.DataFrame([_row(party, party_round(loss, method, cfg, _state_of(row), g, np.array([party]), t, batch, control))])

    return run


def local_round(examples: DataFrame, part: DataFrame, active: DataFrame, loss, method: Method, cfg: Rounds, g: np.ndarray, t: int, control: np.ndarray) -> DataFrame:
    """New states of the active parties. part: their states; active: their ids."""
    rows = needed_rows(examples, cfg, t).join(few(active, cfg.active), "party_id", "left_semi")
    return rows.groupBy("party_id").cogroup(part.groupBy("party_id")).applyInPandas(_solver(loss, method, cfg, g, t, control), STATE)


def _beginning(examples: DataFrame, method: Method, g: np.ndarray) -> DataFrame:
    one = _row(0, initial(method, 1, g))
    columns = [F.lit(None).cast("array<double>").alias(f) if one[f] is None else F.array(*[F.lit(float(a)) for a in one[f]]).alias(f) for f in _FIELDS[:-1]]
    return examples.select("party_id").distinct().select("party_id", *columns, F.lit(one["alpha"]).cast("double").alias("alpha"))


def run_rounds(examples: DataFrame, loss, method: Method, cfg: Rounds, g0: np.ndarray | None = None, resume: RunResult | None = None) -> RunResult:
    """examples: training rows. resume: what an earlier run gave; it goes on for cfg.rounds more. No parties: nothing happens."""
    spark = examples.sparkSession
    tables = Tables(spark)
    if resume:
        states, g, first = States(resume.state, tables), resume.g, resume.rounds
        control = np.zeros(loss.size) if resume.control is None else resume.control
    else:
        g, first, control = np.zeros(loss.size) if g0 is None else g0, 0, np.zeros(loss.size)
        states = States(tables.keep(_beginning(examples, method, g), "state"), tables)
    log, before = [], g
    parties = tables.keep(states.base.select("party_id"), "parties")
    total = parties.count()
    for t in range(first, first + (cfg.rounds if total else 0)):
        begun = time.perf_counter()
        ids = [r.party_id for r in draw_active(parties, cfg.active, t, cfg.seed).collect()]  # the round's size, whatever the number of parties
        k = len(ids)
        active = spark.createDataFrame([(i,) for i in ids], "party_id long")
        part = states.latest(active, k)
        solved = tables.keep(local_round(examples, part, active, loss, method, cfg, g, t, control), "solved")
        before = g
        if method.kind == "control":
            news, old = (_vector(solve(x.select("party_id", F.col("c").alias("w")), method.reg, parties=k, size=loss.size)[0]) for x in (solved, part))
            control = control + k / total * (news - old)
        states.add(solved, k)
        g, took = next_centre(solved if cfg.scope == "active" else states.latest(), k if cfg.scope == "active" else total, loss, method, cfg, g)
        change = change_at_aggregation(solved, g, method.lam)
        steps = int(steps_of(np.array(ids), t, cfg).sum())
        moved = 2 * k * loss.size * (2 if method.kind == "control" else 1)
        log.append((t, k, steps, steps * (cfg.batch or 0), moved, took, *change, cfg.advised, time.perf_counter() - begun))
        states.settle()
    state = states.fold()
    tables.drop(parties)
    if method.score == "adapted":
        a = cfg.eta if method.extra["alpha"] is None else method.extra["alpha"]
        state = tables.keep(adapted(examples, state, loss, g, a), "adapted")
    return RunResult(state, g, (resume.log if resume else []) + log, control, first + cfg.rounds, before)


def next_centre(pool: DataFrame, count: int, loss, method: Method, cfg: Rounds, g: np.ndarray) -> tuple[np.ndarray, int]:
    """The centre after a round, from the models in scope, and the aggregator's steps."""
    if not method.aggregates:
        return g, 0
    models = pool.select("party_id", "w")
    if method.layout:
        found, took = hybrid(models, list(method.layout), cfg.sigma, method.exact, method.solver, count)
    else:
        found, took = solve(models, method.reg, cfg.sigma, method.exact, method.solver, count, loss.size)
    new = _vector(found)
    if method.kind == "control":
        new = g + method.extra["eta_g"] * (new - g)
    elif method.kind == "envelope":
        new = (1 - method.extra["beta"]) * g + method.extra["beta"] * new
    return new, took


def adapted(examples: DataFrame, state: DataFrame, loss, g: np.ndarray, a: float) -> DataFrame:
    """State with theta: one personal step from the global model over all of a party's training rows, added up in parts."""

    def part(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for party, rows in frame.groupby("party_id"):
                x, y = np.stack(rows["x"].to_numpy())[None], np.stack(rows["y"].to_numpy())[None]
                out.append({"party_id": party, "grad": len(rows) * loss.grad(g[None], x, y)[0], "rows": len(rows)})
            yield pd.DataFrame(out, columns=["party_id", "grad", "rows"])

    parts = examples.select("party_id", "x", "y").mapInPandas(part, "party_id long, grad array<double>, rows long")
    sums = parts.select("party_id", "rows", F.posexplode("grad").alias("at", "v")).groupBy("party_id", "at").agg(F.sum("v").alias("v"), F.sum("rows").alias("rows"))
    mean = sums.groupBy("party_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("at", (F.col("v") / F.col("rows")).alias("m")))), lambda e: e["m"]).alias("m"))
    centre = F.array(*[F.lit(float(b)) for b in g])
    theta = F.coalesce(F.zip_with(centre, "m", lambda b, d: b - a * d), "w").alias("theta")
    return state.join(mean, "party_id", "left").select("party_id", "w", "c", theta, "v", "alpha")


def change_at_aggregation(solved: DataFrame, g: np.ndarray, lam: float) -> tuple[float, float]:
    """Mean and deviation, over parties and coordinates, of what the start of the next round adds to a party's model."""
    if lam == 0:
        return 0.0, 0.0

    def part(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            if len(frame):
                r = lam * (g - np.stack(frame["w"].to_numpy()))
                yield pd.DataFrame({"n": [r.size], "mean": [r.mean()], "square": [((r - r.mean()) ** 2).sum()]})

    rows = np.array(solved.select("w").mapInPandas(part, "n long, mean double, square double").collect(), float).reshape(-1, 3)  # a row a batch
    n, mean, square = rows.T
    if not n.sum():
        return float("nan"), float("nan")
    middle = float((n * mean).sum() / n.sum())
    return middle, float(np.sqrt((square + n * (mean - middle) ** 2).sum() / n.sum()))


def judged_models(result: RunResult, loss, method: Method, cfg: Rounds) -> DataFrame:
    """(party_id, w): the parameters that each party is scored with."""
    g = result.g

    def own(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for _, row in frame.iterrows():
                state = _state_of(row)
                w = state["theta"] if method.score == "adapted" else judged(loss, method, cfg, state, g)
                out.append({"party_id": int(row["party_id"]), "w": w[0]})
            yield pd.DataFrame(out, columns=["party_id", "w"])

    return result.state.mapInPandas(own, "party_id long, w array<double>")


def scores(rows: DataFrame, result: RunResult, loss, method: Method, cfg: Rounds) -> DataFrame:
    """(party_id, score, n) on given rows (accuracy, squared error or growth); a party without rows has no score."""
    return scored(rows, judged_models(result, loss, method, cfg), loss).select("party_id", "score", "n")


def scored(rows: DataFrame, models: DataFrame, loss) -> DataFrame:
    """(party_id, score, loss, n): parties' models on rows (party_id, pos, x, y). A large party is scored in shards."""
    dealt = rows.select("party_id", F.floor(F.col("pos") / SHARD_ROWS).alias("shard"), "x", "y")

    def judge(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not len(left) or not len(right):
            return pd.DataFrame(columns=["party_id", "score", "loss", "n"])
        x, y = np.stack(left["x"].to_numpy())[None], np.stack(left["y"].to_numpy())[None]
        own = np.stack(right["w"].to_numpy())[:1]
        value = float(loss.value(own, x, y)[0])
        if loss.task == "classification":
            s = float((loss.predict(own, x)[0] == y[0]).mean())
        else:
            s = float(((loss.predict(own, x)[0] - y[0]) ** 2).mean()) if loss.task == "regression" else -value
        return pd.DataFrame({"party_id": [int(left["party_id"].iloc[0])], "score": [s * len(left)], "loss": [value * len(left)], "n": [len(left)]})

    shards = dealt.select(F.col("party_id").alias("party"), F.col("shard").alias("part")).distinct().join(models.withColumnRenamed("party_id", "party"), "party")
    parts = dealt.groupBy("party_id", "shard").cogroup(shards.groupBy("party", "part")).applyInPandas(judge, "party_id long, score double, loss double, n long")
    return parts.groupBy("party_id").agg((F.sum("score") / F.sum("n")).alias("score"), (F.sum("loss") / F.sum("n")).alias("loss"), F.sum("n").alias("n"))


def lambda_path(rows: DataFrame, result: RunResult, loss, points: int = 5) -> DataFrame:
    """(lam, loss, worst): mean and worst loss of parties on their rows, on the way from their own models to the centre."""
    g = F.array(*[F.lit(float(a)) for a in result.g])
    out = None
    for k in range(points + 1):
        lam = k / points
        mixed = result.state.select("party_id", F.zip_with("w", g, lambda a, b: (1 - lam) * a + lam * b).alias("w"))  # noqa: B023
        at = scored(rows, mixed, loss).agg(F.avg("loss").alias("loss"), F.max("loss").alias("worst")).select(F.lit(lam).alias("lam"), "loss", "worst")
        out = at if out is None else out.unionByName(at)
    return out


def curve(examples: DataFrame, tests: DataFrame, loss, method: Method, cfg: Rounds, every: int) -> Iterator[tuple[int, DataFrame, RunResult]]:
    """(rounds done, scores, run) after every so many rounds of one run."""
    run, done = None, 0
    while done < cfg.rounds:
        more = min(every or cfg.rounds, cfg.rounds - done)
        run = run_rounds(examples, loss, method, replace(cfg, rounds=more), resume=run)
        done += more
        yield done, scores(tests, run, loss, method, cfg), run
