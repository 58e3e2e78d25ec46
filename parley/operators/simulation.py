"""Whole small federations inside one task: sweeps over datasets, methods and seeds run one setting to a task."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parley.functions.prox import envelope_np
from parley.operators.methods import Method, Rounds, batch_rows, draw_active, initial, judged, party_round
from parley.plans.choose import TASK_BYTES


@dataclass
class Federation:
    """Training and test rows of each party (lists of arrays); ids: the parties' own numbers, ascending, if not 0, 1, ..."""

    x: list[np.ndarray]
    y: list[np.ndarray]
    xt: list[np.ndarray]
    yt: list[np.ndarray]
    ids: np.ndarray | None = None

    @property
    def parties(self) -> np.ndarray:
        return np.arange(len(self.x))

    @property
    def nbytes(self) -> int:
        return sum(a.nbytes for part in (self.x, self.y, self.xt, self.yt) for a in part)


def split(x: list[np.ndarray], y: list[np.ndarray], share: float, seed: int) -> Federation:
    rng, parts = np.random.default_rng(seed), []
    for a, b in zip(x, y, strict=True):
        order = rng.permutation(len(a))
        cut = min(max(1, int(np.ceil(share * len(a)))), max(1, len(a) - 1))
        parts.append((a[order[:cut]], b[order[:cut]], a[order[cut:]], b[order[cut:]]))
    return Federation(*map(list, zip(*parts, strict=True)))


def bytes_of(examples: DataFrame) -> int:
    """Room that an example table takes in one task: from its row count and the width of its widest row."""
    got = examples.agg(F.count("*").alias("n"), F.max(F.size("x")).alias("d")).first()
    return got["n"] * ((got["d"] or 0) + 8) * 8


def fits(examples: DataFrame, held: int = 0, limit: int = TASK_BYTES) -> bool:
    """Whether a task that holds so many bytes already can hold an example table too."""
    return held + bytes_of(examples) <= limit


def gathered(examples: DataFrame) -> Federation:
    """The federation of an example table that fits a task; a party without test rows trains and has no score."""
    rows = examples.select("party_id", "pos", "split", "x", "y").orderBy("party_id", "pos").toPandas()
    parts: dict[int, dict[str, tuple]] = {}
    for (party, name), own in rows.groupby(["party_id", "split"], sort=True):
        parts.setdefault(int(party), {})[name] = np.stack(own["x"].to_numpy()), np.stack(own["y"].to_numpy())
    ids = sorted(k for k, p in parts.items() if "train" in p)
    test = [parts[k].get("test", tuple(a[:0] for a in parts[k]["train"])) for k in ids]
    return Federation([parts[k]["train"][0] for k in ids], [parts[k]["train"][1] for k in ids], [x for x, _ in test], [y for _, y in test], np.array(ids, np.int64))


def score(loss, w: np.ndarray, x: list[np.ndarray], y: list[np.ndarray]) -> np.ndarray:
    """Accuracy, mean squared error or log growth of each party's parameters on its rows."""
    out = np.full(len(x), np.nan)
    for k, (a, b) in enumerate(zip(x, y, strict=True)):
        if len(a):
            if loss.task == "classification":
                out[k] = (loss.predict(w[k : k + 1], a[None])[0] == b).mean()
            elif loss.task == "regression":
                out[k] = ((loss.predict(w[k : k + 1], a[None])[0] - b) ** 2).mean()
            else:
                out[k] = -loss.value(w[k : k + 1], a[None], b[None])[0]
    return out


def _mean(scores: np.ndarray) -> float:
    """Of the parties that have a score; none: not a number."""
    known = scores[~np.isnan(scores)]
    return float(known.mean()) if len(known) else float("nan")


def objective(loss, method: Method, cfg: Rounds, w: np.ndarray, g: np.ndarray, fed: Federation) -> float:
    """The joint objective with offsets and centre minimised out, for the models w and the centre g."""
    f = np.array([loss.value(w[k : k + 1], fed.x[k][None], fed.y[k][None])[0] for k in fed.parties])
    return float((f + envelope_np(method.reg.kind, w - g, method.reg.delta, cfg.sigma)).mean())


def simulate(loss, fed: Federation, method: Method, cfg: Rounds, every: int = 0, g0: np.ndarray | None = None, watch: Callable | None = None) -> dict:
    """Final scores, and a log with a row for each watched round: (round, mean test score, mean and deviation of the change at aggregation)."""
    parties, n = fed.parties, np.array([len(a) for a in fed.x])
    ids = parties if fed.ids is None else fed.ids
    g = np.zeros(loss.size) if g0 is None else g0
    state, log = initial(method, len(parties), g), []
    control = np.zeros(loss.size)

    def rows(k: np.ndarray, t: int) -> Callable:
        def batch(i: int):
            if cfg.batch is None:
                at = [np.arange(n[j]) for j in k]
            else:
                at = batch_rows(n[k], t, i, cfg)
            return np.stack([fed.x[j][a] for j, a in zip(k, at, strict=True)]), np.stack([fed.y[j][a] for j, a in zip(k, at, strict=True)])

        return batch

    def train_gradient(start: np.ndarray) -> np.ndarray:
        return np.concatenate([loss.grad(start[j : j + 1], fed.x[j][None], fed.y[j][None]) for j in parties])

    for t in range(cfg.rounds):
        k = np.searchsorted(ids, draw_active(ids, cfg.active, t, cfg.seed))
        part = {name: v[k] for name, v in state.items()}
        if cfg.batch is None and len(set(n[k])) > 1:
            new = [party_round(loss, method, cfg, {m: v[j : j + 1] for m, v in part.items()}, g, ids[k[j : j + 1]], t, rows(k[j : j + 1], t), control) for j in range(len(k))]
            new = {m: np.concatenate([x[m] for x in new]) for m in part}
        else:
            new = party_round(loss, method, cfg, part, g, ids[k], t, rows(k, t), control)
        if method.kind == "control":
            control = control + len(k) / len(parties) * (new["c"] - part["c"]).mean(0)
        before = new["w"]
        for name, v in new.items():
            state[name][k] = v
        if method.aggregates:
            pool = state["w"] if cfg.scope == "all" else new["w"]
            if method.kind == "control":
                g_new = g + method.extra["eta_g"] * (new["w"] - g).mean(0)
            elif method.kind == "envelope":
                g_new = (1 - method.extra["beta"]) * g + method.extra["beta"] * pool.mean(0)
            else:
                g_new = method.centre(pool, cfg.sigma)
        else:
            g_new = g
        if watch:
            watch(t, state, g, g_new, k)
        g = g_new
        if every and (t + 1) % every == 0 or t == cfg.rounds - 1:
            after = (1 - method.lam) * before + method.lam * g  # what the parties go on from
            change = after - before
            own = judged(loss, method, cfg, state, g, train_gradient)
            log.append((t + 1, _mean(score(loss, own, fed.xt, fed.yt)), float(change.mean()), float(change.std())))
    own = judged(loss, method, cfg, state, g, train_gradient)
    return {"state": state, "g": g, "log": log, "party": score(loss, own, fed.xt, fed.yt), "own": own}


RESULT = "dataset string, n_parties int, method string, seed int, round int, score double, worst double, change_mean double, change_std double"


def sweep(spark: SparkSession, settings: Iterable[tuple], build: Callable[[str, int, int], tuple]) -> DataFrame:
    """Results of settings (dataset, n_parties, method, rounds-config, every[, name]), each in a task; build(dataset, n, seed) gives (loss, federation)."""
    listed = [(*s, s[0]) if len(s) == 5 else s for s in settings]

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            rows = []
            for i in frame["id"]:
                dataset, n, method, cfg, every, name = listed[i]
                loss, fed = build(dataset, n, cfg.seed)
                r = simulate(loss, fed, method, cfg, every)
                known = r["party"][~np.isnan(r["party"])]
                worst = (known.max() if loss.task == "regression" else known.min()) if len(known) else np.nan
                rows += [(name, n, method.name, cfg.seed, t, s, float(worst), m, d) for t, s, m, d in r["log"]]
            yield pd.DataFrame(rows, columns=[c.split()[0] for c in RESULT.split(", ")])

    return spark.range(0, len(listed), 1, max(1, len(listed))).mapInPandas(run, RESULT)
