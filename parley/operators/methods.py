"""The round loop's methods: one configuration each, and what a party does in a round.

party_round() is used by the distributed loop (one party at a time) and by the in-task simulation (all parties at once):
state arrays have a leading party axis.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

import numpy as np

from parley.functions.centres import Layout, centre
from parley.functions.draws import mixed_np, uniform_np
from parley.functions.losses import minimiser
from parley.functions.prox import Regulariser

MEAN, GEO, COORD = Regulariser("sq", 0.1), Regulariser("l2", 0.1), Regulariser("l1", 0.1)


@dataclass(frozen=True)
class Method:
    """lam: share of the global model that a party starts a round from. score: what is judged, "own" or "global" or a baseline's own rule."""

    name: str
    reg: Regulariser
    lam: float = 0.0
    tied: bool = True  # False: sigma is 0
    aggregates: bool = True
    exact: bool = False
    solver: str = "accelerated"
    score: str = "own"
    kind: str = "loop"
    layout: tuple = ()
    extra: dict = field(default_factory=dict, hash=False)

    def centre(self, w: np.ndarray, sigma: float) -> np.ndarray:
        return centre(w, self.reg, sigma, self.solver, self.exact, list(self.layout) or None)

    def offset(self, r: np.ndarray, sigma: float) -> np.ndarray:
        if self.layout:
            return np.concatenate([q.prox(r[..., lo:hi], sigma) for lo, hi, q in self.layout], axis=-1)
        return self.reg.prox(r, sigma)


@dataclass(frozen=True)
class Rounds:
    """One run: T rounds of K active parties, E local steps on batches of B; seed decides draws, batches and stragglers."""

    eta: float
    sigma: float = 1.0
    rounds: int = 30
    active: int = 10
    steps: int = 20
    batch: int | None = 20  # None: full gradients
    seed: int = 1
    scope: str = "active"
    stragglers: float = 0.0
    local: str = "steps"  # "exact": each party minimises its penalised loss over its batch (losses.minimiser)

    @property
    def kappa(self) -> float:
        return 1 / (1 + self.sigma * self.eta)

    @property
    def advised(self) -> bool:
        return 0.9 <= self.kappa <= 0.999


def personal_mean(delta: float = 0.1, lam: float = 0.0) -> Method:
    return Method("personal_mean", Regulariser("sq", delta), lam)


def personal_geomed(delta: float = 0.1, lam: float = 0.0, solver: str = "accelerated") -> Method:
    return Method("personal_geomed", Regulariser("l2", delta), lam, solver=solver)


def personal_comed(delta: float = 0.1, lam: float = 0.0, solver: str = "accelerated") -> Method:
    return Method("personal_comed", Regulariser("l1", delta), lam, solver=solver)


def personal_hybrid(layout: Layout) -> Method:
    return Method("personal_hybrid", layout[0][2], layout=tuple(layout))


def personal_general(prox: Callable, value: Callable | None = None) -> Method:
    return Method("personal_general", Regulariser("user", user_prox=prox, user_value=value))


def untied() -> Method:
    return Method("untied", Regulariser("free"))


def local_only() -> Method:
    return Method("local_only", Regulariser("free"), tied=False, aggregates=False)


def fed_mean() -> Method:
    return Method("fed_mean", Regulariser("consensus"), 1.0, tied=False, score="global")


def fed_geomed(delta: float = 0.0) -> Method:
    return Method("fed_geomed", Regulariser("l2", delta), 1.0, tied=False, exact=delta == 0, score="global")


def fed_comed(delta: float = 0.0) -> Method:
    return Method("fed_comed", Regulariser("l1", delta), 1.0, tied=False, exact=delta == 0, score="global")


def fed_prox_mean() -> Method:
    return Method("fed_prox_mean", Regulariser("consensus"), 1.0, score="global")


def _baseline(name: str, score: str, kind: str, **extra) -> Method:
    """Parties go on from the mean, each baseline by its own steps."""
    return Method(name, Regulariser("consensus"), 1.0, tied=False, score=score, kind=kind, extra=extra)


def control_variate_mean(eta_g: float = 1.0) -> Method:
    return _baseline("control_variate_mean", "global", "control", eta_g=eta_g)


def envelope_personal(lam_p: float = 15.0, inner: int = 5, beta: float = 1.0) -> Method:
    return _baseline("envelope_personal", "theta", "envelope", lam_p=lam_p, inner=inner, beta=beta)


def meta_init_personal(alpha: float | None = None, mode: str = "fo") -> Method:
    return _baseline("meta_init_personal", "adapted", "meta", alpha=alpha, mode=mode)


def adaptive_mix_personal(alpha0: float = 0.5, adapt: bool = True) -> Method:
    return _baseline("adaptive_mix_personal", "mixture", "mix", alpha0=alpha0, adapt=adapt)


PERSONAL = (personal_mean, personal_geomed, personal_comed)
STANDARD = (fed_mean, fed_geomed, fed_comed, fed_prox_mean)
COMPARED = (control_variate_mean, envelope_personal, meta_init_personal, adaptive_mix_personal)


def bench_personal(regression: bool = False, **change) -> Rounds:
    """Settings of the personalised comparison."""
    return replace(Rounds(1e-4, 1.0, 500, 10, 20, 10) if regression else Rounds(0.02, 15.0, 500, 10, 20, 20), **change)


#: Step lengths of the standard datasets; every run there has sigma .01, batches of 10, ten active parties.
STANDARD_ETA = {"softmax": 0.01, "one_label": 0.03, "five_labels": 0.003, "text": 0.3}


def bench_standard(dataset: str, **change) -> Rounds:
    return replace(Rounds(STANDARD_ETA[dataset], 0.01, 200, 10, 20, 10, stragglers=0.9 if dataset == "text" else 0.0), **change)


def standard_methods(dataset: str) -> list[Method]:
    lam = 0.001 if dataset == "text" else 0.0
    return [personal_mean(0.001, lam), personal_geomed(0.1, lam), personal_comed(0.1, lam)]


def draw_active(parties: np.ndarray, k: int, t: int, seed: int) -> np.ndarray:
    """The k parties with the smallest draws of round t (ties: smaller id)."""
    return parties[np.lexsort((parties, mixed_np(seed, 101, t, parties)))[:k]]


def steps_of(parties: np.ndarray, t: int, cfg: Rounds) -> np.ndarray:
    """Local steps of each party in round t; stragglers make fewer."""
    late = uniform_np(cfg.seed, 202, t, parties) < cfg.stragglers
    return np.where(late, 1 + mixed_np(cfg.seed, 303, t, parties) % cfg.steps, cfg.steps)


def batch_rows(n: np.ndarray, t: int, i: int, cfg: Rounds) -> np.ndarray:
    """Row places of step i of round t, for parties with n rows each."""
    b = cfg.batch or int(n.max())
    return ((t * cfg.steps + i) * b + np.arange(b))[None, :] % n[:, None]


def party_round(
    loss,
    method: Method,
    cfg: Rounds,
    state: dict[str, np.ndarray],
    g: np.ndarray,
    parties: np.ndarray,
    t: int,
    rows: Callable[[int], tuple[np.ndarray, np.ndarray]],
    control: np.ndarray | None = None,
) -> dict[str, np.ndarray]:
    """New state of active parties (leading axis). rows(i) gives step i's batch (x, y); control: the server's variate."""
    w0, eta, e = state["w"], cfg.eta, method.extra
    sigma = cfg.sigma if method.tied else 0.0
    kappa = 1 / (1 + eta * sigma)
    anchor = g + method.offset(w0 - g, cfg.sigma) if sigma else np.zeros_like(w0)
    w = (1 - method.lam) * w0 + method.lam * g
    out, start, steps = dict(state), w, steps_of(parties, t, cfg)
    if method.kind == "mix":
        v, alpha = state["v"], state["alpha"]
    if method.kind == "envelope":
        theta = w.copy()
    for i in range(int(steps.max())):
        x, y = rows(i)
        on = (i < steps)[:, None]
        if method.kind == "loop" and cfg.local == "exact":
            new = minimiser(loss, w, x, y, anchor, sigma)
        elif method.kind == "loop":
            new = kappa * (w - eta * loss.grad(w, x, y)) + (1 - kappa) * anchor
        elif method.kind == "control":
            new = w - eta * (loss.grad(w, x, y) - state["c"] + control)
        elif method.kind == "envelope":
            inside = w.copy()
            for _ in range(e["inner"]):
                inside = inside - eta * (loss.grad(inside, x, y) + e["lam_p"] * (inside - w))
            new = w - eta * e["lam_p"] * (w - inside)
            theta = np.where(on, inside, theta)  # a party's own steps end before those of others
        elif method.kind == "meta":
            a = eta if e["alpha"] is None else e["alpha"]
            inner = loss.grad(w - a * loss.grad(w, x, y), *rows(i + 1))
            if e["mode"] == "hvp":  # times (I - a H), H by central differences
                n = np.maximum(np.linalg.norm(inner, axis=1, keepdims=True), 1e-12)
                u = inner / n * 1e-4
                inner = inner - a * n * (loss.grad(w + u, x, y) - loss.grad(w - u, x, y)) / 2e-4
            new = w - eta * inner
        else:
            mixed = alpha[:, None] * v + (1 - alpha[:, None]) * w
            gm = loss.grad(mixed, x, y)
            if e["adapt"] and i == 0:
                alpha = np.clip(alpha - eta * (gm * (v - w)).sum(1), 0, 1)
            v = np.where(on, v - eta * alpha[:, None] * gm, v)
            new = w - eta * loss.grad(w, x, y)
        w = np.where(on, new, w)
    if method.kind == "control":
        out["c"] = state["c"] - control + (start - w) / (eta * steps[:, None])
    if method.kind == "envelope":
        out["theta"] = theta
    if method.kind == "mix":
        out["v"], out["alpha"] = v, alpha
    return out | {"w": w}


def initial(method: Method, n: int, g0: np.ndarray) -> dict[str, np.ndarray]:
    w = np.repeat(g0[None, :], n, 0)
    more = {"control": {"c": np.zeros_like(w)}, "envelope": {"theta": w.copy()}, "mix": {"v": w.copy(), "alpha": np.full(n, method.extra.get("alpha0", 0.5))}}
    return {"w": w} | more.get(method.kind, {})


def judged(loss, method: Method, cfg: Rounds, state: dict[str, np.ndarray], g: np.ndarray, train: Callable | None = None) -> np.ndarray:
    """Parameters that a method is scored with, one row for each party."""
    if method.score == "global":
        return np.repeat(g[None, :], len(state["w"]), 0)
    if method.score == "theta":
        return state["theta"]
    if method.score == "mixture":
        return state["alpha"][:, None] * state["v"] + (1 - state["alpha"][:, None]) * state["w"]
    if method.score == "adapted":
        a = cfg.eta if method.extra["alpha"] is None else method.extra["alpha"]
        start = np.repeat(g[None, :], len(state["w"]), 0)
        return start - a * train(start)
    return state["w"]
