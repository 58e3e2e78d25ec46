"""Losses over flat parameter vectors, for many parties at once: W (P, d), X (P, B, ...), y (P, B, ...)."""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import Protocol, runtime_checkable

import numpy as np


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def _flat(*parts: np.ndarray) -> np.ndarray:
    return np.concatenate([p.reshape(len(p), -1) for p in parts], axis=1)


def _ones(x: np.ndarray) -> np.ndarray:
    return np.concatenate([x, np.ones((*x.shape[:-1], 1))], axis=-1)


@runtime_checkable
class Loss(Protocol):
    """What the round loop needs of a loss: any object with these members trains, built in or not.

    size: numbers in a model; task: "classification", "regression" or "growth". value, grad and predict take models W (P, size)
    and rows X (P, B, ...), y (P, B, ...) of P parties. Optional: lipschitz(x) for step lengths and exact minimisers,
    solve(w, x, y, z, sigma) where the penalised minimiser has a closed form.
    """

    task: str

    @property
    def size(self) -> int: ...

    def value(self, w: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray: ...

    def grad(self, w: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray: ...

    def predict(self, w: np.ndarray, x: np.ndarray) -> np.ndarray: ...


def minimiser(loss: Loss, w: np.ndarray, x: np.ndarray, y: np.ndarray, z: np.ndarray, sigma: float, tol: float = 1e-10, limit: int = 50_000) -> np.ndarray:
    """The exact minimiser of each party's loss + sigma / 2 |w - z|^2: closed form where the loss has one, else accelerated gradients."""
    if hasattr(loss, "solve"):
        return loss.solve(w, x, y, z, sigma)
    smooth = loss.lipschitz(list(x)) + sigma
    turn = (np.sqrt(smooth) - np.sqrt(sigma)) / (np.sqrt(smooth) + np.sqrt(sigma))
    ahead = w
    for _ in range(limit):
        slope = loss.grad(ahead, x, y) + sigma * (ahead - z)
        new = ahead - slope / smooth
        if np.abs(slope).max() <= tol:
            return new
        ahead, w = new + turn * (new - w), new
    return w


@dataclass(frozen=True)
class Linear:
    """Half the squared error, no intercept."""

    features: int
    task: str = "regression"

    @property
    def size(self) -> int:
        return self.features

    def value(self, w, x, y):
        return 0.5 * ((np.einsum("pbf,pf->pb", x, w) - y) ** 2).mean(1)

    def grad(self, w, x, y):
        return np.einsum("pbf,pb->pf", x, np.einsum("pbf,pf->pb", x, w) - y) / x.shape[1]

    def predict(self, w, x):
        return np.einsum("pbf,pf->pb", x, w)

    def solve(self, w, x, y, z, sigma):
        gram = np.einsum("pbf,pbg->pfg", x, x) / x.shape[1] + sigma * np.eye(self.features)
        return np.linalg.solve(gram, (np.einsum("pbf,pb->pf", x, y) / x.shape[1] + sigma * z)[..., None])[..., 0]

    def lipschitz(self, x):
        return float(max(np.linalg.eigvalsh(a.T @ a / len(a))[-1] for a in x))


@dataclass(frozen=True)
class Softmax:
    """Cross-entropy of a linear classifier with intercepts."""

    features: int
    classes: int
    task: str = "classification"

    @property
    def size(self) -> int:
        return self.classes * (self.features + 1)

    def _z(self, w, x):
        return np.einsum("pbf,pcf->pbc", _ones(x), w.reshape(len(w), self.classes, -1))

    def value(self, w, x, y):
        p = np.take_along_axis(_softmax(self._z(w, x)), y[..., None].astype(int), 2)[..., 0]
        return -np.log(np.maximum(p, 1e-300)).mean(1)

    def grad(self, w, x, y):
        p = _softmax(self._z(w, x)) - np.eye(self.classes)[y.astype(int)]
        return np.einsum("pbc,pbf->pcf", p, _ones(x)).reshape(len(w), -1) / x.shape[1]

    def predict(self, w, x):
        return self._z(w, x).argmax(-1)

    def lipschitz(self, x):
        return 0.5 * float(max(np.linalg.eigvalsh(a.T @ a / len(a))[-1] for a in map(_ones, x)))


@dataclass(frozen=True)
class Logistic:
    features: int
    task: str = "classification"

    @property
    def size(self) -> int:
        return self.features + 1

    def value(self, w, x, y):
        z = np.einsum("pbf,pf->pb", _ones(x), w)
        return (np.logaddexp(0, z) - y * z).mean(1)

    def grad(self, w, x, y):
        x1 = _ones(x)
        return np.einsum("pbf,pb->pf", x1, _sigmoid(np.einsum("pbf,pf->pb", x1, w)) - y) / x.shape[1]

    def predict(self, w, x):
        return (np.einsum("pbf,pf->pb", _ones(x), w) > 0).astype(int)

    def lipschitz(self, x):
        return 0.25 * float(max(np.linalg.eigvalsh(a.T @ a / len(a))[-1] for a in map(_ones, x)))


@dataclass(frozen=True)
class Mlp:
    """One hidden tanh layer and a softmax output; blocks: hidden layer, output layer."""

    features: int
    hidden: int
    classes: int
    task: str = "classification"

    @property
    def cut(self) -> int:
        return (self.features + 1) * self.hidden

    @property
    def size(self) -> int:
        return self.cut + (self.hidden + 1) * self.classes

    def _forward(self, w, x):
        a = w[:, : self.cut].reshape(len(w), self.features + 1, self.hidden)
        b = w[:, self.cut :].reshape(len(w), self.hidden + 1, self.classes)
        h = np.tanh(np.einsum("pbf,pfh->pbh", _ones(x), a))
        return b, h, np.einsum("pbh,phc->pbc", _ones(h), b)

    def value(self, w, x, y):
        p = np.take_along_axis(_softmax(self._forward(w, x)[2]), y[..., None].astype(int), 2)[..., 0]
        return -np.log(np.maximum(p, 1e-300)).mean(1)

    def _back(self, b, h, x, g):
        gb = np.einsum("pbh,pbc->phc", _ones(h), g)
        gh = np.einsum("pbc,phc->pbh", g, b[:, :-1]) * (1 - h * h)
        return _flat(np.einsum("pbf,pbh->pfh", _ones(x), gh), gb)

    def grad(self, w, x, y):
        b, h, z = self._forward(w, x)
        return self._back(b, h, x, (_softmax(z) - np.eye(self.classes)[y.astype(int)]) / x.shape[1])

    def predict(self, w, x):
        return self._forward(w, x)[2].argmax(-1)


@dataclass(frozen=True)
class Portfolio(Mlp):
    """An allocation policy over `classes` assets: minus the mean log growth; y holds price relatives (P, B, assets)."""

    task: str = "growth"

    def value(self, w, x, y):
        p = _softmax(self._forward(w, x)[2])
        return -np.log(np.maximum((p * y).sum(-1), 1e-12)).mean(1)

    def grad(self, w, x, y):
        b, h, z = self._forward(w, x)
        p = _softmax(z)
        gain = np.maximum((p * y).sum(-1, keepdims=True), 1e-12)
        return self._back(b, h, x, -p * (y / gain - 1) / x.shape[1])

    def predict(self, w, x):
        return _softmax(self._forward(w, x)[2])


@dataclass(frozen=True)
class Lstm:
    """Stacked LSTM layers over looked-up symbols and a logistic output; x holds symbol numbers (P, B, T)."""

    vocabulary: int
    embedding: int
    hidden: int
    layers: int = 2
    seed: int = 0
    task: str = "classification"
    lookup: np.ndarray | None = field(default=None, compare=False)

    def table(self) -> np.ndarray:
        return self.lookup if self.lookup is not None else np.random.default_rng(self.seed).normal(size=(self.vocabulary, self.embedding)) / np.sqrt(self.embedding)

    def shapes(self) -> list[tuple[int, int]]:
        ins = [self.embedding] + [self.hidden] * (self.layers - 1)
        return [(i + self.hidden + 1, 4 * self.hidden) for i in ins] + [(self.hidden + 1, 1)]

    @property
    def size(self) -> int:
        return sum(a * b for a, b in self.shapes())

    def _parts(self, w):
        out, at = [], 0
        for a, b in self.shapes():
            out.append(w[:, at : at + a * b].reshape(len(w), a, b))
            at += a * b
        return out

    def _forward(self, w, x):
        parts, seq, tape = self._parts(w), self.table()[x.astype(int)], []
        p, b, steps = x.shape
        for layer in parts[:-1]:
            h = c = np.zeros((p, b, self.hidden))
            cells, outs = [], []
            for t in range(steps):
                u = _ones(np.concatenate([seq[:, :, t], h], -1))
                z = np.einsum("pbi,pij->pbj", u, layer)
                i, f, o = (_sigmoid(z[..., k * self.hidden : (k + 1) * self.hidden] + (k == 1)) for k in range(3))
                g = np.tanh(z[..., 3 * self.hidden :])
                before, c = c, f * c + i * g
                h = o * np.tanh(c)
                cells.append((u, i, f, o, g, before, c))
                outs.append(h)
            tape.append(cells)
            seq = np.stack(outs, 2)
        return parts, tape, seq[:, :, -1], np.einsum("pbi,pij->pbj", _ones(seq[:, :, -1]), parts[-1])[..., 0]

    def value(self, w, x, y):
        z = self._forward(w, x)[3]
        return (np.logaddexp(0, z) - y * z).mean(1)

    def grad(self, w, x, y):
        parts, tape, last, z = self._forward(w, x)
        gz = ((_sigmoid(z) - y) / x.shape[1])[..., None]
        grads = [np.einsum("pbi,pbj->pij", _ones(last), gz)]
        steps, n = x.shape[2], self.hidden
        into = np.zeros((*x.shape[:2], steps, n))
        into[:, :, -1] = np.einsum("pbj,pij->pbi", gz, parts[-1][:, :-1])
        for layer, cells in zip(reversed(parts[:-1]), reversed(tape), strict=True):
            gw, gh, gc = np.zeros_like(layer), np.zeros((*x.shape[:2], n)), np.zeros((*x.shape[:2], n))
            width = layer.shape[1] - n - 1
            below = np.zeros((*x.shape[:2], steps, width))
            for t in reversed(range(steps)):
                u, i, f, o, g, before, c = cells[t]
                h = gh + into[:, :, t]
                tc = np.tanh(c)
                gc = gc + h * o * (1 - tc * tc)
                gz4 = np.concatenate([gc * g * i * (1 - i), gc * before * f * (1 - f), h * tc * o * (1 - o), gc * i * (1 - g * g)], -1)
                gw += np.einsum("pbi,pbj->pij", u, gz4)
                gu = np.einsum("pbj,pij->pbi", gz4, layer)
                below[:, :, t], gh, gc = gu[..., :width], gu[..., width : width + n], gc * f
            grads.insert(0, gw)
            into = below
        return _flat(*grads)

    def predict(self, w, x):
        return (self._forward(w, x)[3] > 0).astype(int)
