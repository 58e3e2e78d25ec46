"""Toxicity by a support vector machine over a gap-weighted subsequence kernel with Nyström landmarks.

Words are compared by the subsequences of three letters they share, each weighted by DECAY to the power of its span, so
that stretched, gapped and interrupted spellings stay near the word they hide; marks inside a word only widen spans.
Letters written apart ("w o r d") are read as one word. The normalised kernel k is made local, exp((k - 1) / WIDTH), and
cut to 0 below CUT. Landmarks are words tied to the label and the clean words nearest to them. A text's features are, for
each landmark, the greatest kernel that any of its words has with it, whitened by the landmarks' own kernel matrix, and
the logarithm of its number of words; a linear machine with squared hinge loss is trained on the labelled texts, and a
logistic curve over its margins on the same texts gives scores.
A bound from each subsequence's greatest landmark weight spares most words the kernel, without changing any score.

The model is fitted on at most PER_CLASS labelled rows of each class, chosen by a hash of their ids. Scores read whole
texts: long words are read in overlapping windows.
Defined results: null and empty texts score as a text without any word near a landmark; without labels of both classes
every score is the share of toxic labels (0 if none); repeated rows get equal scores; of equally strong tied words the
first in order comes first; very long texts are read whole; an empty table gives an empty result; other columns are
ignored.
"""

from __future__ import annotations

import re
import string
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from parley.llm.common import tidy

DECAY = 0.7
ORDER = 3
#: Longest stretch of a word that a subsequence is taken from.
SPAN = 7
#: The bound on labelled rows that a class's training takes.
PER_CLASS = 2000
LANDMARKS = 120
#: Similarities below CUT count as none; the local kernel falls by e for each WIDTH below 1.
CUT, WIDTH = 0.55, 0.15
#: Ridge of the machine's weights.
RIDGE = 1.0
WINDOW, STEP = 16, 8
MEMORY = 1_000_000
SCORED = "doc_id long, score double, predicted int"

SYMBOLS = 64
_EDGES = string.punctuation + "“”„«»¡¿…–—"
_APART = re.compile(r"(?<!\S)(?:\S[ \t]){2,}\S(?!\S)")
_CODE = np.full(0x110000, 63, np.int64)
_CODE[[ord(c) for c in string.ascii_lowercase]] = np.arange(1, 27)
_CODE[[ord(c) for c in string.digits]] = np.arange(27, 37)
_CODE[[ord(c) for c in "àâäáçéèêëíìîïñóòôöúùûüß"]] = np.arange(37, 60)
_CODE[[2, 3]] = [61, 62]  # where a word begins and ends
_CODE[[ord(c) for c in _EDGES]] = 0  # 0 takes room but is no letter


def windows(word: str) -> list[str]:
    """A stripped word whole, or in overlapping windows."""
    w = "\2" + word.strip(_EDGES) + "\3"
    return [w] if len(w) <= WINDOW else [w[k : k + WINDOW] for k in range(0, len(w) - WINDOW + STEP, STEP)]


def words_of(text: str | None) -> set[str]:
    low = (text or "").lower()
    return set(low.split()) | {re.sub(r"\s", "", m) for m in _APART.findall(low)}


def codes(words: list[str]) -> np.ndarray:
    """Symbols of words of one length, a row each."""
    flat = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32)
    return _CODE[flat].reshape(len(words), -1)


def subsequences(c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Numbers of all three-letter subsequences (a row for each word), 0 where a mark takes part; their weights."""
    picks = np.array([x for x in combinations(range(c.shape[1]), ORDER) if x[-1] - x[0] < SPAN], np.int64).reshape(-1, ORDER)
    a, b, d = c[:, picks[:, 0]], c[:, picks[:, 1]], c[:, picks[:, 2]]
    number = np.where((a > 0) & (b > 0) & (d > 0), (a * SYMBOLS + b) * SYMBOLS + d, 0)
    return number, DECAY ** (picks[:, 2] - picks[:, 0] + 1.0)


def self_kernel(number: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Sum over distinct subsequences of the square of their total weight."""
    if not number.shape[1]:
        return np.zeros(len(number))
    order = np.argsort(number, axis=1, kind="stable")
    n, w = np.take_along_axis(number, order, 1), weight[order]
    total = np.cumsum(w, axis=1)
    last = np.ones(n.shape, bool)
    last[:, :-1] = n[:, 1:] != n[:, :-1]
    row, col = np.nonzero(last)
    upto = total[row, col]
    first = np.append(True, row[1:] != row[:-1])
    part = upto - np.where(first, 0, np.append(0, upto[:-1]))
    return np.bincount(row, np.where(n[row, col] > 0, part * part, 0), minlength=len(number))


def by_length(words: list[str]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Positions and symbols of the words of each length, in pieces."""
    size = np.fromiter(map(len, words), np.int64, len(words))
    for n in np.unique(size):
        at = np.nonzero(size == n)[0]
        step = max(1, 400_000 // max(1, int(n) * SPAN * SPAN // 2))
        for k in range(0, len(at), step):
            part = at[k : k + step]
            yield part, codes([words[i] for i in part]) if n else np.zeros((len(part), 0), np.int64)


class Landmarks:
    """Normalised subsequence weights of landmark words: a row for each subsequence that any of them has."""

    def __init__(self, words: list[str]):
        self.words = words
        rows: list[tuple[np.ndarray, np.ndarray, int]] = [(number[i], weight, k) for at, c in by_length(words) for number, weight in [subsequences(c)] for i, k in enumerate(at)]
        self.numbers = np.unique(np.concatenate([np.zeros(1, np.int64), *(n for n, _, _ in rows)]))  # the first is 0
        self.row = np.zeros(SYMBOLS**ORDER, np.int32)
        self.row[self.numbers] = np.arange(len(self.numbers))
        self.table = np.zeros((len(self.numbers), len(words)))
        for n, w, k in rows:
            np.add.at(self.table[:, k], self.row[n], w)
        self.table[0] = 0
        self.table = (self.table / np.maximum(np.sqrt((self.table**2).sum(axis=0)), 1e-9)).astype(np.float32)

    def kernel(self, c: np.ndarray, number: np.ndarray, weight: np.ndarray) -> np.ndarray:
        """Local kernel of words (of one length) with the landmarks: 0 below CUT, then rising to 1 for equal words."""
        raw = np.zeros((len(c), self.table.shape[1]), np.float32)
        for k in range(number.shape[1]):
            raw += weight[k] * self.table[self.row[number[:, k]]]
        raw /= np.sqrt(np.maximum(self_kernel(number, weight), 1e-12))[:, None]
        return np.where(raw < CUT, 0, np.exp((np.minimum(raw, 1) - 1) / WIDTH))

    def kernel_of(self, words: list[str]) -> np.ndarray:
        out = np.zeros((len(words), self.table.shape[1]))
        for at, c in by_length(words):
            number, weight = subsequences(c)
            if number.shape[1]:
                out[at] = self.kernel(c, number, weight)
        return out

    def bounds(self, which: np.ndarray, most: int = 24) -> np.ndarray:
        """Greatest weight of each subsequence in the chosen landmarks, for groups of similar ones (a column each)."""
        groups: list[list[int]] = []
        for k in which.tolist():
            like = [float(self.table[:, g[0]] @ self.table[:, k]) for g in groups]
            if groups and (max(like) > 0.25 or len(groups) == most):
                groups[int(np.argmax(like))].append(k)
            else:
                groups.append([k])
        return np.stack([self.table[:, g].max(axis=1) for g in groups], axis=1) if groups else np.zeros((len(self.table), 1), np.float32)


@dataclass
class Model:
    base: float
    marks: Landmarks | None = None
    alpha: np.ndarray | None = None  # of each landmark's kernel
    bias: float = -1.0
    bound: np.ndarray | None = None
    length: float = 0.0  # of the logarithm of the number of words
    curve: np.ndarray | None = None
    known: dict[str, tuple[np.ndarray, np.ndarray] | None] = field(default_factory=dict, repr=False)

    def near(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Which windows any landmark is near to, and their kernels with all of them."""
        at_, rows = [np.empty(0, np.int64)], [np.empty((0, len(self.marks.words)))]
        for at, c in by_length(words):
            number, weight = subsequences(c)
            if number.shape[1]:
                most = np.zeros((len(c), self.bound.shape[1]), np.float32)
                for k in range(number.shape[1]):
                    most += np.float32(weight[k]) * self.bound[self.marks.row[number[:, k]]]
                best = most.max(axis=1)
                least = np.sqrt((number > 0) @ weight**2)  # of a word's own norm, to which equal subsequences only add; marks make it small
                some = np.nonzero((best > 0) & (best >= CUT * least - 1e-6))[0]
                some = some[best[some] >= CUT * np.sqrt(self_kernel(number[some], weight)) - 1e-6]
                if len(some):
                    own = self.marks.kernel(c[some], number[some], weight)
                    hit = own.any(axis=1)
                    at_.append(at[some[hit]])
                    rows.append(own[hit])
        return np.concatenate(at_), np.concatenate(rows)

    def margins(self, words: list[str]) -> np.ndarray:
        """What each window alone gives a text, the bias included."""
        out = np.full(len(words), self.bias)
        at, rows = self.near(words)
        out[at] += rows @ self.alpha
        return out

    def _learn(self, words: list[str]) -> None:
        """Remember the landmarks near each word, through any of its windows."""
        parts = [windows(w) for w in words]
        owner = np.repeat(np.arange(len(words)), [len(p) for p in parts])
        at, rows = self.near([p for ps in parts for p in ps])
        self.known.update(dict.fromkeys(words))
        for k, row in zip(owner[at].tolist(), rows, strict=True):
            mark = np.nonzero(row)[0]
            before = self.known[words[k]]
            self.known[words[k]] = (mark, row[mark]) if before is None else (np.concatenate([before[0], mark]), np.concatenate([before[1], row[mark]]))

    def features(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """A row for each text: its greatest kernel with each landmark; the logarithm of its number of distinct words, in fifths."""
        sets = [words_of(t) for t in texts]
        if len(self.known) > MEMORY:
            self.known.clear()
        new = list(set().union(*sets).difference(self.known)) if sets else []
        for at in range(0, len(new), 20_000):
            self._learn(new[at : at + 20_000])
        out = np.zeros((len(sets), len(self.marks.words)))
        for row, s in zip(out, sets, strict=True):
            for mark, value in filter(None, map(self.known.__getitem__, s)):
                row[mark] = np.maximum(row[mark], value) if len(mark) < 2 else _greater(row, mark, value)
        return out, np.log1p(np.fromiter(map(len, sets), float, len(sets))) / 5

    def sums(self, texts: list[str | None]) -> np.ndarray:
        """The machine's margin of each text."""
        kernels, length = self.features(texts)
        return kernels @ self.alpha + self.length * length + self.bias

    def scores(self, texts: list[str | None]) -> np.ndarray:
        if self.marks is None:
            return np.full(len(texts), self.base)
        return 1 / (1 + np.exp(-np.clip(self.curve[0] * self.sums(texts) + self.curve[1], -30, 30)))


def _greater(row: np.ndarray, mark: np.ndarray, value: np.ndarray) -> np.ndarray:
    """What row[mark] becomes; a landmark can come twice, through two windows of a word."""
    np.maximum.at(row, mark, value)
    return row[mark]


def tied(rows: list[set[str]], toxic: np.ndarray, least: float = 12.0, lift: float = 20.0) -> tuple[list[str], set[str]]:
    """Words that toxic texts hold far more often than others, by the log-likelihood ratio, strongest first; words that may be such."""
    with_, without = Counter(), Counter()
    for s, y in zip(rows, toxic, strict=True):
        (with_ if y else without).update({p for w in s for p in windows(w) if len(p) > ORDER})
    n1, n0, out, unclear = int(toxic.sum()), int((~toxic).sum()), [], set()

    def gain(k: float, n: float, p: float) -> float:
        return (k * np.log(p) if k else 0) + ((n - k) * np.log(1 - p) if n > k else 0)

    for w, a in with_.items():
        b = without[w]
        if a >= 2 and a / n1 > 3 * b / n0:
            unclear.add(w)
            p = (a + b) / (n1 + n0)
            g = 2 * (gain(a, n1, a / n1) + gain(b, n0, b / n0) - gain(a, n1, p) - gain(b, n0, p))
            if g >= least and a >= 3 and a / n1 >= lift * b / n0:
                out.append((-g, w))
    return [w for _, w in sorted(out)], unclear


def squared_hinge(x: np.ndarray, y: np.ndarray, cost: np.ndarray, ridge: float = 1e-3, rounds: int = 40) -> np.ndarray:
    """Weights (the last one the bias) of a linear machine, by Newton steps on the active rows."""
    x = np.hstack([x, np.ones((len(x), 1))])
    w = np.zeros(x.shape[1])
    reg = np.full(len(w), ridge)
    reg[-1] = 1e-8
    for _ in range(rounds):
        on = y * (x @ w) < 1
        a = x[on] * cost[on, None]
        new = np.linalg.solve(a.T @ x[on] + np.diag(reg), a.T @ y[on])
        if np.allclose(new, w, atol=1e-9):
            break
        w = new
    return w


def fit(rows: list[tuple[str, int]], share: float | None = None) -> Model:
    """rows: (text, 1 if toxic else 0); share: of toxic labels among all labels, if the rows are a sample by class."""
    toxic = np.array([y == 1 for _, y in rows], bool)
    base = float(toxic.mean()) if len(rows) else 0.0
    share = base if share is None else share
    if not len(rows) or toxic.all() or not toxic.any():
        return Model(share)
    sets = [words_of(t) for t, _ in rows]
    bad, unclear = tied(sets, toxic)
    if not bad:
        return Model(share)
    common = Counter(p for s, y in zip(sets, toxic, strict=True) if not y for w in s for p in windows(w) if len(p) > ORDER)
    good = [w for w, _ in sorted(common.items(), key=lambda x: (-x[1], x[0])) if w not in unclear]
    tie = Landmarks(bad[:LANDMARKS])
    near = np.concatenate([tie.kernel_of(good[k : k + 5000]).max(axis=1) for k in range(0, len(good), 5000)]) if good else np.empty(0)
    hard = np.argsort(-near, kind="stable")
    marks = Landmarks(bad[:LANDMARKS] + [good[k] for k in hard[:LANDMARKS] if near[k] > 0])
    inner = marks.kernel_of(marks.words)
    value, vector = np.linalg.eigh((inner + inner.T) / 2)
    white = vector / np.sqrt(np.maximum(value, 1e-3)) @ vector.T
    model = Model(share, marks, np.zeros(len(marks.words)), 0.0, marks.bounds(np.arange(len(marks.words))))
    kernels, length = model.features([t for t, _ in rows])
    cost = np.where(toxic, share, 1 - share) / np.where(toxic, base, 1 - base)  # undoes the sampling by class
    w = squared_hinge(np.hstack([kernels @ white, length[:, None]]), np.where(toxic, 1.0, -1.0), cost, RIDGE)
    model.alpha, model.length, model.bias = white @ w[:-2], float(w[-2]), float(w[-1])
    margin = kernels @ model.alpha + model.length * length + model.bias
    model.curve = logistic(margin[:, None], toxic, cost)
    model.known.clear()
    return model


def logistic(x: np.ndarray, toxic: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Weights (the last one the bias) of a logistic curve over texts' margins, by Newton steps."""
    x = np.hstack([x, np.ones((len(x), 1))])
    b, ridge = np.zeros(x.shape[1]), np.append(np.full(x.shape[1] - 1, 0.5), 1e-3)
    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(x @ b, -30, 30)))
        h = (x * (weight * np.maximum(p * (1 - p), 1e-6))[:, None]).T @ x + np.diag(ridge)
        step = np.linalg.solve(h, x.T @ (weight * (toxic - p)) - ridge * b)
        b = b + np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-8:
            break
    return b


def sample(labels: DataFrame, id_col: str, label_col: str, per_class: int) -> tuple[list[tuple[int, int]], float]:
    """(id, label) of at most per_class labelled rows of each class, by a hash of the id; the share of toxic labels among all."""
    labelled = labels.where(F.col(label_col).isin(0, 1) & F.col(id_col).isNotNull())
    counts = {r[0]: r["count"] for r in labelled.groupBy(label_col).count().collect()}
    scale, mark, chosen = 1 << 30, F.xxhash64(F.lit("toxicity"), F.col(id_col)), []
    for y, n in sorted(counts.items()):
        share = min(scale, int(1.2 * per_class * scale / n) + 1)
        rows = labelled.where((F.col(label_col) == y) & (F.pmod(mark, F.lit(scale)) < share)).orderBy(mark, id_col).limit(per_class)
        chosen += [(r[0], y) for r in rows.select(F.col(id_col).cast("long")).collect()]
    return chosen, counts.get(1, 0) / max(1, sum(counts.values()))


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", per_class: int = PER_CLASS) -> Model:
    """labels: one row for each labelled id. The chosen ids (at most 2 x per_class) go to the documents, whose texts stay where they are."""
    chosen, share = sample(labels, id_col, label_col, per_class)
    if not chosen:
        return Model(share)
    ids = docs.sparkSession.createDataFrame(chosen, "chosen_id long, chosen_label int")
    rows = docs.join(F.broadcast(ids), F.col(id_col).cast("long") == F.col("chosen_id")).select("chosen_id", text_col, "chosen_label").collect()
    return fit([(r[1] or "", r[2]) for r in sorted(rows, key=lambda r: (r[2], r[0], r[1] or ""))], share)


def score(df: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, score, predicted) for each row."""
    shared = df.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, out = batch.column(1).to_pylist(), [np.empty(0)]
            for at in range(0, len(texts), 500):
                out.append(shared.value.scores(texts[at : at + 500]))
            s = np.concatenate(out)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(s), pa.array((s >= 0.5).astype(np.int32))], ["doc_id", "score", "predicted"])

    return df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(tidy(run), SCORED)
