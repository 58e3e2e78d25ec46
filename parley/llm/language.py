"""Language identification by nearest centroid over TF-IDF character n-grams.

A text's runs of letters (lower case, everything else one blank) give 1- to 3-grams, hashed to DIMS features, weighted by
1 + ln(tf) and idf, and normalised. Each language has several centroids, found by spherical k-means among its training
texts; the language of the centroid with the greatest cosine wins. A text too far from every centroid, for its length, is
rejected: the limit is what nearly all training texts, cut to that length, exceed by a margin.

The model is fitted on at most PER_LANGUAGE labelled rows of each language, chosen by a hash of their ids; idf, centroids
and limits belong to that model. Prediction reads nothing but whole texts.
Defined results: null texts and texts without a letter get ``und``, score 0, and are rejected; so does every text where
no labelled row exists; ties go to the language first in order; repeated rows get equal results; an empty table gives an
empty result; very long texts are read whole, in which memory grows with one text; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from parley.llm.common import tidy

DIMS = 4096
#: The bound on labelled rows that a language's training takes.
PER_LANGUAGE = 800
CENTROIDS = 4
LENGTHS = (4, 8, 16, 32, 64, 128, 256, 512, 1024, 4096)
#: Of the least cosine that 99.8 % of training texts reach, the share below which a text is rejected.
MARGIN = 0.75
UNKNOWN = "und"
PREDICTION = "doc_id long, lang_pred string, score double, rejected boolean"

#: Of every code point, whether Unicode calls it a letter.
_LETTER = np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)
_P = [np.uint32(x) for x in (2654435761, 2246822519, 3266489917)]


def letters(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of the texts with each run of other characters as one blank, a blank around each text; the text each belongs to."""
    low = [" " + t.lower() + " " for t in texts]
    code = np.frombuffer("".join(low).encode("utf-32-le", "surrogatepass"), np.uint32).copy()
    owner = np.repeat(np.arange(len(low)), np.fromiter(map(len, low), np.int64, len(low)))
    blank = ~_LETTER[code]
    code[blank] = 32
    keep = np.ones(len(code), bool)
    keep[1:] = ~(blank[1:] & blank[:-1] & (owner[1:] == owner[:-1]))
    return code[keep], owner[keep]


def features(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Counts of hashed n-grams, one row for each text; the number of letters in each."""
    code, owner = letters(texts)
    counts = np.zeros(len(texts) * DIMS, np.int64)
    for n in (1, 2, 3):
        if len(code) < n:
            continue
        h = code[: len(code) - n + 1] * _P[0]
        for k in range(1, n):
            h = (h ^ (h >> np.uint32(15))) * _P[k] + code[k : len(code) - n + 1 + k] * _P[0]
        h ^= h >> np.uint32(13)
        h *= _P[1] + np.uint32(2 * n)
        own = owner[: len(h)] == owner[n - 1 :]
        if n == 1:
            own &= code != 32
        counts += np.bincount((owner[: len(h)] * DIMS + (h >> np.uint32(20)))[own], minlength=len(counts))
    return counts.reshape(len(texts), DIMS), np.bincount(owner[code != 32], minlength=len(texts))


def in_pieces(texts: list[str], chars: int = 200_000) -> Iterator[slice]:
    """Slices of a list of texts with so many characters, or one text, each."""
    start = size = 0
    for k, t in enumerate(texts):
        if k > start and (size + len(t) > chars or k - start >= 64):
            yield slice(start, k)
            start, size = k, 0
        size += len(t)
    if start < len(texts):
        yield slice(start, len(texts))


@dataclass
class Model:
    names: list[str]
    idf: np.ndarray
    centroids: np.ndarray
    language: np.ndarray
    limits: np.ndarray

    def vectors(self, counts: np.ndarray) -> np.ndarray:
        x = np.log1p(counts, dtype=np.float32)
        np.log1p(x, out=x)
        x *= self.idf
        return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)

    def predict(self, texts: list[str | None]) -> list[tuple[str, float, bool]]:
        out = []
        full = [t or "" for t in texts]
        for part in in_pieces(full):
            counts, n = features(full[part])
            cosine = self.vectors(counts) @ self.centroids.T
            best = cosine.argmax(axis=1)
            score = np.clip(cosine[np.arange(len(best)), best], 0, 1)
            limit = self.limits[np.searchsorted(LENGTHS, n, side="right") - 1]
            limit[n < LENGTHS[0]] = 0
            out += [(self.names[self.language[b]], float(s), bool(s < lim)) if k else (UNKNOWN, 0.0, True) for b, s, lim, k in zip(best, score, limit, n, strict=True)]
        return out


def clusters(x: np.ndarray, k: int, rounds: int = 12) -> np.ndarray:
    """Spherical k-means, begun with the texts farthest from those chosen before."""
    picked = [x.mean(axis=0)]
    for _ in range(k - 1):
        picked.append(x[(x @ np.stack(picked).T).max(axis=1).argmin()])
    c = np.stack(picked)
    for _ in range(rounds):
        c /= np.maximum(np.linalg.norm(c, axis=1, keepdims=True), 1e-12)
        own = (x @ c.T).argmax(axis=1)
        c = np.stack([x[own == j].mean(axis=0) if (own == j).any() else c[j] for j in range(k)])
    return c / np.maximum(np.linalg.norm(c, axis=1, keepdims=True), 1e-12)


def fit(rows: list[tuple[str, str]]) -> Model | None:
    """rows: (language, text) with a letter in each text."""
    names = sorted({lang for lang, _ in rows})
    if not names:
        return None
    texts = [t for _, t in rows]
    counts = np.concatenate([features(texts[p])[0].astype(np.float32) for p in in_pieces(texts)])
    idf = np.log((1 + len(texts)) / (1 + (counts > 0).sum(axis=0))).astype(np.float32) + np.float32(0.1)
    model = Model(names, idf, np.empty((0, DIMS), np.float32), np.empty(0, np.int64), np.zeros(len(LENGTHS)))
    x = model.vectors(counts)
    del counts
    owner = np.array([names.index(lang) for lang, _ in rows])
    centres, language = [], []
    for j in range(len(names)):
        own = x[owner == j]
        k = min(CENTROIDS, 1 + len(own) // 25)
        centres.append(clusters(own, k))
        language += [j] * k
    model.centroids, model.language = np.concatenate(centres).astype(np.float32), np.array(language)
    some = [t for t in texts if len(t) >= LENGTHS[0]][:: max(1, len(texts) // 1500)]
    lowest = 0.0
    for at, n in enumerate(LENGTHS):
        cut = [t[:n] for t in some if len(t) >= n]
        cut = [t for t in cut if any(map(str.isalpha, t))]
        if len(cut) >= 20:
            scores = np.concatenate([(model.vectors(features(cut[p])[0]) @ model.centroids.T).max(axis=1) for p in in_pieces(cut)])
            lowest = float(np.quantile(scores, 0.002)) * MARGIN
        model.limits[at] = lowest
    return model


def remainder(id_col: str, n: int) -> Column:
    """crc32 of the id as text, modulo n."""
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % n


def sample(df: DataFrame, id_col: str, text_col: str, lang_col: str, per_language: int) -> list[tuple[str, str]]:
    """At most per_language labelled rows of each language, by a hash of the id: the counts read no text."""
    labelled = df.where(F.col(lang_col).isNotNull())
    counts = labelled.groupBy(lang_col).count().collect()
    if not counts:
        return []
    scale = 1 << 30
    share = F.create_map(*[F.lit(x) for r in counts for x in (r[0], min(scale, int(1.2 * per_language * scale / r["count"]) + 1))])
    mark = F.xxhash64(F.lit("language"), F.col(id_col))
    rows = labelled.where(F.pmod(mark, F.lit(scale)) < share[F.col(lang_col)]).where(F.col(text_col).isNotNull()).select(lang_col, text_col, mark.alias("mark")).collect()
    out: dict[str, list] = {}
    for r in sorted(rows, key=lambda r: (r[0], r.mark)):
        own = out.setdefault(r[0], [])
        if len(own) < per_language and any(map(str.isalpha, r[1])):
            own.append((r[0], r[1]))
    return [x for own in out.values() for x in own]

def train(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_language: int = PER_LANGUAGE) -> Model | None:
    return fit(sample(df, id_col, text_col, lang_col, per_language))


def predict(df: DataFrame, model: Model | None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, lang_pred, score, rejected) for each row."""
    shared = df.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(1).to_pylist()
            got = shared.value.predict(texts) if shared.value else [(UNKNOWN, 0.0, True)] * len(texts)
            lang, score, no = zip(*got, strict=True) if got else ([], [], [])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array(no, pa.bool_())], ["doc_id", "lang_pred", "score", "rejected"])

    return df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(tidy(run), PREDICTION)


def recognised(df: DataFrame, model: Model | None, text_col: str = "text") -> DataFrame:
    """The rows of df that aren't rejected, whole: null texts and texts without a letter go, repeated rows fare alike, ids don't matter."""
    shared = df.sparkSession.sparkContext.broadcast(model)
    at = df.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(at).to_pylist()
            yield batch.filter(pa.array([not no for _, _, no in shared.value.predict(texts)] if shared.value else [False] * len(texts), pa.bool_()))

    return df.mapInArrow(tidy(run), df.schema)
