"""Benchmark decontamination: BM25 with block-max WAND over test items, queried by every training passage.

Test items are cut into segments of at most 32 words and indexed; a segment's weights are divided by its own full score,
so one threshold serves all. A training passage is 64 words, one beginning every 32 words, so that each stretch of 32
words lies whole in a passage. Every passage is a query and gets all segments that score half of what they would score
on themselves. Most passages are given up by a bound first: terms are parted so that no segment holds more than 0.3 of
its weight in common ones; what a passage shares with a segment in rare terms must make up the rest (exact: a passage
that fails this can't reach the threshold). The rest is searched with block-max WAND.
A retrieved item is then verified on the words around the passage: five-word shingles of its question (all sentences but
the last) and of its answer (the last one). It counts if 0.8 of all its shingles are there, or 0.8 of the question's and
half of the answer's.

Items of fewer than SHORT words have an index of their own, and count only where all their words follow each other.

The index must fit in memory on each worker: items are taken in shards of at most INDEX_BYTES of text, each with a pass
over the documents.
Defined results: null and empty texts, and texts of punctuation alone, contain nothing and are contained in nothing;
repeated rows are judged alike; equal items are all reported; very long texts are read whole, passage by passage; without
items or documents the result is empty; a null item id is kept as null; other columns are ignored.
"""

from __future__ import annotations

import math
import re
import string
from bisect import bisect_left
from collections import Counter, defaultdict
from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from parley.llm.common import tidy

SEGMENT, PASSAGE, STRIDE = 32, 64, 32
SHORT = 8
SHINGLE = 5
THRESHOLD = 0.5
OVERLAP = 0.8
COMMON_MASS = 0.3
BLOCK = 32
#: Text of one shard's items; a worker holds about 30 MB of index for each MB of it (measured).
INDEX_BYTES = 4 << 20
K1, B = 1.2, 0.75
RESULT = "doc_id long, item_id long, score double, question_overlap double, answer_overlap double"

_PUNCTUATION = string.punctuation.encode()


def words(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").lower().translate(None, _PUNCTUATION).split()


def shingles(w: list[bytes]) -> set[bytes]:
    return {b" ".join(w[k : k + SHINGLE]) for k in range(max(1, len(w) - SHINGLE + 1))} if w else set()


class Item:
    """A test item; its shingles, parted into question and answer, are made when a passage first meets it."""

    def __init__(self, item_id: int | None, text: str):
        self.item_id, self.text = item_id, text

    @cached_property
    def words(self) -> list[bytes]:
        return words(self.text)

    @cached_property
    def sentences(self) -> list[str]:
        return [s for s in re.split(r"(?<=[.!?])\s+", self.text.strip()) if words(s)]

    @cached_property
    def all(self) -> set[bytes]:
        return shingles(self.words)

    @cached_property
    def answer(self) -> set[bytes]:
        return shingles(words(self.sentences[-1])) if len(self.sentences) > 1 else self.all

    @cached_property
    def question(self) -> set[bytes]:
        return shingles(words(" ".join(self.sentences[:-1]))) if len(self.sentences) > 1 else self.all

    def overlaps(self, around: list[bytes]) -> tuple[float, float, float]:
        there = {n: {b" ".join(around[k : k + n]) for k in range(len(around) - n + 1)} for n in {min(SHINGLE, s.count(b" ") + 1) for s in self.all | self.answer | self.question}}
        share = lambda own: sum(s in there[min(SHINGLE, s.count(b" ") + 1)] for s in own) / len(own)
        return share(self.all), share(self.question), share(self.answer)


class Index:
    """Inverted index of item segments, postings in blocks with their greatest weight."""

    def __init__(self, items: list[tuple[int | None, str]], short: bool = False):
        """Of the items, those of SHORT words or more, or the others."""
        self.short, self.items = short, []
        segments, self.owner = [], []
        for key, text in items:
            own = words(text)
            if not own or (len(own) < SHORT) != short:
                continue
            n = -(-len(own) // SEGMENT)
            cut = [round(k * len(own) / n) for k in range(n + 1)]
            for a, b in zip(cut, cut[1:], strict=False):
                segments.append(Counter(own[a:b]))
                self.owner.append(len(self.items))
            self.items.append(Item(key, text))
        df = Counter(t for s in segments for t in s)
        mean = sum(sum(s.values()) for s in segments) / max(1, len(segments))
        postings: dict[bytes, list[tuple[int, float]]] = defaultdict(list)
        for d, s in enumerate(segments):
            length = sum(s.values())
            w = {t: math.log(1 + (len(segments) - df[t] + 0.5) / (df[t] + 0.5)) * f * (K1 + 1) / (f + K1 * (1 - B + B * length / mean)) for t, f in s.items()}
            full = sum(w.values())
            for t, x in w.items():
                postings[t].append((d, x / full))
        self.postings = {t: self._blocks(p) for t, p in postings.items()}
        self._part(df, postings, len(segments))

    @staticmethod
    def _blocks(p: list[tuple[int, float]]) -> tuple:
        docs, weights = [d for d, _ in p], [w for _, w in p]
        starts = range(0, len(p), BLOCK)
        return docs, weights, max(weights), [docs[min(s + BLOCK, len(p)) - 1] for s in starts], [max(weights[s : s + BLOCK]) for s in starts]

    def _part(self, df: Counter, postings: dict, n: int) -> None:
        """Rare terms: as few as leave no segment more than COMMON_MASS in the others."""
        common = np.zeros(n)
        by_df: dict[int, list[bytes]] = defaultdict(list)
        for t, f in df.items():
            by_df[f].append(t)
        cut = 0
        for f in sorted(by_df, reverse=True):
            more = np.zeros(n)
            for t in by_df[f]:
                for d, w in postings[t]:
                    more[d] += w
            if n and (common + more).max() > COMMON_MASS:
                cut = f
                break
            common += more
        rare = sorted(t for t, f in df.items() if f <= cut)
        self.rare = {t: k for k, t in enumerate(rare)}
        size = np.array([len(postings[t]) for t in rare], np.int64)
        self.rare_at = np.concatenate([[0], np.cumsum(size)]).astype(np.int64)
        flat = [x for t in rare for x in postings[t]]
        self.rare_doc = np.array([d for d, _ in flat], np.int64)
        self.rare_weight = np.array([w for _, w in flat])
        self.need = THRESHOLD - common - 1e-9

    def hopeful(self, ids: np.ndarray) -> np.ndarray:
        """Passages (their numbers) of one text that could reach the threshold; ids: rare-term number of each word, or -1."""
        place = np.nonzero(ids >= 0)[0]
        if not len(place):
            return place
        term = ids[place]
        n = self.rare_at[term + 1] - self.rare_at[term]
        flat = np.repeat(self.rare_at[term] - (np.cumsum(n) - n), n) + np.arange(n.sum())
        at, doc, w = np.repeat(place // STRIDE, n), self.rare_doc[flat], self.rare_weight[flat]
        last = max(0, -(-(len(ids) - PASSAGE) // STRIDE))
        both = np.concatenate([np.minimum(at, last), np.clip(at - 1, 0, last)])  # a word at the text's end lies in the last passage
        twice = np.concatenate([np.ones(len(at), bool), np.clip(at - 1, 0, last) != np.minimum(at, last)])
        key = (both * len(self.need) + np.tile(doc, 2))[twice]
        pairs, inverse = np.unique(key, return_inverse=True)
        mass = np.bincount(inverse, np.tile(w, 2)[twice])
        return np.unique(pairs[mass >= self.need[pairs % len(self.need)]] // len(self.need))

    def search(self, terms: set[bytes], threshold: float = THRESHOLD) -> list[tuple[int, float]]:
        """Every segment scoring threshold or more, by block-max WAND."""
        lists = [[0, *self.postings[t]] for t in sorted(terms) if t in self.postings]  # cursor, docs, weights, max, block ends, block max
        found, slack = [], threshold - 1e-12
        while lists:
            lists.sort(key=lambda x: x[1][x[0]])
            bound, pivot = 0.0, -1
            for k, x in enumerate(lists):
                bound += x[3]
                if bound >= slack:
                    pivot = k
                    break
            if pivot < 0:
                break
            doc = lists[pivot][1][lists[pivot][0]]
            while pivot + 1 < len(lists) and lists[pivot + 1][1][lists[pivot + 1][0]] == doc:
                pivot += 1
            shallow = [(x, bisect_left(x[4], doc)) for x in lists[: pivot + 1]]
            if sum(x[5][b] for x, b in shallow if b < len(x[5])) >= slack:
                if lists[0][1][lists[0][0]] == doc:
                    score = sum(x[2][x[0]] for x in lists[: pivot + 1])
                    if score >= slack:
                        found.append((doc, score))
                    goal = doc + 1
                else:
                    goal = doc
            else:  # no document up to the nearest block end can do it
                ends = [x[4][b] for x, b in shallow if b < len(x[4])]
                goal = min(ends, default=doc) + 1
                if pivot + 1 < len(lists):
                    goal = min(goal, lists[pivot + 1][1][lists[pivot + 1][0]])
                goal = max(goal, doc + 1)
            for x in lists[: pivot + 1]:
                if x[1][x[0]] < goal:
                    x[0] = bisect_left(x[1], goal, x[0])
            lists = [x for x in lists if x[0] < len(x[1])]
        return found

    def judge(self, text: str | None) -> list[tuple[int | None, float, float, float]]:
        """(item id, best score, question overlap, answer overlap) of the items that text contains."""
        w = words(text)
        ids = np.fromiter(map(self.rare.get, w, [-1] * len(w)), np.int64, len(w))
        best: dict[int, list[tuple[float, int]]] = defaultdict(list)
        for p in self.hopeful(ids).tolist():
            for segment, score in self.search(set(w[p * STRIDE : p * STRIDE + PASSAGE])):
                best[self.owner[segment]].append((score, p))
        out = []
        whole = b" %b " % b" ".join(w) if self.short and best else b""
        for at, hits in best.items():
            item = self.items[at]
            if self.short:
                if b" %b " % b" ".join(item.words) in whole:
                    out.append((item.item_id, max(hits)[0], 1.0, 1.0))
                continue
            reach = 2 * len(item.words) + PASSAGE
            found = max((item.overlaps(w[max(0, p * STRIDE - reach) : p * STRIDE + reach]) for _, p in hits), default=(0, 0, 0))
            if found[0] >= OVERLAP or (found[1] >= OVERLAP and found[2] >= 0.5):
                out.append((item.item_id, max(hits)[0], found[1], found[2]))
        return out


def shards_of(items: DataFrame, id_col: str, text_col: str) -> Iterator[list[Index]]:
    """Indexes of items of at most INDEX_BYTES of text (one item at least), one shard at a time on the driver."""

    def indexes(rows: list[tuple[int | None, str]]) -> list[Index]:
        return [x for x in (Index(rows), Index(rows, True)) if x.items]

    held, size = [], 0
    for row in items.select(F.col(id_col).cast("long"), F.col(text_col)).where(F.col(text_col).isNotNull()).toLocalIterator():
        if held and size + len(row[1]) > INDEX_BYTES:
            yield indexes(held)
            held, size = [], 0
        held.append((row[0], row[1]))
        size += len(row[1])
    if held:
        yield indexes(held)


def contaminated(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id: str = "item_id", item_text: str = "text") -> DataFrame:
    """One row for each document and item that it contains."""
    spark, parts = docs.sparkSession, []
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    for shard in shards_of(items, item_id, item_text):
        shared = spark.sparkContext.broadcast(shard)

        def judge(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                texts = zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)
                rows = [(doc, *hit) for doc, text in texts for index in shared.value for hit in index.judge(text)]
                a, b, s, q, r = zip(*rows, strict=True) if rows else ([],) * 5
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), *(pa.array(x, pa.float64()) for x in (s, q, r))], ["doc_id", "item_id", "score", "question_overlap", "answer_overlap"])

        parts.append(texts.mapInArrow(tidy(judge), RESULT))
    out = parts[0] if parts else spark.createDataFrame([], RESULT)
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def clean(docs: DataFrame, items: DataFrame, text_col: str = "text") -> DataFrame:
    """docs without those that contain a test item: a filter in place, so that nothing moves and ids don't matter."""
    spark, at = docs.sparkSession, docs.columns.index(text_col)
    for shard in shards_of(items, "item_id", "text"):
        shared = spark.sparkContext.broadcast(shard)

        def keep(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                yield batch.filter(pa.array([not any(index.judge(t) for index in shared.value) for t in batch.column(at).to_pylist()], pa.bool_()))

        docs = docs.mapInArrow(tidy(keep), docs.schema)
    return docs
