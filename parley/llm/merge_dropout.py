"""SentencePiece BPE encoding with seeded merge-dropout, and lossless decoding.

Encoding is the usual agenda: adjacent symbols that form a piece wait in a queue by score (ties: leftmost first). When a
candidate's turn comes it is skipped for good if a keyed hash of it falls below the dropout rate, which leaves a coarser
or finer segmentation into pieces that merges can reach. The key is (seed, document, number of the word, number of the
turn), so every occurrence of a word draws its own skips, equal on every run and machine. A worker remembers what each
word becomes without skips and how many turns that takes; an occurrence that skips one of them has an agenda of its own,
and the agendas of thousands of words run side by side, a turn of each at a time. Rate 0 is plain BPE.

No piece holds anything before a blank mark, so words (blank marks and what follows) are encoded apart; characters
outside the vocabulary become byte pieces, and so does a blank mark that the text itself holds, which keeps decoding
lossless. Decoding joins the pieces' bytes, turns blank marks into blanks and drops the leading one.

Defined results: null and empty texts have no ids and decode to the empty text; repeated rows with equal ids get equal
ids of pieces; equal scores go to the leftmost candidate; very long texts and words are encoded whole; an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import heapq
import re
import zlib
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from parley.llm.common import tidy

MARK = "▁"
RATE = 0.1
SEED = 20
#: Words that one worker remembers before it starts anew.
MEMORY = 250_000
#: Words whose agendas run side by side.
ABREAST = 8192
ENCODED = "doc_id long, ids array<int>, lossless boolean"
DIGEST = "doc_id long, n_tokens long, ids_crc32 long, n_chars long, lossless boolean"

_ALL = (1 << 64) - 1
_WORD = re.compile(f"{MARK}+[^{MARK}\n]*|[^{MARK}\n]+|\n+")


_KEYS = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93)]
#: Longer words are encoded one by one.
LONGEST = 24


class Pairs:
    """Which two pieces join to a third: an open-addressing table that whole arrays look up."""

    def __init__(self, piece: dict[str, tuple[float, int]]):
        rows = [(piece[p[:k]][1], piece[p[k:]][1], score, i) for p, (score, i) in piece.items() for k in range(1, len(p)) if p[:k] in piece and p[k:] in piece]
        self.shift = np.uint64(64 - max(4, (8 * len(rows)).bit_length()))
        size = 1 << (64 - int(self.shift))
        self.key, self.rank, self.id = np.full(size + 64, -1, np.int64), np.full(size + 64, np.inf, np.float32), np.full(size + 64, -1, np.int32)
        for a, b, score, i in rows:
            key = a << 20 | b
            at = int((key * 0x9E3779B97F4A7C15 & _ALL) >> int(self.shift))
            while self.key[at] != -1:
                at += 1
            self.key[at], self.rank[at], self.id[at] = key, score, i

    def find(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank (infinite: none) and id of what each pair joins to; negative symbols never join."""
        key = a.astype(np.int64) << 20 | b
        with np.errstate(over="ignore"):
            at = ((key.view(np.uint64) * _KEYS[0]) >> self.shift).astype(np.int64)
        there = self.key[at]
        hit = (there == key) & (a >= 0) & (b >= 0)
        rank, merged = np.where(hit, self.rank[at], np.float32(np.inf)), self.id[at]
        todo = np.nonzero((there != -1) & (there != key) & (a >= 0) & (b >= 0))[0]
        while len(todo):  # the place was taken by another pair
            at[todo] += 1
            there = self.key[at[todo]]
            found = todo[there == key[todo]]
            rank[found], merged[found] = self.rank[at[found]], self.id[at[found]]
            todo = todo[(there != -1) & (there != key[todo])]
        return rank, merged


class Pool:
    """An array that grows at its end."""

    def __init__(self, kind: type):
        self.kept, self.size = np.zeros(1024, kind), 0

    def add(self, more: np.ndarray) -> int:
        """Where it begins."""
        at, self.size = self.size, self.size + len(more)
        if self.size > len(self.kept):
            self.kept = np.append(self.kept[:at], np.zeros(2 * self.size - at, self.kept.dtype))
        self.kept[at : self.size] = more
        return at


def spread(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The places starts[k], starts[k] + 1, ... of each k, one after the other."""
    return np.repeat(starts - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())


@lru_cache(maxsize=4)
def codec(path: str, rate: float = RATE, seed: int = SEED) -> Codec:
    return Codec(path, rate, seed)


class Codec:
    def __init__(self, path: str, rate: float = RATE, seed: int = SEED):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        special = {i for i in range(n) if sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i)}
        self.piece = {sp.id_to_piece(i): (-sp.get_score(i), i) for i in range(n) if i not in special}
        self.byte = [sp.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
        self.raw = [b"" if i in special else sp.id_to_piece(i).replace(MARK, " ").encode() for i in range(n)]
        for b, i in enumerate(self.byte):
            self.raw[i] = bytes([b])
        self.limit, self.seed = int(rate * (1 << 64)), seed & _ALL
        self.pairs = Pairs(self.piece)
        single = {ord(p): i for p, (_, i) in self.piece.items() if len(p) == 1}
        self.of_char = np.full(0x110000, -1, np.int32)
        self.of_char[list(single)] = list(single.values())
        if any(MARK in p.lstrip(MARK) for p in self.piece) or any("\n" in p for p in self.piece if p != "\n"):
            raise ValueError("this vocabulary merges over blanks")
        self.forget()

    def segment(self, word: str, draw: int = 0) -> tuple[int, ...]:
        """Ids of one word; draw: the key of its skips."""
        piece, n = self.piece, len(word)
        if not self.limit and word in piece and n == 1:
            return (piece[word][1],)
        turn = 0
        sym: list[str | None] = list(word)
        before, after = list(range(-1, n - 1)), list(range(1, n + 1))
        queue = []
        for i in range(n - 1):
            if found := piece.get(word[i : i + 2]):
                queue.append((found[0], i, i + 1, i + 2))
        heapq.heapify(queue)
        while queue:
            _, i, mid, end = heapq.heappop(queue)
            left = sym[i]
            if left is None or i + len(left) != mid or mid >= n or sym[mid] is None or mid + len(sym[mid]) != end:
                continue  # one of them has changed meanwhile
            if self.limit:
                h = draw * 0x165667B19E3779F9 + turn * 0xC2B2AE3D27D4EB4F & _ALL
                turn += 1
                h = (h ^ h >> 31) * 0xD6E8FEB86659FD93 & _ALL
                h = (h ^ h >> 29) * 0x9E3779B97F4A7C15 & _ALL
                if h < self.limit:
                    continue
            sym[i], sym[mid] = left + sym[mid], None
            after[i] = after[mid]
            if after[mid] < n:
                before[after[mid]] = i
                nxt = after[mid]
                if found := piece.get(sym[i] + sym[nxt]):
                    heapq.heappush(queue, (found[0], i, nxt, nxt + len(sym[nxt])))
            if before[i] >= 0:
                p = before[i]
                if found := piece.get(sym[p] + sym[i]):
                    heapq.heappush(queue, (found[0], p, i, end))
        out: list[int] = []
        for s in sym:
            if s is not None:
                if found := piece.get(s):
                    out.append(found[1])
                else:
                    out += [self.byte[b] for b in s.encode("utf-8", "surrogatepass")]
        return tuple(out)

    def skipped(self, draws: np.ndarray, turns: np.ndarray | int) -> np.ndarray:
        """Which turns are skipped."""
        with np.errstate(over="ignore"):
            h = draws * _KEYS[2] + np.asarray(turns, np.uint64) * _KEYS[1]
            h = (h ^ (h >> np.uint64(31))) * _KEYS[3]
            h = (h ^ (h >> np.uint64(29))) * _KEYS[0]
        return h < np.uint64(self.limit)

    def segment_all(self, words: list[str], draws: np.ndarray) -> list[list[int]]:
        """Ids of many words of known characters, as segment() gives them."""
        size = np.fromiter(map(len, words), np.int64, len(words))
        code = self.of_char[np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32)]
        flat, count, _ = self._agendas(code, np.cumsum(size) - size, size, draws)
        return [x.tolist() for x in np.split(flat, np.cumsum(count)[:-1])] if len(words) else []

    def _agendas(self, code: np.ndarray, begins: np.ndarray, size: np.ndarray, draws: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of words code[begins : begins + size]: their ids one after the other, how many each has, and the turns taken.

        draws: the keys of their skips; None: no turn is skipped. Words of like length go side by side.
        """
        n = len(size)
        order = np.argsort(size, kind="stable")
        count, turns = np.zeros(n, np.int64), np.zeros(n, np.int64)
        ids, whose = [np.empty(0, np.int32)], [np.empty(0, np.int64)]
        for at in range(0, n, ABREAST):
            part = order[at : at + ABREAST]
            top = int(size[part[-1]])
            inside = np.arange(top + 1)[None, :] < size[part][:, None]
            sym = np.full((len(part), top + 1), -2, np.int32)
            sym[inside] = code[spread(begins[part], size[part])]
            left, took = self._agenda(sym, size[part], None if draws is None else draws[part])
            turns[part], count[part] = took, (left != -2).sum(axis=1)
            ids.append(left[left != -2])
            whose.append(part)
        flat, place = np.concatenate(ids), np.concatenate(whose)
        out, starts = np.empty(len(flat), np.int32), np.cumsum(count) - count
        out[spread(starts[place], count[place])] = flat
        return out, count, turns

    def _agenda(self, sym: np.ndarray, size: np.ndarray, draws: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
        """Symbols left of each row (-2: merged away), and turns. The last column is no symbol: what has no neighbour points there."""
        n, end = len(sym), sym.shape[1] - 1
        turns = np.zeros(n, np.int64)
        if end < 2:
            return sym, turns
        after = np.minimum(np.arange(1, end + 2)[None, :], np.where(np.arange(end + 1)[None, :] + 1 < size[:, None], end + 1, end)).astype(np.int32)
        after[:, end] = end
        prior = np.tile(np.append(np.arange(-1, end - 1), end).astype(np.int32), (n, 1))
        prior[:, 0] = end
        rank, merged = self.pairs.find(sym[:, :-1].ravel(), sym[:, 1:].ravel())
        rank = np.hstack([rank.reshape(n, end), np.full((n, 1), np.inf, np.float32)])
        merged = np.hstack([merged.reshape(n, end), np.full((n, 1), -1, np.int32)])
        whole, live, turn = sym, np.arange(n), 0
        while True:
            best = rank.argmin(axis=1)
            row = np.nonzero(rank[np.arange(len(rank)), best] < np.inf)[0]
            if not len(row):
                break
            turns[live[row]] = turn + 1
            if 2 * len(row) < len(live):  # most are done
                if sym is not whole:
                    whole[live] = sym
                sym, after, prior, rank, merged, live, best = sym[row], after[row], prior[row], rank[row], merged[row], live[row], best[row]
                row = np.arange(len(live))
            at = best[row]
            if draws is not None:
                skip = self.skipped(draws[live[row]], turn)
                rank[row[skip], at[skip]] = np.inf
                row, at = row[~skip], at[~skip]
            turn += 1
            gone, before, new = after[row, at], prior[row, at], merged[row, at]
            follows = after[row, gone]
            sym[row, at], sym[row, gone] = new, -2
            rank[row, gone] = np.inf
            after[row, at], prior[row, follows] = follows, at
            prior[row, end] = end
            rank[row, at], merged[row, at] = self.pairs.find(new, sym[row, follows])
            rank[row, before], merged[row, before] = self.pairs.find(sym[row, before], new)
        if sym is not whole:
            whole[live] = sym
        return whole, turns

    def words(self, text: str) -> list[str]:
        """Words of a text without literal blank marks, before which a mark has been put."""
        if "  " in text or "\n" in text or text[:1] == " " or text[-1:] == " ":
            return _WORD.findall(MARK + text.replace(" ", MARK))
        return [MARK + w for w in text.split(" ")]

    def _split(self, text: str | None, doc_id: int | None) -> tuple[list[str | None], np.ndarray]:
        """A text's words (None: a literal blank mark) and the keys of their skips."""
        if not text:
            return [], np.zeros(0, np.uint64)
        parts = text.split(MARK)
        words: list[str | None] = list(self.words(parts[0]))
        for p in parts[1:]:
            words.append(None)
            words += _WORD.findall(p.replace(" ", MARK))
        if not self.limit:
            return words, np.zeros(len(words), np.uint64)
        with np.errstate(over="ignore"):
            h = (np.arange(len(words), dtype=np.uint64) + np.uint64(xxhash.xxh64_intdigest(str(doc_id).encode(), self.seed))) * _KEYS[0]
            return words, (h ^ (h >> np.uint64(29))) * _KEYS[3]

    def forget(self) -> None:
        self.root: dict[str | None, int] = {}
        self.code, self.ids = Pool(np.int32), Pool(np.int32)  # characters and plain ids of the words met
        self.rows = {name: Pool(np.int64) for name in ("code_at", "code_n", "ids_at", "ids_n", "turns")}
        self._remember([None], np.empty(0, np.int32), np.zeros(1, np.int64), np.array([self.byte[b] for b in MARK.encode()], np.int32), np.array([len(MARK.encode())]), np.zeros(1, np.int64))

    def _remember(self, words: list, code: np.ndarray, code_n: np.ndarray, ids: np.ndarray, ids_n: np.ndarray, turns: np.ndarray) -> None:
        first = self.rows["turns"].size
        self.root.update(zip(words, range(first, first + len(words)), strict=True))
        own = {"code_at": self.code.add(code) + np.cumsum(code_n) - code_n, "code_n": code_n, "ids_at": self.ids.add(ids) + np.cumsum(ids_n) - ids_n, "ids_n": ids_n, "turns": turns}
        for name, column in own.items():
            self.rows[name].add(column)

    def _meet(self, words: list[str]) -> None:
        """New words; those too long or with characters outside the vocabulary are marked by -1 turns and encoded one by one."""
        size = np.fromiter(map(len, words), np.int64, len(words))
        code = self.of_char[np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32)]
        begins = np.cumsum(size) - size
        odd = (np.add.reduceat(code < 0, begins) > 0) | (size > LONGEST)
        names = [words[k] for k in np.nonzero(~odd)[0].tolist()]
        own = code[spread(begins[~odd], size[~odd])]
        flat, count, turns = self._agendas(own, np.cumsum(size[~odd]) - size[~odd], size[~odd], None)
        self._remember(names, own, size[~odd], flat, count, turns)
        names = [words[k] for k in np.nonzero(odd)[0].tolist()]
        zero = np.zeros(len(names), np.int64)
        self._remember(names, np.empty(0, np.int32), zero, np.empty(0, np.int32), zero, zero - 1)

    def encode_all(self, texts: list[str | None], doc_ids: list[int | None]) -> list[np.ndarray]:
        if len(self.root) > MEMORY:
            self.forget()
        split = [self._split(t, d) for t, d in zip(texts, doc_ids, strict=True)]
        flat = [w for words, _ in split for w in words]
        keys = np.concatenate([np.zeros(0, np.uint64), *(k for _, k in split)])
        if new := list(set(flat).difference(self.root)):
            self._meet(new)
        at = np.fromiter(map(self.root.__getitem__, flat), np.int64, len(flat))
        column = {name: pool.kept[at] for name, pool in self.rows.items()}
        count, source = column["ids_n"], column["ids_at"]
        pieces = self.ids.kept[: self.ids.size]
        if self.limit and len(own := np.nonzero(self._skips(keys, column["turns"]))[0]):
            some, n, _ = self._agendas(self.code.kept, column["code_at"][own], column["code_n"][own], keys[own])
            count[own], source[own] = n, len(pieces) + np.cumsum(n) - n
            pieces = np.concatenate([pieces, some])
        if len(odd := np.nonzero(column["turns"] < 0)[0]):
            each = [self.segment(flat[k], int(keys[k])) for k in odd.tolist()]
            n = np.fromiter(map(len, each), np.int64, len(each))
            count[odd], source[odd] = n, len(pieces) + np.cumsum(n) - n
            pieces = np.concatenate([pieces, np.fromiter((i for ids in each for i in ids), np.int32, int(n.sum()))])
        out = pieces[spread(source, count)].astype("<i4")
        words = np.cumsum([0, *(len(w) for w, _ in split)])
        edges = np.append(0, np.cumsum(count))[words]
        return [out[a:b] for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True)]

    def _skips(self, keys: np.ndarray, turns: np.ndarray) -> np.ndarray:
        """Which occurrences skip one of the turns that their word takes without skips."""
        met, looking, turn = np.zeros(len(keys), bool), np.nonzero(turns > 0)[0], 0
        while len(looking):
            skip = self.skipped(keys[looking], turn)
            met[looking[skip]] = True
            turn += 1
            looking = looking[~skip & (turns[looking] > turn)]
        return met

    def encode(self, text: str | None, doc_id: int | None = 0) -> list[int]:
        return self.encode_all([text], [doc_id])[0].tolist()

    def decode(self, ids: list[int]) -> str:
        return b"".join(map(self.raw.__getitem__, ids))[1:].decode("utf-8", "surrogatepass")


def _runner(path: str, rate: float, seed: int, digest: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path, rate, seed)
        for batch in batches:
            docs, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for at in range(0, len(docs), 128):
                part, key = texts[at : at + 128], batch.column(0).slice(at, 128)
                ids = own.encode_all(part, docs[at : at + 128])
                size = [len(x) for x in ids]
                back = [own.decode(x.tolist()) for x in ids]
                same = pa.array([b == (t or "") for b, t in zip(back, part, strict=True)], pa.bool_())
                if digest:
                    crc = [zlib.crc32(x) for x in ids]
                    yield pa.RecordBatch.from_arrays([key, pa.array(size, pa.int64()), pa.array(crc, pa.int64()), pa.array([len(b) for b in back], pa.int64()), same], ["doc_id", "n_tokens", "ids_crc32", "n_chars", "lossless"])
                else:
                    lists = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *size]), pa.int32()), pa.array(np.concatenate([np.empty(0, "<i4"), *ids]), pa.int32()))
                    yield pa.RecordBatch.from_arrays([key, lists, same], ["doc_id", "ids", "lossless"])

    return tidy(run, lambda: codec(path, rate, seed).forget())


def _two(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))


def encode(df: DataFrame, path: str, rate: float = RATE, seed: int = SEED, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids, lossless): each text's ids, and whether they decode to it."""
    return _two(df, id_col, text_col).mapInArrow(_runner(path, rate, seed, False), ENCODED)


def decode(df: DataFrame, path: str) -> DataFrame:
    """(doc_id, text) of (doc_id, ids)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([own.decode(x or []) for x in batch.column(1).to_pylist()], pa.string())], ["doc_id", "text"])

    return df.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def round_trips(df: DataFrame, path: str, rate: float = RATE, seed: int = SEED, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids_crc32, n_chars, lossless): each text encoded, decoded and compared."""
    return _two(df, id_col, text_col).mapInArrow(_runner(path, rate, seed, True), DIGEST)
