"""Fuzzy duplicate lines by MinHash: banding, exact Jaccard verification, distributed union-find.

A line of a document is normalised (lower case, blanks collapsed); its set of 8-character shingles is hashed once and
dealt over 60 bins, whose minima form the signature (empty bins borrow from the next full one). Twelve bands of five
bins bring together lines of Jaccard 0.8 with odds of 99 % or more; whatever meets in a band is compared exactly on
whole lines before it counts as a link. Of each component the first line, by doc_id, text and place, stays.

Lines from SHINGLE normalised characters on are compared by shingles, shorter ones by their whole text; blank lines are
none. ``line_components`` groups them all; ``dedup_documents`` leaves lines below its bound (MIN_CHARS unless told
otherwise) in their texts: headings, list marks and one-word answers aren't copies there.

A row is known by its id and its text's hash (its mark), so that rows which share an id keep their own lines.
Defined results: null and empty texts have no line to remove; rows without an id stay whole and make no line go; of
several rows with equal id and equal text one stays, if it has a line to compare; of equal lines the first place stays,
also within one text; very long texts and lines are compared whole; an empty table gives an empty result; other columns
pass through ``dedup_documents`` untouched. Lines and shingles are named by 64-bit hashes (n distinct lines: n*n/2**65
expected false identities).
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from parley.llm.common import Tables, free_name, one_of_each, tidy
from parley.llm.components import components

SHINGLE = 8
MIN_CHARS = 20
THRESHOLD = 0.8
BANDS, ROWS = 12, 5
BINS = BANDS * ROWS
#: Lines of one band bucket that one task compares; larger buckets are cut into chunks, and each pair of chunks is a group.
CHUNK = 512
#: Buckets of so few lines are compared pair by pair; in larger ones bitmaps of the lines rule most pairs out first.
FEW = 8
#: Lines that a task remembers having signed.
SIGNED = 200_000
#: Pairs of band key and line that a task puts together before they move.
PAIRS = 1 << 21
LINES = "doc_id long, mark long, line_no int, lid long, head boolean, fresh boolean, bands array<long>"
MET = "least long, i int, j int, lid long, bucket long, side int"

_A, _B, _C, _M = (np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93))


def normal(line: str) -> str:
    return " ".join(line.lower().split())


#: What a lower-case text must not hold for its lines to be normal as they stand (nor may it begin or end with a blank).
_UNEVEN = ("  ", " \n", "\n ", *(chr(c) for c in range(0x3001) if chr(c).isspace() and chr(c) not in " \n"))


def normal_lines(text: str) -> list[str]:
    """normal() of every line of a text."""
    low = text.lower()
    lines = low.split("\n")
    if low[:1] == " " or low[-1:] == " " or any(x in low for x in _UNEVEN):
        return [" ".join(x.split()) for x in lines]
    return lines


def line_id(line: str) -> int:
    x = xxhash.xxh64_intdigest(line.encode("utf-8", "surrogatepass"))
    return x - (1 << 64) if x >> 63 else x


def shingle_hashes(lines: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of every 8-character shingle of the lines, and where each line's begin. Lines have SHINGLE or more."""
    code = np.frombuffer("".join(lines).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    with np.errstate(over="ignore"):
        h = code * _A
        h = h[:-1] + ((code[1:] * _B) ^ (h[:-1] >> np.uint64(29)))
        h = (h ^ (h >> np.uint64(32))) * _A
        h = h[:-2] + ((h[2:] * _B) ^ (h[:-2] >> np.uint64(31)))
        h = (h ^ (h >> np.uint64(29))) * _C
        h = h[:-4] + ((h[4:] * _B) ^ (h[:-4] >> np.uint64(30)))
        h = (h ^ (h >> np.uint64(32))) * _M
        h ^= h >> np.uint64(29)
    size = np.fromiter(map(len, lines), np.int64, len(lines))
    begins = np.cumsum(size) - size
    count = size - (SHINGLE - 1)
    starts = np.cumsum(count) - count
    return h[np.repeat(begins - starts, count) + np.arange(count.sum())], starts


def signatures(lines: list[str]) -> np.ndarray:
    """One row of BANDS band hashes for each line."""
    h, starts = shingle_hashes(lines)
    n, empty = len(lines), np.uint64(0xFFFFFFFFFFFFFFFF)
    sig = np.full(n * BINS, empty)
    line = np.repeat(np.arange(n), np.diff(np.append(starts, len(h))))
    np.minimum.at(sig, line * BINS + ((h >> np.uint64(40)) * np.uint64(BINS) >> np.uint64(24)).astype(np.int64), h & np.uint64(0xFFFFFFFFFF))
    sig = sig.reshape(n, BINS)
    for _ in range(BINS):
        gap = sig == empty
        if not gap.any():
            break
        nxt = np.roll(sig, -1, axis=1)
        with np.errstate(over="ignore"):
            sig = np.where(gap & (nxt != empty), nxt + _A, sig)  # the distance borrowed over is part of the value
    with np.errstate(over="ignore"):
        out = np.zeros((n, BANDS), np.uint64)
        for r in range(ROWS):
            out = (out ^ sig[:, r::ROWS]) * _M
            out ^= out >> np.uint64(31)
        out = (out + np.arange(BANDS, dtype=np.uint64)[None, :]) * _C
    return out


def _line_rows(least: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    least = max(1, least)  # a blank line is none

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        signed: set[int] = set()
        for batch in batches:
            rows, chars = [], 0
            for doc, mark, text in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                head = True
                for at, line in enumerate(normal_lines(text or "")):
                    if len(line) >= least:
                        rows.append((doc, mark, at, head, line))
                        head, chars = False, chars + len(line)
                    if chars > 100_000:  # keeps the arrays within the processor's caches
                        yield _line_batch(rows, signed)
                        rows, chars = [], 0
            if rows:
                yield _line_batch(rows, signed)

    return run


def _line_batch(rows: list[tuple[int, int, int, bool, str]], signed: set[int]) -> pa.RecordBatch:
    docs, marks, places, heads, lines = zip(*rows, strict=True)
    lids = list(map(line_id, lines))
    if len(signed) > SIGNED:
        signed.clear()
    fresh = np.zeros(len(lines), bool)  # the first of its kind in this task; shorter lines have no bands: their id is all they share
    for k, (lid, line) in enumerate(zip(lids, lines, strict=True)):
        if len(line) >= SHINGLE and lid not in signed:
            signed.add(lid)
            fresh[k] = True
    bands = signatures([x for x, f in zip(lines, fresh.tolist(), strict=True) if f]).view(np.int64) if fresh.any() else np.empty((0, BANDS), np.int64)
    nested = pa.ListArray.from_arrays(np.append(0, np.cumsum(fresh * BANDS)).astype(np.int32), bands.ravel())
    columns = [pa.array(docs, pa.int64()), pa.array(marks, pa.int64()), pa.array(places, pa.int32()), pa.array(lids, pa.int64()), pa.array(heads, pa.bool_()), pa.array(fresh), nested]
    return pa.RecordBatch.from_arrays(columns, ["doc_id", "mark", "line_no", "lid", "head", "fresh", "bands"])


def _marked(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return df.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text_col).alias("mark"), F.col(text_col).alias("text"))


def line_rows(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: int = 1) -> DataFrame:
    """One row for each line of at least so many normalised characters, of rows with an id.

    head marks a row's first such line; fresh marks lines that carry bands, at least one for each line of SHINGLE characters.
    """
    return _marked(df, id_col, text_col).mapInArrow(tidy(_line_rows(least)), LINES)


def _cells(bits: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Rows (lid, bands) as pairs of band key and line id, put together by the first bits of the key: a row a cell, not a row a pair."""

    def dealt(held: list[tuple[np.ndarray, np.ndarray]]) -> pa.RecordBatch:
        k, x = (np.concatenate(c) for c in zip(*held, strict=True))
        order = np.argsort(k, kind="stable")
        k, x = k[order], x[order]
        cell = (k >> np.uint64(64 - bits)).astype(np.int32)
        starts = np.nonzero(np.append(True, cell[1:] != cell[:-1]))[0]
        edges = pa.py_buffer((np.append(starts, len(k)) * 8).astype(np.int32).tobytes())
        blobs = [pa.Array.from_buffers(pa.binary(), len(starts), [None, edges, pa.py_buffer(c.tobytes())]) for c in (k, x)]
        return pa.RecordBatch.from_arrays([pa.array(cell[starts]), *blobs], ["cell", "keys", "lids"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, pairs = [], 0
        for batch in batches:
            if batch.num_rows:
                held.append((batch.column(1).flatten().to_numpy().view(np.uint64), np.repeat(batch.column(0).to_numpy(), BANDS)))
                pairs += len(held[-1][0])
                if pairs > PAIRS:
                    yield dealt(held)
                    held, pairs = [], 0
        if held:
            yield dealt(held)

    return run


def _meetings(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (cell, keys, lids) sorted by cell: buckets of two and more, named by what they hold, cut into pairs of chunks.

    least is the bucket's smallest line id, by which buckets are dealt: those that share lines mostly share it, and at
    most one bucket of each band has it, so that a task which gets them all compares each line's shingles once.
    """

    def rows(least, i, j, x: np.ndarray, name, side) -> pa.RecordBatch:
        full = lambda v, kind: pa.array(np.broadcast_to(np.asarray(v, kind), len(x)))
        return pa.RecordBatch.from_arrays([full(least, np.int64), full(i, np.int32), full(j, np.int32), pa.array(x), full(name, np.int64), full(side, np.int32)], ["least", "i", "j", "lid", "bucket", "side"])

    def out(held: list[tuple[bytes, bytes]]) -> Iterator[pa.RecordBatch]:
        k, x = (np.frombuffer(b"".join(c), np.int64) for c in zip(*held, strict=True))
        order = np.lexsort((x, k))
        k, x = k[order], x[order]
        new = np.ones(len(k), bool)
        new[1:] = (k[1:] != k[:-1]) | (x[1:] != x[:-1])
        k, x = k[new], x[new]
        starts = np.nonzero(np.append(True, k[1:] != k[:-1]))[0]
        size = np.diff(np.append(starts, len(k)))
        run = np.repeat(np.arange(len(starts)), size)
        with np.errstate(over="ignore"):
            mixed = (x.view(np.uint64) ^ (x.view(np.uint64) >> np.uint64(32))) * _M
            name = np.add.reduceat(mixed * (mixed >> np.uint64(17) | np.uint64(1)), starts).view(np.int64)
        small = (size[run] > 1) & (size[run] <= CHUNK)
        if small.any():
            yield rows(x[starts][run[small]], 0, 0, x[small], name[run[small]], 0)
        for r in np.nonzero(size > CHUNK)[0]:
            own = x[starts[r] : starts[r] + size[r]]
            parts = -(-len(own) // CHUNK)
            for one in range(parts):
                part = own[one * CHUNK : (one + 1) * CHUNK]
                for other in range(parts):
                    yield rows(own[0], min(one, other), max(one, other), part, name[r], one)

    held, size, at = [], 0, None
    for batch in batches:
        for cell, k, x in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if cell != at and size > 1 << 20:
                yield from out(held)
                held, size = [], 0
            at = cell
            held.append((k, x))
            size += len(k)
    if held:
        yield from out(held)


def _bitmaps(hashes: list[np.ndarray]) -> np.ndarray:
    """A row of bits for each line, set where its shingles' hashes fall."""
    size = np.fromiter(map(len, hashes), np.int64, len(hashes))
    width = 1 << min(14, max(8, (4 * int(size.max()) - 1).bit_length()))
    bits = np.zeros((len(size), width), np.uint8)
    bits[np.repeat(np.arange(len(size)), size), (np.concatenate(hashes) >> np.uint64(20)).astype(np.int64) % width] = 1
    return np.packbits(bits, axis=1).view(np.uint64)


class _Verifier:
    """Links of one group of buckets: lines of Jaccard `threshold` or more, skipping pairs that are already connected."""

    def __init__(self, lids: list[int], hashes: list[np.ndarray], threshold: float):
        self.lids, self.hashes, self.threshold = lids, hashes, threshold
        self.sets: list[frozenset | None] = [None] * len(lids)
        self.root = np.arange(len(lids))
        self.a: list[int] = []
        self.b: list[int] = []

    def shingles(self, k: int) -> frozenset:
        if self.sets[k] is None:
            self.sets[k] = frozenset(self.hashes[k].tolist())
        return self.sets[k]

    def compare(self, k: int, o: int) -> bool:
        """Whether two lines are linked; if so, their components become one."""
        own, other = self.shingles(k), self.shingles(o)
        n, m = len(own), len(other)
        if min(n, m) < self.threshold * max(n, m) or (c := len(own & other)) < self.threshold * (n + m - c):
            return False
        self.a.append(self.lids[k])
        self.b.append(self.lids[o])
        self.root[self.root == self.root[o]] = self.root[k]
        return True

    def bucket(self, members: list[tuple[int, int]], across: bool) -> None:
        """members: places of lines and their sides; across: only pairs of different sides are new."""
        if len(members) <= FEW:
            for at, (k, side) in enumerate(members):
                for o, other in members[:at]:
                    if self.root[k] != self.root[o] and not (across and side == other):
                        self.compare(k, o)
            return
        places, sides = np.array(members, np.int64).T
        size = np.array([len(self.shingles(k)) for k in places.tolist()])
        order = np.argsort(size, kind="stable")
        places, sides, size = places[order], sides[order], size[order]
        marks = _bitmaps([self.hashes[k] for k in places.tolist()])
        ones = np.bitwise_count(marks).sum(axis=1, dtype=np.int64)
        share = self.threshold / (1 + self.threshold)
        for at, k in enumerate(places.tolist()):
            # bits that only one of two lines sets are shingles that only it has: what is ruled out here can't be a link
            common = np.bitwise_count(marks[at] & marks[:at]).sum(axis=1, dtype=np.int64)
            need = share * (size[at] + size[:at]) - 1e-9
            near = (ones[at] - common <= size[at] - need) & (ones[:at] - common <= size[:at] - need)
            if across:
                near &= sides[:at] != sides[at]
            while len(left := np.nonzero(near & (self.root[places[:at]] != self.root[k]))[0]):
                o = left[-1]  # the newest: closest in size
                near[o] = False
                self.compare(k, int(places[o]))


def _linked(group: list[tuple[int, list[dict], str]], hashes: list[np.ndarray], across: bool, threshold: float = THRESHOLD) -> tuple[list[int], list[int]]:
    """Links of the buckets that a group of lines (line id, its buckets, text) makes up."""
    buckets: dict[int, list[tuple[int, int]]] = defaultdict(list)
    for k, (_, own, _) in enumerate(group):
        for b in own:
            buckets[b["bucket"]].append((k, b["side"]))
    work = _Verifier([lid for lid, _, _ in group], hashes, threshold)
    for members in buckets.values():
        work.bucket(members, across)
    return work.a, work.b


def _links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (least, i, j, lid, buckets, line) sorted by the first three."""
    name, groups, chars = None, [], 0

    def flush() -> pa.RecordBatch:
        a, b = [], []
        lines = [line for _, g in groups for _, _, line in g]
        h, starts = shingle_hashes(lines) if lines else (np.empty(0, np.uint64), np.empty(0, np.int64))
        ends, at = [*starts[1:].tolist(), len(h)], 0
        for across, g in groups:
            own = [h[starts[k] : ends[k]] for k in range(at, at + len(g))]
            at += len(g)
            if len(g) > 1:
                x, y = _linked(g, own, across)
                a += x
                b += y
        return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    for batch in batches:
        for least, i, j, lid, buckets, line in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if (least, i, j) != name:
                if chars > 200_000:
                    yield flush()
                    groups, chars = [], 0
                name = (least, i, j)
                groups.append((i != j, []))
            groups[-1][1].append((lid, buckets, line))
            chars += len(line)
    yield flush()


def _texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (text, wanted: places and ids of lines): those lines, normalised."""
    for batch in batches:
        lids, lines = [], []
        for text, wanted in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            own = text.split("\n")
            for w in wanted:
                lids.append(w["lid"])
                lines.append(normal(own[w["line_no"]]))
        yield pa.RecordBatch.from_arrays([pa.array(lids, pa.int64()), pa.array(lines, pa.string())], ["lid", "line"])


def line_components(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: int = 1) -> DataFrame:
    """(doc_id, mark, line_no, lid, head, root, first_doc, first_line, keep) for each line of at least so many normalised characters.

    root names its component within a run, (first_doc, first_line) is the component's first line, which keep marks. Rows
    with equal id and text give equal rows here: whoever takes lines out must leave the kept ones in one of them.
    """
    docs, tables = _marked(df, id_col, text_col), Tables(df.sparkSession)
    rows = tables.keep(line_rows(df, id_col, text_col, least), "lines")
    fresh = rows.where("fresh")
    bits = max(12, (16 * int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")) - 1).bit_length())  # so that a cell stays small where partitions do
    cells = fresh.select("lid", "bands").mapInArrow(tidy(_cells(bits)), "cell int, keys binary, lids binary").repartition("cell").sortWithinPartitions("cell")
    grouped = cells.mapInArrow(tidy(_meetings), MET).groupBy("least", "i", "j", "lid").agg(F.collect_set(F.struct("bucket", "side")).alias("buckets"))
    met = tables.keep(grouped, "met")
    # the text of a candidate comes from one document that has it, so that only candidates' lines move; a task names a line once,
    # so that no line weighs more here than there are tasks
    wanted = fresh.select("lid", "doc_id", "mark", "line_no").join(met.select("lid").distinct(), "lid", "left_semi").groupBy("lid").agg(F.min(F.struct("doc_id", "mark", "line_no")).alias("at"))
    by_doc = wanted.groupBy("at.doc_id", "at.mark").agg(F.collect_list(F.struct(F.col("at.line_no").alias("line_no"), "lid")).alias("wanted"))
    texts = docs.join(by_doc, ["doc_id", "mark"]).select("text", "wanted").mapInArrow(tidy(_texts), "lid long, line string").dropDuplicates(["lid"])
    groups = met.join(texts, "lid").select("least", "i", "j", "lid", "buckets", "line").repartition("least", "i", "j").sortWithinPartitions("least", "i", "j")
    moved = components(groups.mapInArrow(tidy(_links), "a long, b long"), tables)
    named = rows.select("doc_id", "mark", "line_no", "lid", "head").join(moved.withColumnRenamed("node", "lid"), "lid", "left").withColumn("root", F.coalesce("root", "lid"))
    named = tables.keep(named, "named")
    tables.leave(named)
    # only components of several lines are joined; stored, so that a join can split the rows of a common line
    several = named.groupBy("root").agg(F.min(F.struct("doc_id", "mark", "line_no")).alias("at"), F.count("*").alias("n")).where("n > 1")
    first = tables.keep(several.select("root", F.col("at.doc_id").alias("first_doc"), F.col("at.mark").alias("first_mark"), F.col("at.line_no").alias("first_line")), "first")
    at = named.join(first, "root", "left")
    keep = F.coalesce((F.col("doc_id") == F.col("first_doc")) & (F.col("mark") == F.col("first_mark")) & (F.col("line_no") == F.col("first_line")), F.lit(True))
    return at.select("doc_id", "mark", "line_no", "lid", "head", "root", F.coalesce("first_doc", "doc_id").alias("first_doc"), F.coalesce("first_line", "line_no").alias("first_line"), keep.alias("keep"))


def removals(decided: DataFrame) -> DataFrame:
    """(doc_id, mark, drop, copies): the sorted places of the lines that go, and how many rows have this id and text."""
    own = decided.groupBy("doc_id", "mark").agg(F.sort_array(F.collect_set(F.when(~F.col("keep"), F.col("line_no")))).alias("drop"), F.sum(F.col("head").cast("long")).alias("copies"))
    return own.where((F.size("drop") > 0) | (F.col("copies") > 1))


def dedup_documents(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", drop_emptied: bool = True, least: int = MIN_CHARS) -> DataFrame:
    """df with repeated lines of at least so many normalised characters taken out of its texts; a document that loses all its words goes if drop_emptied."""
    doc, mark, gone, copies = (free_name(df, f"line_{x}") for x in ("doc", "mark", "drop", "copies"))
    tables = Tables(df.sparkSession)
    drop = tables.keep(removals(line_components(df, id_col, text_col, least)).select(F.col("doc_id").alias(doc), F.col("mark").alias(mark), F.col("drop").alias(gone), F.col("copies").alias(copies)), "removals")
    joined = df.join(drop, (F.col(id_col).cast("long") == F.col(doc)) & (F.xxhash64(text_col) == F.col(mark)), "left")
    joined = one_of_each(joined, drop.where(F.col(copies) > 1), copies, [doc, mark])
    left = F.array_join(F.filter(F.split(F.col(text_col), "\n"), lambda x, i: ~F.array_contains(gone, i)), "\n")
    cut = joined.withColumn(text_col, F.when(F.coalesce(F.size(gone), F.lit(0)) > 0, left).otherwise(F.col(text_col)))
    if drop_emptied:
        cut = cut.where(F.coalesce(F.size(gone) < 1, F.lit(True)) | F.col(text_col).rlike(r"[^\x20\x09-\x0D]"))
    return cut.drop(doc, mark, gone, copies)
