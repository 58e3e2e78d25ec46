"""Near-duplicate documents by SimHash, compared as vertical bit planes.

Fingerprints are made from whole texts. Distinct fingerprints that agree on two of six bit blocks are brought
together (of six blocks, at most four can hold the four differing bits, so no link is lost), laid out as bit planes,
and compared 64 at a time: a carry-save counter adds one plane of differences after the other, and a block is given
up once every distance in it exceeds the radius. Buckets too large for one task are cut into chunks, and every pair
of chunks becomes a group of its own. Only a spanning forest of each group leaves it.

Defined results: null and empty texts have fingerprint zero, which links like any other; repeated rows share a
fingerprint, rows that share an id are judged by their own texts; bits set in exactly half of the shingles are 0; a
component without any id has none; very long texts are read whole; an empty table gives an empty result; other columns
are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import accumulate, chain, combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from parley.llm.common import Tables, free_name, one_of_each, tidy
from parley.llm.components import components, forest

RADIUS = 4
SHINGLE = 4
SEED = 42
BLOCKS = 6
#: Fingerprints of one bucket that one task compares with each other; larger buckets are cut into chunks of so many.
CHUNK = 4096
#: Rows that the comparison of small buckets lays out at once.
BATCH = 1 << 17

EDGE = np.array([round(k * 64 / BLOCKS) for k in range(BLOCKS + 1)])


def masks(radius: int = RADIUS) -> list[int]:
    """One mask for each choice of the blocks that must agree when radius bits differ."""
    block = [((1 << int(b)) - 1) ^ ((1 << int(a)) - 1) for a, b in zip(EDGE, EDGE[1:], strict=False)]
    return [sum(block[i] for i in pick) for pick in combinations(range(BLOCKS), BLOCKS - radius)]


def signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def shingle_hashes(text: str | None, k: int = SHINGLE) -> list[int]:
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: only A-Z change, only ASCII blanks part
    if not words:
        return []
    joined, h = b" ".join(words), xxhash.xxh64_intdigest
    if len(words) <= k:
        return [h(joined, SEED)]
    ends = list(accumulate(len(w) + 1 for w in words))
    return [h(joined[a : b - 1], SEED) for a, b in zip([0, *ends], ends[k - 1 :], strict=False)]


def fingerprint_batch(texts: list[str | None]) -> np.ndarray:
    out = np.zeros(len(texts), np.uint64)
    for i, text in enumerate(texts):
        if hashes := shingle_hashes(text):
            counts = np.zeros(64, np.int64)
            all_ = np.array(hashes, np.uint64)
            for at in range(0, len(all_), 1 << 16):
                part = all_[at : at + (1 << 16)]
                counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int32)
            out[i] = np.packbits(counts * 2 > len(hashes), bitorder="little").view(np.uint64)[0]
    return out


def _fingerprints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        fp = fingerprint_batch(batch.column(2).to_pylist()).view(np.int64)
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(fp)], ["doc_id", "mark", "fp"])


def fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, mark, fp): fp holds the unsigned fingerprint's 64 bits as a long, mark is the text's hash."""
    rows = df.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text_col).alias("mark"), F.col(text_col).alias("text"))
    return rows.mapInArrow(tidy(_fingerprints), "doc_id long, mark long, fp long")


def planes_of(fp: np.ndarray) -> np.ndarray:
    """64 rows, one for each bit; each holds that bit of every fingerprint, 64 to a word (the rest of the last word is 0)."""
    bits = np.unpackbits(fp.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").T
    width = -(-len(fp) // 64) * 64
    padded = np.zeros((64, width), np.uint8)
    padded[:, : len(fp)] = bits
    return np.packbits(padded, axis=1, bitorder="little").view(np.uint64)


class CarrySave:
    """Counts, in bit-sliced form, how many planes of differences each lane has had; stops counting beyond the radius."""

    def __init__(self, shape: tuple[int, ...], radius: int):
        self.radius, self.slices = radius, [np.zeros(shape, np.uint64) for _ in range(radius.bit_length())]
        self.over = np.zeros(shape, np.uint64)

    def add(self, carry: np.ndarray) -> None:
        for k, s in enumerate(self.slices):
            self.slices[k], carry = s ^ carry, s & carry
        self.over |= carry

    def beyond(self) -> np.ndarray:
        """Lanes whose count exceeds the radius."""
        more, same = np.zeros_like(self.over), ~np.zeros_like(self.over)
        for k in reversed(range(len(self.slices))):
            if self.radius >> k & 1:
                same = same & self.slices[k]
            else:
                more, same = more | (same & self.slices[k]), same & ~self.slices[k]
        return self.over | more


def near_mask(differences: Iterator[np.ndarray], shape: tuple[int, ...], radius: int) -> np.ndarray | None:
    """Lanes within the radius; None once a block has no such lane left."""
    counter = CarrySave(shape, radius)
    for k, plane in enumerate(differences):
        counter.add(plane)
        if k % 8 == 7 and (counter.beyond() == ~np.uint64(0)).all():
            return None
    return ~counter.beyond()


def _lanes(mask: np.ndarray) -> np.ndarray:
    return np.unpackbits(mask.view(np.uint8), axis=-1, bitorder="little").astype(bool)


def compare(a: np.ndarray, b: np.ndarray, radius: int = RADIUS, rows: int = 128) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs (i, j) of fingerprints a[i], b[j] within the radius, as a forest over their positions; b's come after a's."""
    planes, ones = planes_of(b), ~np.uint64(0)
    left, right = np.empty(0, np.int64), np.empty(0, np.int64)
    for at in range(0, len(a), rows):
        part = a[at : at + rows]
        bits = (part[:, None] >> np.arange(64, dtype=np.uint64)) & np.uint64(1)
        fill = np.where(bits.astype(bool), ones, np.uint64(0))
        near = near_mask((fill[:, p, None] ^ planes[p] for p in range(64)), (len(part), planes.shape[1]), radius)
        if near is not None:
            i, j = np.nonzero(_lanes(near)[:, : len(b)])
            v, u = forest(np.concatenate([left, i + at]), np.concatenate([right, j + len(a)]))
            left, right = v, u
    return left, right


def compare_runs(fp: np.ndarray, run: np.ndarray, radius: int = RADIUS) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (i, i + d) within one run and the radius: at each shift d the planes are compared with themselves, moved by d."""
    left, right, d = [], [], 1
    while len(fp) > d:
        lanes = len(fp) - d
        same = run[:lanes] == run[d:]
        if not same.any():
            break
        pick = np.nonzero(same)[0]
        here, there = planes_of(fp[pick]), planes_of(fp[pick + d])
        near = near_mask((x ^ y for x, y in zip(here, there, strict=True)), here.shape[1:], radius)
        if near is not None:
            hit = pick[_lanes(near)[: len(pick)]]
            left.append(hit)
            right.append(hit + d)
        d += 1
    none = np.empty(0, np.int64)
    return (np.concatenate(left), np.concatenate(right)) if left else (none, none)


def runs_of(*keys: np.ndarray) -> np.ndarray:
    """Start positions of runs of equal keys in sorted columns."""
    change = np.ones(len(keys[0]), bool)
    if len(change):
        change[1:] = np.logical_or.reduce([k[1:] != k[:-1] for k in keys])
    return np.nonzero(change)[0]


def _edge_rows(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    n = len(a)
    return pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), pa.nulls(n, pa.int32()), pa.nulls(n, pa.int32())], ["a", "b", "chunk", "bucket"])


def _bucket_links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (bucket, fp). Gives links (a, b), or the rows of an oversized bucket with their chunk for a second pass."""
    held_k, held_t, held_f = np.empty(0, np.int64), np.empty(0, np.int32), np.empty(0, np.int64)

    def flush(k: np.ndarray, t: np.ndarray, f: np.ndarray) -> pa.RecordBatch:
        starts = runs_of(k, t)
        length = np.diff(np.append(starts, len(k)))
        run = np.repeat(np.arange(len(starts)), length)
        pick, left, right = (length[run] > 1) & (length[run] <= 64), [], []
        fp, rn, pos = f[pick], run[pick], np.nonzero(pick)[0]
        for i, j in [compare_runs(fp.view(np.uint64), rn)] if len(fp) else []:
            left.append(f[pos[i]])
            right.append(f[pos[j]])
        for s, n in zip(starts[length > 64], length[length > 64], strict=True):
            own = f[s : s + n]
            v, u = compare(own.view(np.uint64), own.view(np.uint64))
            v, u = v % n, u % n
            left.append(own[v[v != u]])
            right.append(own[u[v != u]])
        none = np.empty(0, np.int64)
        return _edge_rows(*forest(np.concatenate([none, *left]), np.concatenate([none, *right])))

    big, gone = None, 0  # the bucket that fills more than a buffer, and how many of its rows have left

    for batch in chain(batches, [None]):
        if batch is not None:
            held_t, held_k, held_f = (np.concatenate([x, batch.column(n).to_numpy()]) for x, n in ((held_t, 0), (held_k, 1), (held_f, 2)))
        while len(held_k):
            if big:
                other = np.nonzero((held_t != big[0]) | (held_k != big[1]))[0]
                cut = int(other[0]) if len(other) else len(held_k)
                if cut:
                    yield _chunk_rows(held_k[:cut], held_t[:cut], held_f[:cut], gone + np.arange(cut))
                gone += cut
                big = None if len(other) else big
            elif batch is not None and len(held_k) < BATCH:
                break
            elif (cut := int(runs_of(held_k, held_t)[-1]) if batch is not None else len(held_k)) == 0:
                big, gone = (held_t[0], held_k[0]), 0
                continue
            else:
                yield from _split_large(held_k[:cut], held_t[:cut], held_f[:cut], flush)
            held_k, held_t, held_f = held_k[cut:], held_t[cut:], held_f[cut:]


def _chunk_rows(k: np.ndarray, t: np.ndarray, f: np.ndarray, at: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(f), pa.array(k), pa.array((at // CHUNK).astype(np.int32)), pa.array(t)], ["a", "b", "chunk", "bucket"])


def _split_large(k: np.ndarray, t: np.ndarray, f: np.ndarray, flush) -> Iterator[pa.RecordBatch]:
    """Oversized runs leave with chunk numbers; the rest is compared here."""
    starts = runs_of(k, t)
    length = np.diff(np.append(starts, len(k)))
    run = np.repeat(np.arange(len(starts)), length)
    big = length[run] > CHUNK
    if big.any():
        yield _chunk_rows(k[big], t[big], f[big], (np.arange(len(k)) - starts[run])[big])
    if not big.all():
        yield flush(k[~big], t[~big], f[~big])


def _chunk_pair(key: tuple, table: pa.Table) -> pa.Table:
    """All fingerprints of chunks i and j of one bucket (i = j: of one chunk)."""
    fp, chunk = table.column("a").to_numpy(), table.column("chunk").to_numpy()
    one, two = fp[chunk == key[2].as_py()], fp[chunk == key[3].as_py()]
    v, u = compare(one.view(np.uint64), two.view(np.uint64))
    both = np.concatenate([one, two])
    return pa.table({"a": both[v], "b": both[u]})


def links(distinct: DataFrame, tables: Tables, radius: int = RADIUS) -> DataFrame:
    """distinct: one long column fp. Links (a, b) that connect all fingerprints within the radius of each other."""
    spread = F.explode(F.array(*[F.struct(F.lit(t).alias("bucket"), F.col("fp").bitwiseAND(F.lit(signed(m))).alias("k")) for t, m in enumerate(masks(radius))])).alias("e")
    dealt = distinct.select("fp", spread).select("e.bucket", "e.k", "fp").repartition("bucket", "k").sortWithinPartitions("bucket", "k", "fp")
    first = tables.keep(dealt.mapInArrow(tidy(_bucket_links), "a long, b long, chunk int, bucket int"), "links")
    plain = first.where("chunk IS NULL").select("a", "b")
    large = first.where("chunk IS NOT NULL")
    last = large.groupBy("bucket", "b").agg(F.max("chunk").alias("top"))
    pairs = large.join(last, ["bucket", "b"]).select("bucket", "b", "a", "chunk", F.explode(F.sequence(F.lit(0), "top")).alias("other"))
    grouped = pairs.select("bucket", "b", F.least("chunk", "other").alias("i"), F.greatest("chunk", "other").alias("j"), "a", "chunk").groupBy("bucket", "b", "i", "j")
    return plain.unionByName(grouped.applyInArrow(_chunk_pair, "a long, b long"))


def cluster(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS) -> DataFrame:
    """(doc_id, mark, fp, component_id): component_id is the smallest doc_id reachable over links."""
    tables = Tables(df.sparkSession)
    prints = tables.keep(fingerprints(df, id_col, text_col), "fingerprints")
    reps = tables.keep(prints.groupBy("fp").agg(F.min("doc_id").alias("rep")), "distinct")
    moved = components(links(reps.select("fp"), tables, radius), tables)
    rooted = reps.join(moved, reps.fp == moved.node, "left").select("fp", "rep", F.coalesce("root", "fp").alias("root"))
    least = rooted.groupBy("root").agg(F.min("rep").alias("component_id"))
    named = rooted.join(least, "root").select("fp", "component_id")
    return prints.join(named, "fp").select("doc_id", "mark", "fp", "component_id")


def one_of_each_group(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """df with one row of each component: that of the smallest id, and of rows with that id the one of the smallest text hash.

    Rows without an id stay. A row is known by its id and its text's hash; of rows alike in both, one stays.
    """
    doc, mark, copies = (free_name(df, f"group_{x}") for x in ("doc", "mark", "copies"))
    tables = Tables(df.sparkSession)
    rows = tables.keep(cluster(df, id_col, text_col).where("doc_id IS NOT NULL"), "clusters")
    first = rows.where(F.col("doc_id") == F.col("component_id"))
    several = tables.keep(first.groupBy("component_id").agg(F.min("mark").alias("least"), F.count("*").alias("n")).where("n > 1"), "several")  # repeated ids alone
    twins = first.join(several, "component_id").select("doc_id", "mark", (F.col("mark") == F.col("least")).alias("stays"))
    gone = rows.where(F.col("doc_id") != F.col("component_id")).select("doc_id", "mark").unionByName(twins.where("NOT stays").select("doc_id", "mark")).distinct()
    gone = gone.select(F.col("doc_id").alias(doc), F.col("mark").alias(mark))
    own = [F.col(id_col).cast("long") == F.col(doc), F.xxhash64(text_col) == F.col(mark)]
    left = df.join(gone, own[0] & own[1], "left_anti")
    if several.isEmpty():
        return left
    counted = twins.where("stays").groupBy("doc_id", "mark").agg(F.count("*").alias(copies)).select(F.col("doc_id").alias(doc), F.col("mark").alias(mark), copies)
    return one_of_each(left.join(counted, own[0] & own[1], "left"), counted.where(F.col(copies) > 1), copies, [doc, mark]).drop(doc, mark, copies)


def with_hex(clusters: DataFrame) -> DataFrame:
    return clusters.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
