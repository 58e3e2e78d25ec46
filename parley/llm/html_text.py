"""Main text of web pages: host suffix array over token streams, on top of the pages' own structure.

A page is cut into blocks, each inside an article, inside furniture (menus, headers, footers, sidebars, notices, adverts,
forms, comments, by element, role, class or id), or neither. The token streams of a host's pages are joined and their
suffixes ranked by prefix doubling up to RUN tokens: equal neighbours in that order are substrings of RUN tokens or more
that repeat. What repeats on pages of different content, and on SHARE of them or more, is boilerplate. Of the blocks that
structure leaves open, on any page, those covered by it go and unique ones stay. What an article holds is text and
furniture is not, whatever repeats: a suffix array alone fails there, since hosts repeat whole articles, menus quote
sentences that articles hold, and reader comments are unique. ``extract(structure=False)`` lets the array decide on every
block of every page, for comparison.

Every page of every host is compared, whatever its structure decides, and every block gets the array's verdict. A host above
PAGES is dealt into cohorts of about so many pages, each with a suffix array of its own, so that a host of any size is spread
over tasks. Pages of equal content share a cohort, so that a cohort's counts add up to the host's; a content on more than
PAGES pages has cohorts to itself, and counts once. Substrings go on under 64-bit hashes (odds of a false match:
n*n / 2**65 for n of a host). A cohort leaves out what only one of its many contents holds; where such could make up what a
substring lacks, the host is counted again in full. So shares are those of the whole host, and results depend neither on
cohorts nor on partitions. What is boilerplate then goes to all pages of the host: at most 1 / SHARE times the substrings of
a page, however large the host.

Text: character references decoded, white space within a block one blank, blocks joined by a line feed in page order.
Defined results: null, empty and text-free pages have an empty text; broken markup is read leniently; null urls form a
host of their own; repeated rows get equal texts (pages of equal content never make each other boilerplate); very long
pages are read whole; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parley.llm.common import Tables, tidy
from parley.plans.choose import few

RUN = 8
#: Pages of a host that are in one suffix array, about.
PAGES = 200
#: Cohorts where SHARE is so many contents or more leave out substrings that one content holds; over 1, so that none is left out by all.
MANY = 10
COVERED = 0.6
#: The part of a host's different pages that boilerplate is on, two at least.
SHARE = 0.2
TEXTS = "page_id long, url string, text string, n_chars long"

OUTSIDE, ARTICLE, FURNITURE = 0, 1, 2
_MIX = np.uint64(0x9E3779B97F4A7C15)

_MARKUP = re.compile(r"""<!--.*?(?:-->|\Z)|<![^>]*>|<\?[^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?>[^>"']|"[^"]*"|'[^']*')*+)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)(?:>|\Z)""", re.S)
_NAMES = re.compile(r"""\b(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+))""", re.I)
_PARTS = re.compile(r"[^a-z0-9]+")
_RAW = {k: re.compile(rf"</{k}\b[^>]*>|\Z", re.I) for k in ("script", "style", "noscript", "template", "svg", "iframe", "object", "canvas", "select", "textarea", "title", "math")}
_INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_FURNITURE_TAGS = frozenset("nav aside footer form menu dialog button fieldset".split())
_FURNITURE_STARTS = ("nav", "menu", "sidebar", "foot", "cookie", "consent", "notice", "banner", "advert", "sponsor", "promo", "comment", "share", "sharing", "social", "related", "newsletter", "subscri", "login", "signup", "popup", "modal", "widget", "breadcrumb", "disclaimer", "masthead", "toolbar", "pagination", "disqus", "reply", "replies", "gdpr", "complementary", "contentinfo", "search", "skip")
_FURNITURE_WORDS = frozenset("ad ads adv advertisement header form alert copyright".split())
_ARTICLE_WORDS = frozenset("article post entry story main content".split())


def role_of(tag: str, attributes: str) -> int | None:
    """The role that an element gives to what it holds; None: as around it."""
    if tag in _FURNITURE_TAGS:
        return FURNITURE
    if tag == "header":
        return OUTSIDE - 1  # furniture unless it heads an article
    parts = [p for m in _NAMES.finditer(attributes) for p in _PARTS.split((m[1] or m[2] or m[3] or "").lower()) if p] if "=" in attributes else []
    if tag in ("article", "main"):
        return ARTICLE
    if parts and tag not in ("body", "html"):
        if any(p in _FURNITURE_WORDS or p.startswith(_FURNITURE_STARTS) for p in parts):
            return FURNITURE
        if tag in ("div", "section", "td") and _ARTICLE_WORDS.intersection(parts):
            return ARTICLE
    return None


def blocks_of(page: str | None) -> list[tuple[int, str]]:
    """(role, text) of a page's blocks in order, furniture included."""
    page = page or ""
    out: list[tuple[int, str]] = []
    stack: list[tuple[str, int]] = []
    held: list[str] = []
    role, at, in_head = OUTSIDE, 0, False

    def close() -> None:
        if held:
            text = " ".join(html.unescape("".join(held)).split())
            held.clear()
            if text and not in_head:
                out.append((role, text))

    while at < len(page):
        m = _MARKUP.search(page, at)
        if not m:
            held.append(page[at:])
            break
        if m.start() > at:
            held.append(page[at : m.start()])
        at = m.end()
        tag = (m[2] or m[5] or "").lower()
        if not tag:
            continue
        closing, attributes = (m[1] or m[4]) == "/", m[3] or m[6] or ""
        if tag in _RAW and not closing:
            if tag not in ("title",):
                close()
            end = _RAW[tag].search(page, at)
            at = end.end()
            continue
        if tag in _INLINE:
            if tag == "br":
                held.append(" ")
            if not (tag == "span" and "=" in attributes) or closing:
                continue
            if role_of("span", attributes) != FURNITURE:
                continue
        close()
        if tag == "head":
            in_head = not closing
        elif tag == "body":
            in_head = False
        if closing:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == tag:
                    role = stack[k][1]
                    del stack[k:]
                    break
        elif tag not in _VOID and not attributes.endswith("/"):
            stack.append((tag, role))
            own = role_of(tag, attributes)
            if own == OUTSIDE - 1:
                own = FURNITURE if role == OUTSIDE else None
            if own is not None and role != FURNITURE:
                role = own
    close()
    return out


def suffix_groups(tokens: np.ndarray, page: np.ndarray, run: int = RUN) -> tuple[np.ndarray, np.ndarray]:
    """The suffix array, of suffixes with run tokens or more within their page, and a number for each that equal first run tokens share.

    tokens: all pages' streams, one after the other; page: whose each is.
    """
    n = len(tokens)
    if n < run:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    key, h = tokens.astype(np.int64), 1
    while h < run:  # prefix doubling: ranks of the first h tokens become ranks of the first 2h
        rank, step = np.unique(key, return_inverse=True)[1].astype(np.int64), min(h, run - h)
        nxt = np.full(n, -1, np.int64)
        nxt[:-step] = np.where(page[:-step] == page[step:], rank[step:], -1)
        key = rank * (n + 1) + nxt + 1
        h += step
    whole = np.nonzero(page[: n - run + 1] == page[run - 1 :])[0]
    order = whole[np.argsort(key[whole])]
    r = key[order]
    return order, np.cumsum(np.append(False, r[1:] != r[:-1])) if len(r) else r


def kinds_of(group: np.ndarray, kind: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each group's different kinds: (group, kind), both ascending."""
    most = int(kind.max(initial=0)) + 1
    pair = np.unique(group * most + kind)
    return pair // most, pair % most


def covered_by(starts: np.ndarray, n: int, run: int = RUN) -> np.ndarray:
    """Of n tokens those within run of a start."""
    change = np.zeros(n + 1, np.int64)
    np.add.at(change, starts, 1)
    np.add.at(change, starts + run, -1)
    return np.cumsum(change[:-1]) > 0


def repeats(tokens: np.ndarray, page: np.ndarray, kind: np.ndarray, run: int = RUN, least: int = 2) -> np.ndarray:
    """Tokens covered by substrings of run tokens or more that are on pages of `least` different kinds.

    tokens, page: as in suffix_groups; kind: equal for pages of equal content.
    """
    order, group = suffix_groups(tokens, page, run)
    kinds = np.bincount(kinds_of(group, kind[order])[0])
    return covered_by(order[(kinds >= least)[group]], len(tokens), run)


class _Hashes(dict):
    """64-bit hashes of the words asked for."""

    def __missing__(self, word: str) -> int:
        h = self[word] = xxhash.xxh64_intdigest(word.encode("utf-8", "surrogatepass"))
        return h


class _Numbers(dict):
    """Numbers from 0 on of the words asked for."""

    def __missing__(self, word: str) -> int:
        n = self[word] = len(self)
        return n


def _mixed(parts: list[np.ndarray]) -> np.ndarray:
    """Hashes of runs, from the hashes of their first words, of their second words, and so on."""
    out = np.zeros(len(parts[0]), np.uint64)
    for h in parts:
        out = (out ^ (out >> np.uint64(29))) * _MIX + h
    return (out ^ (out >> np.uint64(32))).view(np.int64)


def run_hashes(words: list[str], known: dict[str, int], run: int = RUN) -> np.ndarray:
    """A 64-bit hash of the run words from each place on, as far as there are so many. known: a _Hashes, kept for further words."""
    h = np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
    n = max(0, len(h) - run + 1)
    return _mixed([h[k : k + n] for k in range(run)])


def texts_of(pages: list[list[tuple[int, str]]], structure: bool = True) -> list[str]:
    """Main texts of pages of one host that fits a task, given as blocks. structure: what an article holds is text, furniture isn't."""
    number: dict[str, int] = {}
    kinds: dict[tuple, int] = {}
    tokens, owner, kind, ends = [], [], [], []
    for p, blocks in enumerate(pages):
        own = kinds.setdefault(tuple(t for r, t in blocks if r != FURNITURE or not structure), len(kinds))
        for _, text in blocks:
            ids = [number.setdefault(w, len(number)) for w in text.lower().split()]
            tokens += ids
            owner += [p] * len(ids)
            kind += [own] * len(ids)
            ends.append(len(tokens))
    least = max(2, int(np.ceil(SHARE * len(kinds))))
    found = repeats(np.array(tokens, np.int64), np.array(owner, np.int64), np.array(kind, np.int64), least=least)
    covered = np.concatenate([[0], np.cumsum(found)])
    out, at, start = [], 0, 0
    for blocks in pages:
        kept = []
        for role, text in blocks:
            end = ends[at]
            at += 1
            unique = covered[end] - covered[start] < COVERED * max(1, end - start)
            if (role == ARTICLE or (role == OUTSIDE and unique)) if structure else unique:
                kept.append(text)
            start = end
        out.append("\n".join(kept))
    return out


def _content(blocks: list[tuple[int, str]], structure: bool) -> int:
    """A hash of what a page's content is known by: equal for copies."""
    h = xxhash.xxh64_intdigest("\n".join(t for r, t in blocks if r != FURNITURE or not structure).encode("utf-8", "surrogatepass"))
    return h - (1 << 64) if h >> 63 else h


def _streams(structure: bool, whole: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows (host, salt, html): each page's content, and if whole its token stream."""
        for batch in batches:
            contents, streams = [], []
            for page in batch.column(2).to_pylist():
                blocks = blocks_of(page)
                contents.append(_content(blocks, structure))
                if whole:
                    streams.append(" ".join(text.lower() for _, text in blocks))
            contents = pa.array(contents, pa.int64())
            if whole:
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), contents, pa.array(streams, pa.string())], ["host", "salt", "content", "stream"])
            else:
                yield pa.RecordBatch.from_arrays([batch.column(0), contents], ["host", "content"])

    return run


def _runs(many: float):
    def found(host: str, cohort: int | None, alone: int | None, pages: list[tuple[int, str]]) -> pa.RecordBatch:
        number, contents = _Numbers(), _Numbers()
        tokens, kind = [], []
        for content, stream in pages:
            words = stream.split()
            tokens.append(np.fromiter(map(number.__getitem__, words), np.int64, len(words)))
            kind.append(contents[content])
        owner = np.repeat(np.arange(len(pages)), [len(t) for t in tokens])
        kind, tokens = np.array(kind, np.int64)[owner], np.concatenate(tokens)
        if cohort is None:  # the whole host
            least, left = max(2, int(np.ceil(SHARE * len(contents)))), 0
        else:
            left = int(alone is None and SHARE * len(contents) >= many)
            least = 1 + left
        order, group = suffix_groups(tokens, owner)
        often = (np.bincount(group) >= least)[group]
        order, group = order[often], group[often]
        of, heads, counts = np.empty((3, 0), np.int64)
        if len(order):
            group = np.cumsum(np.append(False, group[1:] != group[:-1]))
            of = kinds_of(group, kind[order])[0]
            counts = np.bincount(of)
            heads = order[np.append(True, group[1:] != group[:-1])][counts >= least]
            counts = counts[counts >= least]
        names, known = list(number), _Hashes()
        places = tokens[heads.astype(np.int64)[:, None] + np.arange(RUN)]
        used, at = np.unique(places, return_inverse=True)
        hashes = np.fromiter((known[names[k]] for k in used), np.uint64, len(used))[at.reshape(places.shape)]
        n = len(heads) + 1
        # the last row, without a substring, has the number of contents
        return pa.RecordBatch.from_arrays([pa.array([host] * n, pa.string()), pa.array([*_mixed(list(hashes.T)).tolist(), None], pa.int64()), pa.array([alone] * n, pa.int64()), pa.array([*counts.tolist(), len(contents)], pa.int64()), pa.array([left] * n, pa.int64())], ["host", "run", "alone", "n", "left"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows (host, cohort, alone, content, stream), a cohort's one after the other: its substrings, and the number of contents they are on.

        cohort: null for a host in one piece. alone: the content of a cohort that has no other. left: whether a cohort leaves out what one content holds.
        """
        pages, name = [], None
        for batch in batches:
            for host, cohort, alone, content, stream in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if pages and (host, cohort, alone) != name:
                    yield found(*name, pages)
                    pages = []
                name = host, cohort, alone
                pages.append((content, stream))
        if pages:
            yield found(*name, pages)

    return run


def _decide(structure: bool):
    def text_of(blocks: list[tuple[int, str]], boiler: np.ndarray, known: dict[str, int]) -> str:
        words, ends = [], [0]
        for _, text in blocks:
            words += text.lower().split()
            ends.append(len(words))
        at = np.nonzero(np.isin(run_hashes(words, known), boiler))[0]
        covered, kept = np.append(0, np.cumsum(covered_by(at, len(words)))), []
        for (role, text), start, end in zip(blocks, ends, ends[1:], strict=False):
            unique = covered[end] - covered[start] < COVERED * max(1, end - start)
            if (role == ARTICLE or (role == OUTSIDE and unique)) if structure else unique:
                kept.append(text)
        return "\n".join(kept)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows (host, cohort, runs, page_id, url, html), a cohort's boilerplate ahead of its pages: the pages' texts."""
        name, boiler, known = None, np.empty(0, np.int64), _Hashes()
        for batch in batches:
            out = []
            for host, cohort, runs, page_id, url, page in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if (host, cohort) != name:
                    name, boiler, known = (host, cohort), np.empty(0, np.int64), _Hashes()
                if runs is not None:
                    boiler = np.array(runs, np.int64)
                    continue
                text = text_of(blocks_of(page), boiler, known)
                out.append((page_id, url, text, len(text)))
            ids, urls, texts, sizes = zip(*out, strict=True) if out else [[]] * 4
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(urls, pa.string()), pa.array(texts, pa.string()), pa.array(sizes, pa.int64())], ["page_id", "url", "text", "n_chars"])

    return run


def host_of(url: str):
    return F.lower(F.regexp_extract(F.coalesce(F.col(url), F.lit("")), r"^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)", 1))


@contextmanager
def _freed(spark: SparkSession):
    """Shuffle files of what is written inside are deleted once it is written, not when the driver happens to collect its garbage."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, None)
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.unset(key) if before is None else spark.conf.set(key, before)


def _large(df: DataFrame, label: str, tables: Tables) -> DataFrame:
    """df, which has at most a row for every PAGES pages, kept and marked for broadcast if small."""
    kept = tables.keep(df, label)
    return few(kept, kept.count(), 128)


def _together(rows: DataFrame, pages: int, keys: list[str], *order) -> DataFrame:
    """rows by keys, sorted by order within them. pages: how many there are; no task has many more than a few cohorts, however few partitions are set."""
    parts = pages // (8 * PAGES)
    parts = [parts] if parts > int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")) else []
    return rows.repartition(*parts, *keys).sortWithinPartitions(*keys, *order)


def boilerplate(rows: DataFrame, structure: bool, tables: Tables) -> tuple[int, DataFrame, DataFrame]:
    """Of rows (host, page_id, url, html): how many there are, (name, cohorts) of hosts above PAGES, and (host, run) of all hosts' boilerplate."""
    pages = rows.select("host", F.xxhash64("page_id", "url").alias("salt"), "html")
    contents = tables.keep(pages.mapInArrow(tidy(_streams(structure, False)), "host string, content long").groupBy("host", "content").agg(F.count("*").alias("n")), "contents")
    total = contents.agg(F.sum("n")).first()[0] or 0
    large = _large(contents.groupBy("host").agg(F.sum("n").alias("n")).where(F.col("n") > PAGES).select(F.col("host").alias("name"), F.ceil(F.col("n") / PAGES).alias("cohorts")), "hosts", tables)
    hot = _large(contents.where(F.col("n") > PAGES).select(F.col("host").alias("of"), F.col("content").alias("alone"), F.ceil(F.col("n") / PAGES).alias("pieces")), "hot", tables)
    tables.drop(contents)

    def counted(pages: DataFrame, many: float) -> DataFrame:
        """(host, run, n, left): the contents that each substring is on, as far as cohorts tell, and the cohorts among them that leave some out; a null run has the host's."""
        streams = pages.mapInArrow(tidy(_streams(structure, True)), "host string, salt long, content long, stream string")
        dealt = streams.join(large, F.col("host") == F.col("name"), "left").join(hot, (F.col("host") == F.col("of")) & (F.col("content") == F.col("alone")), "left")
        cohort = F.when(F.col("alone").isNull(), F.pmod("content", "cohorts")).otherwise(F.pmod("salt", "pieces"))
        own = _together(dealt.select("host", cohort.alias("cohort"), "alone", "content", "stream"), total, ["host", "cohort", "alone"])
        on = own.mapInArrow(tidy(_runs(many)), "host string, run long, alone long, n long, left long")
        n = F.when(F.col("alone").isNull(), F.sum("n")).otherwise(F.lit(1).cast("long"))
        by_content = on.groupBy("host", "run", "alone").agg(n.alias("n"), F.sum("left").alias("left"))
        return tables.keep(by_content.groupBy("host", "run").agg(F.sum("n").alias("n"), F.sum("left").alias("left")), "runs")

    def often(runs: DataFrame) -> DataFrame:
        """(host, run, sure) of substrings that may be on SHARE of their host's contents; sure: are."""
        of_host = runs.where("run IS NULL").select(F.col("host").alias("name"), F.greatest(F.lit(2), F.ceil(F.col("n") * SHARE)).alias("least"), F.col("left").alias("cohorts"))
        near = runs.where("run IS NOT NULL").join(of_host, F.col("host") == F.col("name")).where("n + cohorts - left >= least")
        return tables.keep(near.select("host", "run", (F.col("n") >= F.col("least")).alias("sure")), "often")

    with _freed(rows.sparkSession):
        runs = counted(pages, MANY)
        found = often(runs)
        tables.drop(runs)
        unsure = tables.keep(found.where("NOT sure").select(F.col("host").alias("again")).distinct(), "again")
        n = unsure.count()
        if n:
            again = few(unsure, n, 128)
            runs = counted(pages.join(again, F.col("host") == F.col("again"), "left_semi"), float("inf"))
            exact = often(runs)
            tables.drop(runs)
            found = found.join(again, F.col("host") == F.col("again"), "left_anti").unionByName(exact)
        else:
            tables.drop(unsure)
    return total, large, found.select("host", "run")


def extract(df: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", structure: bool = True) -> DataFrame:
    """(page_id, url, text, n_chars) for each page."""
    rows = df.select(host_of(url_col).alias("host"), F.col(id_col).cast("long").alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"))
    total, large, found = boilerplate(rows, structure, Tables(df.sparkSession))
    of_host = lambda pages: pages.join(large, F.col("host") == F.col("name"), "left")
    cohort = F.coalesce(F.pmod(F.xxhash64("page_id", "url"), F.col("cohorts")), F.lit(0).cast("long"))
    dealt = of_host(rows).select("host", cohort.alias("cohort"), F.lit(None).cast("array<long>").alias("runs"), "page_id", "url", "html")
    each = F.explode(F.sequence(F.lit(0).cast("long"), F.coalesce("cohorts", F.lit(1).cast("long")) - 1))
    ahead = of_host(found.groupBy("host").agg(F.collect_list("run").alias("runs"))).select("host", each.alias("cohort"), "runs", *(F.lit(None).cast(t).alias(c) for c, t in (("page_id", "long"), ("url", "string"), ("html", "string"))))
    own = _together(ahead.unionByName(dealt), total, ["host", "cohort"], F.col("runs").isNull(), "page_id", "url")
    return own.mapInArrow(tidy(_decide(structure)), TEXTS)
