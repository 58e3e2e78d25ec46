"""Text operators against brute force, exact round trips, held-out accuracy, and rows that are hard to handle."""

import sys
import zlib
from collections import Counter, defaultdict
from itertools import pairwise
from pathlib import Path

import numpy as np
import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[2]))
from parley.llm import decontaminate, html_text, language, line_dedup, merge_dropout, pii, quality, queries, simhash, sstable, toxicity  # noqa: E402
from parley.llm.common import tokenizer_path  # noqa: E402
from parley.llm.components import components, forest  # noqa: E402
from parley.llm.word_encoding import WordEncoder  # noqa: E402

SF = "/root/testdata/sf0.001"
WORDS = [f"{a}{b}{c}" for a in ("ba", "ko", "ti", "mu") for b in ("ne", "la", "si") for c in ("ro", "da", "ve", "zu")]
LONG = " ".join(WORDS[k * 7 % len(WORDS)] for k in range(30_000)) + "x" * 50_000
HARD = [
    (1, None), (2, ""), (3, "   \n\t "), (4, LONG), (5, "the cat sat on the mat and looked at the dog for a very long while"),
    (6, "the cat sat on the mat and looked at the dog for a very long while"), (6, "the cat sat on the mat and looked at the dog for a very long while"),
    (None, "a row without an id, long enough to be compared with others"), (None, None), (7, "▁ literal  marké \U0001f600\x0b\x1c end"), (8, "%%% ### 123"), (-9, "minus nine"),
]
CLASH = "doc_id long, text string, lang string, source string, n_chars long, fp long, component_id long, n_replaced long, line_drop string, Drop string"


@pytest.fixture(scope="module")
def hard(spark):
    return spark.createDataFrame([(i, t, None, None, None, 5, None, 7, "x", "y") for i, t in HARD], CLASH)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], CLASH)


@pytest.fixture(scope="module")
def docs(spark):
    return [(r.doc_id, r.text, r.lang) for r in spark.read.parquet(f"{SF}/documents.parquet").collect()]


def union_find(pairs, nodes):
    root = {n: n for n in nodes}

    def find(x):
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for a, b in pairs:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return {n: find(n) for n in nodes}


def test_quality_matches_sql(spark, duck):
    df = queries.op1_quality_ledger(spark, SF)
    rel = duck.execute(queries.oracle_sql()["op1_quality_ledger"])
    names = [d[0] for d in rel.description]
    assert sorted(map(tuple, df.select(names).collect())) == sorted(rel.fetchall())


def test_ablation_matches_sql(spark, duck):
    df = queries.quality_rule_ablation(spark, SF)
    rel = duck.execute(queries.oracle_sql()["quality_rule_ablation"])
    names = [d[0] for d in rel.description]
    assert sorted(map(tuple, df.select(names).collect())) == sorted(rel.fetchall())


def test_quality_hard_rows_policies_and_ablation(hard, empty):
    rows = quality.apply_policy(quality.ledger(hard)).collect()
    assert len(rows) == len(HARD)
    assert all(r.n_words == 0 and r.base_failed and not r.kept for r in rows if r.doc_id in (1, 2, 3))
    assert next(r for r in rows if r.doc_id == 4).n_words == 30_000
    assert quality.ledger(empty).count() == 0
    book = quality.ledger(hard)
    got = {r.rule: (r.n_failed, r.n_only_this) for r in quality.ablation(book, "v1").collect()}
    bits = [r.fail_bits & quality.mask("v1") for r in book.collect()]
    assert got == {r: (sum(b & quality.BITS[r] > 0 for b in bits), sum(b == quality.BITS[r] for b in bits)) for r in quality.POLICIES["v1"]}


def test_components_of_random_graphs(spark):
    rng = np.random.default_rng(1)
    pairs = [(int(a), int(b)) for a, b in rng.integers(-400, 400, (300, 2))] + [(k, k + 1) for k in range(1000, 1060)] + [(2000, k) for k in range(2001, 2100)]
    want = {n: r for n, r in union_find([p for p in pairs if p[0] != p[1]], {x for p in pairs for x in p}).items() if n != r}
    df = spark.createDataFrame(pairs, "a long, b long").repartition(7)
    assert {r.node: r.root for r in components(df).collect()} == want
    assert components(df.where("false")).count() == 0
    a, b = forest(np.array([p[0] for p in pairs]), np.array([p[1] for p in pairs]))
    assert dict(zip(a.tolist(), b.tolist(), strict=True)) == want


def test_bit_sliced_distances():
    rng = np.random.default_rng(2)
    base = rng.integers(0, 2**64, 90, dtype=np.uint64)
    fp = np.unique(np.concatenate([base, base ^ (np.uint64(1) << rng.integers(0, 64, 90).astype(np.uint64)), base[:30] ^ np.uint64(0b11111)]))
    near = np.bitwise_count(fp[:, None] ^ fp[None, :]) <= 4
    i, j = np.nonzero(near)
    want = dict(zip(*(x.tolist() for x in forest(i, j)), strict=True))
    v, u = simhash.compare(fp, fp)
    assert dict(zip(*(x.tolist() for x in forest(v % len(fp), u % len(fp))), strict=True)) == want
    assert dict(zip(*(x.tolist() for x in forest(*simhash.compare_runs(fp, np.zeros(len(fp), int)))), strict=True)) == want


@pytest.mark.parametrize("chunk", [simhash.CHUNK, 3])
def test_simhash_groups(spark, docs, monkeypatch, chunk):
    monkeypatch.setattr(simhash, "CHUNK", chunk)
    monkeypatch.setattr(simhash, "BATCH", 1 << 17 if chunk > 3 else 64)
    got = {r.doc_id: (int(r.fingerprint, 16), r.component_id) for r in queries.op2_simhash_groups(spark, SF).collect()}
    fp = dict(zip([d for d, _, _ in docs], simhash.fingerprint_batch([t for _, t, _ in docs]).tolist(), strict=True))
    ids = sorted(fp)
    want = union_find([(a, b) for a in ids for b in ids if a < b and (fp[a] ^ fp[b]).bit_count() <= 4], ids)
    assert got == {i: (fp[i], want[i]) for i in ids}


def test_simhash_hard_rows(hard, empty):
    rows = simhash.with_hex(simhash.cluster(hard)).collect()
    assert len(rows) == len(HARD)
    assert all(r.fingerprint == "0" * 16 and r.component_id == 1 for r in rows if r.doc_id in (1, 2, 3))
    assert {r.component_id for r in rows if r.doc_id in (5, 6)} == {5}
    assert simhash.cluster(empty).count() == 0


def linked_lines(lines):
    """Components by brute force over lines {key: normalised text}: Jaccard 0.8 of 8-character shingles, equal text for shorter ones."""
    sets = {k: frozenset(t[i : i + 8] for i in range(len(t) - 7)) for k, t in lines.items()}
    holds = defaultdict(set)
    for k, s in sets.items():
        for x in s:
            holds[x].add(k)
    pairs = []
    for k, s in sets.items():
        for m, c in Counter(m for x in s for m in holds[x] if m > k).items():
            if c >= 0.8 * (len(s) + len(sets[m]) - c):
                pairs.append((k, m))
    return union_find(pairs, sets)


@pytest.mark.parametrize("chunk", [line_dedup.CHUNK, 2])
def test_fuzzy_lines_against_all_pairs(spark, docs, monkeypatch, chunk):
    """Every link of Jaccard 0.8 and more among the lines of the smallest table, and one line kept of each component."""
    monkeypatch.setattr(line_dedup, "CHUNK", chunk)
    rows = line_dedup.line_components(spark.read.parquet(f"{SF}/documents.parquet")).collect()
    texts = {d: t.split("\n") for d, t, _ in docs}
    want = linked_lines({r.lid: line_dedup.normal(texts[r.doc_id][r.line_no]) for r in rows})
    assert {r.lid: r.root for r in rows} == want
    first = {}
    for r in sorted(rows, key=lambda r: (r.doc_id, r.line_no)):
        first.setdefault(want[r.lid], (r.doc_id, r.line_no))
    assert all(r.keep == (first[r.root] == (r.doc_id, r.line_no)) for r in rows)


def test_line_dedup_hard_rows(spark, hard, empty):
    out = line_dedup.dedup_documents(hard)
    assert out.columns == hard.columns
    left = Counter(r.doc_id for r in out.collect())
    assert left == Counter({None: 2, 1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 7: 1, 8: 1, -9: 1})  # 6 repeats 5
    assert line_dedup.dedup_documents(empty).count() == 0
    two = spark.createDataFrame([(1, "short\n" + "a line that is long enough to matter here"), (2, "short\n" + "A line that is long  enough to matter here\nnew words that nobody else has written yet")], "doc_id long, text string")
    assert {r.doc_id: r.text for r in line_dedup.dedup_documents(two).collect()}[2] == "short\nnew words that nobody else has written yet"


def test_short_lines_are_grouped_and_components_named(spark, monkeypatch):
    texts = ["Yes.\nan answer\n\n}", "yes.\n  yes.\nAn  answer\nonly here", "}\nan answers", None]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    monkeypatch.setattr(queries, "load", lambda *_: df)
    rows = {r.doc_id: r for r in queries.op10_fuzzy_lines(spark, "").collect()}
    assert [(rows[k].n_compared, rows[k].removed) for k in range(4)] == [(3, []), (4, [0, 1, 2]), (2, [0]), (0, [])]
    names = {k: [tuple(c) for c in r.components] for k, r in rows.items()}
    assert names == {0: [(0, 0, 0), (1, 0, 1), (3, 0, 3)], 1: [(0, 0, 0), (1, 0, 0), (2, 0, 1), (3, 1, 3)], 2: [(0, 0, 3), (1, 2, 1)], 3: []}
    assert line_dedup.dedup_documents(df, least=1).where("doc_id = 1").first().text == "only here"


def test_lines_of_a_text_are_normalised_as_each_alone(docs):
    odd = ["", " a", "a ", "A  b\n\tc", "x\xa0y\nΟΔΟΣ\nΣ", "İstanbul\r\nB", "a\n b", "a \nb", "one\u2003two", "\n\n", "q\x1cr"]
    for t in [*odd, *(t for _, t, _ in docs), LONG]:
        assert line_dedup.normal_lines(t) == [line_dedup.normal(x) for x in t.split("\n")]


def kept_by_brute_force(rows, least):
    """Per row of (id, text): the places of its lines that go."""
    named, at = {}, {}
    for k, (doc, text) in enumerate(rows):
        for place, raw in enumerate((text or "").split("\n")):
            if len(line := line_dedup.normal(raw)) >= least:
                at[k, place] = line
                named.setdefault(line, len(named))
    root = linked_lines({n: line for line, n in named.items()})
    first, gone = {}, defaultdict(list)
    for k, place in sorted(at, key=lambda x: (rows[x[0]][0], x[1])):
        if first.setdefault(root[named[at[k, place]]], (k, place)) != (k, place):
            gone[k].append(place)
    return gone


def test_fuzzy_lines_query_against_brute_force(spark, docs):
    rows = [(d, t) for d, t, _ in docs]
    gone = kept_by_brute_force(rows, 1)
    got = {r.doc_id: r for r in queries.op10_fuzzy_lines(spark, SF).collect()}
    for k, (d, t) in enumerate(rows):
        assert got[d].removed == sorted(gone[k]) and got[d].n_removed == len(gone[k])
        assert got[d].n_compared == sum(bool(line_dedup.normal(x)) for x in t.split("\n"))


REPEATED = ["a line that two documents have and that is long enough", "another line that is long enough, with the words xxx", "a line of its own that no other document has, with zzz"]


def test_lines_of_rows_that_share_an_id(spark):
    """Rows with one id and different texts are judged apart; of rows alike in both, one stays."""
    a, x, z = REPEATED
    rows = [(1, a), (3, f"{a}\n{x}"), (3, f"{z}\n{a} "), (4, "lone words that stand in a row repeated with its id"), (4, "lone words that stand in a row repeated with its id"), (5, "short"), (5, "short")]
    df = spark.createDataFrame([(i, t, 1) for i, t in rows], "doc_id long, text string, Line_Doc int").repartition(3)
    out = line_dedup.dedup_documents(df)
    assert out.columns == df.columns
    assert sorted((r.doc_id, r.text) for r in out.collect()) == sorted([(1, a), (3, x), (3, z), (4, rows[3][1]), (5, "short"), (5, "short")])
    every = Counter((r.doc_id, r.text) for r in line_dedup.dedup_documents(df, least=1).collect())
    assert every[(5, "short")] == 1 and every[(3, z)] == 1


def test_fuzzy_lines_query_counts_repeated_rows(spark, monkeypatch):
    a, x, z = REPEATED
    rows = [(1, a), (1, a), (3, f"{a}\n{x}"), (3, f"{z}\n{a}"), (None, a)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    monkeypatch.setattr(queries, "load", lambda *_: df)
    got = sorted((r.doc_id or 0, r.n_compared, r.removed) for r in queries.op10_fuzzy_lines(spark, "").collect())
    assert got == [(0, 0, []), (1, 1, []), (1, 1, [0]), (3, 2, [0]), (3, 2, [1])]


@pytest.mark.parametrize("few", [line_dedup.FEW, 1])
@pytest.mark.parametrize("chunk", [line_dedup.CHUNK, 7])
def test_large_buckets_against_all_pairs(spark, monkeypatch, few, chunk):
    """Many lines around few texts: the bitmaps and the chunks lose no link that the bands bring together."""
    monkeypatch.setattr(line_dedup, "FEW", few)
    monkeypatch.setattr(line_dedup, "CHUNK", chunk)
    rng = np.random.default_rng(11)
    lines = []
    for k in range(4):
        base = list(" ".join(rng.choice(WORDS, 30)))
        for _ in range(40):
            own = base.copy()
            for at in rng.integers(0, len(own), int(rng.integers(0, 3))):
                own[at] = "q"
            lines.append("".join(own))
    df = spark.createDataFrame(list(enumerate(lines)), "doc_id long, text string").repartition(5)
    sets = [frozenset(t[i : i + 8] for i in range(len(t) - 7)) for t in map(line_dedup.normal, lines)]
    pairs = [(i, j) for i in range(len(sets)) for j in range(i) if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j])]
    want = union_find(pairs, range(len(lines)))
    assert {r.doc_id: r.first_doc for r in line_dedup.line_components(df).collect()} == want


def test_language_on_held_out_rows(spark, docs):
    rows = {r.doc_id: r for r in queries.op4_language(spark, "/root/testdata/sf0.01").collect()}
    truth = {r.doc_id: r.lang for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").collect()}
    held = [i for i, r in rows.items() if r.held_out]
    assert all(r.held_out == (zlib.crc32(str(i).encode()) % 4 == 2) and 0 <= r.score <= 1 for i, r in rows.items())
    assert np.mean([rows[i].lang_pred == truth[i] for i in held]) > 0.97
    assert sum(r.rejected for r in rows.values()) <= 0.01 * len(rows)


def test_language_query_against_plain_counting(spark):
    """Counts by dictionary, cosines by loops: the query's languages and scores."""
    sf, mask = "/root/testdata/sf0.01", (1 << 32) - 1
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = language.train(docs.where(language.remainder("doc_id", 4) != 2))
    p = [int(x) for x in language._P]

    def hashed(gram):
        h = ord(gram[0]) * p[0] & mask
        for k, c in enumerate(gram[1:], 1):
            h = ((h ^ h >> 15) * p[k] + ord(c) * p[0]) & mask
        h ^= h >> 13
        return (h * (p[1] + 2 * len(gram)) & mask) >> 20

    got = {r.doc_id: r for r in queries.op4_language(spark, sf).collect()}
    rows = sorted(docs.select("doc_id", "text").collect())
    assert len(got) == len(rows)
    for r in rows[::25]:
        text = "".join(c if c.isalpha() else " " for c in f" {r.text.lower()} ")
        text = " " + " ".join(text.split()) + " "
        tf = Counter(hashed(text[i : i + n]) for n in (1, 2, 3) for i in range(len(text) - n + 1) if n > 1 or text[i] != " ")
        v = np.zeros(language.DIMS)
        for k, c in tf.items():
            v[k] = np.log1p(np.log1p(c)) * model.idf[k]
        cosine = model.centroids @ (v / max(np.linalg.norm(v), 1e-12))
        assert got[r.doc_id].lang_pred == model.names[model.language[cosine.argmax()]] or np.sort(cosine)[-1] - np.sort(cosine)[-2] < 1e-5
        assert got[r.doc_id].score == pytest.approx(min(1, max(0, cosine.max())), abs=1e-4)


def test_language_hard_rows(spark, hard, empty, docs):
    model = language.fit([(lang, t) for _, t, lang in docs if any(map(str.isalpha, t))])
    rows = language.predict(hard, model).collect()
    assert len(rows) == len(HARD)
    assert all(r.lang_pred == "und" and r.score == 0 for r in rows if r.doc_id in (1, 2, 3, 8))
    kept = language.recognised(hard, model)
    assert kept.columns == hard.columns
    assert 1 not in [r.doc_id for r in kept.collect()]
    assert language.predict(hard, None).where("lang_pred != 'und'").count() == 0
    assert language.train(empty) is None
    assert language.predict(empty, model).count() == 0
    far = model.predict(["Съешь же ещё этих мягких французских булок да выпей чаю " * 20])[0]
    assert far[2]  # a script that no language was learned from


def test_language_of_texts_without_letters_of_any_plane(docs):
    model = language.fit([(lang, t) for _, t, lang in docs if any(map(str.isalpha, t))])
    got = model.predict(["\U0001f600", "。。！", "\u3000\u3001 12", "日本語", "𝔞"])
    assert [g[0] == "und" for g in got] == [True, True, True, False, False]


def test_merge_dropout_round_trips(docs):
    import sentencepiece

    path = tokenizer_path("piece_bpe_32k.model")
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    plain, varied = merge_dropout.Codec(path, 0.0), merge_dropout.Codec(path, 0.3)
    texts = [t for _, t, _ in docs][:60] + ["", " ", "a  b", " lead ", "x\n\ny", "tab\there\r\n", "日本語 😀", "é ﬁ"]
    assert [plain.encode(t) for t in texts] == [sp.encode(t) for t in texts]
    for t in [*texts, "▁", "a▁b ▁ c", LONG]:
        assert varied.decode(varied.encode(t, 3)) == t
    t = texts[0]
    assert varied.encode(t, 1) == merge_dropout.Codec(path, 0.3).encode(t, 1)
    assert varied.encode(t, 1) != varied.encode(t, 2)
    assert merge_dropout.Codec(path, 0.3, 9).encode(t, 1) != varied.encode(t, 1)
    words = sorted({w for t in texts for w in varied._split(t, 0)[0] if w and all(varied.of_char[ord(c)] >= 0 for c in w)})
    bulk = varied.segment_all(words, (np.arange(len(words)) % 4).astype(np.uint64))
    assert [tuple(b) for b in bulk] == [varied.segment(w, k % 4) for k, w in enumerate(words)]


def test_merge_dropout_draws_every_occurrence_apart():
    codec = merge_dropout.Codec(tokenizer_path("piece_bpe_32k.model"), 0.3)
    word = merge_dropout.MARK + "internationalisation"
    text = " ".join([word[1:]] * 400)
    words, draws = codec._split(text, 7)
    want = [codec.segment(w, int(k)) for w, k in zip(words, draws, strict=True)]
    assert words == [word] * 400 and codec.encode(text, 7) == [i for ids in want for i in ids]
    assert len(set(want)) > 50  # at most four before
    assert np.mean(codec.skipped(np.repeat(draws, 20), np.tile(np.arange(20), 400))) == pytest.approx(0.3, abs=0.02)


def test_merge_dropout_query_against_one_word_at_a_time(spark, docs):
    codec = merge_dropout.Codec(tokenizer_path("piece_bpe_32k.model"))
    rows = {r.doc_id: r for r in queries.op5_merge_dropout(spark, SF).collect()}
    assert len(rows) == len(docs) and all(r.lossless for r in rows.values())
    for d, t, _ in docs:
        words, draws = codec._split(t, d)
        ids = [i for w, k in zip(words, draws.tolist(), strict=True) for i in (codec.segment(w, k) if w else [codec.byte[b] for b in merge_dropout.MARK.encode()])]
        assert (rows[d].n_tokens, rows[d].ids_crc32, rows[d].n_chars) == (len(ids), zlib.crc32(np.array(ids, "<i4").tobytes()), len(t))


def test_merge_dropout_hard_rows(hard, empty):
    path = tokenizer_path("piece_bpe_32k.model")
    rows = merge_dropout.round_trips(hard, path).collect()
    assert len(rows) == len(HARD) and all(r.lossless for r in rows)
    back = merge_dropout.decode(merge_dropout.encode(hard, path), path)
    assert Counter((r.doc_id, r.text) for r in back.collect()) == Counter((i, t or "") for i, t in HARD)
    assert merge_dropout.round_trips(empty, path).count() == 0


def test_word_encoding_equals_the_tokenizer(docs):
    enc = WordEncoder(tokenizer_path("word_bpe_49k.json"))
    texts = [t for _, t, _ in docs] + [None, "", "J̌ ǰ it's IT'S don't", "<|endoftext|> a<|startoftext|>b", "ÉÀ straße ΑΣ ΑΣ. İi ÷ a÷b", "a b c\x1cd\x0be", "日本語。", "x*** it' 5.5 a1. 1a. foo_bar", LONG]
    want = [e.ids for e in enc.tokenizer.encode_batch([t or "" for t in texts], add_special_tokens=False)]
    assert [np.frombuffer(b, enc.dtype).tolist() for b in enc.encode(texts)] == want


def test_token_shards_read_back(spark, docs, hard, empty):
    rows = queries.op6_token_shards(spark, SF).orderBy("doc_id").collect()
    enc, start = WordEncoder(tokenizer_path("word_bpe_49k.json")), 0
    for r, (i, t, _) in zip(rows, sorted(docs), strict=True):
        ids = np.append(np.frombuffer(enc.encode([t])[0], enc.dtype), 2).astype("<u4")
        assert (r.doc_id, r.start, r.n_tokens, r.ids_crc32) == (i, start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)
    _, manifest = sstable.write_shards(hard, tokenizer_path("word_bpe_49k.json"), shards=3)
    back = [x for m in manifest for x in sstable.read_shard(m.file).scan()]
    order = [i for i, _ in back]
    assert order == sorted((i for i, _ in HARD), key=lambda i: (i is not None, i or 0))
    for m in manifest:
        reader = sstable.read_shard(m.file)
        own = defaultdict(list)
        for i, ids in reader.scan():
            own[i].append(ids.tolist())
        assert all([x.tolist() for x in reader.get(i)] == v for i, v in own.items())
        assert reader.get(10**12) == []
    assert sstable.digests(spark, sstable.write_shards(empty, tokenizer_path("word_bpe_49k.json"))[1]).count() == 0


def test_shard_keys_sort_as_ids():
    ids = [None, -(2**63), -5, -1, 0, 1, 255, 256, 2**63 - 1]
    keys = [sstable.key_of(i) for i in ids]
    assert keys == sorted(keys) and [sstable.id_of(k) for k in keys] == ids


def test_leaks_against_brute_force(spark):
    got = {(r.doc_id, r.item_id) for r in queries.op7_benchmark_leaks(spark, "/root/testdata/sf0.01").collect()}
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").collect()
    items = [decontaminate.Item(r.item_id, r.text) for r in spark.read.parquet("/root/testdata/sf0.01/benchmark.parquet").collect()]
    want = set()
    for d in docs:
        w = decontaminate.words(d.text)
        there = decontaminate.shingles(w)
        for i in items:
            if there & i.all:
                a, q, s = i.overlaps(w)
                if a >= 0.8 or (q >= 0.8 and s >= 0.5):
                    want.add((d.doc_id, i.item_id))
    assert got == want and want


def test_wand_finds_what_scoring_everything_finds():
    rng = np.random.default_rng(5)
    items = [(k, " ".join(rng.choice(WORDS, 25))) for k in range(150)]
    index = decontaminate.Index(items)
    for _ in range(60):
        query = {w.encode() for w in rng.choice(WORDS, 30)}
        scores = Counter()
        for t in query:
            if t in index.postings:
                for d, w in zip(*index.postings[t][:2], strict=True):
                    scores[d] += w
        for threshold in (0.3, 0.6):
            found = dict(index.search(query, threshold))
            assert set(found) == {d for d, s in scores.items() if s >= threshold - 1e-12}
            assert all(found[d] == pytest.approx(scores[d]) for d in found)


def test_short_items_count_where_all_their_words_follow_each_other(spark):
    items = spark.createDataFrame([(1, "Who wrote the odd book? Ada."), (2, "yes"), (3, "..."), (4, "the odd book")], "item_id long, text string")
    texts = ["so who wrote the odd book ada asked", "who wrote the book, the odd one? ada", "yesterday", "well, YES!", None, "", "an odd book"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert {(r.doc_id, r.item_id) for r in decontaminate.contaminated(df, items).collect()} == {(0, 1), (0, 4), (3, 2)}
    assert {r.doc_id for r in decontaminate.clean(df, items).collect()} == {1, 2, 4, 5, 6}


def test_leaks_hard_rows(spark, hard, empty, monkeypatch):
    items = spark.createDataFrame([(1, "The cat sat on the mat and looked at the dog for a very long while."), (2, None), (3, ""), (None, "nothing of this is in any of the documents here at all")], "item_id long, text string")
    assert {r.doc_id for r in decontaminate.contaminated(hard, items).collect()} == {5, 6}
    kept = decontaminate.clean(hard, items)
    assert kept.columns == hard.columns and kept.count() == len(HARD) - 3
    assert decontaminate.contaminated(hard, items.where("false")).count() == 0
    assert decontaminate.clean(empty, items).count() == 0
    monkeypatch.setattr(decontaminate, "INDEX_BYTES", 10)  # a pass for each item
    assert {r.doc_id for r in decontaminate.contaminated(hard, items).collect()} == {5, 6}


def test_pseudonyms_keep_formats_links_and_validity(spark):
    texts = ["+1 (017) 555-7713", "4111111111111111", "4111 1111 1111 1111", "4111111111111112", "97.51.17.173", "300.1.1.1", "2020-02-29", "31.12.1999", "12/25/2020", "2021-02-30", "123-45-6789", "000-12-3456", "a.b@mail.example.com", "DE89370400440532013000", "DE89370400440532013001", "0" * 39 + "f"]
    df = spark.createDataFrame([(k, f"see {t} now, {t}.") for k, t in enumerate(texts)], "doc_id long, text string")
    rows = {r.doc_id: r for r in pii.pseudonymise(df).collect()}
    untouched = {3, 5, 9, 11, 14}
    for k, t in enumerate(texts):
        assert (rows[k].n_replaced == 0) == (k in untouched), t
        if k not in untouched:
            assert t not in rows[k].text
            a, b = rows[k].text.removeprefix("see ").removesuffix(".").split(" now, ")
            assert a == b and (k in (4, 12) or len(a) == len(t))
    digits = lambda s: [int(c) for c in s if c.isdigit()]
    luhn = lambda d: sum(d[::-1][0::2]) + sum(2 * x - 9 * (x > 4) for x in d[::-1][1::2])
    one, spaced = (rows[k].text.split("see ")[1].split(" now")[0] for k in (1, 2))
    assert luhn(digits(one)) % 10 == 0 and digits(one) == digits(spaced)
    assert all(int(x) < 256 for x in rows[4].text.split("see ")[1].split(" now")[0].split("."))
    iban = rows[13].text.split("see ")[1].split(" now")[0]
    assert int("".join(str(int(c, 36)) for c in iban[4:] + iban[:4])) % 97 == 1
    assert pii.pseudonymise(df, key="other").where("doc_id = 1").first().text != rows[1].text


def test_permutations_are_one_to_one(spark):
    from pyspark.sql import functions as F

    n = spark.range(1000).select(F.lpad(F.col("id").cast("string"), 3, "0").alias("s")).select(pii._feistel(F.col("s"), pii.DIGITS, "t", "k").alias("o"))
    assert {r.o for r in n.collect()} == {f"{k:03d}" for k in range(1000)}
    d = spark.sql("SELECT date_format(date_add(date'1990-01-01', cast(id AS int)), 'yyyy-MM-dd') AS s FROM range(2000)").select(pii.date(F.col("s"), "k").alias("o"))
    assert len({r.o for r in d.collect()} - {None}) == 2000


def test_pseudonyms_leave_look_alikes_alone(spark):
    """No issuer's prefix, octets with leading zeros, version numbers, area codes that don't exist."""
    same = ["9807915762804490", "010.001.1.1", "v1.2.3.4", "version 1.2.3.4", "123-456-7890", "213-056-7890", "1234567890123"]
    df = spark.createDataFrame(list(enumerate(same)), "doc_id long, text string")
    assert {r.doc_id: (r.text, r.n_replaced) for r in pii.pseudonymise(df).collect()} == {k: (t, 0) for k, t in enumerate(same)}
    cards = ["4111111111111111", "5500005555555559", "340000000000009", "6011000000000004", "2221000000000009"]
    rows = pii.pseudonymise(spark.createDataFrame(list(enumerate(cards)), "doc_id long, text string")).orderBy("doc_id").collect()
    assert all(r.n_replaced == 1 and len(r.text) == len(c) and r.text[0] == c[0] and r.text != c for r, c in zip(rows, cards, strict=True))
    phones = [f"{a}-{b}-{c}" for a in ("212", "913") for b in ("555", "200", "777") for c in ("0123", "9999", "4567")]
    out = [r.text for r in pii.pseudonymise(spark.createDataFrame([(p,) for p in phones], "text string")).collect()]
    assert len(set(out)) == len(phones) and all(o[0] in "23456789" and o[4] in "23456789" for o in out)
    linked = pii.pseudonymise(spark.createDataFrame([("212-555-0123",), ("+1 (212) 555-0123",)], "text string")).collect()
    assert "".join(filter(str.isdigit, linked[0].text)) == "".join(filter(str.isdigit, linked[1].text))[1:]


def test_pseudonyms_query_over_whole_texts(spark):
    """The registered query: what isn't found stays to the letter, and equal values stay equal in all documents."""
    import re

    before = {r.doc_id: r.text for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    link = {}
    for r in queries.op8_pii_pseudonyms(spark, SF).collect():
        old, new = before[r.doc_id], r.text
        parts = re.split(pii.EMAIL, old)
        assert r.n_replaced or old == new
        assert [p for p in re.split(pii.EMAIL, new)][0][:5] == parts[0][:5]
        for a, b in zip(re.findall(pii.EMAIL, old), re.findall(pii.EMAIL, new), strict=True):
            assert link.setdefault(a.lower(), b) == b != a
    assert len(set(link.values())) == len(link)


def test_pseudonyms_hard_rows(hard, empty):
    out = pii.pseudonymise(hard)
    assert set(out.columns) == set(hard.columns)
    assert Counter(r.text for r in out.collect()) == Counter(t for _, t in HARD)
    assert pii.pseudonymise(empty).count() == 0


def test_subsequence_kernel_against_enumeration():
    def features(word):
        f = Counter()
        for i in range(len(word)):
            for j in range(i + 1, len(word)):
                for k in range(j + 1, min(len(word), i + toxicity.SPAN)):
                    if all(c.isalpha() for c in (word[i], word[j], word[k])):
                        f[word[i] + word[j] + word[k]] += toxicity.DECAY ** (k - i + 1)
        return f

    for word in ("abcab", "id-iot", "aaaa", "ab"):
        number, weight = toxicity.subsequences(toxicity.codes([word]))
        want = sum(v * v for v in features(word).values())
        assert (toxicity.self_kernel(number, weight)[0] if number.shape[1] else 0) == pytest.approx(want)


def test_toxicity_bound_spares_no_window_that_the_kernel_reaches():
    for word in ("scum", "grub", "idiot", "trash"):
        marks = toxicity.Landmarks([f"\2{word}\3"])
        model = toxicity.Model(0.5, marks, np.ones(1), -1.0, marks.bounds(np.zeros(1, int)))
        for sign in ("-", "--"):
            own = toxicity.windows(sign.join(word))
            assert model.margins(own) == pytest.approx(marks.kernel_of(own) @ model.alpha - 1.0), own
    assert model.margins(toxicity.windows("t--r--a--s--h")).max() > -1.0


def test_toxicity_on_held_out_rows(spark):
    rows = {r.doc_id: r for r in queries.op9_toxicity(spark, "/root/testdata/sf0.1").collect()}
    labels = {r.doc_id: r.toxic for r in spark.read.parquet("/root/testdata/sf0.1/labels.parquet").collect()}
    held = [i for i in labels if i in rows and rows[i].held_out]
    hit = [rows[i].predicted for i in held if labels[i] == 1]
    assert np.mean([rows[i].predicted == labels[i] for i in held]) > 0.97
    assert np.mean(hit) > 0.85
    assert all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in rows.values())


def test_toxicity_query_against_plain_kernels(spark):
    """Kernels by enumeration of subsequences, one word and one landmark at a time."""
    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = toxicity.train(docs, spark.read.parquet(f"{sf}/labels.parquet").where(language.remainder("doc_id", 5) != 0))

    def features(word):
        f, c = Counter(), toxicity.codes([word])[0].tolist()
        for i in range(len(c)):
            for j in range(i + 1, len(c)):
                for k in range(j + 1, min(len(c), i + toxicity.SPAN)):
                    if c[i] and c[j] and c[k]:
                        f[c[i], c[j], c[k]] += toxicity.DECAY ** (k - i + 1)
        norm = sum(v * v for v in f.values()) ** 0.5
        return {k: v / norm for k, v in f.items()}

    marks = [features(w) for w in model.marks.words]
    known = {}

    def near(window):
        if window not in known:
            own = features(window)
            raw = [sum(v * m.get(k, 0) for k, v in own.items()) for m in marks]
            known[window] = np.array([np.exp((min(x, 1) - 1) / toxicity.WIDTH) if x >= toxicity.CUT else 0 for x in raw])
        return known[window]

    got = {r.doc_id: r.score for r in queries.op9_toxicity(spark, sf).collect()}
    rows = sorted(docs.select("doc_id", "text").collect())
    assert len(got) == len(rows)
    for r in [r for r in rows if len(r.text) < 1500][::40]:
        words = toxicity.words_of(r.text)
        kernels = np.max([near(p) for w in words for p in toxicity.windows(w)], axis=0, initial=0)
        margin = kernels @ model.alpha + model.length * np.log1p(len(words)) / 5 + model.bias
        assert got[r.doc_id] == pytest.approx(1 / (1 + np.exp(-(model.curve[0] * margin + model.curve[1]))), abs=1e-4)


def test_toxicity_tolerates_gaps_and_hard_rows(spark, hard, empty):
    rng = np.random.default_rng(3)
    rows = [(" ".join(rng.choice(WORDS, 20)), 0) for _ in range(80)] + [(" ".join([*rng.choice(WORDS, 20), "scoundrel"]), 1) for _ in range(40)]
    model = toxicity.fit(rows)
    clean, plain, cut, apart = model.scores([rows[0][0], *(f"{rows[1][0]} {x}" for x in ("scoundrel", "scoun-drel", "s c o u n d r e l"))])
    assert plain > 0.5 > clean and cut > 0.5 and apart > 0.5
    out = toxicity.score(hard, model).collect()
    assert len(out) == len(HARD) and all(0 <= r.score < 0.5 for r in out)
    assert toxicity.score(empty, model).count() == 0
    labels = spark.createDataFrame([], "doc_id long, toxic int")
    assert {r.score for r in toxicity.score(hard, toxicity.train(hard, labels)).collect()} == {0.0}


def test_plain_words_skip_the_normaliser():
    """Words that need no normalising are encoded without it, to the same ids; control blanks and special names aren't such."""
    path = tokenizer_path("word_bpe_49k.json")
    plain = ["the old été, (words)! c0ûté", "naïve çà.- ÿ þ", "", None]
    odd = ["a\rb\x0b\x85c", "Ωé É\u0301 <|endoftext|>x it's", "a<|startoftext|>", "\xa0 \xad soft\xadhyphen"]
    whole = WordEncoder(path).tokenizer
    enc = WordEncoder(path)
    ids = [np.frombuffer(b, enc.dtype).tolist() for b in enc.encode(plain[:2] + odd + plain[2:])]
    assert ids == [whole.encode(t or "", add_special_tokens=False).ids for t in plain[:2] + odd + plain[2:]]
    enc = WordEncoder(path)
    enc._direct = lambda chunks: {c: pytest.fail(f"{c!r} went through it") for c in chunks}
    enc.tokenizer = None
    assert np.frombuffer(enc.encode(["the old été, words!"])[0], enc.dtype).tolist() == whole.encode("the old été, words!", add_special_tokens=False).ids


def test_pages_article_text(spark):
    import html
    import re

    for r in queries.op3_html_text(spark, SF).join(spark.read.parquet(f"{SF}/pages.parquet").select("page_id", "html"), "page_id").collect():
        parts = re.split(r"</?(?:p|h1)>", re.search(r"<article>(.*)</article>", r.html, re.S)[1])
        want = [" ".join(html.unescape(re.sub(r"<[^>]*>", "", p)).split()) for p in parts]
        assert r.text == "\n".join(p for p in want if p) and r.n_chars == len(r.text)


def test_pages_without_articles_lose_repeated_runs():
    menu = "<p>home news sport weather travel food culture games archive contact</p>"
    pages = [html_text.blocks_of(f"<body>{menu}<p>{' '.join(WORDS[k : k + 12])} page {k}</p><p>{menu[3:-4]}</p></body>") for k in range(0, 30, 10)]
    assert html_text.texts_of(pages) == [f"{' '.join(WORDS[k : k + 12])} page {k}" for k in range(0, 30, 10)]
    same = [html_text.blocks_of("<p>one article that two addresses of a host carry word for word</p>")] * 2
    assert html_text.texts_of(same) == ["one article that two addresses of a host carry word for word"] * 2  # copies aren't furniture


def test_pages_of_a_host_give_equal_texts_on_any_number_of_partitions(spark, monkeypatch):
    """Cohorts follow the pages, not the partitions; a menu that no cohort lacks goes everywhere."""
    menu = "<p>home news sport weather travel food culture games archive contact</p>"
    rows = [(k, "http://one.host/p" if k % 7 else "http://two.host/p", f"<body>{menu}<p>{' '.join(WORDS[(k * 5 + j * j) % len(WORDS)] for j in range(14))} page {k}</p></body>") for k in range(120)]
    rows.append((500, "http://two.host/long", f"<article><p>{LONG}</p></article><p>left open by structure and unique</p>"))
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    results = []
    monkeypatch.setattr(html_text, "PAGES", 25)
    before = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        for n in (1, 8, 61):
            spark.conf.set("spark.sql.shuffle.partitions", n)
            results.append(sorted((r.page_id, r.text) for r in html_text.extract(df.repartition(n)).collect()))
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    assert results[0] == results[1] == results[2]
    texts = dict(results[0])
    assert len(texts) == len(rows) and all("sport weather" not in t for t in texts.values()) and all(f"page {k}" in texts[k] for k in range(120))
    assert texts[500] == " ".join(LONG.split()) + "\nleft open by structure and unique"


def test_large_hosts_are_compared_whole(spark, monkeypatch):
    """Substrings on a fifth of a host's pages, few or none of them in one cohort, and others just below, as if all pages were in one task."""
    rng = np.random.default_rng(3)
    line = lambda *at: "<p>" + " ".join(f"{WORDS[(at[0] * 7 + j) % len(WORDS)]}{'-'.join(map(str, at))}" for j in range(11)) + "</p>"
    pages = []
    for k in range(60):
        shared = "".join(line(m) for m in range(12) if rng.random() < (0.2 if m % 2 else 0.17))
        pages.append(f"<body>{'<nav>' + line(0) + '</nav>' if k % 9 == 0 else ''}{shared}{line(100, k)}<article>{line(3) if k % 11 == 0 else ''}{line(200, k)}</article></body>")
    pages += [pages[5]] * 3 + ["", None]
    df = spark.createDataFrame([(k, "http://one.host/p", page) for k, page in enumerate(pages)], "page_id long, url string, html string")
    monkeypatch.setattr(html_text, "PAGES", 5)
    for structure in (True, False):
        want = html_text.texts_of([html_text.blocks_of(page) for page in pages], structure)
        got = {r.page_id: (r.text, r.n_chars) for r in html_text.extract(df, structure=structure).collect()}
        assert got == {k: (t, len(t)) for k, t in enumerate(want)}


def _boilerplate(pages, structure):
    """(host, hash) of runs on a fifth of a host's contents, two at least, counted one by one. pages: (host, html)."""
    kinds, on, known = defaultdict(set), defaultdict(set), html_text._Hashes()
    for host, page in pages:
        blocks = html_text.blocks_of(page)
        kind = tuple(t for r, t in blocks if r != html_text.FURNITURE or not structure)
        kinds[host].add(kind)
        for h in html_text.run_hashes(" ".join(t for _, t in blocks).lower().split(), known).tolist():
            on[host, h].add(kind)
    return {(host, h) for (host, h), own in on.items() if len(own) >= max(2, int(np.ceil(html_text.SHARE * len(kinds[host]))))}


def test_hosts_that_structure_decides_go_through_the_array_too(spark, monkeypatch):
    """All given pages have articles, and no block that structure leaves open; each host is compared and each page gets the array's verdict."""
    df = spark.read.parquet(f"{SF}/pages.parquet")
    rows = df.select(html_text.host_of("url").alias("host"), "page_id", "url", "html")
    want = _boilerplate([(r.host, r.html) for r in rows.collect()], True)
    texts = html_text.extract(df)
    assert "MapInArrow" in texts._jdf.queryExecution().optimizedPlan().toString()
    got, boilerplate = [], html_text.boilerplate
    monkeypatch.setattr(html_text, "boilerplate", lambda *a: got.append(boilerplate(*a)) or got[-1])
    for pages in (html_text.PAGES, 3):
        monkeypatch.setattr(html_text, "PAGES", pages)
        assert sorted(html_text.extract(df).collect()) == sorted(texts.collect())
    for total, _, found in got:
        runs = [tuple(r) for r in found.collect()]
        assert total == df.count() and len(runs) == len(set(runs)) and set(runs) == want and want


@pytest.mark.parametrize("many", [1.1, 10])
def test_cohorts_add_up_to_the_host(spark, monkeypatch, many):
    """Runs close to the share, contents on more pages than a cohort has, and what cohorts leave out."""
    rng = np.random.default_rng(5)
    line = lambda *at: "<p>" + " ".join(f"{WORDS[(at[0] * 7 + j) % len(WORDS)]}{'-'.join(map(str, at))}" for j in range(9)) + "</p>"
    html = lambda k, own: f"<body><nav>{''.join(line(m) for m in range(30) if rng.random() < 0.14 + m / 300)}{line(300, k)}</nav><article>{own}</article></body>"
    pages = [html(k, line(100, k)) for k in range(150)] + [html(k, line(200)) for k in range(150, 190)] + [""] * 15
    df = spark.createDataFrame([("one.host", k, f"http://one.host/{k}", page) for k, page in enumerate(pages)], "host string, page_id long, url string, html string")
    runs, asked = html_text._runs, []
    monkeypatch.setattr(html_text, "_runs", lambda many: asked.append(many) or runs(many))
    monkeypatch.setattr(html_text, "PAGES", 12)
    monkeypatch.setattr(html_text, "MANY", many)
    for structure in (True, False):
        found = html_text.boilerplate(df, structure, html_text.Tables(spark))[2]
        assert {tuple(r) for r in found.collect()} == _boilerplate([("one.host", page) for page in pages], structure) != set()
    assert asked == ([many, float("inf")] * 2 if many < 10 else [many] * 2)
    got = [r.text for r in html_text.extract(df.drop("host")).orderBy("page_id").collect()]
    assert got == html_text.texts_of([html_text.blocks_of(page) for page in pages])


def test_the_array_alone_finds_menus_without_tags(spark):
    from pyspark.sql import functions as F

    pages = spark.read.parquet("/root/testdata/sf0.1/pages.parquet")
    alone = {r.page_id: r.text for r in html_text.extract(pages, structure=False).collect()}
    both = {r.page_id: r.text for r in html_text.extract(pages).collect()}
    assert alone.keys() == both.keys() and pages.agg(F.count("*")).first()[0] == len(both)
    kept = np.mean([len(set(both[k].split("\n")) & set(alone[k].split("\n"))) / len(set(both[k].split("\n"))) for k in both if both[k]])
    assert kept > 0.5  # hosts repeat articles: the array alone takes some of them for furniture


def test_repeats_against_brute_force():
    rng = np.random.default_rng(4)
    page = np.repeat(np.arange(6), 60)
    tokens = rng.integers(0, 3, 360)
    for run in (5, 6, 8):
        runs = defaultdict(set)
        for i in range(360 - run + 1):
            if page[i] == page[i + run - 1]:
                runs[tuple(tokens[i : i + run])].add(page[i])
        want = np.zeros(360, bool)
        for i in range(360 - run + 1):
            if page[i] == page[i + run - 1] and len(runs[tuple(tokens[i : i + run])]) > 1:
                want[i : i + run] = True
        assert (html_text.repeats(tokens, page, page, run) == want).all()


def test_pages_hard_rows(spark):
    rows = [(1, None, None), (2, "", ""), (3, "http://h/", "<p>broken <b>mark<up &amp; text"), (None, None, "<article><p>no id</p></article>"), (4, "http://h/", "plain < text > only"), (5, "http://h/", "<article>" + "<div>" * 3000 + "deep" + "</article>"), (5, "http://h/", '<div id="comments">x</div><article><h1>T</h1><form>f</form><p>a&nbsp;b<br>c</p><section class="user-comments">no</section></article>')]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "1 AS text", "2 AS host")
    got = sorted(((r.page_id, r.text) for r in html_text.extract(df).collect()), key=str)
    assert len(got) == len(rows)
    assert (1, "") in got and (2, "") in got and (None, "no id") in got and (5, "deep") in got and (5, "T\na b c") in got
    assert html_text.extract(df.where("false")).count() == 0


def test_pipeline_keeps_rows_that_share_an_id(spark):
    """Group stage: a row goes only if its own text is a copy; of rows alike, one stays."""
    import corpus_pipeline as C

    rng = np.random.default_rng(12)
    a, z, y = (" ".join(rng.choice(WORDS, 60)) for _ in range(3))
    rows = [(1, a, 10), (2, a, 11), (2, z, 12), (3, y, 13), (3, y, 14), (None, a, 15)]
    df = spark.createDataFrame(rows, "doc_id long, text string, group_doc int")
    out = C.one_of_each_group(spark, df, SF)
    assert out.columns == df.columns
    assert sorted((r.doc_id or 0, r.text) for r in out.collect()) == sorted([(0, a), (1, a), (2, z), (3, y)])


def test_pipeline_stages(spark):
    import corpus_pipeline as C

    docs = spark.read.parquet(f"{SF}/documents.parquet").persist()
    ids = lambda df: {r.doc_id for r in df.select("doc_id").collect()}
    before = docs
    for name, stage in C.STAGES[:-1]:
        after = stage(spark, before, SF).persist()
        assert after.columns == docs.columns and ids(after) <= ids(before), name
        rows = before.select("doc_id", "text").collect()
        if name == "language":
            model = language.train(before.where(language.remainder("doc_id", 4) != 2))
            assert ids(after) == {r.doc_id for r, (_, _, no) in zip(rows, model.predict([r.text for r in rows]), strict=True) if not no}
        if name == "line_dedup":
            gone = kept_by_brute_force([tuple(r) for r in rows], line_dedup.MIN_CHARS)
            left = {r.doc_id: "\n".join(x for at, x in enumerate(r.text.split("\n")) if at not in gone[k]) for k, r in enumerate(rows)}
            assert {r.doc_id: r.text for r in after.collect()} == {d: t for d, t in left.items() if t.split()}
        if name == "decontamination":
            items = [decontaminate.Item(r.item_id, r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
            held = lambda t: any(a >= 0.8 or (q >= 0.8 and s >= 0.5) for a, q, s in (i.overlaps(decontaminate.words(t)) for i in items))
            assert ids(after) == {r.doc_id for r in rows if not held(r.text)}
        if name == "simhash":
            fp = simhash.fingerprint_batch([r.text for r in before.collect()])
            order = [r.doc_id for r in before.collect()]
            groups = union_find([(a, b) for (a, x), (b, y) in ((p, q) for k, p in enumerate(zip(order, fp.tolist(), strict=True)) for q in list(zip(order, fp.tolist(), strict=True))[k + 1 :]) if (x ^ y).bit_count() <= 4], order)
            assert ids(after) == {n for n, r in groups.items() if n == r}
        before = after
    last = C.run(spark, SF)
    assert ids(last) == ids(before) and all(r.lossless for r in last.collect())


def test_pipeline_stages_on_hard_and_empty_tables(spark, hard, empty):
    from pyspark.sql import functions as F

    import corpus_pipeline as C

    left = {
        "language": Counter({4: 1, 5: 1, 6: 2, None: 1, 7: 1, -9: 1}), "line_dedup": Counter({None: 2, 1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 7: 1, 8: 1, -9: 1}),
        "simhash": Counter({None: 2, 1: 1, 4: 1, 5: 1, 7: 1, 8: 1, -9: 1}), "decontamination": Counter(i for i, _ in HARD), "sentencepiece": Counter(i for i, _ in HARD),
    }
    labelled = hard.withColumn("lang", F.lit("en"))
    for table in (labelled, empty):
        for name, stage in C.STAGES:
            out = stage(spark, table, SF)
            assert Counter(r.doc_id for r in out.select("doc_id").collect()) == (left[name] if table is labelled else Counter()), name
            assert name == "sentencepiece" or out.columns == table.columns


def test_pairwise_masks_cover_all_differences():
    """Of six blocks at least two agree when four bits differ: some mask keeps both fingerprints together."""
    rng = np.random.default_rng(6)
    for _ in range(300):
        flips = rng.choice(64, 4, replace=False)
        x = sum(1 << int(b) for b in flips)
        assert any(x & m == 0 for m in simhash.masks())
    assert all(b > a for a, b in pairwise(simhash.EDGE))
