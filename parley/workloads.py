"""The experiment workloads: example tables over the given tables, generated federations, and sweeps over both.

A workload on a given table is an example table (party_id, pos, n, split, x, y) of all its rows. Where one fits a task
(plans.choose.TASK_BYTES), sweeps run each setting whole in a task; where not, the distributed loop runs the same rounds.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from parley.functions.draws import laplace_np, mixed, mixed_np, normal_np, uniform, uniform_np
from parley.functions.losses import Linear, Logistic, Mlp, Portfolio, Softmax
from parley.operators import parties
from parley.operators.methods import COMPARED, PERSONAL, STANDARD, Method, Rounds, bench_personal, bench_standard, local_only, standard_methods
from parley.operators.rounds import curve
from parley.operators.simulation import RESULT, Federation, fits, gathered, split, sweep
from parley.sources.tables import Tables, load

CLASSES = 10


def teacher(features: int, classes: int, seed: int) -> np.ndarray:
    return normal_np(seed, 9001, np.arange(classes)[:, None], np.arange(features)[None, :])


# ---- generated federations ---------------------------------------------------------------------------------------------


def planted_regression(n: int, seed: int, d: int = 1000, rows: int = 100, scale_kind: str = "var") -> tuple:
    """Own weights around a common centre, the last party around a far one; decaying input variances."""
    sd = (lambda v: np.sqrt(v)) if scale_kind == "var" else (lambda v: v)
    j = np.arange(d)
    spread = sd(((j % 50) + 1.0) ** -1.1)
    xs, ys = [], []
    for k in range(n):
        base = normal_np(seed, 1, j) * sd(5.0) if k < n - 1 else normal_np(seed, 2, j) * sd(50.0)
        w = base + 0.5 * laplace_np(seed, 3, k, j)
        x = normal_np(seed, 4, k) * sd(0.5) + normal_np(seed, 5, k, np.arange(rows)[:, None], j[None, :]) * spread
        xs.append(x)
        ys.append(x @ w + normal_np(seed, 6, k, np.arange(rows)) * sd(2.0))
    return Linear(d), split(xs, ys, 0.5, seed)


def power_sizes(n: int, seed: int, least: int = 20, most: int = 400) -> np.ndarray:
    """Party sizes by a power law."""
    u = uniform_np(seed, 71, np.arange(n))
    return np.minimum(most, least * u ** (-1 / 1.5)).astype(int)


def softmax_generator(n: int, seed: int, zeta: float = 1000.0, beta: float = 10.0, features: int = 60) -> tuple:
    """Models around party centres of variance zeta, inputs around party centres of variance beta."""
    j, c = np.arange(features), np.arange(CLASSES)
    spread = np.sqrt((j + 1.0) ** -1.2)
    xs, ys = [], []
    for k, size in enumerate(power_sizes(n, seed)):
        u = np.sqrt(zeta) * normal_np(seed, 1, k)
        w, b = u + normal_np(seed, 2, k, c[:, None], j[None, :]), u + normal_np(seed, 3, k, c)
        v = np.sqrt(beta) * normal_np(seed, 4, k) + normal_np(seed, 5, k, j)
        x = v + spread * normal_np(seed, 6, k, np.arange(size)[:, None], j[None, :])
        xs.append(x)
        ys.append((x @ w.T + b).argmax(1))
    return Softmax(features, CLASSES), split(xs, ys, 0.8, seed)


def generated_images(n: int, seed: int, kind: str, features: int = 64) -> tuple:
    """Parties of drawn vectors around ten class centres, at any number of parties.

    kind: robust or personal (equal parties, a tenth of ten or a fifth of more sees negatives; personal: two classes of
    each party blurred), one_label (sizes by a power law) or five_labels.
    """
    centre = 0.6 * teacher(features, CLASSES, 5)
    sizes = power_sizes(n, seed, 8, 120) if kind == "one_label" else np.full(n, 40 if kind == "five_labels" else 200)
    xs, ys, share = [], [], 0.1 if n <= 10 else 0.2
    for k, size in enumerate(sizes):
        own = {"one_label": [k % CLASSES], "five_labels": [(k + j * (1 + k // CLASSES % 2)) % CLASSES for j in range(5)]}.get(kind, range(CLASSES))
        y = np.array(sorted(set(own)))[mixed_np(seed, 41, k, np.arange(size)) % len(set(own))]
        x = centre[y] + normal_np(seed, 42, k, np.arange(size)[:, None], np.arange(features)[None, :])
        if kind in ("robust", "personal") and k < round(share * n):
            x = -x
        if kind == "personal":
            hit = np.isin(y, [(mixed_np(seed, 5, k) + j) % CLASSES for j in range(2)])
            x[hit] += 2 * laplace_np(seed, 6, k, np.arange(hit.sum())[:, None], np.arange(features)[None, :])
        xs.append(x)
        ys.append(y)
    return Softmax(features, CLASSES), split(xs, ys, 0.5 if kind in ("robust", "personal") else 0.8, seed)


# ---- example tables ----------------------------------------------------------------------------------------------------


def placed(rows: DataFrame, share: float, seed: int, key: str) -> DataFrame:
    """(party_id, pos, n, split, x, y): training and test rows, each part of a party numbered by its seeded order."""
    cut = F.ceil(F.col("n") * share).cast("long")
    both = parties.split(rows, share, seed, key)
    test = F.col("split") == "test"
    return both.select(
        "party_id",
        F.when(test, F.col("pos") - cut).otherwise(F.col("pos")).cast("long").alias("pos"),
        F.when(test, F.col("n") - cut).otherwise(cut).cast("long").alias("n"),
        "split", "x", "y",
    )


def labelled_images(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vec_id, x, y): vectors standing for images, at unit variance, with labels that a fixed teacher plants."""
    rows = load(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda a: a.cast("double") * 8.0).alias("x"))
    t = teacher(64, CLASSES, 5)
    scores = F.array(*[F.aggregate(F.zip_with("x", F.array(*[F.lit(float(a)) for a in t[c]]), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v) for c in range(CLASSES)])
    return rows.withColumn("y", (F.array_position(scores, F.array_max(scores)) - 1).cast("double"))


def image_examples(spark: SparkSession, sf_dir: str, n: int = 10, seed: int = 1, share: float = 0.5, noisy: bool = False) -> DataFrame:
    """Equal parties of images; a tenth of ten parties (a fifth of more) sees negatives; noisy: two classes of each blurred."""
    rows = parties.equal(labelled_images(spark, sf_dir), n, seed, "vec_id")
    rows = parties.negate(rows, 0.1 if n <= 10 else 0.2, n)
    if noisy:
        rows = parties.noisy_classes(rows, seed, "vec_id", scale=2.0)
    return placed(rows, share, seed, "vec_id")


def label_examples(spark: SparkSession, sf_dir: str, n: int = 100, seed: int = 1, each: int = 1) -> DataFrame:
    """Every image at one party: parties of one label, sizes by a power law, or of `each` labels."""
    rows = labelled_images(spark, sf_dir).withColumn("label", F.col("y").cast("long"))
    dealt = parties.one_label(rows, n, seed, "vec_id", "label", CLASSES) if each == 1 else parties.some_labels(rows, n, seed, "vec_id", "label", CLASSES, each)
    return placed(dealt, 0.8, seed, "vec_id")


def accounts(docs: DataFrame, n: int, seed: int) -> DataFrame:
    """docs with party_id, an account: each source has its own accounts, n among all sources (a source at least one)."""
    names = docs.select("source").distinct().withColumns({"rank": F.row_number().over(Window.orderBy("source")) - 1, "sources": F.count("*").over(Window.partitionBy(F.lit(1)))})  # a row a source
    first, after = F.floor(F.col("rank") * n / F.col("sources")), F.floor((F.col("rank") + 1) * n / F.col("sources"))
    own = F.least(F.floor(uniform(seed, 13, F.col("doc_id")) * (after - first)), F.greatest(after - first - 1, F.lit(0)))
    return docs.join(names, docs.source.eqNullSafe(names.source)).select(docs["*"], (first + own).cast("long").alias("party_id"))


def labelled_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = load(spark, sf_dir, "labels").select("doc_id", "toxic")
    return load(spark, sf_dir, "documents").select("doc_id", "source", "text").join(labels, "doc_id")


def text_examples(spark: SparkSession, sf_dir: str, n: int = 77, seed: int = 1, features: int = 64) -> DataFrame:
    """Accounts' labelled documents: hashed counts of their distinct words, and whether they are toxic."""
    words = F.filter(F.array_distinct(F.split(F.lower("text"), r"[^\p{L}]+")), lambda w: w != "")
    hashed = F.transform(words, lambda w: F.pmod(F.crc32(w.cast("binary")), F.lit(features)).cast("int"))
    x = F.transform(F.sequence(F.lit(0), F.lit(features - 1)), lambda j: F.size(F.filter("h", lambda h: h == j)) / F.sqrt(F.greatest(F.size("h"), F.lit(1))))
    rows = accounts(labelled_text(spark, sf_dir), n, seed).withColumn("h", hashed)
    return placed(rows.select("party_id", "doc_id", x.alias("x"), F.col("toxic").cast("double").alias("y")), 0.8, seed, "doc_id")


def sequence_examples(spark: SparkSession, sf_dir: str, n: int = 77, seed: int = 1, length: int = 25, symbols: int = 64) -> DataFrame:
    """Accounts' labelled documents cut into sequences of `length` characters, whole texts."""
    docs = accounts(labelled_text(spark, sf_dir), n, seed)
    cut = F.transform(F.sequence(F.lit(0), F.floor(F.greatest(F.length("text") - 1, F.lit(0)) / length)), lambda k: F.substr(F.lower("text"), (k * length + 1).cast("int"), F.lit(length)))
    each = docs.select("party_id", "doc_id", "toxic", F.posexplode(cut).alias("part", "t"))
    x = F.transform(F.sequence(F.lit(1), F.lit(length)), lambda j: F.pmod(F.coalesce(F.ascii(F.substr(F.rpad("t", length, " "), j, F.lit(1))), F.lit(32)), F.lit(symbols)).cast("double"))
    rows = each.select("party_id", (F.col("doc_id") * 100003 + F.col("part")).alias("key"), x.alias("x"), F.col("toxic").cast("double").alias("y"))
    return placed(rows, 0.8, seed, "key")


def price_relatives(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(hour, event_type, relative): for each event type the ratio of its mean value in an hour to that in the hour before."""
    e = load(spark, sf_dir, "events").select(F.date_trunc("hour", "ts").alias("hour"), "event_type", "value")
    hourly = e.groupBy("hour", "event_type").agg(F.avg("value").alias("price"))
    w = Window.partitionBy("event_type").orderBy("hour")
    return hourly.withColumn("relative", F.col("price") / F.lag("price").over(w)).where("relative IS NOT NULL").select("hour", "event_type", "relative")


def portfolio_examples(spark: SparkSession, sf_dir: str, n: int = 8, seed: int = 1, assets: tuple = ("click", "error", "purchase", "signup", "view")) -> DataFrame:
    """Parties trade the same assets in regimes of their own: each has its own stretch of hours and its own tilt of the returns."""
    bounded = F.least(F.greatest("relative", F.lit(0.25)), F.lit(4.0))
    by_hour = price_relatives(spark, sf_dir).groupBy("hour").agg(*[F.coalesce(F.max(F.when(F.col("event_type") == a, bounded)), F.lit(1.0)).alias(f"r{k}") for k, a in enumerate(assets)])
    w = Window.orderBy("hour")  # a row an hour, whatever the number of events
    r = [F.col(f"r{k}") for k in range(len(assets))]
    rows = by_hour.select("hour", F.array(*[F.log(c) for c in r]).alias("x"), F.array(*[F.lead(c).over(w) for c in r]).alias("next"), F.row_number().over(w).alias("at"), F.count("*").over(Window.partitionBy(F.lit(1))).alias("hours"))
    mine = rows.where(F.get("next", F.lit(0)).isNotNull()).withColumn("party_id", F.floor((F.col("at") - 1) * n / (F.col("hours") - 1)).cast("long"))
    tilts = np.exp(0.5 * normal_np(seed, 21, np.arange(n)[:, None], np.arange(len(assets))[None, :]))
    tilt = F.array(*[F.array(*[F.lit(float(a)) for a in row]) for row in tilts])
    y = F.zip_with("next", F.get(tilt, F.col("party_id").cast("int")), lambda a, b: F.least(F.greatest(a * b, F.lit(0.1)), F.lit(10.0)))
    return placed(mine.select("party_id", F.col("at").cast("long").alias("key"), "x", y.alias("y")), 0.5, seed, "key")


def quality_examples(spark: SparkSession, sf_dir: str, seed: int = 1) -> DataFrame:
    """Four measures of labelled documents by source, with their quality label."""
    d = load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels"), "doc_id")
    words = F.split("text", " ")
    size = F.col("n_chars") + 1
    x = F.array(F.log(size + 0.0) / 5, 4.0 * F.length(F.regexp_replace("text", r"[\p{L} ]", "")) / size, 20.0 * F.length(F.regexp_replace("text", "[^\n]", "")) / size, F.size(F.array_distinct(words)) / F.size(words))
    rows = d.select("doc_id", F.regexp_extract("source", r"(\d+)", 1).cast("long").alias("party_id"), x.alias("x"), F.col("quality").cast("double").alias("y"))
    return placed(rows, 0.5, seed, "doc_id")


def order_examples(spark: SparkSession, sf_dir: str, seed: int = 1) -> DataFrame:
    """Nations' orders: price against one and the day of the year."""
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate", "o_totalprice")
    c = load(spark, sf_dir, "customer").select("c_custkey", F.col("c_nationkey").cast("long").alias("party_id"))
    x = F.array(F.lit(1.0), F.dayofyear("o_orderdate") / 366.0)
    return placed(o.join(c, o.o_custkey == c.c_custkey).select("party_id", "o_orderkey", x.alias("x"), (F.col("o_totalprice") / 1e5).alias("y")), 0.8, seed, "o_orderkey")


def planted(rows: DataFrame, features: int, n: int, seed: int) -> DataFrame:
    """rows with y: a linear target by weights of the party's own around common ones; the last party's are far out."""
    k = F.col("party_id")
    weights = [F.when(k == n - 1, 8.0).otherwise(1.0) * (j % 4 + 1) + (F.pmod(mixed(seed, 31, k, j), F.lit(1000)) / 1000.0 - 0.5) for j in range(features)]
    return rows.withColumn("y", F.aggregate(F.zip_with("x", F.array(*weights), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v))


def vector_regression_examples(spark: SparkSession, sf_dir: str, n: int = 10, seed: int = 1) -> DataFrame:
    """Embeddings as inputs of planted regressions, one party far out."""
    rows = parties.equal(load(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda a: a.cast("double")).alias("x")), n, seed, "vec_id")
    return placed(planted(rows, 64, n, seed), 0.5, seed, "vec_id")


def regression_examples(spark: SparkSession, sf_dir: str, seed: int = 1, n: int = 10) -> DataFrame:
    """Lineitem measures with a planted target for each party."""
    x = F.array(F.col("l_quantity") / 50, F.col("l_extendedprice") / 1e5, F.col("l_discount") * 10, F.col("l_tax") * 10)
    rows = load(spark, sf_dir, "lineitem").select(F.pmod(F.col("l_suppkey"), F.lit(n)).alias("party_id"), F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_quantity").alias("row_id"), x.alias("x"))
    return placed(planted(rows, 4, n, seed), 0.5, seed, "row_id")


#: dataset -> loss, example table (spark, sf_dir, n, seed)
ON_TABLES: dict[str, tuple] = {
    "robust_images": (Softmax(64, CLASSES), image_examples),
    "personal_images": (Softmax(64, CLASSES), lambda s, d, n, seed: image_examples(s, d, n, seed, noisy=True)),
    "one_label": (Softmax(64, CLASSES), label_examples),
    "five_labels": (Softmax(64, CLASSES), lambda s, d, n, seed: label_examples(s, d, n, seed, 5)),
    "text": (Logistic(64), text_examples),
    "text_layers": (Mlp(64, 16, 2), text_examples),
    "portfolio": (Portfolio(5, 8, 5), portfolio_examples),
    "vector_regression": (Linear(64), vector_regression_examples),
}
#: dataset -> (loss, federation) of (n, seed), drawn and not read
GENERATED: dict[str, Callable[[int, int], tuple]] = {
    "softmax": softmax_generator,
    "drawn_robust": lambda n, seed: generated_images(n, seed, "robust"),
    "drawn_personal": lambda n, seed: generated_images(n, seed, "personal"),
    "drawn_one_label": lambda n, seed: generated_images(n, seed, "one_label"),
    "drawn_five_labels": lambda n, seed: generated_images(n, seed, "five_labels"),
}


# ---- experiments -------------------------------------------------------------------------------------------------------


def experiment(spark: SparkSession, sf_dir: str, settings: Iterable[tuple], d: int = 1000) -> DataFrame:
    """Results of settings (dataset, n, method, rounds-config, every[, name])."""
    listed = [(*s, s[0]) if len(s) == 5 else s for s in settings]
    generated = GENERATED | {"regression": lambda n, seed: planted_regression(n, seed, d)}
    small: dict[tuple, Federation] = {}
    large: dict[tuple, DataFrame] = {}
    tables = Tables(spark)
    for dataset, n, _, cfg, _, _ in listed:
        key = (dataset, n, cfg.seed)
        if dataset in ON_TABLES and key not in small and key not in large:
            examples = tables.keep(ON_TABLES[dataset][1](spark, sf_dir, n, cfg.seed), "examples")
            if fits(examples, sum(f.nbytes for f in small.values())):  # tasks hold all that are small
                small[key] = gathered(examples)
                tables.drop(examples)
            else:
                large[key] = examples
    shared = spark.sparkContext.broadcast(small)

    def build(dataset: str, n: int, seed: int) -> tuple:
        return (ON_TABLES[dataset][0], shared.value[dataset, n, seed]) if dataset in ON_TABLES else generated[dataset](n, seed)

    inside = [s for s in listed if (s[0], s[1], s[3].seed) not in large]
    out = sweep(spark, inside, build)
    for dataset, n, method, cfg, every, name in listed:
        if (key := (dataset, n, cfg.seed)) in large:
            rows, loss = [], ON_TABLES[dataset][0]
            train, test = (large[key].where(F.col("split") == part) for part in ("train", "test"))
            for done, scores, run in curve(train, test, loss, method, cfg, every):
                worst = F.max("score") if loss.task == "regression" else F.min("score")
                got = scores.agg(F.avg("score").alias("s"), worst.alias("w")).first()
                rows.append((name, n, method.name, cfg.seed, done, got["s"], got["w"], run.log[-1][6], run.log[-1][7]))
            out = out.unionByName(spark.createDataFrame(rows, RESULT))
    return out


def compare_personal(spark: SparkSession, sf_dir: str, rounds: int = 500, seeds: range = range(1, 6), d: int = 1000, every: int = 0, drawn: bool = False) -> DataFrame:
    """Seven methods on five personalised datasets. drawn: generated images in place of the given vectors."""
    settings = []
    names = ("drawn_robust", "drawn_personal") if drawn else ("robust_images", "personal_images")
    for dataset, n in ((names[0], 10), (names[0], 50), (names[1], 10), (names[1], 50), ("regression", 10)):
        regression = dataset == "regression"
        for make in (*COMPARED, *PERSONAL):
            method = make(lam_p=1.0) if regression and make.__name__ == "envelope_personal" else make()
            settings += [(dataset, n, method, bench_personal(regression, rounds=rounds, seed=s), every) for s in seeds]
    return experiment(spark, sf_dir, settings, d)


#: Parties of the standard datasets, and of the ablation over their number.
STANDARD_PARTIES = {"softmax": 30, "drawn_one_label": 1000, "drawn_five_labels": 200, "text": 772}
ABLATION_PARTIES = {"softmax": (3, 15, 30), "drawn_one_label": (100, 500, 1000), "drawn_five_labels": (20, 100, 200), "text": (77, 386, 772)}


def _kind(dataset: str) -> str:
    return dataset.removeprefix("drawn_")


def compare_standard(spark: SparkSession, sf_dir: str, rounds: int = 200, seeds: range = range(1, 6), every: int = 10, sizes: dict | None = None) -> DataFrame:
    """Non-personalised methods against the three variants on the standard datasets."""
    settings = []
    for dataset, n in (sizes or STANDARD_PARTIES).items():
        for method in [*(make() for make in STANDARD), *standard_methods(_kind(dataset))]:
            settings += [(dataset, n, method, bench_standard(_kind(dataset), rounds=rounds, seed=s), every) for s in seeds]
    return experiment(spark, sf_dir, settings)


def party_ablation(spark: SparkSession, sf_dir: str, rounds: int = 200, seeds: range = range(1, 6), counts: dict | None = None) -> DataFrame:
    """Mean score of the three variants as parties are added."""
    settings = [(dataset, n, m, bench_standard(_kind(dataset), rounds=rounds, seed=s), 0) for dataset, ns in (counts or ABLATION_PARTIES).items() for n in ns for m in standard_methods(_kind(dataset)) for s in seeds]
    return experiment(spark, sf_dir, settings).groupBy("dataset", "n_parties").agg(F.avg("score").alias("score"), F.count("*").alias("runs"))


def training_failure(spark: SparkSession, sf_dir: str, rounds: int = 60, n: int = 8, seeds: range = range(1, 6)) -> DataFrame:
    """Change at aggregation and test growth by round, without any adversary."""
    methods: list[Method] = [local_only(), *(make() for make in STANDARD), PERSONAL[0]()]
    cfg = Rounds(0.2, 1.0, rounds, n, 10, 10)
    return experiment(spark, sf_dir, [("portfolio", n, m, replace(cfg, seed=s), 1) for m in methods for s in seeds])


def stragglers(spark: SparkSession, sf_dir: str, rounds: int = 200, seeds: range = range(1, 6), sizes: dict | None = None) -> DataFrame:
    """The three variants as more parties are late."""
    settings = []
    for dataset, n in (sizes or {"softmax": 30, "text": 772}).items():
        for share in (0.0, 0.5, 0.9):
            settings += [(dataset, n, m, bench_standard(dataset, rounds=rounds, seed=s, stragglers=share), 0, f"{dataset} late {share}") for m in standard_methods(dataset) for s in seeds]
    return experiment(spark, sf_dir, settings)
