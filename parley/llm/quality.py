"""Quality rules as a bitmask ledger, built from DataFrame functions only.

Every rule is evaluated once per document; the ledger keeps its measurements and one failure bit for each rule.
Policies are versioned bit masks over that ledger, so changing a policy or asking what a rule contributes never
reads a text again.

Defined results: null and empty texts measure 0 everywhere and fail ``few_words``; repeated rows are judged row by
row; of equal lines or windows the first counts as the original; very long texts are measured whole, in arrays of one
row; an empty table gives an empty ledger; columns other than the id and the text are ignored.
Repeated windows are found by their 64-bit XXH64 within one document (n windows: a false repeat with odds n*n/2**65).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from parley.llm.common import WORD_GAP

WINDOW = 8

#: name -> failing condition over the measurements; a rule's position is its bit.
RULES: dict[str, str] = {
    "few_words": "n_words < 20",
    "repeated_windows": "100 * n_repeat_words > 30 * n_words",
    "symbols": "4 * n_symbols > n_words",
    "repeated_lines": "2 * n_dup_lines > n_lines",
    "tiny_words": "word_chars < 2 * n_words",
    "giant_words": "word_chars > 20 * n_words",
}
BITS = {name: 1 << k for k, name in enumerate(RULES)}

#: version -> rules that must hold.
POLICIES: dict[str, tuple[str, ...]] = {
    "base": ("few_words", "repeated_windows"),
    "v1": ("few_words", "repeated_windows", "symbols"),
    "v2": tuple(RULES),
}


def mask(policy: str | tuple[str, ...]) -> int:
    return sum(BITS[r] for r in (POLICIES[policy] if isinstance(policy, str) else policy))


def measure(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words), each a long."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    step = df.select(
        F.col(id_col),
        F.array_remove(F.split(text, WORD_GAP), "").alias("words"),
        F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")).alias("lines"),
        F.length(F.regexp_replace(text, r"[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"),
    )
    step = step.withColumn("marks", F.when(F.size("words") > WINDOW, F.transform(F.sequence(F.lit(1), F.greatest(F.size("words") - (WINDOW - 1), F.lit(1))), lambda i: F.xxhash64(F.slice("words", i, WINDOW)))))
    sized = step.select(
        id_col,
        F.size("words").cast("long").alias("n_words"),
        F.length(F.array_join("words", "")).cast("long").alias("word_chars"),
        "n_symbols",
        F.size("lines").cast("long").alias("n_lines"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.when(F.size(F.array_distinct("marks")) < F.size("marks"), F.sort_array(F.transform("marks", lambda h, i: F.struct(h.alias("h"), i.alias("at"))))).alias("ranked"),
    )

    def twin(x: Column, i: Column) -> Column:
        same = lambda k: F.coalesce(F.get(F.col("ranked"), k)["h"] == x["h"], F.lit(False))
        return same(i - 1) | same(i + 1)

    placed = sized.withColumn("starts", F.sort_array(F.transform(F.filter("ranked", twin), lambda x: x["at"])))
    covered = F.aggregate(
        F.transform("starts", lambda at, i: F.when(i == 0, F.lit(WINDOW)).otherwise(F.least(F.lit(WINDOW), at - F.get(F.col("starts"), i - 1)))),
        F.lit(0),
        lambda total, x: total + x,
    )
    return placed.select(id_col, "n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", F.coalesce(covered, F.lit(0)).cast("long").alias("n_repeat_words"))


def ledger(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Measurements and fail_bits (long) for each row of df."""
    bits = F.lit(0).cast("long")
    for name, failing in RULES.items():
        bits = bits.bitwiseOR(F.when(F.expr(failing), F.lit(BITS[name])).otherwise(F.lit(0)).cast("long"))
    return measure(df, id_col, text_col).withColumn("fail_bits", bits)


def apply_policy(book: DataFrame, policy: str = "v2") -> DataFrame:
    """Add base_failed and kept, from the bits alone."""
    failed = lambda p: F.col("fail_bits").bitwiseAND(F.lit(mask(p))) != 0
    return book.withColumns({"base_failed": failed("base"), "kept": ~failed("base") & ~failed(policy)})


def ablation(book: DataFrame, policy: str = "v2") -> DataFrame:
    """For each rule of a policy: documents failing it, and those that only it rejects.

    One aggregation to at most 2**len(RULES) distinct ledgers; the rest works on those few rows.
    """
    own = F.col("fail_bits").bitwiseAND(F.lit(mask(policy)))
    counts = book.groupBy(own.alias("bits")).agg(F.count("*").alias("n"))
    rules = F.array(*[F.struct(F.lit(r).alias("rule"), F.lit(BITS[r]).cast("long").alias("bit")) for r in POLICIES[policy]])
    each = counts.select("bits", "n", F.explode(rules).alias("r")).select("bits", "n", "r.*")
    hit = F.col("bits").bitwiseAND(F.col("bit")) != 0
    return each.groupBy("rule").agg(
        F.coalesce(F.sum(F.when(hit, F.col("n"))), F.lit(0)).alias("n_failed"),
        F.coalesce(F.sum(F.when(F.col("bits") == F.col("bit"), F.col("n"))), F.lit(0)).alias("n_only_this"),
        F.bit_or(F.when(hit, F.col("bits"))).alias("fails_with"),
    )
