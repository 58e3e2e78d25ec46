"""Named queries of the text operators, each over its whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parley.llm import decontaminate, html_text, language, line_dedup, merge_dropout, pii, quality, simhash, sql, sstable, toxicity
from parley.llm.common import load, tokenizer_path


def op1_quality_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.apply_policy(quality.ledger(load(spark, sf_dir, "documents").select("doc_id", "text")))


def quality_rule_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What each rule of the latest policy rejects, and what it alone rejects."""
    return quality.ablation(quality.ledger(load(spark, sf_dir, "documents").select("doc_id", "text")))


def op2_simhash_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.with_hex(simhash.cluster(load(spark, sf_dir, "documents")))


def op10_fuzzy_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for each document: its lines, those that go, and each line's component, named by the component's first line.

    Of rows with equal id and text the first keeps what is kept; the others lose every line. A row without an id has no lines here.
    """
    docs = load(spark, sf_dir, "documents")
    decided = line_dedup.line_components(docs)
    own = decided.groupBy("doc_id", "mark").agg(F.sort_array(F.collect_set(F.struct("line_no", "first_doc", "first_line", "keep"))).alias("lines"))
    named = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("mark"))
    rows = named.where("doc_id IS NOT NULL").groupBy("doc_id", "mark").agg(F.count("*").alias("copies")).join(own, ["doc_id", "mark"], "left")
    rows = rows.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), "copies"))).unionByName(named.where("doc_id IS NULL"), allowMissingColumns=True)
    lines = F.coalesce("lines", F.array())
    gone = F.filter(lines, lambda x: ~x["keep"] | (F.col("copy") > 1))
    return rows.select(
        "doc_id",
        F.size(lines).cast("long").alias("n_compared"),
        F.size(gone).cast("long").alias("n_removed"),
        F.transform(gone, lambda x: x["line_no"]).alias("removed"),
        F.transform(lines, lambda x: F.struct(x["line_no"].alias("line_no"), x["first_doc"].alias("first_doc"), x["first_line"].alias("first_line"))).alias("components"),
    )


def op6_token_shards(spark: SparkSession, sf_dir: str, tokenizer: str | None = None) -> DataFrame:
    _, manifest = sstable.write_shards(load(spark, sf_dir, "documents"), tokenizer or tokenizer_path("word_bpe_49k.json"))
    return sstable.digests(spark, manifest)


def op7_benchmark_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contaminated(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark"))


def op4_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    model = language.train(docs.where(language.remainder("doc_id", 4) != 2))
    return language.predict(docs, model).withColumn("held_out", language.remainder("doc_id", 4) == 2)


def op5_merge_dropout(spark: SparkSession, sf_dir: str, model: str | None = None) -> DataFrame:
    return merge_dropout.round_trips(load(spark, sf_dir, "documents"), model or tokenizer_path("piece_bpe_32k.model"))


def op8_pii_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.pseudonymise(load(spark, sf_dir, "documents").select("doc_id", "text"))


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    model = toxicity.train(docs, load(spark, sf_dir, "labels").where(language.remainder("doc_id", 5) != 0))
    return toxicity.score(docs, model).withColumn("held_out", language.remainder("doc_id", 5) == 0)


def op3_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(load(spark, sf_dir, "pages"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_quality_ledger": op1_quality_ledger,
        "quality_rule_ablation": quality_rule_ablation,
        "op2_simhash_groups": op2_simhash_groups,
        "op10_fuzzy_lines": op10_fuzzy_lines,
        "op6_token_shards": op6_token_shards,
        "op7_benchmark_leaks": op7_benchmark_leaks,
        "op4_language": op4_language,
        "op5_merge_dropout": op5_merge_dropout,
        "op8_pii_pseudonyms": op8_pii_pseudonyms,
        "op9_toxicity": op9_toxicity,
        "op3_html_text": op3_html_text,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_quality_ledger": sql.QUALITY, "quality_rule_ablation": sql.ABLATION}
