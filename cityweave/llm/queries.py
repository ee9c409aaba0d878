"""Queries of the training-data operators over whole tables, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cityweave.llm import decontam, langid, licenses, packing, pii, quality, simhash, suffix, urlfilter
from cityweave.scratch import Scratch
from cityweave.session import ship


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_suffix_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix.without_repeats(table(spark, sf_dir, "documents"))


def op2_weighted_url_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlfilter.judged(table(spark, sf_dir, "pages"))


def op3_boosted_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality.judged_by_rules(docs, quality.train_rules(docs, table(spark, sf_dir, "labels")))


def op4_neighbour_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = quality.scored_by_neighbours(docs, quality.train_neighbours(docs, table(spark, sf_dir, "labels")))
    return found.select("doc_id", langid.held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")


def op5_spaced_seed_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op6_hierarchical_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = langid.identify(docs, langid.train(docs))
    return found.select("doc_id", langid.held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")


def op7_inherited_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    # the table has no paths: a source is a tree with a directory for each language
    path = F.concat_ws("/", F.coalesce("source", F.lit("-")), F.coalesce("lang", F.lit("-")), F.concat(F.col("doc_id").cast("string"), F.lit(".txt")))
    return licenses.license_scan(docs.select("doc_id", path.alias("path"), "text"), Scratch(spark, "licenses"))


def _count(spans: Column, kind: str) -> Column:
    return F.size(F.filter(spans, lambda s: s["kind"] == pii.KINDS.index(kind))).cast("long").alias(f"n_{kind}")


def op8_bootstrapped_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.personal_data(table(spark, sf_dir, "documents"))
    base = F.col("base")
    return found.select("doc_id", *[_count(base, k) for k in pii.KINDS], F.sha2(pii.rendered(base), 256).alias("base_sha256"), pii.rendered(pii.in_order(F.concat("base", "added"))).alias("spans"))


def op9_simhash_trie(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.simhash_components(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op10_certified_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.best_fit_packing(table(spark, sf_dir, "documents"), tokenizer_path())


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_suffix_repeats,
        op2_weighted_url_terms,
        op3_boosted_quality_rules,
        op4_neighbour_quality,
        op5_spaced_seed_decontamination,
        op6_hierarchical_language,
        op7_inherited_licenses,
        op8_bootstrapped_pii,
        op9_simhash_trie,
        op10_certified_packing,
    )
}

ORACLE: dict[str, str] = {"op2_weighted_url_terms": urlfilter.oracle_sql()}
