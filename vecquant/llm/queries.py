"""The operators' queries over the given tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecquant.llm import (
    backoff_lm,
    codec,
    feature_digest,
    license_scan,
    packing,
    prefix_counts,
    quality_rules,
    rule_ensemble,
    simhash,
    url_rules,
)

#: The rules of the URL query.
URL_RULES = [("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/")]
#: The score from which quality is predicted, and tokenizer files by name.
QUALITY_THRESHOLD = 0.3
RANKS_FILE, TOKENIZER_FILE = "byte_bpe_50k.tiktoken", "byte_bpe_50k.json"


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def op1_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = read(spark, sf_dir, "pages").select("page_id", "url")
    judged = url_rules.judge_urls(pages, url_rules.rule_table(spark, URL_RULES))
    return judged.select("page_id", "host", "path", "rule", "verdict")


def op2_feature_digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return feature_digest.edit_sensitivity(read(spark, sf_dir, "documents"))


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.quality_rules(read(spark, sf_dir, "documents"))


def op4_rule_ensemble(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    model = rule_ensemble.fit_on_documents(docs, read(spark, sf_dir, "labels"))
    scored = rule_ensemble.score_documents(docs, model, ("doc_id",))
    held = rule_ensemble.held_out(F.col("doc_id"))
    predicted = (F.col("score") >= QUALITY_THRESHOLD).cast("int")
    return scored.select("doc_id", held.alias("held_out"), "score", predicted.alias("predicted"))


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(read(spark, sf_dir, "documents"))


def op6_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return codec.encode_documents(read(spark, sf_dir, "documents"), public_tokenizers.path(RANKS_FILE))


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return prefix_counts.count_tokens(read(spark, sf_dir, "documents"), public_tokenizers.path(TOKENIZER_FILE))


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(read(spark, sf_dir, "documents"), public_tokenizers.path(TOKENIZER_FILE))


def op9_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan_licenses(read(spark, sf_dir, "documents"), license_scan.train())


def op10_backoff_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = backoff_lm.score_documents(read(spark, sf_dir, "documents"))
    return scored.select("doc_id", "n_tokens", *[F.round(c, 4).alias(c) for c in ("log10_score", "mean_log10_score")])


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = (
        op1_url_rules, op2_feature_digest, op3_quality_rules, op4_rule_ensemble, op5_simhash,
        op6_byte_bpe, op7_token_counts, op8_packing, op9_license_scan, op10_backoff_lm, pipeline,
    )
    return {f.__name__: f for f in found}


def _rule_fits(host: str, path: str) -> str:
    return f"((host = '{host}' OR suffix(host, '.{host}')) AND starts_with(path, '{path}'))"


def oracle_sql() -> dict[str, str]:
    longest = sorted(URL_RULES, key=lambda r: -len(r[1]))
    fits = [(_rule_fits(*url_rules._parts(r)), v, r) for v, r in longest]
    rule = "CASE " + " ".join(f"WHEN {f} THEN '{r}'" for f, _, r in fits) + " END"
    verdict = "CASE " + " ".join(f"WHEN {f} THEN '{v}'" for f, v, _ in fits) + " ELSE 'allow' END"
    letters = f"'{url_rules.UPPER}', '{url_rules.LOWER}'"
    return {
        "op1_url_rules": f"""
            WITH rest AS (
                SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substring(url, instr(url, '://') + 3) ELSE '' END AS r
                FROM pages),
            split AS (SELECT page_id, r, regexp_extract(r, '^[^/?#]*') AS h FROM rest),
            parts AS (
                SELECT page_id, translate(h, {letters}) AS host,
                    regexp_extract(substring(r, length(h) + 1), '^[^?#]*') AS path FROM split)
            SELECT page_id, host, path, {rule} AS rule, {verdict} AS verdict FROM parts""",
        "op10_backoff_lm": backoff_lm.oracle_sql(),
    }
