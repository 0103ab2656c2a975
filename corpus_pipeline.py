"""Corpus pipeline: quality classifier, quality rules, near-duplicate removal, packing.

Every stage is written as Parquet and read again as the next one's documents. All but the
last return the columns of documents.
"""

from __future__ import annotations

import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecquant.llm import packing, quality_rules, rule_ensemble, simhash
from vecquant.llm.common import ensure_checkpoint_dir
from vecquant.llm.queries import QUALITY_THRESHOLD, TOKENIZER_FILE, read


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that the rule ensemble, learned from the labels, does not reject."""
    model = rule_ensemble.fit_on_documents(docs, read(spark, sf_dir, "labels"))
    places = [f"c{i}" for i in range(len(docs.columns))]
    source = docs.toDF(*places)
    text = places[docs.columns.index("text")]
    scored = rule_ensemble.score_documents(source, model, tuple(places), text)
    return scored.where(F.col("score") >= QUALITY_THRESHOLD).select(*places).toDF(*docs.columns)


def rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that the quality rules keep."""
    return quality_rules.keep_clean(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group, the one with the smallest id.

    Links are fingerprints within 4 bits, and 5-word Jaccard similarity of 0.8 or more.
    """
    return simhash.keep_one_similar(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents in windows of several lengths."""
    return packing.pack_documents(docs, public_tokenizers.path(TOKENIZER_FILE))


STAGES = [
    ("quality classifier", quality_classifier),
    ("quality rules", rules),
    ("simhash near-dedup", near_duplicates),
    ("packing", pack),
]

#: Fingerprints, windows and learned rules have no SQL form; a brute-force version tests them.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents, each from the table that the one before wrote."""
    shared = ensure_checkpoint_dir(spark).rstrip("/")
    docs = read(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        path = f"{shared}/stage-{name.replace(' ', '-')}-{uuid.uuid4().hex}"
        made = stage(spark, docs, sf_dir)
        made.write.parquet(path)
        docs = spark.read.schema(made.schema).parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)
