"""The training-data pipeline: five stages over ``documents``, each written and read again.

Every stage maps the documents it is given to those it keeps, with the columns of
``documents``; the last gives sampled pieces instead of texts. Nulls, empty tables and extra
columns have the results that the stages' operators define.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from opatlas.llm import mixing, piece_sampling, quality_model, quality_rules, simhash
from opatlas.llm.common import table
from opatlas.llm.registry import tokenizer_path
from opatlas.plans.planning import spread
from opatlas.session import shared_dir

#: None: a trained model, fingerprints and sampled pieces have no SQL form.
ORACLE_SQL = None


def stage_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the default rule policy keeps."""
    return quality_rules.keep(docs)


def stage_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that a model, fitted on the labelled ones among them, scores at the threshold or above."""
    return quality_model.keep(docs, table(spark, sf_dir, "labels"))


def stage_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The first document of each group of near copies: five-word shingles, a similarity of 0.8 or more."""
    return simhash.dedup(docs)


def stage_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The sources at their target weights: a row for each time a document is taken, in shard order."""
    return mixing.mix(docs)


def stage_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sampled pieces of each text, which decode to it."""
    return piece_sampling.sample_pieces(docs, tokenizer_path("piece_bpe_32k.model"), keep=("doc_id", "lang", "source"))


STAGES = [
    ("quality_rules", stage_rules),
    ("quality_classifier", stage_classifier),
    ("simhash_dedup", stage_dedup),
    ("source_mixing", stage_mixing),
    ("piece_sampling", stage_pieces),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spread(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    at = f"{shared_dir(spark).rstrip('/')}/pipeline-{uuid.uuid4().hex}"
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs.write.parquet(f"{at}/{k}_{name}")
            docs = spark.read.parquet(f"{at}/{k}_{name}")
    return docs
