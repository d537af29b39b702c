"""The corpus pipeline: language ID, exact dedup, near-dedup, source mixing, then encoding.

Each stage is (name, function of (spark, docs, sf_dir)); its result is written as Parquet and
read again as the next stage's documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplerank.llm import bpe, common, exact_dedup, lang_id, near_dedup, source_mix
from ripplerank.llm.queries import tokenizer_spec

#: Certainty under which a text's language counts as not recognised.
LEAST_SCORE = 0.5


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep documents whose language is recognised; texts without letters and undecided ones go. `lang` stays as given."""
    model = lang_id.fit(lang_id.train_split(docs))
    rows, names = common.neutral(docs, "doc_id", "text")
    found = lang_id.identify(rows, model)
    return found.where((F.col("lang_pred") != lang_id.UNKNOWN) & (F.col("score") >= LEAST_SCORE)).select(*names).toDF(*docs.columns)


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts one row stays, that of the largest doc_id: every row is decided on its own, repeated and null ids included."""
    return exact_dedup.survivors(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicates (five-word shingles, similarity 0.8 or more), the least doc_id stays.

    Rows that share a doc_id are one document and stay or go together; rows without one link with nothing and stay.
    """
    ids = near_dedup.near_dedup(docs).where("kept and doc_id is not null").select(F.col("doc_id").alias("__kept")).distinct()
    rows, names = common.neutral(docs, "doc_id", "text")
    kept = rows.where("doc_id is not null").join(ids, F.col("doc_id") == F.col("__kept"), "left_semi")
    return kept.unionByName(rows.where("doc_id is null")).select(*names).toDF(*docs.columns)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Emit each document as often as the mix of its source takes it."""
    return source_mix.emit_mix(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Encode every document of the mix."""
    return bpe.encode_documents(docs, tokenizer_spec())


STAGES = [
    ("language_id", identify_language),
    ("exact_dedup", drop_exact_copies),
    ("near_dedup", drop_near_copies),
    ("source_mix", mix),
    ("bpe", encode),
]

#: SQL has neither the learned model nor the tokenizer; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = common.cut(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
