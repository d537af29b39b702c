"""The thin contract queries over the corpus operators, and SQL that checks them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, exact_dedup, lang_id, license_scan, near_dedup, passage_chains, secret_scan, source_mix, spot_signatures, url_filter
from .common import table


def tokenizer_spec(name: str = "word_bpe_49k.json") -> str:
    """Text of a public tokenizer file, where the installed package keeps it."""
    import public_tokenizers

    with open(public_tokenizers.path(name), encoding="utf-8") as f:
        return f.read()


def op1_bpe_lexicon(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_documents(table(spark, sf_dir, "documents"), tokenizer_spec())


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_dedup(table(spark, sf_dir, "documents"))


def op3_spot_signatures(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spot_signatures.fingerprint_documents(table(spark, sf_dir, "documents"))


def op4_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return source_mix.mix_sources(table(spark, sf_dir, "documents")).select(
        "doc_id", "size", "source_size", F.round("target", 6).alias("target"), "taken"
    )


def op5_language_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = lang_id.fit(lang_id.train_split(docs))
    return lang_id.identify(docs.select("doc_id", "text"), model).select(
        "doc_id", lang_id.held_out().alias("held_out"), "lang_pred", "score", "is_ambiguous"
    )


def op6_chosen_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_dedup(table(spark, sf_dir, "documents"), k=4)


def op7_redirect_blocklist(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.filter_urls(table(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", "verdict")


def op8_collinear_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return passage_chains.passages_by_document(table(spark, sf_dir, "documents"))


def op9_confirmed_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.scan_secrets(table(spark, sf_dir, "documents"))


def op10_license_diagonals(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan_licenses(table(spark, sf_dir, "documents"))


def spot_similar_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The similarity join of op3's signatures over the whole table: length partitions, rarest-first prefixes, pruned Jaccard."""
    return spot_signatures.similar_documents(table(spark, sf_dir, "documents"))


def queries() -> dict:
    found = {k: f for k, f in globals().items() if k.startswith("op") and callable(f) and k[2].isdigit()}
    return found | {"spot_similar_documents": spot_similar_documents}


def oracle_sql() -> dict[str, str]:
    from .oracles import SQL

    return dict(SQL)
