"""The queries of this subpackage, and the SQL that says the same where SQL can."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe import bpe_digests
from .common import small
from .embedding_dedup import embedding_links
from .flac import media_digests
from .html_extract import extract_pages
from .jaccard_join import jaccard_components
from .language_id import language_predictions
from .mixing import mixture, source_targets, word_count
from .secrets import find_secrets
from .toxicity import toxicity_scores
from .url_filter import url_verdicts


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Links, components and kept vectors of all `embeddings`; null labels, null, zero and non-finite vectors link with nothing. See embedding_links."""
    return embedding_links(_table(spark, sf_dir, "embeddings"))


def op2_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Set sizes and components of all `documents`; wordless and null texts link with nothing, rows with one id are apart by their texts. See jaccard_components."""
    return jaccard_components(_table(spark, sf_dir, "documents"))


def op3_secret_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spans of secrets in all `documents`; null texts have none, repeated rows the same. See find_secrets."""
    return find_secrets(_table(spark, sf_dir, "documents"))


def op4_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Token digests of all `documents`, and of the texts decoded again; null texts have no tokens. See bpe_digests."""
    return bpe_digests(_table(spark, sf_dir, "documents"))


def op5_flac_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Digests of all `documents` stored as FLAC and read back; null texts are one block of 255. See media_digests."""
    return media_digests(_table(spark, sf_dir, "documents"))


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Languages of all `documents`, learnt from those not held out; `und` without a letter. See identify."""
    return language_predictions(_table(spark, sf_dir, "documents"))


def op7_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main texts of all `pages`; null pages give an empty text. See extract_pages."""
    return extract_pages(_table(spark, sf_dir, "pages"))


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity of all `documents`, learnt from `labels` not held out; null texts score by the bias. See score."""
    return toxicity_scores(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op9_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words that the mixture takes of all `documents`; null texts have size 0, null is a source. See mixture."""
    return mixture(_table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op10_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Verdicts on all `pages`; null urls and those without :// have an empty host and path. See url_verdicts."""
    return url_verdicts(_table(spark, sf_dir, "pages"))


def mixing_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Size, source size and target of all `documents`: what the mixture aims at, without the draw."""
    docs = _table(spark, sf_dir, "documents").select("doc_id", "source", word_count().alias("size"))
    targets = source_targets(docs.groupBy("source").agg(F.sum("size").alias("source_size"))).withColumnRenamed("source", "of")
    return docs.join(small(targets, 10_000), docs["source"].eqNullSafe(targets["of"])).select("doc_id", "size", "source_size", F.round("target", 6).alias("target"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_embedding_near_dedup": op1_embedding_near_dedup,
        "op2_ngram_jaccard_join": op2_ngram_jaccard_join,
        "op3_secret_scans": op3_secret_scans,
        "op4_bpe_round_trip": op4_bpe_round_trip,
        "op5_flac_media": op5_flac_media,
        "op6_language_id": op6_language_id,
        "op7_html_extraction": op7_html_extraction,
        "op8_toxicity": op8_toxicity,
        "op9_source_mixing": op9_source_mixing,
        "op10_url_filters": op10_url_filters,
        "mixing_targets": mixing_targets,
    }


def oracle_sql() -> dict[str, str]:
    from .sql import SQL

    return dict(SQL)
