"""The corpus pipeline: language ID, near duplicates, secrets, mixing, tokens.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written as Parquet and
read again as the next stage's docs. All but the last return the columns of `documents`.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from quillon.llm.bpe import bpe_digests
from quillon.llm.common import crc_held_out, stored
from quillon.llm.jaccard_join import one_of_each_group
from quillon.llm.language_id import identify, learn_dictionaries
from quillon.llm.mixing import mixed_documents
from quillon.llm.secrets import without_secrets

OWN = ("__lang_pred", "__lang_score", "__lang_ok")


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the documents whose language is told by the operator's own margin; without a letter, with a tie
    of languages or a margin below it, they go.

    Null texts have no letter and go. Null languages, sources and ids stay as they are; repeated rows are judged
    alike. An empty table gives an empty one. Other columns stay, whatever their names, but for three of this
    stage's own (`OWN`), which are left out.
    """
    model = learn_dictionaries(docs.where(~crc_held_out()))
    return identify(docs, model, names=OWN).where(OWN[2]).drop(*OWN)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group of near copies: the one with the smallest id, once if its row repeats.

    Documents with null ids come after all others; different texts under one id, or without one, are documents
    of their own. Null and wordless texts all stay. An empty table gives an empty one; other columns stay.
    """
    return one_of_each_group(docs)


def secret_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces the secrets in the texts; all documents stay, null texts as they are, repeated rows alike.

    A column n_chars follows the new text. An empty table gives an empty one; other columns stay.
    """
    return without_secrets(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Takes each document as many times as its source's target asks for.

    Documents without words are not taken; a null source is a source, a null id an id like others; repeated rows
    share what they are taken together. An empty table gives an empty one; other columns stay, whatever their names.
    """
    return mixed_documents(docs)


def token_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of each document taken: doc_id, n_tokens, ids_sha256, decoded_sha256.

    Null texts have no tokens; null ids stay, repeated rows give repeated rows. An empty table gives an empty
    one; other columns are left out.
    """
    return bpe_digests(docs)


STAGES = [
    ("language_id", language_stage),
    ("near_duplicates", near_duplicate_stage),
    ("secret_scans", secret_stage),
    ("source_mixing", mixing_stage),
    ("bpe_tokens", token_stage),
]

#: No SQL expresses compression, lexing or byte-pair encoding.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = stored(docs, name)
    return docs
