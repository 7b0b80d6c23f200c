"""The corpus pipeline: language ID, exact and near dedup, mixing, tokenization.

``STAGES`` lists (name, function); each function takes (spark, docs, sf_dir), works on every row of
``docs`` and returns a DataFrame, the columns of ``documents`` in all stages but the last.  ``run``
writes each stage's result to the shared folder and reads it as the next one's ``docs``.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from splitsort.llm import exact_dedup, language_id, mixing, near_dedup, sentencepiece_codec
from splitsort.llm.common import apart, doc_crc, staged, table, unstage

#: Fitted codes, random rounding and a tokenizer: SQL can't express these stages.
ORACLE_SQL: str | None = None


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter go, and those whose language is undecided between several.

    The codes are fitted on a bounded sample of the rows with a language outside the held-out fold.
    """
    model = language_id.train(docs.where(doc_crc(F.col("doc_id")) % 4 != 2))
    lang, score, ambiguous = names = apart(docs, "lang_pred", "lang_score", "lang_ambiguous")
    found = language_id.identify(docs, model, names=tuple(names))
    clear = (F.col(lang) != language_id.UNKNOWN) & ~(F.col(ambiguous) & (F.col(score) < 0.5))
    return found.where(clear).select(*[F.col(f"`{c}`") for c in docs.columns])


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the one with the largest id stays."""
    return exact_dedup.without_copies(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates the one with the least id stays."""
    return near_dedup.without_near_duplicates(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it."""
    return mixing.mixture(docs)


def token_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids, and whether decoding them gives the text back."""
    coded = sentencepiece_codec.encode_decode(docs)
    same = F.col("decoded") == F.coalesce("text", F.lit(""))
    return coded.select("doc_id", "lang", "source", "n_tokens", "ids", same.alias("lossless"))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("language ID", language_stage),
    ("exact dedup", exact_stage),
    ("near dedup", near_stage),
    ("mixing", mixing_stage),
    ("sentencepiece", token_stage),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written and read again before the next."""
    docs = table(spark, sf_dir, "documents")
    before: list[DataFrame] = []
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = staged(docs, "pipeline")
            unstage(*before)
            before = [docs]
    return docs
