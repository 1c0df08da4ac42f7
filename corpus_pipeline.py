"""From raw documents to sampled token sequences: five stages, each on all that its predecessor kept.

1. The quality classifier, trained on the labelled documents outside its held-out fifth, rejects documents.
2. Of each component of near copies (five-word shingles, similarity 0.8 or more) the document with the smallest doc_id stays.
3. Passages of 50 words that an earlier document has leave a document; one that loses nothing keeps its text as it is.
4. Documents that hold a benchmark item go.
5. Every document left gets its sampled segmentations, one row each.

Defined results: documents with a null doc_id go through stages 2 to 4 unchanged; a null text stays null; extra columns are
kept by all stages but the last; an empty table gives an empty result; rows with equal doc_ids are one document to stages 2 to 4.
"""

from __future__ import annotations

import posixpath
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from symseek.llm import decontaminate, ngram_join, quality, sp_sampling, substring_dedup
from symseek.llm.common import crc_bucket, shared_folder, table


def _carried(docs: DataFrame) -> dict[str, Column]:
    """All columns but the text, under names that can't clash with an operator's own."""
    return {f"carried_{i}": F.col(f"`{c}`") for i, c in enumerate(docs.columns) if c != "text"}


def _restored(rows: DataFrame, docs: DataFrame) -> DataFrame:
    """The documents' columns again; an operator has returned the text as carried_text."""
    return rows.select(*[F.col("carried_text" if c == "text" else f"carried_{i}").alias(c) for i, c in enumerate(docs.columns)])


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = quality.train(docs, table(spark, sf_dir, "labels"), crc_bucket(F.col("doc_id"), 5) != 0)
    return _restored(quality.score(docs, model, keep=_carried(docs), text_as="carried_text").where(F.col("score") >= quality.ACCEPT), docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    found = ngram_join.near_copies(docs, n=5, percent=80)
    extra = found.where(F.col("component_id") < F.col("doc_id")).select("doc_id").distinct()
    return docs.join(extra, "doc_id", "left_anti").select(*[F.col(f"`{c}`") for c in docs.columns])


def substring_removal(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    out = _restored(substring_dedup.remove_repeats(docs, keep=_carried(docs), text_as="carried_text"), docs)
    return out.withColumn("n_chars", F.char_length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.without_items(docs, table(spark, sf_dir, "benchmark"))


def sampled_segmentations(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return sp_sampling.sample(docs)


STAGES = [
    ("quality classifier", quality_classifier),
    ("n-gram Jaccard join", near_copies),
    ("substring dedup", substring_removal),
    ("benchmark decontamination", decontamination),
    ("SentencePiece sampling", sampled_segmentations),
]

#: A trained classifier and a sampler aren't SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each stage's result is written to the shared folder and read again."""
    docs = table(spark, sf_dir, "documents")
    root = posixpath.join(shared_folder(spark), f"pipeline-{uuid.uuid4().hex}")
    for number, (_, stage) in enumerate(STAGES):
        path = f"{root}/{number}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
