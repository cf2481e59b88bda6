"""The corpus pipeline: documents through five operators, each stage written as Parquet and read again.

Stages work on all that the stage before kept, and all but the last return the columns of documents:

1. language_id: documents without a letter, or whose best language has less than MIN_SCORE of the words, go.
2. line_dedup: repeated runs of lines are deleted from later places; a document of which nothing but white space stays goes. n_chars is
   that of the text that stays.
3. ngram_join: of each component of near copies the document of least doc_id stays.
4. decontaminate: documents with a verified overlap with a benchmark item go.
5. sentencepiece: the texts are encoded; the last stage returns doc_id, lang, source, n_chars, ids, n_tokens and round_trip.

Rows with null doc_id pass the stages that filter by doc_id. Null and empty texts have no letter and go first. Empty tables pass through as empty tables.
Further columns of documents come along to the last stage, whatever their names. Rows that repeat are one document for every stage; of equal
documents under several ids the least id stays, and of equal runs of lines the one at the least doc_id, then line.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridjoin.llm import decontaminate, language_id, line_dedup, ngram_join, pieces
from gridjoin.llm.common import drop_stored, hand_back, set_aside, stored, table, without

MIN_SCORE = 0.35


def stage_language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    docs, back = set_aside(docs, ("lang_pred", "score"))
    found = language_id.identify(docs, docs.where(language_id.fold(docs, 3) != 1).select("doc_id", "text", "lang"))
    return found.where((F.col("lang_pred") != "und") & (F.col("score") >= MIN_SCORE)).select(*back)


def stage_line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    docs, back = set_aside(docs, line_dedup.ADDED)
    kept = line_dedup.dedup_lines(docs).where((F.col("n_deleted") == 0) | (F.trim(F.regexp_replace("kept_text", r"\s", "")) != ""))
    changed = kept.withColumn("n_chars", F.when(F.col("n_deleted") == 0, F.col("n_chars")).otherwise(F.length("kept_text").cast("long")))
    return changed.withColumn("text", F.col("kept_text")).select(*back)


def stage_ngram_join(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    hand_back(spark)
    found = ngram_join.link_documents(docs.select("doc_id", "text"))
    return without(docs, found.where("doc_id <> component_id"))


def stage_decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def stage_sentencepiece(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    hand_back(spark)
    return pieces.encode_texts(docs.select("doc_id", "lang", "source", "n_chars", "text"))


STAGES = [
    ("language_id", stage_language_id),
    ("line_dedup", stage_line_dedup),
    ("ngram_join", stage_ngram_join),
    ("decontaminate", stage_decontaminate),
    ("sentencepiece", stage_sentencepiece),
]

#: The first stage is a trained model and the last a Viterbi: SQL cannot express them. tests/llm holds run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each stage's table is removed when the next is written."""
    docs = table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES):
        done = stored(stage(spark, docs, sf_dir), f"stage-{name}")
        if i:
            drop_stored(docs)
        docs = done
    return docs
