"""A corpus pipeline of five stages over ``documents``; each stage's rows are written and read again before the next.

Every stage takes (spark, docs, sf_dir). All but the last return the columns of ``documents``; the last returns one row per
remaining document with its token count and the hashes of its ids and of the decoded text.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sightline.llm import bpe, decontam, lines, ngram_join, toxicity
from sightline.llm.common import saved
from sightline.llm.queries import BYTE_BPE, REJECT, learn, table

#: SQL cannot express the toxicity stage; tests/llm/test_pipeline.py compares run() with a plain Python version.
ORACLE_SQL = None
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Without the documents whose score reaches the rejection threshold. Null and empty texts are scored as texts without features."""
    model = learn(spark, docs, sf_dir)
    return toxicity.score_texts(docs.select(*COLUMNS), model).where(F.col("score") < REJECT).select(*COLUMNS)


def drop_common_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the lines that three documents or more share; all rows stay, n_chars follows the text. A null text becomes empty."""
    kept = lines.dedup_lines(docs.select(*COLUMNS))
    return kept.withColumn("text", F.col("kept_text")).withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest doc_id of each near-duplicate component (five-word shingles, Jaccard 0.8).

    Documents without words link with nothing and stay; rows of one doc_id are one document and stay together; rows with
    a null doc_id stay.
    """
    gone = ngram_join.jaccard_components(docs, words=5, percent=80).where("doc_id <> component_id").select("doc_id")
    return docs.select(*COLUMNS).join(gone, "doc_id", "left_anti")


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Without the documents that hold a benchmark item."""
    leaks = decontam.find_leaks(docs, table(spark, sf_dir, "benchmark")).select("doc_id").distinct()
    return docs.select(*COLUMNS).join(leaks, "doc_id", "left_anti")


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token count, hashes and round trip of every document."""
    return bpe.encode_decode(docs, BYTE_BPE())


STAGES = [
    ("toxicity", drop_toxic),
    ("line dedup", drop_common_lines),
    ("n-gram Jaccard join", drop_near_copies),
    ("benchmark decontamination", drop_leaks),
    ("BPE encoding and decoding", encode),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = saved(docs, f"stage{k}")
    return docs
