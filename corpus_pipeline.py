"""A corpus pipeline: language, repeated lines, near copies, benchmark leaks, then the mix of sources.

Each stage takes (spark, docs, sf_dir), works on all that the stage before it kept, and gives the columns of
documents; the last adds `copy`. run() writes every stage to Parquet in the shared folder and reads it again, so a
lost executor costs no more than a part of one stage; a stage's files go as soon as the next one's are written.
Null texts, empty texts and texts without a letter go in the first stage. Rows with null doc_id, and repeated rows, pass all
stages by the rules that each operator states; an empty table gives an empty result; other columns pass through unchanged.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutlearn.llm import decontam, langid, line_dedup, mixing, near_jaccard, simhash
from cutlearn.llm.session import drop_path, shared_dir


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without any letter have no language and go; without any label to learn from, the others still stay."""
    found = langid.identify(docs, langid.learn(docs), prefix="_found_")
    return found.where((F.col("_found_lang_pred") != langid.UNKNOWN) | F.col("text").rlike(r"\p{L}")).select(*docs.columns)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts lose the lines that a smaller doc_id holds; n_chars follows."""
    return line_dedup.dedup_text(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays: links of five-word SimHash covering tables and, beyond their radius, of an exact
    prefix join, each confirmed by a five-word Jaccard similarity of 0.8 or more. Rows with null doc_id stay."""
    return simhash.representatives(docs, found=near_jaccard.components(docs))


def leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item, whole or edited, go; null and empty texts hold none."""
    return decontam.clean_documents(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row for each time that the mix takes a document; texts without words have size 0 and are never taken."""
    return mixing.mixed_documents(docs)


STAGES = [
    ("language_id", language),
    ("line_dedup", lines),
    ("simhash_near_dedup", near_copies),
    ("decontamination", leaks),
    ("mixing", mix),
]

#: The language, near-copy, leak and mixing stages can't be said in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    top, last = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}", None
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{top}/{name}")
        docs = spark.read.parquet(f"{top}/{name}")
        if last:
            drop_path(spark, last)
        last = f"{top}/{name}"
    return docs
