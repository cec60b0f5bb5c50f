"""Documents through four stages: quality classifier, line dedup, near-duplicate removal, packing.

Each stage takes the whole table that the one before it wrote. All but the last return the columns of documents, whatever
names those have; empty tables give empty ones. What each does with nulls, empty and very long texts, ties and repeated
rows is said below; tests hold it on a table of such rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from progressive_text.llm import line_templates, near_dup, packing, quality
from progressive_text.llm.common import documents, saved


def good_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose whole text the classifier accepts (score 0.5 or more). It learns from labels of documents at hand, never from
    rows held out by id. Rows with a null or empty text stay, and so do null ids; repeated rows share their fate."""
    return quality.keep_good(docs, quality.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def fresh_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows without the lines that a document of smaller id has, or has alike. A document that loses all its lines goes; null
    and empty texts and rows with a null id stay as they are; rows of one id are one document; n_chars follows the text."""
    return line_templates.drop_recurring(docs, by=line_templates.like_lines)


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of linked documents (five-word shingles, similarity 0.8 or more) the one of smallest id, with all its rows.
    Null and empty texts and null ids stay."""
    return near_dup.keep_one(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents with their sequence and their place in it: a null or empty text is one piece of the end id, a
    longer text as many as it needs; repeated rows and null ids are packed as all others."""
    return packing.pack(docs)


STAGES = [("quality_classifier", good_documents), ("line_dedup", fresh_lines), ("minhash_near_dedup", one_of_each), ("best_fit_packing", packed)]

#: The classifier and the tokenizer have no SQL form; tests hold the stages against brute-force versions of them, one by one.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pieces of what the stages leave of documents; each stage's table is written and read again."""
    docs = documents(spark, sf_dir)
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = saved(docs, name)
    return docs
