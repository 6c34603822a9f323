"""The training-data pipeline: five operators over ``documents``, each stage's result written and read again as the next one's input.

Rows go for quality rules, quality classifier and near copies; repeated passages are cut out of the
texts; what is left is packed.  Every stage but the last returns the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subweight.llm import packing, quality_classifier, quality_rules, simhash, substring_dedup
from subweight.llm.common import durable, table

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail the base rules or the thresholds of their language and source go."""
    return quality_rules.keep_by_rules(docs.select(*COLUMNS))


def classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a score under the threshold go; the model learns from the whole input tables, as few rejected ones are left here."""
    model = quality_classifier.fit(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return quality_classifier.keep_by_score(docs.select(*COLUMNS), model)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the document of the smallest id stays: fingerprints of five-word shingles that differ in 4 or fewer bits, or, farther apart, a similarity of the shingle sets of 0.8 or more."""
    return simhash.drop_near_duplicates(docs.select(*COLUMNS), shingle=5, similarity=None, beyond=0.8)


def passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Windows of 50 words that also start in a document of a smaller id are cut out; n_chars follows the text."""
    out = substring_dedup.remove_repeats(docs.select(*COLUMNS), min_words=50, stats=False)
    return out.withColumn("n_chars", F.length("text").cast("long"))


def bins(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Bins of 2048 tokens, without two documents of one source or of equal texts in one bin."""
    return packing.pack_documents(docs.select(*COLUMNS), capacity=2048)


STAGES = [("quality rules", rules), ("quality classifier", classifier), ("simhash near-dedup", near_copies), ("substring dedup", passages), ("best-fit packing", bins)]

#: Thresholds of a trained network and greedy packing have no SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each result is cut from its lineage before the next stage."""
    docs = table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = durable(docs)
    return docs
