"""Corpus pipeline over ``documents``: rules, classifier, line and near-duplicate removal, packing.

``STAGES`` lists (name, function); each function takes (spark, docs, sf_dir) and returns a DataFrame, which ``run`` writes as
Parquet to the shared folder and reads again as the next stage's ``docs``. All but the last return the columns of documents.
Models are trained on labelled rows of the whole ``documents`` table, whatever earlier stages removed, but never on the rows that
``quality_knn.held_out`` sets apart, so that their verdicts can be judged on labels that no model has seen.

Edge cases, of every stage: an empty table gives an empty table; columns of other names are dropped, and none can clash; rows that
repeat an id are rows of their own. A null, empty or blank text fails the first stage's word count. Without labels no document is
rejected for its score. A text of any length is handled whole.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dpgrid.llm import dart_minhash, line_dedup, packing, quality_knn, quality_rules
from dpgrid.llm.queries import BYTE_BPE
from dpgrid.plans.scratch import materialise

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def _raw(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Texts and labels that train."""
    docs, labels = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"), spark.read.parquet(f"{sf_dir}/labels.parquet")
    return docs.where(~quality_knn.held_out()), labels.where(~quality_knn.held_out())


def quality_rules_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail a count or the calibrated regression go."""
    model = quality_rules.train(*_raw(spark, sf_dir))
    return quality_rules.apply_rules(docs, model).where("kept").select(*COLUMNS)


def quality_classifier_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that their labelled neighbours vote down go."""
    model = quality_knn.train(*_raw(spark, sf_dir))
    return quality_knn.score(docs, model).where("predicted = 1").select(*COLUMNS)


def line_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeated lines leave the texts; ``n_chars`` follows the text, and texts left without a word go."""
    cleaned = line_dedup.dedup_lines(docs.select(*COLUMNS))
    return cleaned.where(F.col("text").rlike(r"[^\x20\x09-\x0D]")).withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)).select(*COLUMNS)


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays: that of least id, and of rows equal in id and words one.

    A row is told by its id and the hash of its text, so of an id with several texts only those that are copies go. Rows without an id stay.
    """
    return dart_minhash.drop_near_duplicates(docs.select(*COLUMNS)).select(*COLUMNS)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of token sequences, as ``op8_packing`` returns them."""
    return packing.pack_documents(docs, public_tokenizers.path(BYTE_BPE), end_id=0)


STAGES = [
    ("quality_rules", quality_rules_stage),
    ("quality_classifier", quality_classifier_stage),
    ("line_dedup", line_dedup_stage),
    ("near_dedup", near_dedup_stage),
    ("packing", packing_stage),
]

#: Two stages are trained models, which SQL cannot express; tests/llm checks each stage instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; the last stage's rows."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select(*COLUMNS)
    for name, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir), f"stage_{name}")
    return docs
