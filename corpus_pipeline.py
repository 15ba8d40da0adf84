"""The training-data pipeline: five stages over ``documents``, each keeping what the next one reads.

Every stage takes ``(spark, docs, sf_dir)`` and works on all rows of ``docs``; all but the last
return the columns of ``documents``. :func:`run` writes each stage's rows as Parquet in the
session's shared folder, reads them again, and deletes them once the next stage is written.

Defined results: rows with a null text, or an empty one, pass the classifier by its score of an empty text,
are nobody's near duplicate, keep their text and are packed as one end mark; rows without a doc_id
are documents of their own and pass all stages; rows repeated under one doc_id are judged
row by row, so texts that differ both stay and of equal ones one does; ties go to the
smallest doc_id; empty tables give an empty table; very long texts are read whole; other columns pass
all stages but the last, whatever their names (only ``n_chars`` follows its text).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphparts.llm.common import dropped, fold_column, table, written
from graphparts.llm.ngram_join import without_near_duplicates
from graphparts.llm.packing import pack
from graphparts.llm.quality_mil import fit, keep
from graphparts.llm.secret_scan import labelled_findings, redact, train
from graphparts.llm.substring_dedup import remove_repeats


def _counted(docs: DataFrame) -> DataFrame:
    """``n_chars`` follows the text."""
    if "n_chars" not in docs.columns:
        return docs
    return docs.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier rejects go."""
    labels = table(spark, sf_dir, "labels")
    return keep(docs, fit(docs, labels.where(fold_column() != 1)))


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near duplicates stays, that of the smallest doc_id; rows without a doc_id stay."""
    return without_near_duplicates(docs)


def substring_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Words in repeated windows go; a document that keeps no word goes. Blocks and slabs are half as large as alone, as executors hold what earlier stages left."""
    cut = remove_repeats(docs, block_docs=512, slab_docs=20_000, prefix="_stage_")
    return _counted(cut.where("_stage_n_removed < _stage_n_words or _stage_n_words = 0").select(*docs.columns))


def secret_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are replaced by a mark."""
    return _counted(redact(docs, train(labelled_findings(spark, 8000, wide=True), wide=True), wide=True))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each piece of each document lies in the training sequences."""
    return pack(docs)


STAGES = [
    ("quality classifier", quality_stage),
    ("n-gram Jaccard join", near_duplicate_stage),
    ("substring dedup", substring_stage),
    ("secret scans", secret_stage),
    ("best-fit packing", packing_stage),
]

#: No SQL: the classifier, the forest and the packing cannot be expressed in it.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, before = table(spark, sf_dir, "documents"), None
    for k, (_, stage) in enumerate(STAGES):
        docs = written(stage(spark, docs, sf_dir), f"stage{k}")
        if before is not None:
            dropped(spark, before)
        before = docs
    return docs
