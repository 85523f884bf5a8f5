"""The corpus pipeline: quality, repeated lines, near duplicates, source mix, packing.

Each stage takes (spark, docs, sf_dir) and works on every document its predecessor kept; all but the last
return the columns of ``documents``. ``run`` stores each stage's result before the next one reads it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from relseq.llm import line_dedup, mixing, near_dup, packing, quality, store


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier takes for good ones."""
    store.small_batches(spark)
    return quality.select_quality(docs, quality.label_grades(spark, sf_dir))


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without later copies of repeated line runs; a text that was nothing else goes."""
    store.small_batches(spark)
    return line_dedup.dedupe_lines(docs)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates; documents with a null id stay."""
    store.small_batches(spark)
    gone = near_dup.near_duplicates(docs).where("not kept").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as its source's share asks for."""
    return mixing.apply_mix(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the mixed documents and their places in sequences."""
    store.small_batches(spark)
    return packing.best_fit_pack(docs)


STAGES = [
    ("quality_classifier", quality_stage),
    ("line_dedup", line_stage),
    ("near_duplicates", near_duplicate_stage),
    ("source_mixing", mixing_stage),
    ("best_fit_packing", packing_stage),
]

#: The first stage's model has no SQL form, so the pipeline is tested stage by stage instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = store.table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = store.materialise(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
