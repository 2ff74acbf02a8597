"""A corpus from raw documents to packed sequences, in five stages.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and read
back as the next one's ``docs``.  All stages but the last return the columns of ``docs``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from narrative_engine.llm.common import staged, table
from narrative_engine.llm.decontamination import contamination
from narrative_engine.llm.jaccard_join import representatives
from narrative_engine.llm.line_dedup import deduped
from narrative_engine.llm.packing import packed
from narrative_engine.llm.quality_rules import ledger, passing


def _held(docs: DataFrame) -> DataFrame:
    """``doc_id``, ``text`` and the whole row as a struct, out of the way of an operator's own names."""
    return docs.select("doc_id", "text", F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_doc"))


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the production policy keeps."""
    return passing(ledger(_held(docs), "_doc")).select("_doc.*")


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, the later ones without the blocks they share with an earlier one."""
    rows = deduped(docs)
    rows = rows.toDF(*docs.columns, "_told_").drop("_told_")  # by place: docs may have a column of that name
    return rows.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else rows


def jaccard_join(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of linked texts: the smallest doc_id (and text hash); equal rows count as one."""
    return representatives(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the benchmark doesn't contaminate."""
    return contamination(_held(docs), table(spark, sf_dir, "benchmark"), "_doc").where("NOT contaminated").select("_doc.*")


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces with their sequence and offset."""
    return packed(docs)


STAGES = [
    ("quality_rules", quality_rules),
    ("line_dedup", line_dedup),
    ("jaccard_join", jaccard_join),
    ("decontamination", decontamination),
    ("packing", packing),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)


#: Packing isn't expressible in SQL.
ORACLE_SQL = None
