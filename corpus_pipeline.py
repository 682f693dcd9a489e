"""A corpus pipeline of five stages, each one of the training-data operators.

``run`` applies the stages to ``documents``. Each stage's result is written to the shared
folder and read again as the next one's input. All but the last return the columns of
``documents``; the last returns a row per packed piece.

Defined cases: null or empty texts have no words and fail a base rule, so they leave with the
first stage; a null id is a value of its own where ids decide, except that near copies never
remove a row without an id; repeated rows are judged alike and stay or go together, and are
packed each; an empty table gives an empty result; columns beside those named pass through.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from attention_engine.llm.common import materialise
from attention_engine.llm.decontaminate import contamination
from attention_engine.llm.linededup import deduplicated
from attention_engine.llm.nearcopies import near_copies
from attention_engine.llm.packing import best_fit
from attention_engine.llm.quality import quality

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep; of a repeated id all rows must be kept."""
    bad = quality(docs).where(~F.col("kept")).select(F.col("doc_id").alias("bad")).distinct()
    return docs.join(bad, docs.doc_id.eqNullSafe(bad.bad), "left_anti")


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines without an earlier line that matches; n_chars follows the text."""
    out = deduplicated(docs)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def keep_one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document that names its component of near copies (Jaccard 0.8 on shingles of five words); rows without an id stay, and all rows of the id that stays."""
    gone = near_copies(docs).where(F.col("component_id") < F.col("doc_id")).select(F.col("doc_id").alias("gone")).distinct()
    return docs.join(gone, docs.doc_id == gone.gone, "left_anti")


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a passage of the benchmark."""
    found = contamination(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).where("contaminated").select(F.col("doc_id").alias("leak")).distinct()
    return docs.join(found, docs.doc_id.eqNullSafe(found.leak), "left_anti")


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents that are left, by bin."""
    return best_fit(docs)


STAGES: list[tuple[str, Stage]] = [
    ("quality rules", keep_good),
    ("line dedup", drop_repeated_lines),
    ("SimHash near-dedup", keep_one_of_near_copies),
    ("benchmark decontamination", drop_contaminated),
    ("best-fit packing", pack),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage over all documents."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), "stage-" + name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
