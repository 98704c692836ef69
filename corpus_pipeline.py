"""A training corpus from raw documents: stages that each read what the one before has kept.

Every stage takes the columns doc_id and text, and n_chars where there is one; other columns pass through
with their values, whatever their names, up to packing, which returns its own.  Defined results of all
stages: ids may be null or repeat, because no stage tells rows apart by id; an empty table gives an empty
result; very long texts are read whole.  What each stage does beside that stands with it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from joindash.llm.common import new_path, remove_path, table
from joindash.llm.decontaminate import without_contaminated
from joindash.llm.packing import pack_documents
from joindash.llm.pii import mask_personal_data
from joindash.llm.quality_rules import passing
from joindash.llm.resemblance import one_of_resembling


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the quality rules.  Null, empty and blank texts fail them; repeated rows share a verdict."""
    return passing(docs)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of texts with a 5-word Jaccard similarity of 0.8 or more: the one with the
    least id; any of a group's repeated rows, or of those without an id where none has one.  Texts without
    words are one group."""
    return one_of_resembling(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no passage of the benchmark; texts without words hold none."""
    return without_contaminated(docs, table(spark, sf_dir, "benchmark"))


def mask_personal(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data masked; n_chars, where there is one, follows the text.  Null texts stay null."""
    out = mask_personal_data(docs)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces, packed into sequences.  A null or empty text is the end token alone; repeated rows are packed each."""
    return pack_documents(docs)


STAGES = [
    ("quality_rules", keep_quality),
    ("near_dedup", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("personal_data", mask_personal),
    ("packing", pack_sequences),
]

#: No SQL: the fingerprints, compression ratios and token ids have no counterpart in it.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        path = new_path(spark, name)
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
        if before:
            remove_path(spark, before)
        before = path
    return docs
