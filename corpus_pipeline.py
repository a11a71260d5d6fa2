"""A corpus pipeline of five stages over ``documents``.

Each stage is a function ``(spark, docs, sf_dir) -> DataFrame`` over what its
predecessor kept; ``run`` writes each result as Parquet to the shared folder and
reads it back for the next.  All but the last return the columns of the table.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ngramlake.llm import common, language_id, line_dedup, mixing, near_dedup, packing
from ngramlake.llm.queries import vocabulary

#: Words in a shingle of the near-duplicate stage.
SHINGLE = 5


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop texts that no language prototype claims (no letter, or like none)."""
    common.ship(spark)
    return language_id.keep_identified(docs, language_id.prototypes(docs))


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cut lines that repeat an earlier one but for two edits (below 24 bytes: that equal it);
    ``n_chars`` follows the text."""
    common.ship(spark)
    out = line_dedup.dedup_lines(docs, report=False, exact=1)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep one document of each component of near fingerprints."""
    common.ship(spark)
    return near_dedup.keep_one(docs, words=SHINGLE)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeat or thin documents until each source has its target of words."""
    return mixing.mixed_documents(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pack all that is left into sequences; one row for each piece."""
    common.ship(spark)
    return packing.pack_documents(docs, vocabulary())


STAGES = [
    ("language ID", language_stage),
    ("line dedup", line_stage),
    ("SimHash near-dedup", near_duplicate_stage),
    ("mixing sources to target weights", mixing_stage),
    ("packing", packing_stage),
]

#: Language prototypes, edit joins and packing have no SQL form.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.read(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = common.spool(docs, f"stage-{k}")
    return docs
