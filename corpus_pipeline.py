"""The corpus pipeline: quality rules, line dedup, SimHash near-dedup, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and read again as
the next stage's documents.  All but the last return the columns of documents.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from skewgraph.llm import lines, packing, quality, simhash
from skewgraph.llm.common import Shared, documents


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rules and both log-likelihood ratios.

    Null and empty texts fail the base rules; repeated rows are judged one by one; scores that tie with the threshold
    are kept; further columns stay, whatever their names; an empty table gives an empty result.
    """
    model = quality.fit_labelled(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return quality.judge(docs, model, keep_columns=True)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without lines that stay elsewhere; ``n_chars`` follows the text.

    Documents that lost lines and have no word left go.  Null texts and rows without a ``doc_id`` come back as they
    are; of equal lines the one with the least ``doc_id`` and place stays; rows that repeat a ``doc_id`` and text keep
    the same lines; further columns stay, whatever their names; an empty table gives an empty result.
    """
    out = lines.dedup(docs, measures=False)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of similar texts, the least ``doc_id``; of rows that repeat a document one.

    Null, empty and wordless texts and rows without a ``doc_id`` stay; further columns stay, whatever their names; an
    empty table gives an empty result.
    """
    return simhash.keep_one(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of the documents in their sequences.

    Null and empty texts are the end id alone; repeated rows are packed one by one; further columns are left out; an
    empty table gives an empty result.
    """
    return packing.pack(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


STAGES = [("quality rules", quality_rules), ("line dedup", line_dedup), ("SimHash near-dedup", near_dedup), ("packing", packed)]

#: No stage can be told in SQL; the tests hold each against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = Shared(stage(spark, docs, sf_dir), "pipeline-" + name.replace(" ", "-")).frame
    return STAGES[-1][1](spark, docs, sf_dir)
