"""A corpus pipeline of five stages; each works on all that the one before kept.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame, written as
Parquet and reread as the next one's docs.  All but the last return the columns
of ``documents``; the last returns the packed pieces.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from blocksketch.llm import decontaminate, line_dedup, ngram_join, packing, quality
from blocksketch.llm.common import discard, materialise, read_table

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: Sites from which on a line is shared across sites, however small the corpus; the operator's own SQL has ten.
FEW_SITES = 3


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go."""
    return quality.keep_good(docs.select(*COLUMNS), read_table(spark, sf_dir, "labels"))


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that are not blank and shown by FEW_SITES sources go, but for their first occurrence; n_chars follows."""
    return line_dedup.without_boilerplate(docs.select(*COLUMNS), min_sites=FEW_SITES, min_chars=1)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of similar documents the one of smallest doc_id stays."""
    return ngram_join.one_of_each(docs.select(*COLUMNS))


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a twentieth of their words inside benchmark windows go."""
    return decontaminate.clean_documents(docs.select(*COLUMNS), read_table(spark, sf_dir, "benchmark"))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every kept document in sequences of at most 1024 tokens: one row per piece."""
    return packing.pack(docs, capacity=1024, end_id=2)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality classifier", quality_stage),
    ("line dedup", line_stage),
    ("n-gram Jaccard join", near_duplicate_stage),
    ("benchmark decontamination", decontamination_stage),
    ("best-fit packing", packing_stage),
]

#: Learned scores, MinHash recall and packing order have no SQL twin.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on the table ``documents``."""
    docs = read_table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        kept, docs = docs, stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = materialise(docs, f"stage{i}")
            discard(kept)
    return docs
