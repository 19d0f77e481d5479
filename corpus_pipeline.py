"""A training corpus in four stages: quality, near duplicates, repeated passages, packing.

Each stage takes what its predecessor kept, as a table; all but the last return
the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from binsketch.llm.common import scratch, table, written
from binsketch.llm.jaccard_join import near_duplicates, some_docs
from binsketch.llm.packing import packed
from binsketch.llm.quality import accepted
from binsketch.llm.queries import vocabulary
from binsketch.llm.suffix_dedup import cleaned
from binsketch.session import ship


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects (poor or toxic) go."""
    ship(spark)
    return accepted(docs, table(spark, sf_dir, "labels"))


def near_duplicate_groups(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of linked documents the one with the smallest doc_id stays."""
    ship(spark)
    others = written(near_duplicates(docs).filter("component_id <> doc_id").select("doc_id").distinct(), "near-copies")
    return some_docs(docs, others, "left_anti").select(*(f"`{c}`" for c in docs.columns))


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Bytes of passages that also occur earlier go."""
    ship(spark)
    return cleaned(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of 4096-token windows, neighbours by words together."""
    ship(spark)
    return packed(docs, vocabulary("word_bpe_49k.json"))


STAGES = [("quality", quality), ("near_duplicates", near_duplicate_groups), ("repeated_passages", repeated_passages), ("packing", packing)]

#: SQL can't express the stages; tests compare them with plain versions on small tables.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written as Parquet and read again."""
    with scratch(spark) as last:  # what a stage has written goes when the next one's result is written
        docs = table(spark, sf_dir, "documents")
        for name, stage in STAGES[:-1]:
            with scratch(spark) as own:
                docs = own.keep(written(stage(spark, docs, sf_dir), f"stage-{name}"))
        return last.keep(written(STAGES[-1][1](spark, docs, sf_dir), "stage-packing"))
