"""A training corpus from `documents`, in five stages; each works on all rows that the stage before it kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dictparse.llm.common import read, written
from dictparse.llm.decontamination import decontaminate
from dictparse.llm.line_dedup import drop_repeated_lines
from dictparse.llm.near_dedup import keep_first
from dictparse.llm.packing import pack_documents
from dictparse.llm.toxicity import drop_toxic


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the weakly supervised classifier takes for toxic go."""
    return drop_toxic(docs, read(spark, sf_dir, "labels").select("doc_id", "toxic"))


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines repeated over documents go, but for the largest document that holds them."""
    found = drop_repeated_lines(docs)
    kept, _, dropped = found.columns[-3:]
    text = F.when(F.col(dropped) > 0, F.col(kept)).otherwise(F.col("text"))
    return found.withColumn("text", text).withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates stays: the one with the smallest id."""
    return keep_first(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of a benchmark item go."""
    return decontaminate(docs, read(spark, sf_dir, "benchmark"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of the documents' token sequences, packed."""
    return pack_documents(docs)


STAGES = [("toxicity", toxicity), ("line_dedup", line_dedup), ("near_dedup", near_dedup), ("decontamination", decontamination), ("packing", packing)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on `documents`."""
    docs = read(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        if k:
            docs = written(docs, f"pipeline-{k}")
        docs = stage(spark, docs, sf_dir)
    return docs


#: The first stage is a trained classifier, which SQL can't express; the stages are tested against brute force.
ORACLE_SQL = None
