"""From raw documents to packed training sequences.

Every stage takes ``(spark, docs, sf_dir)`` and returns a DataFrame that is written as Parquet and read again as the
next stage's ``docs``. All stages but the last return the columns of ``docs``.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from setsim.llm.decontaminate import decontaminate
from setsim.llm.lines import dedup_lines
from setsim.llm.near_duplicates import keep_one
from setsim.llm.packing import digest, pack
from setsim.llm.quality import keep_good
from setsim.scratch import Scratch


def quality(spark, docs, sf_dir):
    """Documents that the classifier, fitted on labelled documents outside its held-out fold, does not reject."""
    return keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def lines(spark, docs, sf_dir):
    """Lines that no earlier line resembles; documents that lose all their lines go, ``n_chars`` follows the text."""
    kept = dedup_lines(docs, drop_emptied=True)
    return kept.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else kept


def near_duplicates(spark, docs, sf_dir):
    """One document of each near-duplicate group."""
    return keep_one(docs)


def benchmark(spark, docs, sf_dir):
    """Documents without a benchmark window."""
    return decontaminate(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def packing(spark, docs, sf_dir):
    """Pieces of token sequences (see the packing operator for the ids themselves)."""
    return digest(pack(docs))


STAGES = [("quality", quality), ("line_dedup", lines), ("near_duplicates", near_duplicates), ("decontamination", benchmark), ("packing", packing)]

#: Trained scores and token ids are beyond SQL; tests hold every stage against brute force.
ORACLE_SQL = None


def run(spark, sf_dir):
    """All stages over ``documents``."""
    scratch = Scratch(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = scratch.save(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
