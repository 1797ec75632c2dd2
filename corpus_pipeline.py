"""A corpus pipeline: language, near-duplicates, repeated passages, benchmark leaks, packing.

Each stage takes (spark, docs, sf_dir), works on all that its predecessor kept, and all but the last
return the columns of ``documents``; ``run`` writes each stage as Parquet and rereads it.
"""

from __future__ import annotations

import functools

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from comovement.llm import decontaminate, langid, minhash, packing, suffixes
from comovement.llm.shared import drop, recorded, written

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
LEAST_SCORE = 0.2
"""Texts whose language is less sure than this are rejected, as are those without letters."""


_MADE: list = []


def stage(f):
    """A stage, which first drops the tables that the stage before it wrote on its way: they are not needed once
    that one's rows are written, as they are between stages. Tables that docs still reads stay."""

    @functools.wraps(f)
    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        drop(_MADE, docs)
        with recorded() as made:
            out = f(spark, docs, sf_dir)
        _MADE.extend(made)
        return out

    return run_stage


@stage
def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents with a recognisable language.

    Null, empty and letterless texts go; a null lang, source or doc_id is kept as it is; repeated rows stand or
    fall together; without a labelled document (an empty table, say) no language is known and all rows go."""
    found = langid.identify(docs, docs, carried=("lang", "source", "n_chars"))
    return found.where((F.col("lang_pred") != "und") & (F.col("score") >= LEAST_SCORE)).select(*COLUMNS)


@stage
def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each near-duplicate group: the one with the least id.

    Null and empty texts have no duplicates and stay, as do rows with a null doc_id, which are in no group; of rows
    that repeat a doc_id and text one stays, of different texts under one doc_id all or none; extra columns go."""
    groups = written(minhash.near_duplicates(docs, percent=80), "groups")
    gone = groups.where(~F.col("kept")).select("doc_id").distinct()
    kept = docs.select(*COLUMNS).join(gone, "doc_id", "left_anti")
    repeated = groups.where("doc_id is not null").groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1").select("doc_id")
    if not repeated.limit(1).count():
        return kept
    once = kept.join(repeated, "doc_id", "left_semi").dropDuplicates(["doc_id", "text"])
    return kept.join(repeated, "doc_id", "left_anti").select(*COLUMNS).unionByName(once.select(*COLUMNS))


@stage
def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Removes byte strings that also start earlier; documents left without text go.

    Null and empty texts stay as empty ones; of rows that repeat doc_id and text each is cut alike; extra columns go."""
    kept = suffixes.remove_repeats(docs, with_text=True, carried=("lang", "source"))
    text = F.when(F.col("n_removed") > 0, F.trim("kept")).otherwise(F.col("kept"))
    kept = kept.withColumn("text", text).where((F.length("text") > 0) | (F.col("n_removed") == 0))
    return kept.withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


@stage
def benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents that hold no benchmark item.

    Null and empty texts hold none; rows of one doc_id, or with a null one, go together; extra columns go."""
    return decontaminate.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).select(*COLUMNS)


@stage
def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs what is left into sequences: null and empty texts as the end id alone, repeated rows one by one."""
    return packing.pack(docs)


STAGES = [("language ID", language), ("MinHash near-dedup", near_duplicates), ("suffix-array dedup", repeated_passages), ("benchmark decontamination", benchmark_leaks), ("packing", packed)]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies the stages to documents; the rows of the last one. A stage's table goes once the next one is written."""
    docs, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), []
    for _, step in STAGES[:-1]:
        out = step(spark, docs, sf_dir)
        with recorded() as made:
            docs = written(out, "stage")
        drop(before, docs)
        before = made
    return STAGES[-1][1](spark, docs, sf_dir)
