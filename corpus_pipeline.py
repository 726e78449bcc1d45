"""From raw documents to packed sequences: each stage is one operator of the llm subpackage.

Stages work on rows, told apart by a number of their own (their input is a written
table), so repeated, null or clashing ids lose nothing. Defined results, in all stages:
a null text counts as empty and stays null; an empty table gives an empty table; rows
that repeat go through as often as they occur, but for those that the two deduplicating
stages are there to drop; extra columns, whatever their names, are carried along.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from quiesce.llm.common import numbered, shared_dir, table
from quiesce.llm.exact_dedup import exact_dedup
from quiesce.llm.packing import pack
from quiesce.llm.pii import sanitise
from quiesce.llm.quality import accepted
from quiesce.llm.simhash import near_duplicates

#: Near copies: five-word shingles, and the fingerprints of texts whose sets of them are alike to 0.8 or more.
#: Such texts differ in 39 of 256 bits on average (an angle of acos(2 * 0.8 / 1.8)), with a deviation of 6.
NEAR = {"width": 5, "words": 4, "radius": 46}


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier accepts, by whole texts; a repeated row is judged each time, alike."""
    return accepted(docs, table(spark, sf_dir, "labels"))


def _without(docs: DataFrame, row: str, gone: DataFrame) -> DataFrame:
    """The rows of numbered ``docs`` whose number is not in ``gone``, which is much the smaller side."""
    return docs.join(gone.select(row), row, "left_anti").drop(row)


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of equal texts: one with the smallest id (any of those that repeat it)."""
    rows, row = numbered(docs)
    return _without(rows, row, exact_dedup(rows, key=row).filter(~F.col("kept"))).select(*docs.columns)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each component of near copies: the first in the order of the table."""
    rows, row = numbered(docs)
    found = near_duplicates(rows, row_id=row, **NEAR)
    return _without(rows, row, found.filter("doc_id <> component_id").withColumnRenamed("doc_id", row)).select(*docs.columns)


def personal(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data and terms that disclose it replaced; the length follows the text, and stays where there is none."""
    out = sanitise(docs)
    length = F.coalesce(F.length("text"), F.col("n_chars")).cast(docs.schema["n_chars"].dataType)
    return out.withColumn("n_chars", length).select(*docs.columns)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each piece of each document goes; of ties the row with the smaller id, then text hash, is placed first."""
    return pack(docs)


STAGES = [("quality", quality), ("exact", exact), ("near", near), ("personal", personal), ("packing", packing)]

#: The classifier is not expressible in SQL; tests hold stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    folder = f"{shared_dir(spark).rstrip('/')}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return docs
