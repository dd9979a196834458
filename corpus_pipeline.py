"""The training-data pipeline: five filters and transforms over ``documents``.

``STAGES`` lists (name, function); each function takes (spark, docs, sf_dir) and returns
a DataFrame that is written as Parquet and read again as the next one's ``docs``.  All
but the last return the columns of ``documents`` and only ever drop whole documents:

1. toxicity: documents that the calibrated classifier holds to be toxic go;
2. quality: documents that the rule ensemble scores below its threshold go;
3. near duplicates: of each component of linked documents the smallest doc_id stays;
4. decontamination: documents that a benchmark item contaminates go;
5. pieces: every remaining text is encoded, and decoded again as a check.

Odd rows have the results that the operators state: null and empty texts pass the
filters that hold nothing against them, have no duplicates and get null or empty ids;
rows with a null doc_id pass the near-duplicate stage; empty tables stay empty; extra
columns are carried to the last stage, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from weightdraw.llm import decontaminate, quality, setsketch, toxicity, unigram
from weightdraw.llm.common import materialise, table, unused


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.keep(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.keep(docs, quality.fit(docs, table(spark, sf_dir, "labels")))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    gone = unused(docs, "_gone")
    dropped = materialise(setsketch.near_duplicates(docs).where("not kept").select(F.col("doc_id").alias(gone)).distinct())
    return docs.join(dropped, docs["doc_id"] == dropped[gone], "left_anti")


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark")).select(*docs.columns)


def to_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return unigram.encode(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("quality", keep_quality),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("pieces", to_pieces),
]

#: Classifiers, similarity search and piece encoding have no SQL form; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = materialise(docs)
    return docs
