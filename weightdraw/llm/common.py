"""Shared plumbing of the training-data operators.

Nothing here knows any single operator.  The two ideas worth knowing:

* ``materialise`` cuts lineage by writing Parquet to the folder the cluster names in
  ``spark.checkpoint.dir`` (every executor sees it) and reading it back, so a lost
  executor never costs more than the stage that was running.
* ``ship`` registers a module for pickling by value, so executors need no copy of
  this repository on their Python path.
"""

from __future__ import annotations

import pickle
import sys
from collections.abc import Callable

from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.stored import materialise, shared_dir

__all__ = ["bounded_labelled", "held_out", "materialise", "share", "shared_dir", "ship", "table", "unused"]


def ship(module_name: str) -> None:
    """Pickle the functions of a module by value, for executors without this repository."""
    cloudpickle.register_pickle_by_value(sys.modules[module_name])


def share(spark: SparkSession, thing: object) -> Callable[[], object]:
    """Broadcast an object of this repository's classes; the result gives it back on any executor."""
    sent = spark.sparkContext.broadcast(cloudpickle.dumps(thing))
    held: list[object] = []

    def get() -> object:
        if not held:
            held.append(pickle.loads(sent.value))  # noqa: S301 - our own bytes
        return held[0]

    return get


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def unused(df: DataFrame, base: str) -> str:
    """``base``, lengthened until no column of ``df`` begins with it: names for temporary columns."""
    while any(c.lower().startswith(base.lower()) for c in df.columns):
        base += "_"
    return base


def held_out(doc_id: Column, modulus: int, remainder: int) -> Column:
    """The contract's fold: crc32 of the id as text, modulo; a null id counts as not held out."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % modulus == remainder, F.lit(False))


def bounded_labelled(docs: DataFrame, labels: DataFrame, label: str, modulus: int, remainder: int, bound: int) -> DataFrame:
    """(doc_id, text, y) of labelled training rows: at most ``bound`` of them, by hash order.

    The bound is the documented sample size for fitting a classifier; the hash order
    makes the choice independent of partitioning.  Repeated label rows count once, and so
    do repeated rows of a document: of several texts the least hash stands for the id, so
    the joined rows keep the bound as well.
    """
    y = labels.select(F.col("doc_id").alias("_id"), F.col(label).cast("int").alias("y")).where("y is not null")
    y = y.where(~held_out(F.col("_id"), modulus, remainder)).groupBy("_id").agg(F.max("y").alias("y"))
    chosen = y.orderBy(F.xxhash64("_id"), "_id").limit(bound)
    rows = docs.select("doc_id", "text").where("text is not null").join(F.broadcast(chosen), F.col("doc_id") == F.col("_id"))
    # written, as a fit goes over its rows several times
    return materialise(rows.groupBy("doc_id", "y").agg(F.min_by("text", F.xxhash64("text")).alias("text")).select("doc_id", "text", "y"))


ship(__name__)
