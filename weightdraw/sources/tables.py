"""Sources and weighted-item fixtures over the given tables, each with its SQL twin."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.items import weighted_items

READERS = ("parquet", "orc", "json", "csv")


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options: str) -> DataFrame:
    """A table from parquet, ORC, JSON or CSV; text formats want a schema, so nothing is inferred."""
    if kind not in READERS:
        raise ValueError(f"unknown format {kind}")
    reader = spark.read.options(**options)
    return (reader.schema(schema) if schema else reader).format(kind).load(path)


def read_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    """A file stream over a folder of parquet files."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def rate_stream(spark: SparkSession, rows_per_second: int) -> DataFrame:
    """A generated stream (ts, id): Spark's rate source with the columns that samplers expect."""
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load().select(F.col("timestamp").alias("ts"), F.col("value").alias("id"))


def write_partitioned(df: DataFrame, path: str, by: str) -> None:
    """A structure on disk, partitioned by class or shard, so a query prunes what it need not read."""
    df.write.mode("overwrite").partitionBy(by).parquet(path)


def write_bucketed(df: DataFrame, name: str, by: str, buckets: int) -> None:
    """A bucketed table: joins on the bucket column then need no exchange of this side."""
    df.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).format("parquet").saveAsTable(name)


@dataclass(frozen=True)
class Fixture:
    """A weighted table: its source, id and weight, as Spark and as DuckDB text."""

    table: str
    id_sql: str
    weight_sql: str
    scale: int

    def items(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        df = spark.read.parquet(f"{sf_dir}/{self.table}.parquet")
        return weighted_items(df.select(F.expr(self.id_sql).alias("id"), F.expr(self.weight_sql).alias("w")), "id", "w", self.scale)

    @property
    def sql(self) -> str:
        return f"items AS (SELECT {self.id_sql} AS id, CAST({self.weight_sql} AS DOUBLE) AS w, CAST(round(CAST({self.weight_sql} AS DOUBLE) * {self.scale}) AS BIGINT) AS units FROM {self.table} WHERE {self.weight_sql} > 0 AND round(CAST({self.weight_sql} AS DOUBLE) * {self.scale}) > 0)"


LINE_ID = "concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey)"
FIXTURES = {
    "orders": Fixture("orders", "o_orderkey", "o_totalprice", 100),
    "events": Fixture("events", "event_id", "value", 100),
    "documents": Fixture("documents", "doc_id", "n_chars", 1),
    "part": Fixture("part", "p_partkey", "p_retailprice", 100),
    "customer": Fixture("customer", "c_custkey", "c_acctbal", 100),
    "supplier": Fixture("supplier", "s_suppkey", "s_acctbal", 100),
    "quantity": Fixture("lineitem", LINE_ID, "l_quantity", 1),
    "lineitem": Fixture("lineitem", LINE_ID, "l_extendedprice", 100),
}
