"""SQL surface: registered functions and a table function for SQL users."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F

from ..functions.variates import py_uniform

class FirstRows:
    """Keeps the first k rows of each partition of a table argument; the caller orders by key."""

    def __init__(self) -> None:
        self.seen = 0

    def eval(self, k: int, row: Row) -> Iterator[tuple[str, int]]:
        if self.seen < k:
            self.seen += 1
            yield row["grp"], row["id"]


class AliasDraws:
    """Draws k times from a small alias table given as a table argument in bucket order."""

    def __init__(self) -> None:
        self.rows, self.k, self.seed = [], 0, 0

    def eval(self, k: int, seed: int, row: Row) -> None:
        self.k, self.seed = k, seed
        self.rows.append((row["bucket"], row["id"], row["part"], row["alias"], row["cap"]))

    def terminate(self) -> Iterator[tuple[int, int]]:
        from hashlib import md5

        uniform = lambda key: (int(md5(f"{self.seed}:{key}".encode()).hexdigest()[:13], 16) + 1) / float(1 << 52)  # noqa: E731, S324
        rows = sorted(self.rows)
        for draw in range(self.k if rows else 0):
            _, own, part, alias, cap = rows[min(int(uniform(f"bucket:{draw}") * len(rows)), len(rows) - 1)]
            yield draw, alias if alias is not None and uniform(f"coin:{draw}") * float(cap) >= float(part) else own


class PoissonRows:
    """Keeps every row (id, pi) of a table argument with its own probability."""

    def eval(self, seed: int, row: Row) -> Iterator[tuple[str]]:
        if row["pi"] is not None and py_uniform(seed, row["id"]) <= row["pi"]:
            yield (row["id"],)


def register(spark: SparkSession) -> None:
    """hash_uniform(seed, key), exp_key(seed, key, w), weight_class(units, least), weighted_sample(k, TABLE), alias_draws(k, seed, TABLE), poisson(seed, TABLE)."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION hash_uniform(seed INT, key STRING) RETURNS DOUBLE RETURN (CAST(conv(substring(md5(concat_ws(':', CAST(seed AS STRING), key)), 1, 13), 16, 10) AS DOUBLE) + 1) / 4503599627370496D")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION exp_key(seed INT, key STRING, w DOUBLE) RETURNS DOUBLE RETURN -ln(hash_uniform(seed, key)) / w")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION weight_class(units DOUBLE, least DOUBLE) RETURNS INT RETURN CAST(floor(log2(units / least)) AS INT)")
    spark.udtf.register("alias_draws", F.udtf(AliasDraws, returnType="draw long, id long"))
    spark.udtf.register("poisson", F.udtf(PoissonRows, returnType="id string"))
    spark.udtf.register("weighted_sample", F.udtf(FirstRows, returnType="grp string, id long"))


def sample_by_group_sql(spark: SparkSession, items: DataFrame, k: int, seed: int = 7) -> DataFrame:
    """(grp, id): k weighted items per group (id, w, grp), asked in SQL through the table function."""
    register(spark)
    items.select("id", "w", "grp").createOrReplaceTempView("_weighted_items")
    spark.sql(f"SELECT id, grp, exp_key({int(seed)}, CAST(id AS STRING), w) AS key FROM _weighted_items").createOrReplaceTempView("_weighted_keys")
    return spark.sql(f"SELECT grp, id FROM weighted_sample({int(k)}, TABLE(_weighted_keys) PARTITION BY grp ORDER BY key)")


def alias_draws_sql(spark: SparkSession, table: DataFrame, k: int, seed: int = 7) -> DataFrame:
    """(draw, id): k draws from a small alias table (bucket, id, part, alias, cap), asked in SQL."""
    register(spark)
    table.select("bucket", "id", "part", "alias", "cap").createOrReplaceTempView("_alias_table")
    return spark.sql(f"SELECT draw, id FROM alias_draws({int(k)}, {int(seed)}, TABLE(_alias_table) WITH SINGLE PARTITION)")


def poisson_sql(spark: SparkSession, items: DataFrame, seed: int = 7) -> DataFrame:
    """(id) as text: every item (id, pi) with its own probability, asked in SQL; partitions stay where they are."""
    register(spark)
    items.select(F.col("id").cast("string").alias("id"), F.col("pi").cast("double").alias("pi")).createOrReplaceTempView("_items_with_pi")
    return spark.sql(f"SELECT id FROM poisson({int(seed)}, TABLE(_items_with_pi))")
