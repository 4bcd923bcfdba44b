"""Weights from text files, and trees, runs and weights to files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

WEIGHTS = "idx BIGINT, key STRING, hit BIGINT, miss BIGINT"


def read_weights(spark: SparkSession, path: str, kind: str = "csv", malformed: str = "FAILFAST") -> DataFrame:
    """(idx, key, hit, miss) from CSV with a header or from JSON lines, by an explicit schema.

    ``malformed`` rows fail the read, are dropped (DROPMALFORMED) or come as nulls (PERMISSIVE).
    """
    reader = spark.read.schema(WEIGHTS).option("mode", malformed)
    return reader.option("header", True).csv(path) if kind == "csv" else reader.json(path)


def write_weights(table: DataFrame, path: str, kind: str = "csv") -> None:
    own = table.select("idx", F.col("key").cast("string").alias("key"), "hit", "miss")
    (own.write.option("header", True).csv if kind == "csv" else own.write.json)(path)


def write_tree(nodes: DataFrame, path: str, kind: str = "parquet") -> None:
    """Nodes (rank, key, depth, parent_rank, side) as Parquet, CSV, or JSON lines with the children of each node nested in it."""
    if kind != "json":
        (nodes.write.parquet if kind == "parquet" else nodes.write.option("header", True).csv)(path)
        return
    child = F.struct("side", "rank", "key")
    below = nodes.where("parent_rank > 0").groupBy(F.col("parent_rank").alias("rank")).agg(F.array_sort(F.collect_list(child)).alias("children"))
    nodes.join(below, "rank", "left").select("rank", "key", "depth", "children").write.json(path)


def register_views(spark: SparkSession, **tables: DataFrame) -> None:
    """Temporary views for SQL users, one for each named table (keys, weights, cells, tree, ...)."""
    for name, table in tables.items():
        table.createOrReplaceTempView(name)
