"""Dictionaries, hit and miss weights from tables of probes.

Probes are counted by key before anything else, so a hot key is one row of every later step. The
dictionary is numbered by ranges of sorted keys; a miss finds its gap in its own range, with the
number of keys in earlier ranges carried over, so no step needs all rows in one task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.kernel import Weights
from ..storage import written


def hit_counts(probes: DataFrame, key: Column, weight: Column | None = None) -> DataFrame:
    """(key, n): probes by key; null keys are left out."""
    n = F.count(F.lit(1)) if weight is None else F.sum(weight).cast("bigint")
    return probes.select(key.alias("key"), *([] if weight is None else [weight.alias("w")])).where("key IS NOT NULL").groupBy("key").agg(n.alias("n") if weight is None else F.sum("w").cast("bigint").alias("n"))


def ranked(keys: DataFrame, column: str = "key") -> DataFrame:
    """``keys`` with ``rank`` 1..n in key order, from the ranges of one sort."""
    own = keys.orderBy(column).select("*", F.spark_partition_id().alias("part"), F.monotonically_increasing_id().alias("at"))
    own = written(own.withColumn("at", F.col("at").bitwiseAND(F.lit((1 << 33) - 1))), "ranked")
    counts = own.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    # One row a partition: a window over them is small whatever the table.
    before = counts.select("part", (F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1))).alias("before"))
    return own.join(F.broadcast(before), "part").select(*keys.columns, (F.col("at") + 1 + F.coalesce("before", F.lit(0))).cast("bigint").alias("rank"))


def most_frequent(counts: DataFrame, limit: int) -> DataFrame:
    """The ``limit`` keys with the most probes; ties go to the smaller key."""
    return counts.orderBy(F.desc("n"), "key").limit(limit)


def weight_table(dictionary: DataFrame, counts: DataFrame) -> DataFrame:
    """(idx, key, hit, miss), idx 0..n: hits of keys, and misses of the gap above each (row 0: below the first)."""
    keys = written(ranked(dictionary.select("key").distinct()), "keys")
    hits = keys.join(counts, "key", "left").select(F.col("rank").alias("idx"), "key", F.coalesce("n", F.lit(0)).alias("hit"))
    misses = counts.join(keys, "key", "left_anti")
    both = keys.select("key", "rank", F.lit(0).cast("bigint").alias("n")).unionByName(misses.select("key", F.lit(None).cast("bigint").alias("rank"), "n"))
    placed = written(both.repartitionByRange("key").withColumn("part", F.spark_partition_id()), "placed")
    own = Window.partitionBy("part").orderBy("key").rowsBetween(Window.unboundedPreceding, 0)
    tops = placed.groupBy("part").agg(F.max("rank").alias("top"))
    before = tops.select("part", F.max("top").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)).alias("before"))
    gaps = placed.select("part", "rank", "n", F.last("rank", True).over(own).alias("last")).join(F.broadcast(before), "part")
    gaps = gaps.where("rank IS NULL").groupBy(F.coalesce("last", "before", F.lit(0)).alias("idx")).agg(F.sum("n").alias("miss"))
    zero = hits.sparkSession.range(1).select(F.col("id").alias("idx"), F.lit(None).cast(dict(keys.dtypes)["key"]).alias("key"), F.lit(0).cast("bigint").alias("hit"))
    return zero.unionByName(hits).join(gaps, "idx", "left").select("idx", "key", "hit", F.coalesce("miss", F.lit(0)).alias("miss"))


def collected(table: DataFrame) -> Weights:
    """The vectors of a weight table on the driver: two numbers a key, bounded by the n^2 cells to be solved."""
    own = table.select("idx", "hit", "miss").toPandas().sort_values("idx")
    return Weights(own["hit"].to_numpy(), own["miss"].to_numpy())


def prefix(table: DataFrame) -> DataFrame:
    """(idx, ps, qs): running sums of hits and misses; one task, n rows bounded as above."""
    own = Window.orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
    return table.select("idx", F.sum("hit").over(own).alias("ps"), F.sum("miss").over(own).alias("qs"), "miss")
