"""Streaming weights: watermarked window counts, and trees that are rebuilt when they have drifted."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.kernel import Weights, depths_of, solve_windowed, tree_cost


def event_stream(spark: SparkSession, path: str, schema: str, files_per_batch: int = 1) -> DataFrame:
    """A file stream; ``ts`` becomes a timestamp with time zone, as watermarks need it."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling_counts(events: DataFrame, key: str, late: str = "1 day", width: str = "1 day") -> DataFrame:
    """(window_start, key, n): hits by window; rows later than ``late`` are dropped."""
    own = events.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), F.col(key).alias("key"))
    return own.agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("window_start"), "key", "n")


def sliding_counts(events: DataFrame, key: str, late: str = "1 day", width: str = "7 days", every: str = "1 day") -> DataFrame:
    """(window_start, key, n): hits by windows of ``width`` that begin ``every`` so often; later rows than ``late`` are dropped."""
    own = events.withWatermark("ts", late).groupBy(F.window("ts", width, every).alias("w"), F.col(key).alias("key"))
    return own.agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("window_start"), "key", "n")


def session_counts(events: DataFrame, key: str, late: str = "1 day", gap: str = "1 hour") -> DataFrame:
    """(session_start, key, n): hits by sessions of a key, ended by ``gap`` without one. In append mode a session comes once it is closed."""
    own = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), F.col(key).alias("key"))
    return own.agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("session_start"), "key", "n")


def once(events: DataFrame, identity: str, late: str = "1 day") -> DataFrame:
    """Each event once: repeats of ``identity`` inside the watermark are dropped, and so is their state after it."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark([identity])


def running_counts(events: DataFrame, key: str) -> DataFrame:
    """(key, n): total hits of a key so far, by a state of one number a key; emits the keys that a batch touches."""
    kind = events.schema[key].dataType.simpleString()

    def add(own: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        total = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((total,))
        yield pd.DataFrame({"key": [own[0]], "n": [total]})

    return events.select(F.col(key).alias("key")).groupBy("key").applyInPandasWithState(add, f"key {kind}, n bigint", "n bigint", "update", GroupStateTimeout.NoTimeout)


def live_depths(events: DataFrame, key: str, depths: DataFrame) -> DataFrame:
    """Events with the ``depth`` of their key in a tree, a static table (key, depth); keys outside it have none."""
    return events.join(depths.select(F.col("key").alias(key), "depth"), key, "left")


def drift_refresher(epsilon: float, publish: Callable[[dict, list], None], most_keys: int = 20_000) -> Callable[[DataFrame, int], None]:
    """A ``foreachBatch`` function over running counts (key, n): a new tree where the old one costs too much.

    The old tree stays until its cost on the current counts is over (1 + epsilon) times the optimum. The program's
    table has n^2 cells, so a dictionary of more than ``most_keys`` keys is refused before anything is collected.
    """
    depth: dict = {}

    def refresh(batch: DataFrame, number: int) -> None:
        own = batch.select("key", "n")
        if own.limit(most_keys + 1).count() > most_keys:
            raise ValueError(f"more than {most_keys} keys; choose a smaller dictionary or the block engine")
        rows = sorted((r["key"], r["n"]) for r in own.collect())
        if not rows:
            return
        w = Weights([0, *(n for _, n in rows)], [0] * (len(rows) + 1))
        s = solve_windowed(w)
        old = sum(depth.get(k, len(depth) + 1) * n for k, n in rows)
        if not depth or old > (1 + epsilon) * s.optimum:
            keys, gaps = depths_of(lambda a, b: int(s.split[a, b]), w.n)
            assert tree_cost(w, keys, gaps) == s.optimum
            depth.clear()
            depth.update({k: int(d) for (k, _), d in zip(rows, keys[1:])})
            publish(dict(depth), rows)

    return refresh
