"""Trees as tables: depths of keys and gaps, lookups of probes, replays of whole probe logs.

A lookup never walks a tree. The tree is flattened once to (idx, depth) of keys and of gaps; a probe that
hits joins its key, a probe that misses finds the last key below it with an as-of join by ranges.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.kernel import Weights, depths_of, heuristic_roots, solve_windowed
from ..storage import written
from .dynamic import Program

DEPTHS = "idx bigint, key_depth bigint, gap_depth bigint"


def depths_of_nodes(nodes: pd.DataFrame, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Depths of keys 0..n (0 for key 0) and gaps 0..n from the nodes (lo, hi, cut, depth) of a tree with at least one key."""
    keys, gaps = np.zeros(n + 1, np.int64), np.zeros(n + 1, np.int64)
    lo, hi, cut, depth = (nodes[c].to_numpy(np.int64) for c in ("lo", "hi", "cut", "depth"))
    keys[cut + 1] = depth
    gaps[lo[lo == cut]] = depth[lo == cut] + 1
    gaps[hi[hi == cut + 1]] = depth[hi == cut + 1] + 1
    return keys, gaps


def program_depths(program: Program) -> DataFrame:
    """``tree_depths`` of a program, which may be solved already."""
    if not program.large:
        return tree_depths_whole(program.table)
    keys, gaps = depths_of_nodes(program.nodes(), program.n)
    return program.spark.createDataFrame(pd.DataFrame({"idx": range(program.n + 1), "key_depth": keys, "gap_depth": gaps}), DEPTHS)


def tree_depths(table: DataFrame, kind: str = "optimal") -> DataFrame:
    """(idx, key_depth, gap_depth), idx 0..n, of the optimal or a heuristic tree; row 0 has key depth 0."""
    return program_depths(Program(table)) if kind == "optimal" else tree_depths_whole(table, kind)


def tree_depths_whole(table: DataFrame, kind: str = "optimal") -> DataFrame:
    """``tree_depths`` in one task; only the optimal tree needs n^2 cells there."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        own = pdf.sort_values("idx")
        w = Weights(own["hit"].to_numpy(), own["miss"].to_numpy())
        if kind == "optimal":
            split = solve_windowed(w).split
            keys, gaps = depths_of(lambda a, b: int(split[a, b]), w.n)
        else:
            keys, gaps = depths_of(heuristic_roots(w, kind), w.n)
        return pd.DataFrame({"idx": range(w.n + 1), "key_depth": keys, "gap_depth": gaps})

    return table.select("idx", "hit", "miss").groupBy(F.lit(1).alias("one")).applyInPandas(run, DEPTHS)


def as_of(probes: DataFrame, keys: DataFrame, on: str, value: str, missing: object = None) -> DataFrame:
    """``probes`` with the ``value`` of the greatest key at or below ``on``; ``missing`` below the first key.

    Keys and probes share the ranges of one sort; each range takes over the last key of the ranges before
    it, so neither side is broadcast and no task sees more than a range. Equal probe keys should be counted
    into one row first. Null probe keys get ``missing``; of equal keys the greatest value counts.
    """
    names = probes.columns
    left = probes.select(F.col(on).alias("at"), F.lit(1).alias("side"), F.struct(*names).alias("row"), F.lit(None).cast(dict(keys.dtypes)[value]).alias("v"))
    right = keys.groupBy(F.col(on).alias("at")).agg(F.max(value).alias("v")).select("at", F.lit(0).alias("side"), F.lit(None).cast(left.schema["row"].dataType).alias("row"), "v")
    both = written(left.unionByName(right).repartitionByRange("at").withColumn("part", F.spark_partition_id()), "as-of")
    own = Window.partitionBy("part").orderBy("at", "side").rowsBetween(Window.unboundedPreceding, 0)
    tops = both.where("side = 0").groupBy("part").agg(F.max_by("v", "at").alias("top"))
    # One row a range that holds keys: a window over all of them is small.
    parts = both.select("part").distinct().join(tops, "part", "left")
    before = parts.select("part", F.last("top", True).over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)).alias("before"))
    got = both.withColumn("last", F.last("v", True).over(own)).join(F.broadcast(before), "part").where("side = 1")
    v = F.when(F.col("at").isNotNull(), F.coalesce("last", "before"))
    return got.select("row.*", F.coalesce(v, F.lit(missing)).alias(value))


def lookup(counts: DataFrame, table: DataFrame, depths: DataFrame) -> DataFrame:
    """(key, n, found, depth): every counted probe key against a tree over the keys of ``table``."""
    keys = written(table.where("key IS NOT NULL").select("key", "idx"), "tree-keys")
    placed = as_of(counts, keys, "key", "idx", 0)
    hit = placed.join(keys.select("key", F.lit(True).alias("own")), "key", "left")
    both = hit.join(depths, "idx")
    found = F.coalesce("own", F.lit(False))
    return both.select("key", "n", found.alias("found"), F.when(found, F.col("key_depth")).otherwise(F.col("gap_depth")).alias("depth"))


def replay_cost(looked_up: DataFrame) -> DataFrame:
    """(probes, hits, cost): the whole log against the tree; the cost is the sum of depths."""
    return looked_up.agg(F.sum("n").alias("probes"), F.sum(F.when(F.col("found"), F.col("n")).otherwise(0)).alias("hits"), F.sum(F.col("n") * F.col("depth")).alias("cost"))


def solved_progressive(table: DataFrame, prefix: DataFrame) -> DataFrame:
    """The cubic program with partial minima from half-way diagonals: (lo, hi, cost, split).

    Step s merges into each open cell all cuts whose wider operand has width s, so a cell of width d is
    worked on from step (d - 1) / 2 on and closes at step d. For small n, as any cubic program.
    """
    pre = written(prefix.select(F.col("idx").cast("int").alias("idx"), "ps", "qs", "miss"), "prefix")
    n = pre.agg(F.max("idx")).first()[0] or 0
    cells = pre.select(F.col("idx").alias("lo"), F.col("idx").alias("hi"), F.col("miss").alias("cost"), F.col("idx").alias("split"))
    partial: DataFrame | None = None
    x, y = pre.alias("x"), pre.alias("y")
    for s in range(n):
        a, b = cells.alias("a"), cells.alias("b")
        wider = F.greatest(F.col("a.hi") - F.col("a.lo"), F.col("b.hi") - F.col("b.lo")) == s
        pairs = a.join(b, F.col("b.lo") == F.col("a.hi") + 1).where(wider)
        new = pairs.select(F.col("a.lo").alias("lo"), F.col("b.hi").alias("hi"), F.struct((F.col("a.cost") + F.col("b.cost")).alias("c"), F.col("a.hi").alias("k")).alias("m"))
        open_cells = new if partial is None else partial.unionByName(new)
        partial = written(open_cells.groupBy("lo", "hi").agg(F.min("m").alias("m")), "partial")
        closed = partial.where(F.col("hi") - F.col("lo") == s + 1).join(F.broadcast(x), F.col("x.idx") == F.col("lo")).join(F.broadcast(y), F.col("y.idx") == F.col("hi"))
        cost = F.col("m.c") + F.col("y.ps") - F.col("x.ps") + F.col("y.qs") - F.col("x.qs") + F.col("x.miss")
        cells = written(cells.unionByName(closed.select("lo", "hi", cost.alias("cost"), F.col("m.k").alias("split"))), "cells")
        partial = partial.where(F.col("hi") - F.col("lo") > s + 1)
    return cells
