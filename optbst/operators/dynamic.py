"""The dynamic program and its graph as relational plans, for small n, and many small problems at once."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.kernel import Solution, Weights, banded_costs, solve_cubic, solve_windowed
from ..plans.engine import WHOLE, Solved, optimum, solve_large, tree_nodes, unpacked
from ..storage import written
from .weights import collected, ranked

CELLS = "lo int, hi int, cost bigint, split int"


def cells_frame(s: Solution) -> pd.DataFrame:
    lo, hi = np.nonzero(s.split >= 0)
    return pd.DataFrame({"lo": lo.astype(np.int32), "hi": hi.astype(np.int32), "cost": s.cost[lo, hi], "split": s.split[lo, hi]})


class Program:
    """The windowed program over one table of weights: its cells, its optimum, its tree.

    Up to ``WHOLE`` keys one task solves the table whole; more are solved once, in blocks of bounded side that lie in
    the shared folder, and the tree is walked through the blocks. The driver holds a few numbers a key.
    """

    def __init__(self, table: DataFrame) -> None:
        self.spark, self.table = table.sparkSession, written(table.select("idx", "hit", "miss"), "program")
        self.n = int(self.table.agg(F.max("idx")).first()[0] or 0)
        self.large = self.n > WHOLE
        self._solved: Solved | None = None
        self._nodes: pd.DataFrame | None = None

    def blocks(self) -> Solved:
        if self._solved is None:
            self._solved = solve_large(self.spark, collected(self.table))
        return self._solved

    def cells(self) -> DataFrame:
        """(lo, hi, cost, split) of every cell."""
        return unpacked(self.blocks().state) if self.large else solved_whole(self.table)

    def optimum(self) -> DataFrame:
        """(cost) of the optimal tree."""
        if self.large:
            return self.spark.createDataFrame([(optimum(self.blocks(), self.n),)], "cost bigint")
        return solved_whole(self.table).where((F.col("lo") == 0) & (F.col("hi") == self.n)).select("cost")

    def nodes(self) -> pd.DataFrame:
        """(lo, hi, cut, depth, side, parent) of every node, one row a key; of a large table."""
        if self._nodes is None:
            self._nodes = tree_nodes(self.spark, self.blocks(), self.n)
        return self._nodes


def solved(table: DataFrame, method: str = "windowed") -> DataFrame:
    """All cells of one problem: the windowed program for any number of keys, the cubic one in one task."""
    return solved_whole(table, method) if method == "cubic" else Program(table).cells()


def solved_whole(table: DataFrame, method: str = "windowed") -> DataFrame:
    """All cells of one problem, by a kernel in one task (n bounded by the n^2 table)."""
    solve = solve_cubic if method == "cubic" else solve_windowed

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        own = pdf.sort_values("idx")
        return cells_frame(solve(Weights(own["hit"].to_numpy(), own["miss"].to_numpy())))

    return table.select("idx", "hit", "miss").groupBy(F.lit(1).alias("one")).applyInPandas(run, CELLS)


def solved_relational(table: DataFrame, prefix: DataFrame) -> DataFrame:
    """The cubic program as a join and an aggregate for each diagonal."""
    pre = written(prefix.select(F.col("idx").cast("int").alias("idx"), "ps", "qs", "miss"), "prefix")
    n = pre.agg(F.max("idx")).first()[0]
    cells = pre.select(F.col("idx").alias("lo"), F.col("idx").alias("hi"), F.col("miss").alias("cost"), F.col("idx").alias("split"))
    for d in range(1, (n or 0) + 1):
        a, b = cells.alias("a"), cells.alias("b")
        pairs = a.join(b, (F.col("b.lo") == F.col("a.hi") + 1) & (F.col("b.hi") - F.col("a.lo") == d))
        best = pairs.groupBy(F.col("a.lo").alias("lo"), F.col("b.hi").alias("hi")).agg(F.min(F.struct((F.col("a.cost") + F.col("b.cost")).alias("c"), F.col("a.hi").alias("k"))).alias("m"))
        x, y = pre.alias("x"), pre.alias("y")
        w = best.join(F.broadcast(x), F.col("x.idx") == F.col("lo")).join(F.broadcast(y), F.col("y.idx") == F.col("hi"))
        new = w.select("lo", "hi", (F.col("m.c") + F.col("y.ps") - F.col("x.ps") + F.col("y.qs") - F.col("x.qs") + F.col("x.miss")).alias("cost"), F.col("m.k").alias("split"))
        cells = cells.unionByName(new)
        if d % 4 == 0 or d == n:
            cells = written(cells, "cells")
    return cells


#: Keys of small groups that are solved together as one band, and keys from which a group is solved alone.
BAND_KEYS, ALONE = 8192, 1024


def costs_of_groups(groups: list[np.ndarray]) -> list[int]:
    """The cost of the optimal tree over each group of hits, without misses, from one band.

    The groups lie one behind another as one long table of keys, of which the cells no wider than the largest group are
    solved: a group's tree is one of them. Groups whose hits are too large together are solved apart.
    """
    sizes = np.array([len(hits) for hits in groups])
    n, total = int(sizes.sum()), sum(int(hits.sum(dtype=object)) for hits in groups)
    if total * (n + 2) < 1 << 63:
        cost = banded_costs(Weights(np.concatenate([[0], *groups]), np.zeros(n + 1, np.int64)), int(sizes.max()))
        if cost is not None:
            return cost[sizes, np.cumsum(sizes) - sizes].tolist()
    if len(groups) > 1:
        return [cost for hits in groups for cost in costs_of_groups([hits])]
    return [solve_windowed(Weights(np.concatenate([[0], *groups]), np.zeros(n + 1, np.int64))).optimum]


def solved_groups(grouped: DataFrame, group: str) -> DataFrame:
    """(grp, n, cost): one optimal tree a group of (grp, key, hit), without misses. A group is one small problem.

    Groups are sorted inside the partitions of one shuffle and solved as they stream by, those of similar size together,
    so thousands of tiny ones cost no more than their rows. A null group is the group ``None``. Groups of more than
    ``WHOLE`` keys are solved in blocks, one after another; the driver holds their names.
    """

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        waiting: dict[int, list[tuple[str, np.ndarray]]] = {}

        def solve(own: list[tuple[str, np.ndarray]]) -> pd.DataFrame:
            return pd.DataFrame({"grp": [name for name, _ in own], "n": [len(hits) for _, hits in own], "cost": costs_of_groups([hits for _, hits in own])})

        def ended(name: str, hits: np.ndarray) -> Iterator[pd.DataFrame]:
            kind = len(hits).bit_length()
            own = waiting.setdefault(kind, [])
            own.append((name, hits))
            if len(hits) >= ALONE or len(own) << kind >= BAND_KEYS:
                yield solve(waiting.pop(kind))

        at, parts = None, []
        for pdf in frames:
            names, own = pdf["grp"].to_numpy(object), pdf["hit"].to_numpy(np.int64)
            edges = [0, *(np.flatnonzero(names[1:] != names[:-1]) + 1).tolist(), len(names)] if len(names) else [0]
            for x, z in zip(edges, edges[1:]):
                if parts and names[x] != at:
                    yield from ended(at, np.concatenate(parts))
                    parts = []
                at = names[x]
                parts.append(own[x:z])
        if parts:
            yield from ended(at, np.concatenate(parts))
        for own in waiting.values():
            yield solve(own)

    own = written(grouped.select(F.coalesce(F.col(group).cast("string"), F.lit("None")).alias("grp"), "key", "hit"), "groups")
    large = [r["grp"] for r in own.groupBy("grp").count().where(F.col("count") > WHOLE).collect()]
    rest = own.where(~F.col("grp").isin(large))
    out = rest.repartition("grp").sortWithinPartitions("grp", "key").select("grp", "hit").mapInPandas(run, "grp string, n int, cost bigint")
    zero = own.sparkSession.range(1).selectExpr("id AS idx", "0L AS hit", "0L AS miss")

    for name in large:
        keys = ranked(own.where(F.col("grp") == name).select("key", "hit"))
        program = Program(zero.unionByName(keys.select(F.col("rank").alias("idx"), "hit", F.lit(0).cast("bigint").alias("miss"))))
        out = out.unionByName(program.optimum().select(F.lit(name).alias("grp"), F.lit(program.n).alias("n"), "cost"))
    return out


def graph_edges(spark: SparkSession, n: int) -> DataFrame:
    """(kind, a, b, i, j): arcs of the dynamic graph, from (a, b) to (i, j); the source is (-1, -1)."""
    v = spark.range(n + 1).select(F.col("id").cast("int").alias("x"))
    i, j, t = v.withColumnRenamed("x", "i"), v.withColumnRenamed("x", "j"), v.withColumnRenamed("x", "t")
    cell = i.join(j, F.col("i") <= F.col("j"))
    start = i.select(F.lit("source").alias("kind"), F.lit(-1).alias("a"), F.lit(-1).alias("b"), "i", F.col("i").alias("j"))
    right = cell.where(F.col("j") < n).select(F.lit("right").alias("kind"), F.col("i").alias("a"), F.col("j").alias("b"), "i", (F.col("j") + 1).alias("j"))
    up = cell.where("i > 0").select(F.lit("up").alias("kind"), F.col("i").alias("a"), F.col("j").alias("b"), (F.col("i") - 1).alias("i"), "j")
    across = cell.where("i < j").join(t, F.col("j") < F.col("t")).select(F.lit("across").alias("kind"), F.col("i").alias("a"), F.col("j").alias("b"), "i", F.col("t").alias("j"))
    above = cell.where("i < j").join(t, F.col("t") < F.col("i")).select(F.lit("above").alias("kind"), F.col("i").alias("a"), F.col("j").alias("b"), F.col("t").alias("i"), "j")
    return start.unionAll(right).unionAll(up).unionAll(across).unionAll(above)


def reduced_edges(spark: SparkSession, n: int) -> DataFrame:
    """One arc for each (cell, cut): across for cuts beyond the first, up for the first; and the source arcs."""
    full = graph_edges(spark, n)
    return full.where("kind IN ('source', 'across', 'up')")
