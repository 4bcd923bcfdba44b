"""The dynamic graph: vertices, arcs with their weights, shortest paths by diagonals, and the tree of a path.

The weight of a jump needs the shortest path of another vertex; so arcs are made from a table of solved
vertices (lo, hi, cost), and the paths are found diagonal by diagonal. For small n: the graph has n^3 / 3 arcs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..broadcasts import opened, sent
from ..functions.kernel import Weights
from ..plans.engine import opened_matrix, packed
from ..storage import written

#: Rows and columns of a tile of costs, of which a task holds three.
TILE = 512


def graph_vertices(spark: SparkSession, n: int) -> DataFrame:
    """(i, j): all vertices with 0 <= i <= j <= n, and the source (-1, -1)."""
    i = spark.range(n + 1).select(F.col("id").cast("int").alias("i"))
    own = i.select("i", F.explode(F.sequence("i", F.lit(n))).alias("j"))
    return own.unionAll(spark.sql("SELECT -1 AS i, -1 AS j"))


def arcs_into(cells: DataFrame, prefix: DataFrame, width: int | None = None) -> DataFrame:
    """(kind, a, b, i, j, weight): arcs into the vertices (of one width, if given), from shortest paths ``cells(lo, hi, cost)``.

    ``prefix`` has (idx, ps, qs, miss). Unit arcs are ``right`` and ``up`` and those of the source, jumps ``across`` and ``above``.
    """
    x, y = prefix.alias("x"), prefix.alias("y")
    own = F.col("y.ps") - F.col("x.ps") + F.col("y.qs") - F.col("x.qs") + F.col("x.miss")
    span = F.col("y.idx") - F.col("x.idx")
    to = x.join(y, span > 0 if width is None else span == width).select(
        F.col("x.idx").cast("int").alias("i"), F.col("y.idx").cast("int").alias("j"), own.alias("w"), F.col("x.miss").alias("qi"), F.col("y.miss").alias("qj")
    )
    source = prefix.select(F.lit("source").alias("kind"), F.lit(-1).alias("a"), F.lit(-1).alias("b"), F.col("idx").cast("int").alias("i"), F.col("idx").cast("int").alias("j"), F.col("miss").alias("weight"))
    right = to.select(F.lit("right").alias("kind"), F.col("i").alias("a"), (F.col("j") - 1).alias("b"), "i", "j", (F.col("qj") + F.col("w")).alias("weight"))
    up = to.select(F.lit("up").alias("kind"), (F.col("i") + 1).alias("a"), F.col("j").alias("b"), "i", "j", (F.col("qi") + F.col("w")).alias("weight"))
    # A jump along a row carries the path of the other operand below, one along a column that of the operand to the left.
    c = cells.select("lo", "hi", "cost")
    across = to.join(c, (F.col("hi") == F.col("j")) & (F.col("lo") > F.col("i") + 1) & (F.col("lo") <= F.col("j"))).select(F.lit("across").alias("kind"), F.col("i").alias("a"), (F.col("lo") - 1).alias("b"), "i", "j", (F.col("cost") + F.col("w")).alias("weight"))
    above = to.join(c, (F.col("lo") == F.col("i")) & (F.col("hi") < F.col("j") - 1) & (F.col("hi") >= F.col("i"))).select(F.lit("above").alias("kind"), (F.col("hi") + 1).alias("a"), F.col("j").alias("b"), "i", "j", (F.col("cost") + F.col("w")).alias("weight"))
    out = right.unionAll(up).unionAll(across).unionAll(above)
    return source.unionAll(out) if width is None else out


#: Arcs of the reduced graph: one for each (vertex, cut).
REDUCED = ("source", "across", "up")


def shortest_paths(prefix: DataFrame, n: int, reduced: bool = False) -> DataFrame:
    """(lo, hi, cost): lengths of shortest paths from the source, diagonal after diagonal, over all or over the reduced arcs."""
    pre = written(prefix.select("idx", "ps", "qs", "miss"), "prefix")
    cells = pre.select(F.col("idx").cast("int").alias("lo"), F.col("idx").cast("int").alias("hi"), F.col("miss").alias("cost"))
    for d in range(1, n + 1):
        arcs = arcs_into(cells, pre, d)
        arcs = arcs.where(F.col("kind").isin(*REDUCED)) if reduced else arcs
        new = arcs.join(cells, (F.col("a") == F.col("lo")) & (F.col("b") == F.col("hi"))).groupBy("i", "j").agg(F.min(F.col("cost") + F.col("weight")).alias("cost"))
        cells = cells.unionByName(new.select(F.col("i").alias("lo"), F.col("j").alias("hi"), "cost"))
        cells = written(cells, "paths")
    return cells


def dual_arcs(arcs: DataFrame, cells: DataFrame) -> DataFrame:
    """(i, j, k, along, dual): for every jump along a row the value of its path and that of the dual arc along the column."""
    start = cells.select(F.col("lo").alias("a"), F.col("hi").alias("b"), F.col("cost").alias("before"))
    value = arcs.join(start, ["a", "b"]).select("kind", "a", "b", "i", "j", (F.col("before") + F.col("weight")).alias("value"))
    row = value.where("kind = 'across'").select("i", "j", F.col("b").alias("k"), F.col("value").alias("along"))
    # The dual of a jump from (i, k) comes from (k + 1, j). No jump starts at (j, j): there the unit arc to the right stands for it.
    column = value.where("kind = 'above'").select("i", "j", (F.col("a") - 1).alias("k"), F.col("value").alias("dual"))
    column = column.unionAll(value.where("kind = 'right'").select("i", "j", F.col("b").alias("k"), F.col("value").alias("dual")))
    return row.join(column, ["i", "j", "k"], "left")


def cost_tiles(cells: DataFrame, n: int, tile: int, shift: int = 0) -> DataFrame:
    """(y, x, data): costs in square tiles, row lo - ``shift``; places outside the table repeat their row's nearest cell."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        y, x = int(pdf["y"].iloc[0]), int(pdf["x"].iloc[0])
        own = np.zeros((tile, tile), np.int64)
        own[pdf["lo"] - shift - y * tile, pdf["hi"] - x * tile] = pdf["cost"]
        lo = np.arange(y * tile, (y + 1) * tile) + shift
        near = np.clip(np.arange(tile), np.clip(lo - x * tile, 0, tile - 1)[:, None], min(n - x * tile, tile - 1))
        return pd.DataFrame({"y": [y], "x": [x], "data": [packed(np.take_along_axis(own, near, 1))]})

    place = lambda c: F.floor(c / tile).cast("int")
    own = cells.where(F.col("lo") >= shift).select("lo", "hi", "cost", place(F.col("lo") - shift).alias("y"), place(F.col("hi")).alias("x"))
    return own.groupBy("y", "x").applyInPandas(run, "y int, x int, data binary")


def dual_counts(w: Weights, left: np.ndarray, right: np.ndarray, target: np.ndarray, i0: int, k0: int, j0: int) -> tuple[int, int, int]:
    """Jumps of one tile, those whose dual differs, and those below the shortest path, from the costs of (i, k), (k + 1, j) and (i, j)."""
    checked = gaps = below = 0
    k1, j1 = min(k0 + len(right), w.n), min(j0 + right.shape[1], w.n + 1)
    k, j = np.arange(k0, k1), np.arange(j0, j1)
    right = right[: len(k), : len(j)]
    beyond = k[:, None] < j if j0 < k1 else None
    unit_k = k[(k + 1 >= j0) & (k + 1 < j1)]
    for i in range(i0, min(i0 + len(left), w.n + 1)):
        first = max(0, i + 1 - k0)
        if first >= len(k):
            break
        start, weight = left[i - i0, first : len(k), None], w.w(np.full(len(j), i), j)
        along, dual = start + (right[first:] + weight), right[first:] + (start + weight)
        # No jump starts at (j, j): there the unit arc to the right stands for the dual.
        at = unit_k[unit_k > i]
        unit = w.miss[at + 1] + w.w(np.full(len(at), i), at + 1)
        dual[at - k0 - first, at + 1 - j0] = left[i - i0, at - k0] + unit
        differ, less = along != dual, along < target[i - i0, : len(j)]
        if beyond is not None:
            own = beyond[first:]
            differ, less, checked = differ & own, less & own, checked + int(np.count_nonzero(own))
        else:
            checked += along.size
        gaps, below = gaps + int(np.count_nonzero(differ)), below + int(np.count_nonzero(less))
    return checked, gaps, below


def duality_in_tiles(cells: DataFrame, w: Weights, tile: int = TILE) -> DataFrame:
    """(checked, gaps, below) over every jump along a row, as from ``dual_arcs``, without rows of arcs.

    A task has the tiles of costs (i, k), (k + 1, j) and (i, j), makes the weights of their arcs and counts. Tiles
    travel about n / (2 tile) times each; jumps are counted where they are made.
    """
    size, weights = -(-(w.n + 1) // tile), sent(cells.sparkSession, w)
    own, lower = written(cost_tiles(cells, w.n, tile), "tiles"), written(cost_tiles(cells, w.n, tile, 1), "lower-tiles")
    left = own.select(F.col("y").alias("i"), F.col("x").alias("k"), F.col("data").alias("left"))
    right = lower.select(F.col("y").alias("k"), F.col("x").alias("j"), F.col("data").alias("right"))
    target = own.select(F.col("y").alias("i"), F.col("x").alias("j"), F.col("data").alias("target"))
    triples = left.join(right, "k").join(target, ["i", "j"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in range(batch.num_rows):
                i, k, j = (batch.column(c)[r].as_py() for c in ("i", "k", "j"))
                tables = [opened_matrix(batch.column(c)[r].as_buffer(), tile) for c in ("left", "right", "target")]
                counted = dual_counts(opened(weights), *tables, i * tile, k * tile, j * tile)
                yield pa.RecordBatch.from_arrays([pa.array([v], pa.int64()) for v in counted], names=["checked", "gaps", "below"])

    # A partition holds about two triples, which travel in one batch.
    spread = triples.select("i", "k", "j", "left", "right", "target").repartition(max(8, size * (size + 1) * (size + 2) // 12), "i", "k", "j")
    got = spread.mapInArrow(run, "checked bigint, gaps bigint, below bigint")
    return got.agg(*[F.sum(c).alias(c) for c in ("checked", "gaps", "below")])


def path_to_tree(arcs: DataFrame, cells: DataFrame, n: int) -> DataFrame:
    """(rank, lo, hi, depth): the tree that a shortest path to (0, n) spells out, level by level.

    The last arc into (i, j) with the least value tells the root of keys i+1..j; ties go to the smaller root.
    """
    start = cells.select(F.col("lo").alias("a"), F.col("hi").alias("b"), F.col("cost").alias("before"))
    cut = F.when(F.col("kind") == "up", F.col("i")).otherwise(F.col("b"))
    best = arcs.where(F.col("kind").isin("up", "across", "right")).join(start, ["a", "b"]).groupBy("i", "j").agg(F.min(F.struct((F.col("before") + F.col("weight")).alias("v"), cut.alias("k"))).alias("m"))
    best = written(best.select(F.col("i").alias("lo"), F.col("j").alias("hi"), F.col("m.k").alias("cut")), "last-arcs")
    frontier = cells.sparkSession.createDataFrame([(0, n, 1)], "lo int, hi int, depth int")
    out: DataFrame | None = None
    while True:
        nodes = written(frontier.where("lo < hi").join(best, ["lo", "hi"]), "level")
        if not nodes.take(1):
            break
        out = nodes if out is None else out.unionByName(nodes)
        children = F.explode(F.expr("array(struct(lo AS lo, cut AS hi), struct(cut + 1 AS lo, hi AS hi))"))
        frontier = nodes.select(children.alias("c"), (F.col("depth") + 1).alias("depth")).select("c.lo", "c.hi", "depth")
    empty = cells.sparkSession.createDataFrame([], "lo int, hi int, depth int, cut int")
    return (empty if out is None else out).select((F.col("cut") + 1).alias("rank"), "lo", "hi", "depth")
