"""The small-block technique: the cubic program over blocks of one small side, evaluated progressively.

Step s closes the blocks of diagonal s. Every later block whose operands of that width have just been
closed takes them in at once as partial minima, so a block of diagonal d is worked on from diagonal d / 2 on
and only the cuts inside its own rows and columns are left when it is closed. Every cut is tried, so this
is for small n; it is the related baseline of the block engine.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..broadcasts import opened, sent
from ..functions.kernel import UNSET, Weights
from ..storage import new_path

_STATE = "kind string, step int, a int, b int, cost binary, split binary"
_FAR = UNSET // 4


def middle_blocks(a: int, b: int, s: int) -> list[int]:
    """The block columns K between a and b whose wider operand, (a, K) or (K, b), has diagonal s."""
    return sorted({k for k in (a + s, b - s) if a < k < b and max(k - a, b - k) == s})


class _Target:
    """A block (a, b) with its operands by role: arrays of cost."""

    def __init__(self, w: Weights, side: int, a: int, b: int):
        size = w.n + 1
        self.w, self.side, self.a, self.b = w, side, a, b
        self.r0, self.r1, self.c0, self.c1 = a * side, min((a + 1) * side, size) - 1, b * side, min((b + 1) * side, size) - 1
        shape = (self.r1 - self.r0 + 1, self.c1 - self.c0 + 1)
        self.cost, self.split = np.full(shape, _FAR, np.int64), np.full(shape, -1, np.int32)

    def take(self, k: int, left: np.ndarray, right: np.ndarray) -> None:
        """Candidates of cut ``k``: a column cost(i, k) and a row cost(k+1, j); equal ones go to the smaller cut."""
        sums = left[:, None] + right[None, :]
        better = (sums < self.cost) | ((sums == self.cost) & (k < self.split))
        self.cost, self.split = np.where(better, sums, self.cost), np.where(better, k, self.split).astype(np.int32)

    def through(self, k: int, left: np.ndarray, right: np.ndarray, below: np.ndarray) -> None:
        """All cuts in block column ``k``: ``right`` are the rows of block (k, b), ``below`` the first row of (k+1, b)."""
        rows = np.concatenate([right[1:], below[:1]])
        for at in range(left.shape[1]):
            self.take(k * self.side + at, left[:, at], rows[at])

    def close(self, first: np.ndarray | None = None, last: np.ndarray | None = None, below: np.ndarray | None = None) -> None:
        """The cuts in the block's own rows and columns; ``first`` and ``last`` are the triangles at its ends."""
        if self.a == self.b:
            first = last = self.cost
        for d in range(max(0, self.c0 - self.r1), self.c1 - self.r0 + 1):
            for i in range(max(self.r0, self.c0 - d), min(self.r1, self.c1 - d) + 1):
                j, x, y = i + d, i - self.r0, i + d - self.c0
                if d == 0:
                    self.cost[x, y], self.split[x, y] = self.w.miss[i], i
                    continue
                own = [(int(self.cost[x, y]), int(self.split[x, y]))] if self.split[x, y] >= 0 else []
                for k in range(i, min(self.r1, j - 1) + 1):
                    right = self.cost[k + 1 - self.r0, y] if k < self.r1 else below[0, y]
                    own.append((int(first[x, k - self.r0] + right), k))
                if self.a != self.b:
                    own += [(int(self.cost[x, k - self.c0] + last[k + 1 - self.c0, y]), k) for k in range(self.c0, j)]
                value, cut = min(own)
                self.cost[x, y], self.split[x, y] = value + int(self.w.w(np.array(i), np.array(j))), cut


def _step(weights, side: int, s: int):  # noqa: ANN001, ANN202
    """Partial minima of step ``s``, or the closed block where its diagonal is reached."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        t = _Target(opened(weights), side, int(pdf["ta"].iloc[0]), int(pdf["tb"].iloc[0]))
        size = t.w.n + 1
        height = lambda x: min((x + 1) * side, size) - x * side
        got = {}
        for r in pdf.itertuples():
            if r.cost is None:
                continue
            if r.role == "partial":
                t.cost, t.split = np.frombuffer(r.cost, np.int64).reshape(t.cost.shape).copy(), np.frombuffer(r.split, np.int32).reshape(t.cost.shape).copy()
            else:
                got[r.role, int(r.middle)] = np.frombuffer(r.cost, np.int64).reshape(height(int(r.a)), height(int(r.b)))
        for k in sorted(m for role, m in got if role == "left"):
            t.through(k, got["left", k], got["right", k], got["below", k])
        done = t.b - t.a == s
        if done:
            t.close(got.get(("first", -1)), got.get(("last", -1)), got.get(("after", -1)))
        return pd.DataFrame({"kind": ["closed" if done else "partial"], "step": [s], "a": [t.a], "b": [t.b], "cost": [t.cost.tobytes()], "split": [t.split.tobytes()]})

    return run


def solve_progressive(spark: SparkSession, w: Weights, side: int = 16) -> DataFrame:
    """(lo, hi, cost, split) of every cell, by one job a diagonal of blocks of ``side`` rows."""
    blocks = -(-(w.n + 1) // side)
    weights, root, paths = sent(spark, w), new_path(spark, "progressive"), []
    for s in range(blocks):
        # What each open block reads: (role, middle block, source block).
        plan = []
        for a in range(blocks):
            for b in range(a + s, blocks):
                reads = [("partial", -1, a, b)] if s > 1 else []
                for k in middle_blocks(a, b, s - 1) if s > 1 else []:
                    reads += [("left", k, a, k), ("right", k, k, b), ("below", k, k + 1, b)]
                if b - a == s and s:
                    reads += [("first", -1, a, a), ("last", -1, b, b), ("after", -1, a + 1, b)]
                if b - a == s or any(r[0] == "left" for r in reads):
                    plan += [(a, b, *r) for r in reads] or [(a, b, "none", -1, -1, -1)]
        wanted = spark.createDataFrame(plan, "ta int, tb int, role string, middle int, a int, b int")
        if paths:
            state = spark.read.schema(_STATE).parquet(*paths)
            # The latest partial minima of a block stand for the earlier ones.
            closed, partial = state.where("kind = 'closed'"), spark.read.schema(_STATE).parquet(*paths).where("kind = 'partial'").groupBy("a", "b").agg(F.max_by(F.struct("cost", "split"), "step").alias("x"))
            rows = wanted.where("role <> 'partial'").join(closed.drop("kind", "step"), ["a", "b"], "left").unionByName(wanted.where("role = 'partial'").join(partial.select("a", "b", "x.cost", "x.split"), ["a", "b"], "left"))
        else:
            rows = wanted.selectExpr("*", "cast(null AS binary) AS cost", "cast(null AS binary) AS split")

        paths.append(f"{root}/step-{s:06d}")
        rows.groupBy("ta", "tb").applyInPandas(_step(weights, side, s), _STATE).write.parquet(paths[-1])

    def cells(frames):  # noqa: ANN001, ANN202
        for pdf in frames:
            for r in pdf.itertuples():
                t = _Target(opened(weights), side, int(r.a), int(r.b))
                split = np.frombuffer(r.split, np.int32).reshape(t.cost.shape)
                i, j = np.nonzero(split >= 0)
                yield pd.DataFrame({"lo": i + t.r0, "hi": j + t.c0, "cost": np.frombuffer(r.cost, np.int64).reshape(t.cost.shape)[i, j], "split": split[i, j]})

    return spark.read.schema(_STATE).parquet(*paths).where("kind = 'closed'").mapInPandas(cells, "lo int, hi int, cost bigint, split int")
