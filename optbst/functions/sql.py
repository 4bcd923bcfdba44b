"""Functions of the engine for SQL: scalars as SQL expressions, a table function and an aggregate."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import IntegerType, LongType, StructType

from ..plans import geometry
from .kernel import Weights, solve_windowed


_BLOCK = StructType()
for _name in ("block_id", "round", "level", "r0", "r1", "c0", "c1"):
    _BLOCK.add(_name, IntegerType())


@udtf(returnType=_BLOCK)
class PartitionBlocks:
    """Rows of a partition of the table of n keys for p workers with k fragmentations."""

    def eval(self, n: int, p: int, k: int):  # noqa: ANN201
        for b in geometry.blocks(n, p, k):
            yield tuple(vars(b).values())


@pandas_udf(LongType())
def optimal_cost(key: pd.Series, hit: pd.Series) -> int:
    """Cost of the optimal tree over a group's keys with their hits; a group is one small problem."""
    own = pd.DataFrame({"key": key, "hit": hit}).dropna().groupby("key")["hit"].sum().sort_index()
    return int(solve_windowed(Weights([0, *own], [0] * (len(own) + 1))).optimum)


def register(spark: SparkSession) -> None:
    """Make grid_side, block_side, partition_blocks and optimal_cost known to SQL of this session."""
    # Scalars are SQL expressions: Catalyst folds and inlines them.
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION grid_side(p BIGINT) RETURNS INT RETURN CAST(ceil(sqrt(2 * p)) AS INT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION block_side(n BIGINT, p BIGINT) RETURNS INT RETURN CAST(ceil((n + 1) / ceil(sqrt(2 * p))) AS INT)")
    spark.udtf.register("partition_blocks", PartitionBlocks)
    spark.udf.register("optimal_cost", optimal_cost)
