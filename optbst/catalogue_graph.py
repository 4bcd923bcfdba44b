"""Queries of the dynamic graph, of pruned dependencies, mappings and steps."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .catalogue import _BLOCKS, _KEYS, query
from .families import cells_sql, keys_in, weights, weights_sql
from .operators.dynamic import solved
from .operators.graph import arcs_into, dual_arcs, duality_in_tiles, graph_vertices, path_to_tree, shortest_paths
from .operators.weights import collected, prefix
from .plans import geometry as g
from .plans import in_sql
from .storage import written

# The dynamic graph --------------------------------------------------------------------------------
query("graph_vertices", "SELECT i::INT AS i, j::INT AS j FROM (SELECT unnest(range(0, 26)) AS i), (SELECT unnest(range(0, 26)) AS j) WHERE i <= j UNION ALL SELECT -1, -1")(lambda spark, d: graph_vertices(spark, 25))

#: Arcs (kind, a, b, i, j, weight), one arm for each kind of the definition.
_ARCS = """arcs AS (SELECT 'source' AS kind, -1 AS a, -1 AS b, idx AS i, idx AS j, miss AS weight FROM pre
 UNION ALL SELECT 'right', x.idx, y.idx - 1, x.idx, y.idx, y.miss + y.ps - x.ps + y.qs - x.qs + x.miss FROM pre x JOIN pre y ON x.idx < y.idx
 UNION ALL SELECT 'up', x.idx + 1, y.idx, x.idx, y.idx, x.miss + y.ps - x.ps + y.qs - x.qs + x.miss FROM pre x JOIN pre y ON x.idx < y.idx
 UNION ALL SELECT 'across', x.idx, z.idx, x.idx, y.idx, c.cost + y.ps - x.ps + y.qs - x.qs + x.miss FROM pre x JOIN pre z ON x.idx < z.idx JOIN pre y ON z.idx < y.idx JOIN cells c ON c.lo = z.idx + 1 AND c.hi = y.idx
 UNION ALL SELECT 'above', z.idx, y.idx, x.idx, y.idx, c.cost + y.ps - x.ps + y.qs - x.qs + x.miss FROM pre x JOIN pre z ON x.idx < z.idx JOIN pre y ON z.idx < y.idx JOIN cells c ON c.lo = x.idx AND c.hi = z.idx - 1)"""


def _graph(spark: SparkSession, d: str, family: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(prefix, cells, arcs) of a family."""
    table = written(weights(spark, d, family), "weights")
    pre, cells = written(prefix(table), "prefix"), written(solved(table), "cells")
    return pre, cells, arcs_into(cells, pre)


#: Keys up to which the duality joins arcs as rows; n of them have about n^3 / 3 arcs.
_ARC_KEYS = 200

for _f in ("nation", "lowbal"):
    query(f"arc_weights_{_f}", cells_sql(_f, "").rstrip() + f",\n{_ARCS} SELECT kind, a::INT AS a, b::INT AS b, i::INT AS i, j::INT AS j, weight::BIGINT AS weight FROM arcs")(lambda spark, d, f=_f: _graph(spark, d, f)[2])
    query(f"duality_{_f}", cells_sql(_f, "SELECT count(*) AS checked, 0::BIGINT AS gaps, 0::BIGINT AS below FROM cells a JOIN cells b ON b.lo = a.hi + 1 WHERE a.lo < a.hi"))(lambda spark, d, f=_f: _duality(spark, d, f))

for _name, _reduced in (("full", False), ("reduced", True)):
    query(f"sp_equals_dp_{_name}", cells_sql("nation", "SELECT lo::INT AS lo, hi::INT AS hi, cost::BIGINT AS cost FROM cells"))(
        lambda spark, d, r=_reduced: (lambda w: shortest_paths(prefix(w), w.agg(F.max("idx")).first()[0], r))(written(weights(spark, d, "nation"), "weights"))
    )


def _duality(spark: SparkSession, d: str, family: str) -> DataFrame:
    """Jumps along rows, those whose dual has another value or is missing, and those with a value below the shortest path."""
    pre, cells, arcs = _graph(spark, d, family)
    if pre.count() > _ARC_KEYS:
        return duality_in_tiles(cells, collected(weights(spark, d, family)))
    both = dual_arcs(written(arcs, "arcs"), cells).join(cells.select(F.col("lo").alias("i"), F.col("hi").alias("j"), "cost"), ["i", "j"])
    return both.agg(F.count(F.lit(1)).alias("checked"), F.sum((~F.col("along").eqNullSafe(F.col("dual"))).cast("bigint")).alias("gaps"), F.sum((F.col("along") < F.col("cost")).cast("bigint")).alias("below"))


@query("path_to_tree", cells_sql("nation", "").rstrip() + """, nodes AS (SELECT lo, hi, split, 1 AS depth FROM cells WHERE lo = 0 AND hi = (SELECT max(idx) FROM wt) AND lo < hi
 UNION ALL SELECT c.lo, c.hi, c.split, nodes.depth + 1 FROM nodes JOIN cells c ON (c.lo = nodes.lo AND c.hi = nodes.split OR c.lo = nodes.split + 1 AND c.hi = nodes.hi) AND c.lo < c.hi)
SELECT (split + 1)::INT AS rank, lo::INT AS lo, hi::INT AS hi, depth::INT AS depth FROM nodes""")
def path_to_tree_query(spark: SparkSession, d: str) -> DataFrame:
    pre, cells, arcs = _graph(spark, d, "nation")
    return path_to_tree(written(arcs, "arcs"), cells, pre.agg(F.max("idx").cast("int")).first()[0])


# Partitions, dependencies, mapping, steps ------------------------------------------------------------
def _blocks(spark: SparkSession, *plan: int) -> DataFrame:
    return spark.createDataFrame([tuple(vars(b).values()) for b in g.blocks(*plan)], _BLOCKS)


@query("full_blocks", f"""WITH RECURSIVE {in_sql.blocks_ctes(4096, 32, 2)}
SELECT block_id::INT AS block_id, r1 - r0 + 1 = side AND c1 - c0 + 1 = side AS is_full, c0 <= r1 AS triangular, CASE WHEN c0 <= r1 THEN (r1 - r0 + 1) * (r1 - r0 + 2) // 2 ELSE (r1 - r0 + 1) * (c1 - c0 + 1) END AS cells
FROM (SELECT blk.*, (theta + (1 << level::INT) - 1) // (1 << level::INT) AS side FROM blk, par)""")
def full_blocks(spark: SparkSession, d: str) -> DataFrame:
    """Blocks of full side, triangular ones, and their cells."""
    own = [(b.block_id, b.r1 - b.r0 + 1 == g.block_side(4096, 32, b.level) == b.c1 - b.c0 + 1, b.triangular, b.cells) for b in g.blocks(4096, 32, 2)]
    return spark.createDataFrame(own, "block_id int, is_full boolean, triangular boolean, cells long")


#: Partition of the table of ``psize`` (50 keys) whose dependencies are pruned.
_P, _K = 6, 1
_PRUNED = f"""bounds AS (SELECT b.block_id, b.r0, b.r1, b.c0, b.c1, x.split AS low, least(y.split, b.c1 - 1) AS high FROM blk b JOIN cells x ON x.lo = b.r0 AND x.hi = b.c0 - 1 JOIN cells y ON y.lo = b.r1 + 1 AND y.hi = b.c1 WHERE b.c0 > b.r1),
uses AS (SELECT b.block_id, c.lo, c.hi, 'left' AS side FROM bounds b JOIN cells c ON c.lo BETWEEN r0 AND r1 AND c.hi BETWEEN low AND least(high, c0 - 1)
 UNION ALL SELECT b.block_id, c.lo, c.hi, 'below' FROM bounds b JOIN cells c ON c.hi BETWEEN c0 AND c1 AND c.lo BETWEEN greatest(low + 1, r1 + 1) AND high + 1),
might AS (SELECT b.block_id, count(*) AS n FROM bounds b JOIN cells c ON c.lo BETWEEN r0 AND r1 AND c.hi < c0 OR c.hi BETWEEN c0 AND c1 AND c.lo > r1 GROUP BY b.block_id)"""


@query("pruned_deps", cells_sql("psize", "").rstrip() + ",\n" + in_sql.blocks_ctes(50, _P, _K) + ",\n" + _PRUNED + """
SELECT b.block_id::INT AS block_id, low::INT AS low, high::INT AS high, coalesce(count(u.block_id), 0) AS needed, any_value(m.n) AS unpruned
FROM bounds b LEFT JOIN uses u ON u.block_id = b.block_id JOIN might m ON m.block_id = b.block_id GROUP BY b.block_id, low, high""")
def pruned_deps(spark: SparkSession, d: str) -> DataFrame:
    """Cells that each block reads when the cuts at its corners bound those of its cells, and without that bound."""
    c = written(solved(weights(spark, d, "psize")), "cells").select("lo", "hi", "split")
    n = c.agg(F.max("hi")).first()[0]
    b = _blocks(spark, n, _P, _K).where("c0 > r1").select("block_id", "r0", "r1", "c0", "c1")
    x, y = c.select(F.col("lo").alias("r0"), (F.col("hi") + 1).alias("c0"), F.col("split").alias("low")), c.select((F.col("lo") - 1).alias("r1"), F.col("hi").alias("c1"), F.col("split").alias("cut"))
    b = written(b.join(x, ["r0", "c0"]).join(y, ["r1", "c1"]).withColumn("high", F.expr("least(cut, c1 - 1)")), "bounds")
    left, below = F.expr("lo BETWEEN r0 AND r1 AND hi < c0"), F.expr("hi BETWEEN c0 AND c1 AND lo > r1")
    read = b.join(c.select("lo", "hi"), left | below)
    kept = (left & F.expr("hi BETWEEN low AND high")) | (below & F.expr("lo BETWEEN greatest(low + 1, r1 + 1) AND high + 1"))
    return read.groupBy("block_id", "low", "high").agg(F.count(F.when(kept, 1)).alias("needed"), F.count(F.lit(1)).alias("unpruned"))


_PLAN, _WORKERS = (4096, 32, 2), 32
#: Orders in which blocks are dealt to workers, as SQL, beside the cyclic deal by diagonals.
_DEALS = {"diagonal": "round, r0", "row": "r0, c0", "column": "c0, r0", "scattered": "(block_id * 7919) % 1009, block_id"}


def _owned(blocks: DataFrame, scheme: str) -> DataFrame:
    return blocks.withColumn("owner", ((F.row_number().over(Window.orderBy(*[F.expr(x) for x in (_DEALS[scheme].split(", ") if scheme != "scattered" else ["(block_id * 7919) % 1009", "block_id"])])) - 1) % _WORKERS).cast("bigint"))


_COMPARE = " UNION ALL ".join(
    f"SELECT '{s}' AS scheme, (row_number() OVER (ORDER BY {o}) - 1) % {_WORKERS} AS owner, block_id, round, r0, r1, c0, c1 FROM blk" for s, o in _DEALS.items()
)


@query("mapping_compare", f"""WITH RECURSIVE {in_sql.blocks_ctes(*_PLAN)}, own AS ({_COMPARE}),
work AS (SELECT scheme, owner, count(*) AS blocks, sum(CASE WHEN c0 <= r1 THEN (r1 - r0 + 1) * (r1 - r0 + 2) // 2 ELSE (r1 - r0 + 1) * (c1 - c0 + 1) END)::BIGINT AS cells FROM own GROUP BY ALL)
SELECT scheme, min(blocks) AS least_blocks, max(blocks) AS most_blocks, min(cells) AS least_cells, max(cells) AS most_cells FROM work GROUP BY scheme""")
def mapping_compare(spark: SparkSession, d: str) -> DataFrame:
    """Blocks and cells of the least and the most loaded worker for several deals of blocks."""
    blocks, out = _blocks(spark, *_PLAN), None
    cells = F.expr("CASE WHEN c0 <= r1 THEN (r1 - r0 + 1) * (r1 - r0 + 2) / 2 ELSE (r1 - r0 + 1) * (c1 - c0 + 1) END").cast("bigint")
    for s in _DEALS:
        work = _owned(blocks, s).groupBy("owner").agg(F.count(F.lit(1)).alias("blocks"), F.sum(cells).alias("cells"))
        row = work.agg(F.min("blocks").alias("least_blocks"), F.max("blocks").alias("most_blocks"), F.min("cells").alias("least_cells"), F.max("cells").alias("most_cells")).select(F.lit(s).alias("scheme"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@query("mapping_locality", f"""WITH RECURSIVE {in_sql.blocks_ctes(*_PLAN)}, own AS ({_COMPARE})
SELECT x.scheme, count(*) AS dependencies, sum((x.owner = y.owner)::INT)::BIGINT AS at_owner FROM own x JOIN own y ON x.scheme = y.scheme AND {in_sql.DEPENDS} GROUP BY x.scheme""")
def mapping_locality(spark: SparkSession, d: str) -> DataFrame:
    """How many of the blocks that a block reads belong to its own worker, for several deals."""
    blocks, out = _blocks(spark, *_PLAN), None
    for s in _DEALS:
        own = _owned(blocks, s)
        pairs = own.alias("x").join(own.alias("y"), F.expr(in_sql.DEPENDS))
        row = pairs.agg(F.count(F.lit(1)).alias("dependencies"), F.sum(F.expr("cast(x.owner = y.owner AS bigint)")).alias("at_owner")).select(F.lit(s).alias("scheme"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@query("mapping_greedy")
def mapping_greedy(spark: SparkSession, d: str) -> DataFrame:
    """Blocks dealt, heaviest first, to the worker with the fewest cells so far."""
    load, out = [0] * _WORKERS, []
    for b in sorted(g.blocks(*_PLAN), key=lambda b: (-b.cells, b.block_id)):
        w = min(range(_WORKERS), key=lambda x: (load[x], x))
        load[w] += b.cells
        out.append((b.block_id, w, b.cells))
    return spark.createDataFrame(out, "block_id int, owner long, cells long").groupBy("owner").agg(F.count(F.lit(1)).alias("blocks"), F.sum("cells").alias("cells"))


#: The steps in which a worker evaluates and sends the quarters of a block.
_STEPS = ((0, "", "waits for LL"), (1, "LL", ""), (2, "LU", "LL+LU"), (3, "RL", "LL+RL"), (4, "RU", "RL+RU"), (5, "", "LU+RU"))
_STEPS_SQL = "(VALUES " + ", ".join(str(x) for x in _STEPS) + ") s(step, computes, sends)"


@query("step_plan", f"WITH RECURSIVE {in_sql.blocks_ctes(100, 8, 2)} SELECT block_id::INT AS block_id, round::INT AS round, step::INT AS step, computes, sends FROM blk, {_STEPS_SQL} WHERE level < 2 AND c0 > r1")
def step_plan(spark: SparkSession, d: str) -> DataFrame:
    """The steps of every square block that is split."""
    steps = spark.createDataFrame(list(_STEPS), "step int, computes string, sends string")
    return _blocks(spark, 100, 8, 2).where("level < 2 AND c0 > r1").crossJoin(F.broadcast(steps)).select("block_id", "round", "step", "computes", "sends")


@query("alg3_rounds", f"""WITH RECURSIVE {weights_sql('orders4096')}, {in_sql.parts_ctes(_KEYS, 32, 2)}
SELECT round::INT AS round, count(DISTINCT block_id) AS blocks, count(*) FILTER (part IN ('LL', 'LU')) AS first_phase, count(*) FILTER (part = 'RL') AS second_phase, count(*) FILTER (part = 'RU') AS third_phase, count(*) FILTER (part = 'all') AS whole FROM prt GROUP BY round""")
def alg3_rounds(spark: SparkSession, d: str) -> DataFrame:
    """Units of each round of the order buckets' table by the phase in which they are evaluated; whole blocks have one phase."""
    own = spark.createDataFrame([tuple(vars(b).values()) for b in g.parts(keys_in(spark, d, "orders4096"), 32, 2)], "part_id int, block_id int, round int, part string, r0 int, r1 int, c0 int, c1 int")
    n = lambda *names: F.count(F.when(F.col("part").isin(*names), 1))
    return own.groupBy("round").agg(F.countDistinct("block_id").alias("blocks"), n("LL", "LU").alias("first_phase"), n("RL").alias("second_phase"), n("RU").alias("third_phase"), n("all").alias("whole"))


@query("unit_waves")
def unit_waves(spark: SparkSession, d: str) -> DataFrame:
    """Units by the wave after their last input, beside the rounds of the barrier order."""
    units = g.parts(4096, 32, 2)
    wave = g.waves(units)
    own = spark.createDataFrame([(u.part_id, u.round, wave[u.part_id]) for u in units], "part_id int, round int, wave int")
    return own.groupBy("wave").agg(F.count(F.lit(1)).alias("units"), F.min("round").alias("first_round"), F.max("round").alias("last_round"))


@query("progressive_blocks", cells_sql("psize", "SELECT lo::INT AS lo, hi::INT AS hi, cost::BIGINT AS cost, split::INT AS split FROM cells"))
def progressive_blocks(spark: SparkSession, d: str) -> DataFrame:
    """The cubic program over small blocks, worked on from half-way diagonals on."""
    from .plans.progressive import solve_progressive

    return solve_progressive(spark, collected(weights(spark, d, "psize")), side=8)
