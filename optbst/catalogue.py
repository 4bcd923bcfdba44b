"""All registered queries of the search-tree engine and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .families import FAMILIES, LARGE, all_counts, cells_sql, keys_in, vocabulary_weights, weights, weights_sql, words
from .functions.kernel import Weights, brute_force, build_tree, depths_of, heuristic_roots, solve_interval, solve_windowed, tree_cost
from .operators import dynamic
from .operators.dynamic import Program, graph_edges, reduced_edges, solved, solved_groups, solved_relational
from .operators.weights import collected, hit_counts, prefix
from .plans import geometry as g
from .plans import in_sql
from .plans.engine import by_units, optimum, solve_blocks, unpacked, workers
from .plans.published import runs
from .plans.simulate import PROFILES, TECHNIQUES, WorkMap, cubic_map, simulated_runs, work_map
from .sources.tables import load
from .storage import written

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):  # noqa: ANN201
    def register(f):  # noqa: ANN001, ANN202
        QUERIES[name] = f
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return register


_CELLS = "SELECT lo::INT AS lo, hi::INT AS hi, cost::BIGINT AS cost, split::INT AS split FROM cells"

# Weights ------------------------------------------------------------------------------------------
for _f in (*FAMILIES, *LARGE):
    query(f"weights_{_f}", f"WITH {weights_sql(_f)} SELECT idx, CAST(key AS VARCHAR) AS key, hit, miss FROM wt")(
        lambda spark, d, f=_f: weights(spark, d, f).withColumn("key", F.col("key").cast("string"))
    )


@query("weights_prob", f"WITH {weights_sql('benchwords')} SELECT idx, round(hit / s, 9) AS p, round(miss / s, 9) AS q FROM wt, (SELECT sum(hit + miss) AS s FROM wt)")
def weights_prob(spark: SparkSession, d: str) -> DataFrame:
    w = weights(spark, d, "benchwords")
    total = w.agg(F.sum(F.col("hit") + F.col("miss")).alias("s"))
    return w.join(F.broadcast(total)).select("idx", F.round(F.col("hit") / F.col("s"), 9).alias("p"), F.round(F.col("miss") / F.col("s"), 9).alias("q"))


for _f in ("parts", "benchwords", "vocabulary"):
    query(f"prefix_{_f}", f"WITH {weights_sql(_f)} SELECT idx, sum(hit) OVER (ORDER BY idx)::BIGINT AS ps, sum(miss) OVER (ORDER BY idx)::BIGINT AS qs FROM wt")(
        lambda spark, d, f=_f: prefix(weights(spark, d, f)).select("idx", "ps", "qs")
    )


@query("interval_weight", f"WITH {weights_sql('nation')}, pre AS (SELECT idx, sum(hit) OVER (ORDER BY idx) AS ps, sum(miss) OVER (ORDER BY idx) AS qs, miss FROM wt) SELECT x.idx AS lo, y.idx AS hi, (y.ps - x.ps + y.qs - x.qs + x.miss)::BIGINT AS w FROM pre x JOIN pre y ON x.idx <= y.idx")
def interval_weight(spark: SparkSession, d: str) -> DataFrame:
    pre = written(prefix(weights(spark, d, "nation")), "prefix")
    x, y = pre.alias("x"), pre.alias("y")
    return x.join(y, F.col("x.idx") <= F.col("y.idx")).select(F.col("x.idx").alias("lo"), F.col("y.idx").alias("hi"), (F.col("y.ps") - F.col("x.ps") + F.col("y.qs") - F.col("x.qs") + F.col("x.miss")).alias("w"))


query("hits_quantity", "SELECT l_suppkey AS key, sum(l_quantity)::BIGINT AS n FROM lineitem GROUP BY l_suppkey")(lambda spark, d: hit_counts(load(spark, d, "lineitem"), F.col("l_suppkey"), F.col("l_quantity").cast("bigint")))
query("json_keys", "SELECT (props->>'$.k')::INT AS key, count(*) AS n FROM events GROUP BY 1")(lambda spark, d: hit_counts(load(spark, d, "events"), F.get_json_object("props", "$.k").cast("int")))

# Sequential solvers -------------------------------------------------------------------------------
for _f in FAMILIES:
    query(f"windowed_{_f}", cells_sql(_f, _CELLS))(lambda spark, d, f=_f: solved(weights(spark, d, f)))
for _f in ("nation", "psize", "hours"):
    query(f"cubic_{_f}", cells_sql(_f, _CELLS))(lambda spark, d, f=_f: solved(weights(spark, d, f), "cubic"))


@query("relational_nation", cells_sql("nation", _CELLS))
def relational_nation(spark: SparkSession, d: str) -> DataFrame:
    w = written(weights(spark, d, "nation"), "weights")
    return solved_relational(w, prefix(w))


@query("five_trees", "SELECT * FROM (VALUES (1::BIGINT, 20::BIGINT), (1, 26), (2, 21), (3, 18), (3, 16)) v(root, cost)")
def five_trees(spark: SparkSession, d: str) -> DataFrame:
    return spark.createDataFrame(brute_force(Weights(np.array([0, 3, 1, 7]), np.zeros(4, int))), "root bigint, cost bigint")


_OPTIMA = "\nUNION ALL ".join(
    "(SELECT * FROM ({}))".format(cells_sql(f, f"SELECT '{f}' AS family, (SELECT max(idx) FROM wt)::BIGINT AS n, (SELECT sum(hit + miss) FROM wt)::BIGINT AS total_weight, cost::BIGINT AS cost FROM cells WHERE lo = 0 AND hi = (SELECT max(idx) FROM wt)")) for f in FAMILIES
)


def _weights_of(pdf: pd.DataFrame) -> Weights:
    """The vectors of one family from its counted keys; see all_counts."""
    own = pdf.sort_values("key", kind="stable")
    rank = np.cumsum(own["own"].to_numpy(bool))
    n, mine, count = int(rank[-1]) if len(rank) else 0, own["own"].to_numpy(bool), own["n"].to_numpy(np.int64)
    return Weights(np.concatenate([[0], count[mine]]), np.bincount(rank[~mine], count[~mine], n + 1).astype(np.int64))


def by_families(spark: SparkSession, d: str, families: tuple[str, ...], rows_of: Callable[[str, Weights, int], list[tuple]], schema: str) -> DataFrame:
    """``rows_of`` (family, weights, optimum) of every family: one plan counts the keys of all and solves each small one
    in a task; a family of many keys is a program in blocks, and one task gets its vectors and the optimum."""
    every = written(all_counts(spark, d, families), "family-counts")
    sizes = {r["family"]: r["n"] for r in every.groupBy("family").agg(F.count(F.when(F.col("own"), 1)).alias("n")).collect()}
    names = [c.split()[0] for c in schema.split(", ")]

    def small(pdf: pd.DataFrame) -> pd.DataFrame:
        w = _weights_of(pdf)
        return pd.DataFrame(rows_of(pdf["family"].iloc[0], w, solve_windowed(w).optimum), columns=names)

    large = [f for f, n in sizes.items() if n > dynamic.WHOLE]
    out = every.where(~F.col("family").isin(large)).groupBy("family").applyInPandas(small, schema)
    for f in large:
        program = Program(weights(spark, d, f))

        def one(pdf: pd.DataFrame, f: str = f, best: int = optimum(program.blocks(), program.n)) -> pd.DataFrame:
            own = pdf.sort_values("idx")
            return pd.DataFrame(rows_of(f, Weights(own["hit"].to_numpy(), own["miss"].to_numpy()), best), columns=names)

        out = out.unionByName(program.table.repartition(1).mapInPandas(_whole(one), schema))
    return out


def _whole(run: Callable[[pd.DataFrame], pd.DataFrame]):  # noqa: ANN202
    """``run`` on all rows of a partition together."""
    return lambda frames: iter([run(pd.concat(frames))])


@query("optimal_cost_all", _OPTIMA)
def optimal_cost_all(spark: SparkSession, d: str) -> DataFrame:
    """The optimum of every family."""
    return by_families(spark, d, FAMILIES, lambda f, w, best: [(f, w.n, int(w.hit.sum() + w.miss.sum()), best)], "family string, n bigint, total_weight bigint, cost bigint")


#: The dynamic program for many groups at once: from ``own`` (grp, key, hit) to (grp, n, cost), without misses.
_GROUPED = """wt AS (SELECT grp, row_number() OVER (PARTITION BY grp ORDER BY key) AS idx, hit FROM own UNION ALL SELECT DISTINCT grp, 0, 0 FROM own),
pre AS (SELECT grp, idx, sum(hit) OVER (PARTITION BY grp ORDER BY idx) AS ps, max(idx) OVER (PARTITION BY grp) AS n FROM wt),
t AS (SELECT 0 AS step, grp, idx AS lo, idx AS hi, 0::HUGEINT AS cost FROM pre
 UNION ALL
 SELECT * FROM (
  WITH s AS (SELECT * FROM t WHERE step < (SELECT max(n) FROM pre)),
  best AS (SELECT a.step + 1 AS step, a.grp, a.lo, b.hi, min(a.cost + b.cost) AS m FROM s a JOIN s b ON a.grp = b.grp AND b.lo = a.hi + 1 WHERE b.hi - a.lo = a.step + 1 GROUP BY ALL)
  SELECT step + 1 AS step, grp, lo, hi, cost FROM s
  UNION ALL
  SELECT step, best.grp, lo, hi, m + y.ps - x.ps FROM best JOIN pre x ON x.grp = best.grp AND x.idx = lo JOIN pre y ON y.grp = best.grp AND y.idx = hi))
SELECT t.grp, n::INT AS n, cost::BIGINT AS cost FROM t JOIN (SELECT DISTINCT grp, n FROM pre) g ON g.grp = t.grp AND lo = 0 AND hi = n WHERE step = (SELECT max(n) FROM pre)"""
_NATION_CUSTS = "SELECT n_regionkey::VARCHAR AS grp, n_nationkey AS key, count(*) AS hit FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1, 2"


@query("grouped_nation_custs", f"WITH RECURSIVE own AS ({_NATION_CUSTS}),\n{_GROUPED}")
def grouped_nation_custs(spark: SparkSession, d: str) -> DataFrame:
    c = hit_counts(load(spark, d, "customer"), F.col("c_nationkey")).withColumnRenamed("key", "n_nationkey")
    own = load(spark, d, "nation").join(c, "n_nationkey").select(F.col("n_regionkey").alias("grp"), F.col("n_nationkey").alias("key"), F.col("n").alias("hit"))
    return solved_groups(own, "grp")


@query("grouped_daily_events", f"WITH RECURSIVE own AS (SELECT strftime(ts, '%Y-%m-%d') AS grp, event_type AS key, count(*) AS hit FROM events GROUP BY 1, 2),\n{_GROUPED}")
def grouped_daily_events(spark: SparkSession, d: str) -> DataFrame:
    own = load(spark, d, "events").groupBy(F.date_format("ts", "yyyy-MM-dd").alias("grp"), F.col("event_type").alias("key")).agg(F.count(F.lit(1)).alias("hit"))
    return solved_groups(own, "grp")


@query("monotonicity", cells_sql("lowbal", "SELECT count(*) AS checked, coalesce(sum((NOT (a.split <= c.split AND c.split <= b.split))::INT), 0)::BIGINT AS violations FROM cells c JOIN cells a ON a.lo = c.lo AND a.hi = c.hi - 1 JOIN cells b ON b.lo = c.lo + 1 AND b.hi = c.hi WHERE c.hi - c.lo >= 2"))
def monotonicity(spark: SparkSession, d: str) -> DataFrame:
    program = Program(weights(spark, d, "lowbal"))
    if program.large:
        def measure(lo: np.ndarray, hi: np.ndarray, cut: np.ndarray, left: np.ndarray, below: np.ndarray) -> pd.DataFrame:
            wide = hi - lo >= 2
            return pd.DataFrame({"checked": [int(wide.sum())], "violations": [int((wide & ~((left <= cut) & (cut <= below))).sum())]})

        return by_units(spark, program.blocks(), measure, "checked bigint, violations bigint").agg(F.sum("checked").alias("checked"), F.sum("violations").alias("violations"))
    c = written(program.cells(), "cells")
    row, column = Window.partitionBy("lo").orderBy("hi"), Window.partitionBy("hi").orderBy("lo")
    own = c.select("lo", "hi", "split", F.lag("split").over(row).alias("a"), F.lead("split").over(column).alias("b")).where("hi - lo >= 2")
    return own.agg(F.count(F.lit(1)).alias("checked"), F.coalesce(F.sum((~((F.col("a") <= F.col("split")) & (F.col("split") <= F.col("b")))).cast("bigint")), F.lit(0)).alias("violations"))


@query("candidate_profile", cells_sql("users", "SELECT (c.hi - c.lo)::INT AS width, count(*) AS cells, min(least(b.split, c.hi - 1) - a.split + 1)::BIGINT AS min_c, max(least(b.split, c.hi - 1) - a.split + 1)::BIGINT AS max_c, sum(least(b.split, c.hi - 1) - a.split + 1)::BIGINT AS sum_c FROM cells c JOIN cells a ON a.lo = c.lo AND a.hi = c.hi - 1 JOIN cells b ON b.lo = c.lo + 1 AND b.hi = c.hi GROUP BY 1"))
def candidate_profile(spark: SparkSession, d: str) -> DataFrame:
    program = Program(weights(spark, d, "users"))
    if program.large:
        def measure(lo: np.ndarray, hi: np.ndarray, cut: np.ndarray, left: np.ndarray, below: np.ndarray) -> pd.DataFrame:
            own = pd.DataFrame({"width": (hi - lo).astype(np.int32), "c": np.minimum(below, hi - 1).astype(np.int64) - left + 1})
            return own.groupby("width")["c"].agg(cells="count", min_c="min", max_c="max", sum_c="sum").reset_index()

        units = by_units(spark, program.blocks(), measure, "width int, cells bigint, min_c bigint, max_c bigint, sum_c bigint")
        return units.groupBy("width").agg(F.sum("cells").alias("cells"), F.min("min_c").alias("min_c"), F.max("max_c").alias("max_c"), F.sum("sum_c").alias("sum_c"))
    c = written(program.cells(), "cells")
    row, column = Window.partitionBy("lo").orderBy("hi"), Window.partitionBy("hi").orderBy("lo")
    own = c.select("lo", "hi", F.lag("split").over(row).alias("a"), F.lead("split").over(column).alias("b")).where("hi > lo")
    n = F.least("b", F.col("hi") - 1) - F.col("a") + 1
    return own.select((F.col("hi") - F.col("lo")).alias("width"), n.cast("bigint").alias("c")).groupBy("width").agg(F.count(F.lit(1)).alias("cells"), F.min("c").alias("min_c"), F.max("c").alias("max_c"), F.sum("c").alias("sum_c"))


# Trees --------------------------------------------------------------------------------------------
_TREE = """, tree AS (SELECT lo, hi, split, 1 AS depth, 0::BIGINT AS parent_rank, 'root' AS side FROM cells WHERE lo = 0 AND hi = (SELECT max(idx) FROM wt) AND lo < hi
 UNION ALL SELECT c.lo, c.hi, c.split, tree.depth + 1, tree.split + 1, CASE WHEN c.lo = tree.lo THEN 'left' ELSE 'right' END
 FROM tree JOIN cells c ON (c.lo = tree.lo AND c.hi = tree.split OR c.lo = tree.split + 1 AND c.hi = tree.hi) AND c.lo < c.hi)
SELECT split + 1 AS rank, CAST(k.key AS VARCHAR) AS key, depth, parent_rank, side FROM tree JOIN keys k ON k.idx = split + 1"""


def tree_of(spark: SparkSession, d: str, family: str) -> DataFrame:
    """(rank, key, depth, parent_rank, side) of the optimal tree."""
    return tree_over(written(weights(spark, d, family), "weights"))


def tree_over(table: DataFrame) -> DataFrame:
    """``tree_of`` a written table of weights."""
    spark, program = table.sparkSession, Program(table)
    if program.large:
        nodes = program.nodes()
        own = spark.createDataFrame(pd.DataFrame({"rank": nodes["cut"] + 1, "depth": nodes["depth"], "parent_rank": nodes["parent"], "side": nodes["side"]}), "rank bigint, depth int, parent_rank bigint, side string")
        return own.join(table.select(F.col("idx").alias("rank"), F.col("key").cast("string").alias("key")), "rank").select("rank", "key", "depth", "parent_rank", "side")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        own = pdf.sort_values("idx").reset_index(drop=True)
        rows = build_tree(solve_windowed(Weights(own["hit"].to_numpy(), own["miss"].to_numpy())).split)
        return pd.DataFrame([(r, str(own["key"][r]), depth, parent, side) for r, _, _, depth, side, parent in rows], columns=["rank", "key", "depth", "parent_rank", "side"])

    return table.withColumn("key", F.col("key").cast("string")).groupBy(F.lit(1).alias("one")).applyInPandas(run, "rank bigint, key string, depth int, parent_rank bigint, side string")


for _f in ("nation", "users", "lowbal", "pnames"):
    query(f"tree_{_f}", cells_sql(_f, "").rstrip() + _TREE)(lambda spark, d, f=_f: tree_of(spark, d, f))


@query("depth_hist", cells_sql("users", "").rstrip() + _TREE.replace("SELECT split + 1 AS rank, CAST(k.key AS VARCHAR) AS key, depth, parent_rank, side FROM tree JOIN keys k ON k.idx = split + 1", "SELECT depth, count(*) AS nodes, sum(k.n)::BIGINT AS weight FROM tree JOIN keys k ON k.idx = split + 1 GROUP BY depth"))
def depth_hist(spark: SparkSession, d: str) -> DataFrame:
    table = written(weights(spark, d, "users"), "weights")
    hits = table.select(F.col("idx").alias("rank"), "hit")
    return tree_over(table).join(hits, "rank").groupBy("depth").agg(F.count(F.lit(1)).alias("nodes"), F.sum("hit").alias("weight"))


#: Depths of a heuristic's tree for one family, from ``pick`` (lo, hi, k): the root's cut of every interval.
_PICKS = {
    "balanced": "SELECT x.idx AS lo, y.idx AS hi, (x.idx + y.idx - 1) // 2 AS k FROM wt x JOIN wt y ON x.idx < y.idx",
    "chain_left": "SELECT x.idx AS lo, y.idx AS hi, x.idx AS k FROM wt x JOIN wt y ON x.idx < y.idx",
    "chain_right": "SELECT x.idx AS lo, y.idx AS hi, y.idx - 1 AS k FROM wt x JOIN wt y ON x.idx < y.idx",
    "heaviest": "SELECT x.idx AS lo, y.idx AS hi, min((-z.hit, z.idx - 1))[2] AS k FROM wt x JOIN wt y ON x.idx < y.idx JOIN wt z ON z.idx > x.idx AND z.idx <= y.idx GROUP BY 1, 2",
    "weight_balanced": """SELECT x.idx AS lo, y.idx AS hi, min((abs((z.ps - x.ps + z.qs - x.qs + x.miss) - (y.ps - v.ps + y.qs - v.qs + v.miss)), z.idx))[2] AS k
 FROM pre x JOIN pre y ON x.idx < y.idx JOIN pre z ON z.idx >= x.idx AND z.idx < y.idx JOIN pre v ON v.idx = z.idx + 1 GROUP BY 1, 2""",
}


def _heuristic_sql(family: str, kind: str) -> str:
    return f"""(SELECT * FROM (WITH RECURSIVE {weights_sql(family)},
pre AS (SELECT idx, sum(hit) OVER (ORDER BY idx) AS ps, sum(miss) OVER (ORDER BY idx) AS qs, miss FROM wt),
pick AS ({_PICKS[kind]}),
nodes AS (SELECT 0::BIGINT AS lo, max(idx)::BIGINT AS hi, 1::BIGINT AS depth FROM wt
 UNION ALL SELECT CASE WHEN c = 0 THEN nodes.lo ELSE k + 1 END, CASE WHEN c = 0 THEN k ELSE nodes.hi END, depth + 1 FROM nodes JOIN pick ON pick.lo = nodes.lo AND pick.hi = nodes.hi, (VALUES (0), (1)) v(c))
SELECT '{family}' AS family, '{kind}' AS technique, sum(depth * CASE WHEN nodes.lo = nodes.hi THEN g.miss ELSE r.hit END)::BIGINT AS cost
FROM nodes LEFT JOIN pick ON pick.lo = nodes.lo AND pick.hi = nodes.hi LEFT JOIN wt g ON g.idx = nodes.lo LEFT JOIN wt r ON r.idx = k + 1))"""


_HEURISTICS = "\nUNION ALL ".join(_heuristic_sql(f, kind) for f in FAMILIES for kind in _PICKS)


@query("heuristic_costs", f"SELECT h.family, h.technique, h.cost, o.cost AS optimum, round(h.cost / greatest(1, o.cost), 6) AS ratio FROM ({_HEURISTICS}) h JOIN ({_OPTIMA}) o USING (family)")
def heuristic_costs(spark: SparkSession, d: str) -> DataFrame:
    """Costs of the baselines and their ratio to the optimum."""

    def rows_of(family: str, w: Weights, best: int) -> list[tuple]:
        costs = [(kind, tree_cost(w, *depths_of(heuristic_roots(w, kind), w.n))) for kind in _PICKS]
        return [(family, kind, cost, best, round(cost / max(1, best), 6)) for kind, cost in costs]

    return by_families(spark, d, FAMILIES, rows_of, "family string, technique string, cost bigint, optimum bigint, ratio double")


# Graph --------------------------------------------------------------------------------------------
@query("graph_edges", "SELECT n, kind, CASE kind WHEN 'source' THEN n + 1 WHEN 'right' THEN n * (n + 1) // 2 WHEN 'up' THEN n * (n + 1) // 2 ELSE (n + 1) * n * (n - 1) // 6 END AS arcs FROM (VALUES (3::BIGINT), (5), (25)) s(n), (VALUES ('source'), ('right'), ('up'), ('across'), ('above')) k(kind)")
def graph_edge_counts(spark: SparkSession, d: str) -> DataFrame:
    parts = [graph_edges(spark, n).groupBy("kind").agg(F.count(F.lit(1)).alias("arcs")).select(F.lit(n).cast("bigint").alias("n"), "kind", "arcs") for n in (3, 5, 25)]
    return parts[0].unionAll(parts[1]).unionAll(parts[2])


@query("reduced_edges", "SELECT n, n * (n + 1) * (n + 2) // 6 + n + 1 AS arcs FROM (VALUES (3::BIGINT), (5), (25)) s(n)")
def reduced_edge_counts(spark: SparkSession, d: str) -> DataFrame:
    parts = [reduced_edges(spark, n).agg(F.count(F.lit(1)).alias("arcs")).select(F.lit(n).cast("bigint").alias("n"), "arcs") for n in (3, 5, 25)]
    return parts[0].unionAll(parts[1]).unionAll(parts[2])


# Geometry, mapping, schedule ----------------------------------------------------------------------
_GRID = [(n, p, k) for n in range(4096, 40961, 4096) for p in (32, 64, 96, 128) for k in range(6)]
_GRID_SQL = "SELECT n, p, k, ceil(sqrt(2 * p))::BIGINT AS f FROM (SELECT unnest(range(4096, 40961, 4096)) AS n), (SELECT unnest([32, 64, 96, 128])::BIGINT AS p), (SELECT unnest(range(0, 6)) AS k)"


@query("geometry_params", f"SELECT n, p, k, f, ceil((n + 1) / f)::BIGINT AS theta, ceil(ceil((n + 1) / f) / (1 << k::INT))::BIGINT AS side, f + k * (ceil(f / 2)::BIGINT + 1) AS rounds FROM ({_GRID_SQL})")
def geometry_params(spark: SparkSession, d: str) -> DataFrame:
    return spark.createDataFrame([(n, p, k, g.grid_side(p), g.block_side(n, p), g.block_side(n, p, k), g.num_rounds(p, k)) for n, p, k in _GRID], "n bigint, p bigint, k bigint, f bigint, theta bigint, side bigint, rounds bigint")


#: Blocks and sub-blocks of many configurations, counted from the intervals' starts and ends; see plans/in_sql.
_COUNTS_SQL = f"""WITH RECURSIVE grid AS (SELECT *, (f + 1) // 2 AS h, (n + f) // f AS theta FROM ({_GRID_SQL})),
cuts AS (SELECT n, p, k, f, h, theta, 0 AS l, i, least(i * theta, n + 1) AS s, least((i + 1) * theta, n + 1) AS e FROM grid, (SELECT unnest(range(0, 32)) AS i) WHERE i < f
 UNION ALL SELECT n, p, k, f, h, theta, l + 1, 2 * i + c, CASE WHEN c = 0 THEN s ELSE least(s + half, e) END, CASE WHEN c = 0 THEN least(s + half, e) ELSE e END
 FROM (SELECT cuts.*, c, (theta + (1 << (l + 1)::INT) - 1) // (1 << (l + 1)::INT) AS half FROM cuts, (VALUES (0), (1)) v(c) WHERE l <= k)),
kids AS (SELECT n, p, k, l - 1 AS l, i >> 1 AS i, count(*) AS kids FROM cuts WHERE e > s GROUP BY ALL),
own AS (SELECT cuts.*, kids FROM cuts JOIN kids USING (n, p, k, l, i) WHERE e > s),
blk AS (SELECT x.n, x.p, x.k, x.l, x.i AS a, y.i AS b, x.kids * y.kids - CASE WHEN x.i = y.i AND x.kids = 2 THEN 1 ELSE 0 END AS quarters
 FROM own x JOIN own y ON x.n = y.n AND x.p = y.p AND x.k = y.k AND x.l = y.l AND x.i <= y.i
 WHERE x.l <= x.k AND (x.l = 0 OR (y.i >> 1) - (x.i >> 1) >= x.f * (1 << greatest(x.l - 1, 0)::INT) - x.h) AND (x.l = x.k OR y.i - x.i < x.f * (1 << x.l::INT) - x.h))
SELECT n, p, k, count(*) AS blocks, sum(CASE WHEN l < k THEN quarters ELSE 1 END)::BIGINT AS subblocks FROM blk GROUP BY n, p, k"""


@query("geometry_counts", _COUNTS_SQL)
def geometry_counts(spark: SparkSession, d: str) -> DataFrame:
    """Blocks and sub-blocks of every published configuration."""
    grid = spark.createDataFrame(_GRID, "n bigint, p bigint, k bigint").repartition(16, "n", "p", "k")

    def run(frames):  # noqa: ANN001, ANN202
        for pdf in frames:
            yield pd.DataFrame([(n, p, k, len(g.blocks(n, p, k)), len(g.parts(n, p, k))) for n, p, k in pdf.itertuples(index=False)], columns=["n", "p", "k", "blocks", "subblocks"])

    return grid.mapInPandas(run, "n bigint, p bigint, k bigint, blocks bigint, subblocks bigint")


@query("rounds_table", "SELECT p, k, f, f + k * (h + 1) AS rounds, 3 + 4 * (f // 2 - 1) + 4 * (k - 1) * (h + 1) + f + f % 2 AS comm_bound FROM (SELECT p, k, ceil(sqrt(2 * p))::BIGINT AS f, ceil(ceil(sqrt(2 * p)) / 2)::BIGINT AS h FROM (SELECT unnest([32, 64, 96, 128])::BIGINT AS p), (SELECT unnest(range(1, 6)) AS k))")
def rounds_table(spark: SparkSession, d: str) -> DataFrame:
    return spark.createDataFrame([(p, k, g.grid_side(p), g.num_rounds(p, k), g.comm_rounds(p, k)) for p in (32, 64, 96, 128) for k in range(1, 6)], "p bigint, k bigint, f bigint, rounds bigint, comm_bound bigint")


_BLOCKS = "block_id int, round int, level int, r0 int, r1 int, c0 int, c1 int"
#: A scalar subquery beside ``weights_sql``: the number of keys.
_KEYS = "(SELECT max(idx) FROM wt)"


def blocks_of(spark: SparkSession, d: str, family: str, p: int, k: int) -> DataFrame:
    """The partition of a dictionary's table, and the hits of all keys between a block's first row and last column."""
    pre = written(prefix(weights(spark, d, family)), "prefix").select("idx", "ps")
    n = pre.agg(F.max("idx")).first()[0]
    own = spark.createDataFrame([tuple(vars(b).values()) for b in g.blocks(n, p, k)], _BLOCKS)
    first, last = pre.select(F.col("idx").alias("r0"), F.col("ps").alias("before")), pre.select(F.col("idx").alias("c1"), F.col("ps").alias("up_to"))
    return own.join(first, "r0").join(last, "c1").select(*own.columns, (F.col("up_to") - F.col("before")).alias("hits"))


def _blocks_of_sql(family: str, p: int, k: int) -> str:
    return f"""WITH RECURSIVE {weights_sql(family)}, {in_sql.blocks_ctes(_KEYS, p, k)},
pre AS (SELECT idx, sum(hit) OVER (ORDER BY idx)::BIGINT AS ps FROM wt)
SELECT block_id::INT AS block_id, round::INT AS round, level::INT AS level, r0::INT AS r0, r1::INT AS r1, c0::INT AS c0, c1::INT AS c1, y.ps - x.ps AS hits FROM blk JOIN pre x ON x.idx = r0 JOIN pre y ON y.idx = c1"""


#: Dictionaries with 31, 150, 4096 and 40960 keys where the table has them all.
_CUT_OF = {31: "days", 150: "flags", 4096: "orders4096", 40960: "orders40960"}
for _a in ((31, 4, 1), (31, 4, 2), (31, 8, 1), (31, 8, 2), (150, 8, 0), (150, 8, 2), (4096, 32, 3), (40960, 128, 2)):
    _tag, _of = "n{}_p{}_k{}".format(*_a), (_CUT_OF[_a[0]], *_a[1:])
    query(f"blocks_{_tag}", _blocks_of_sql(*_of))(lambda spark, d, a=_of: blocks_of(spark, d, *a))
    query(f"subblocks_{_tag}", in_sql.parts_sql(*_a))(
        lambda spark, d, a=_a: spark.createDataFrame([tuple(vars(b).values()) for b in g.parts(*a)], "part_id int, block_id int, round int, part string, r0 int, r1 int, c0 int, c1 int")
    )


@query("block_deps", f"WITH RECURSIVE {weights_sql('days')}, {in_sql.blocks_ctes(_KEYS, 6, 1)} SELECT x.block_id::INT AS block_id, y.block_id::INT AS dep_block FROM blk x JOIN blk y ON {in_sql.DEPENDS}")
def block_deps(spark: SparkSession, d: str) -> DataFrame:
    """(block_id, dep_block): all blocks of the days' table that a block may read, before pruning."""
    plan = g.blocks(keys_in(spark, d, "days"), 6, 1)
    return spark.createDataFrame([(x.block_id, y.block_id) for x in plan for y in plan if g.depends(x, y)], "block_id int, dep_block int")


@query("block_load", f"WITH RECURSIVE {weights_sql('days')}, {in_sql.blocks_ctes(_KEYS, 6, 1)}, {in_sql.owners_cte(6)} SELECT owner::INT AS owner, count(*) AS blocks FROM own GROUP BY owner")
def block_load(spark: SparkSession, d: str) -> DataFrame:
    own = g.owners(g.blocks(keys_in(spark, d, "days"), 6, 1), 6)
    return spark.createDataFrame(list(own.items()), "block_id int, owner int").groupBy("owner").agg(F.count(F.lit(1)).alias("blocks"))


for _a in ((31, 6, 1), (100, 8, 2), (4096, 32, 2)):
    query("step_messages_n{}_p{}_k{}".format(*_a), in_sql.messages_sql(*_a))(lambda spark, d, a=_a: spark.createDataFrame(g.step_messages(*a), "block_id int, step int, parts string, dst_owner int"))
    query("message_counts_n{}_p{}_k{}".format(*_a), in_sql.messages_sql(*_a, "SELECT step::INT AS step, parts, count(*) AS messages FROM (SELECT DISTINCT block_id, step, parts, dst_owner FROM sent) GROUP BY step, parts"))(
        lambda spark, d, a=_a: spark.createDataFrame(g.step_messages(*a), "block_id int, step int, parts string, dst_owner int").groupBy("step", "parts").agg(F.count(F.lit(1)).alias("messages"))
    )


# Parallel solvers ---------------------------------------------------------------------------------
_SOLVERS = (
    ("regular", "regular", 6, 0, "barrier"), ("irregular_k1", "irregular", 6, 1, "barrier"), ("irregular_k2", "irregular", 6, 2, "barrier"), ("four_split_k0", "four_split", 6, 0, "barrier"),
    ("four_split_k1", "four_split", 6, 1, "barrier"), ("four_split_k2", "four_split", 4, 2, "dataflow"), ("four_split_k3", "four_split", 4, 3, "dataflow"), ("small_block", "small_block", 4, 1, "dataflow"),
)
for _name, _t, _p, _k, _m in _SOLVERS:
    query(f"solve_{_name}", cells_sql("psize", _CELLS))(lambda spark, d, a=(_p, _k, _t, _m): unpacked(solve_blocks(spark, collected(weights(spark, d, "psize")), *a)))
query("solve_users", cells_sql("users", _CELLS))(lambda spark, d: solve_users(spark, d))


def solve_users(spark: SparkSession, d: str) -> DataFrame:
    """By eight workers; by more where their blocks would pass the side that a task holds."""
    w = collected(weights(spark, d, "users"))
    return unpacked(solve_blocks(spark, w, max(8, workers(w.n)), 1, "four_split", "dataflow"))



@query("solver_diff", "SELECT name AS solver, 0::BIGINT AS only_here, 0::BIGINT AS only_sequential FROM (VALUES ('irregular_k1'), ('four_split_k1'), ('small_block')) v(name)")
def solver_diff(spark: SparkSession, d: str) -> DataFrame:
    """Cells (with cost and cut) that one solver has and the sequential one has not, by a full outer join, and the reverse."""
    w = collected(weights(spark, d, "lowbal"))
    one = written(solved(weights(spark, d, "lowbal")), "sequential").withColumn("a", F.lit(1))
    out: DataFrame | None = None
    for name, t, k in (("irregular_k1", "irregular", 1), ("four_split_k1", "four_split", 1), ("small_block", "small_block", 1)):
        other = unpacked(solve_blocks(spark, w, max(4, workers(w.n)), k, t)).withColumn("b", F.lit(1))
        both = one.join(other, ["lo", "hi", "cost", "split"], "full_outer")
        row = both.agg(F.count(F.when(F.col("a").isNull(), 1)).alias("only_here"), F.count(F.when(F.col("b").isNull(), 1)).alias("only_sequential")).select(F.lit(name).alias("solver"), "only_here", "only_sequential")
        out = row if out is None else out.unionByName(row)
    return out


_CHAIN = """WITH RECURSIVE dim AS (SELECT row_number() OVER (ORDER BY p_size) - 1 AS i, p_size::HUGEINT AS d FROM (SELECT DISTINCT p_size FROM part)),
t AS (SELECT 0 AS step, i AS lo, i AS hi, 0::HUGEINT AS cost, i AS split FROM dim WHERE i < (SELECT max(i) FROM dim)
 UNION ALL
 SELECT * FROM (
  WITH s AS (SELECT * FROM t WHERE step < (SELECT max(i) - 1 FROM dim)),
  best AS (SELECT a.step + 1 AS step, a.lo, b.hi, min((a.cost + b.cost + x.d * y.d * z.d) * 1048576 + a.hi) AS m FROM s a JOIN s b ON b.lo = a.hi + 1 JOIN dim x ON x.i = a.lo JOIN dim y ON y.i = a.hi + 1 JOIN dim z ON z.i = b.hi + 1
   WHERE b.hi - a.lo = a.step + 1 GROUP BY a.step, a.lo, b.hi)
  SELECT step + 1 AS step, lo, hi, cost, split FROM s UNION ALL SELECT step, lo, hi, m // 1048576, (m % 1048576)::BIGINT FROM best))
SELECT lo::BIGINT AS lo, hi::BIGINT AS hi, cost::BIGINT AS cost, split::BIGINT AS split FROM t WHERE step = (SELECT max(i) - 1 FROM dim)"""


@query("mpp_chain", _CHAIN)
def mpp_chain(spark: SparkSession, d: str) -> DataFrame:
    """The related chain-parenthesising program on the part sizes as dimensions, in one task."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        dims = sorted(pdf["p_size"].tolist())
        cost, split = solve_interval(len(dims) - 1, lambda i, k, j: dims[i] * dims[k + 1] * dims[j + 1], lambda i: 0)
        i, j = np.nonzero(split >= 0)
        return pd.DataFrame({"lo": i, "hi": j, "cost": cost[i, j], "split": split[i, j].astype(np.int64)})

    sizes = load(spark, d, "part").select("p_size").distinct()
    return sizes.groupBy(F.lit(1).alias("one")).applyInPandas(run, "lo bigint, hi bigint, cost bigint, split bigint")


# Measures -----------------------------------------------------------------------------------------
_RUNS_SQL = "(VALUES " + ", ".join(f"('{a}', '{t}', {n}::BIGINT, {p}::BIGINT, {k}::BIGINT, {s}::DOUBLE)" for a, t, n, p, k, s in runs()) + ") r(platform, technique, n, p, k, total_s)"


def published(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(runs(), "platform string, technique string, n bigint, p bigint, k bigint, total_s double")


@query("published_speedup", f"WITH r AS (SELECT * FROM {_RUNS_SQL}) SELECT r.platform, r.technique, r.n, r.p, r.k, round(s.total_s / r.total_s, 6) AS speedup, round(100 * s.total_s / r.total_s / r.p, 6) AS efficiency FROM r JOIN r s ON s.technique = 'sequential' AND s.platform = r.platform AND s.n = r.n WHERE r.technique <> 'sequential'")
def published_speedup(spark: SparkSession, d: str) -> DataFrame:
    r = published(spark)
    s = r.where("technique = 'sequential'").select("platform", "n", F.col("total_s").alias("one"))
    return r.where("technique <> 'sequential'").join(F.broadcast(s), ["platform", "n"]).select("platform", "technique", "n", "p", "k", F.round(F.col("one") / F.col("total_s"), 6).alias("speedup"), F.round(100 * F.col("one") / F.col("total_s") / F.col("p"), 6).alias("efficiency"))


@query("published_reduction", f"WITH r AS (SELECT * FROM {_RUNS_SQL}) SELECT r.technique, r.n, r.p, r.k, round(100 * (1 - r.total_s / b.total_s), 6) AS reduction FROM r JOIN r b ON b.technique = 'regular' AND b.platform = r.platform AND b.n = r.n AND b.p = r.p WHERE r.k > 0")
def published_reduction(spark: SparkSession, d: str) -> DataFrame:
    r = published(spark)
    b = r.where("technique = 'regular'").select("platform", "n", "p", F.col("total_s").alias("base"))
    return r.where("k > 0").join(F.broadcast(b), ["platform", "n", "p"]).select("technique", "n", "p", "k", F.round(100 * (1 - F.col("total_s") / F.col("base")), 6).alias("reduction"))


@query("ideal_k", f"SELECT platform, n, p, arg_min(k, total_s) AS k FROM {_RUNS_SQL} WHERE technique = 'four_split' GROUP BY platform, n, p")
def ideal_k(spark: SparkSession, d: str) -> DataFrame:
    return published(spark).where("technique = 'four_split'").groupBy("platform", "n", "p").agg(F.min_by("k", "total_s").alias("k"))


@query("runs_rollup", f"SELECT platform, technique, k, count(*) AS runs, round(sum(total_s), 6) AS total_s FROM {_RUNS_SQL} GROUP BY ROLLUP (platform, technique, k)")
def runs_rollup(spark: SparkSession, d: str) -> DataFrame:
    return published(spark).rollup("platform", "technique", "k").agg(F.count(F.lit(1)).alias("runs"), F.round(F.sum("total_s"), 6).alias("total_s"))


@query("runs_pivot", f"SELECT n, max(total_s) FILTER (k = 1) AS k1, max(total_s) FILTER (k = 2) AS k2, max(total_s) FILTER (k = 3) AS k3 FROM {_RUNS_SQL} WHERE platform = 'A' AND p = 32 AND technique = 'four_split' GROUP BY n")
def runs_pivot(spark: SparkSession, d: str) -> DataFrame:
    own = published(spark).where("platform = 'A' AND p = 32 AND technique = 'four_split'").groupBy("n").pivot("k", [1, 2, 3]).agg(F.max("total_s"))
    return own.select("n", F.col("1").alias("k1"), F.col("2").alias("k2"), F.col("3").alias("k3"))


#: Keys of the solved table that simulations stretch to the published sizes.
_SOLVED_KEYS = 4096


def _cases(spark: SparkSession, profiles: tuple[str, ...], sizes: tuple[int, ...], workers: tuple[int, ...], techniques: tuple = TECHNIQUES) -> DataFrame:
    rows = [(name, a, b, t, n, p, k) for name, a, b in PROFILES if name in profiles for n in sizes for p in workers for t, k in techniques]
    return spark.createDataFrame(rows, "profile string, alpha double, beta double, technique string, n long, p long, k long")


def _words_work(spark: SparkSession, d: str):  # noqa: ANN202
    """How candidates lie in the table of the most frequent words, solved in one task."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        own = pdf.sort_values("idx")
        m = work_map(solve_windowed(Weights(own["hit"].to_numpy(), own["miss"].to_numpy())))
        return pd.DataFrame({"size": [m.size], "places": [m.places.tobytes()], "sums": [m.sums.tobytes()]})

    r = vocabulary_weights(spark, d, _SOLVED_KEYS).select("idx", "hit", "miss").groupBy(F.lit(1).alias("one")).applyInPandas(run, "size long, places binary, sums binary").first()
    places = np.frombuffer(r["places"])
    return WorkMap(r["size"], places, np.frombuffer(r["sums"]).reshape(len(places), len(places)))


@query("sim_speedup")
def sim_speedup(spark: SparkSession, d: str) -> DataFrame:
    """Simulated time, waiting, transfer, speedup and efficiency of every technique at the published sizes and workers."""
    small = _cases(spark, ("fast",), tuple(range(4096, 40961, 4096)), (32,))
    return simulated_runs(_words_work(spark, d), small.unionByName(_cases(spark, ("fast",), (36864, 40960), (64, 96, 128))))


@query("sim_communication")
def sim_communication(spark: SparkSession, d: str) -> DataFrame:
    """Waiting plus transfer against the regular partition, for each size and number of workers, and computation beside it."""
    runs_ = written(sim_speedup(spark, d), "simulated")
    total = F.col("waiting") + F.col("transfer")
    base = runs_.where("technique = 'regular'").select("n", "p", total.alias("base"))
    return runs_.join(F.broadcast(base), ["n", "p"]).select("technique", "n", "p", "k", "computation", "waiting", "transfer", F.round(100 * (1 - total / F.col("base")), 6).alias("reduction"))


@query("sim_ideal_k")
def sim_ideal_k(spark: SparkSession, d: str) -> DataFrame:
    """The number of fragmentations of least simulated time on a fast and on a slow network."""
    cases = _cases(spark, ("fast", "slow"), (4096, 8192, 12288, 16384, 40960), (32,), tuple(("four_split", k) for k in range(1, 6)))
    return simulated_runs(_words_work(spark, d), cases).groupBy("profile", "n", "p").agg(F.min_by("k", "makespan").alias("k"), F.min("makespan").alias("makespan"))


@query("load_imbalance")
def load_imbalance(spark: SparkSession, d: str) -> DataFrame:
    """Deviation of the least and the most loaded worker from the mean, and how much it narrows against the regular partition.

    ``windowed`` counts the candidates of the words' table, ``cubic`` tries every cut, as the published times suggest.
    """
    techniques = (("regular", 0), ("irregular", 1), ("irregular", 2), ("four_split", 1), ("four_split", 2))
    cases = _cases(spark, ("free",), (24576, 32768, 40960), (32,), techniques)
    both = [simulated_runs(m, cases).withColumn("program", F.lit(name)) for name, m in (("windowed", _words_work(spark, d)), ("cubic", cubic_map()))]
    runs_ = written(both[0].unionByName(both[1]), "simulated")
    base = runs_.where("technique = 'regular'").select("program", "n", F.col("least_deviation").alias("base_least"), F.col("most_deviation").alias("base_most"))
    narrowed = lambda c: F.round(100 * (1 - F.col(f"{c}_deviation") / F.col(f"base_{c}")), 6).alias(f"{c}_narrowed")
    return runs_.join(F.broadcast(base), ["program", "n"]).select("program", "technique", "n", "k", "least_worker", "most_worker", "least_deviation", "most_deviation", narrowed("least"), narrowed("most"))


@query("engine_units")
def engine_units(spark: SparkSession, d: str, n: int = 1000) -> DataFrame:
    """What each worker of the block engine did: units, candidates, cells, and bytes of needed rows and columns, by technique."""
    from .plans.engine import solve, unit_measures

    w, out = collected(vocabulary_weights(spark, d, n)), None
    for t, k in (("regular", 0), ("irregular", 1), ("four_split", 1)):
        own = unit_measures(spark, solve(spark, w, 32, k, t, "dataflow"), 32)
        row = own.groupBy("owner").agg(F.count(F.lit(1)).alias("units"), F.sum("candidates").alias("candidates"), F.sum("cells").alias("cells"), F.sum("received").alias("received")).select(F.lit(t).alias("technique"), F.lit(k).alias("k"), "*")
        out = row if out is None else out.unionByName(row)
    return out


# Applications and text ----------------------------------------------------------------------------
@query("top_words", "SELECT key, count(*) AS n FROM (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS key FROM documents) GROUP BY key ORDER BY n DESC, key LIMIT 100")
def top_words(spark: SparkSession, d: str) -> DataFrame:
    return hit_counts(words(load(spark, d, "documents")), F.col("key")).orderBy(F.desc("n"), "key").limit(100)


@query("vocab_size", "SELECT lang, count(DISTINCT key) AS words FROM (SELECT lang, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS key FROM documents) GROUP BY lang")
def vocab_size(spark: SparkSession, d: str) -> DataFrame:
    return words(load(spark, d, "documents"), "lang").groupBy("lang").agg(F.countDistinct("key").alias("words"))


@query("next_word_top", "SELECT prev, key, n FROM (SELECT prev, key, n, row_number() OVER (PARTITION BY prev ORDER BY n DESC, key) AS r FROM (SELECT prev, key, count(*) AS n FROM (SELECT w[i] AS prev, w[i + 1] AS key FROM (SELECT w, unnest(range(1, len(w))) AS i FROM (SELECT regexp_extract_all(lower(text), '[a-z]+') AS w FROM conversations))) GROUP BY prev, key)) WHERE r <= 3")
def next_word_top(spark: SparkSession, d: str) -> DataFrame:
    """The three likeliest next words of each word: the candidates that prediction ranks."""
    w = load(spark, d, "conversations").select(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0)).alias("w"))
    pairs = w.select(F.explode(F.expr("transform(slice(w, 2, greatest(size(w) - 1, 0)), (x, i) -> struct(w[i] AS prev, x AS key))")).alias("b")).groupBy("b.prev", "b.key").agg(F.count(F.lit(1)).alias("n"))
    return pairs.withColumn("r", F.row_number().over(Window.partitionBy("prev").orderBy(F.desc("n"), "key"))).where("r <= 3").drop("r")


@query("tumbling_weights", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type AS key, count(*) AS n FROM events GROUP BY 1, 2")
def tumbling_weights(spark: SparkSession, d: str) -> DataFrame:
    """Batch twin of the streaming daily weights."""
    return load(spark, d, "events").groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day"), F.col("event_type").alias("key")).agg(F.count(F.lit(1)).alias("n"))
