"""Queries around the methods: using trees, relational forms of plans, SQL functions, applications, windows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .catalogue import _BLOCKS, _CELLS, _GRID_SQL, _GROUPED, _KEYS, _NATION_CUSTS, _RUNS_SQL, published, query, tree_of
from .families import FAMILIES, cells_sql, counts, counts_sql, keys_in, weights, weights_sql, words
from .functions.sql import register
from .operators.dynamic import Program
from .operators.trees import as_of, lookup, program_depths, replay_cost, solved_progressive, tree_depths
from .operators.weights import hit_counts, prefix, ranked
from .plans import geometry as g
from .plans import in_sql
from .sources.tables import load
from .storage import written

# Using a tree -------------------------------------------------------------------------------------
_DEPTHS = """, nodes AS (SELECT lo, hi, split, 1 AS depth FROM cells WHERE lo = 0 AND hi = (SELECT max(idx) FROM wt)
 UNION ALL SELECT c.lo, c.hi, c.split, nodes.depth + 1 FROM nodes JOIN cells c ON nodes.lo < nodes.hi AND (c.lo = nodes.lo AND c.hi = nodes.split OR c.lo = nodes.split + 1 AND c.hi = nodes.hi)),
looked AS (SELECT cnt.key, cnt.n, own AS found, nodes.depth::BIGINT AS depth FROM (SELECT *, coalesce((SELECT max(idx) FROM keys WHERE keys.key <= cnt.key), 0) AS place FROM cnt WHERE n > 0) cnt
 JOIN nodes ON CASE WHEN own THEN nodes.lo < nodes.hi AND nodes.split + 1 = place ELSE nodes.lo = nodes.hi AND nodes.lo = place END)
"""
_REPLAY = "SELECT sum(n)::BIGINT AS probes, sum(CASE WHEN found THEN n ELSE 0 END)::BIGINT AS hits, sum(n * depth)::BIGINT AS cost FROM looked"


def looked_up(spark: SparkSession, d: str, family: str, kind: str = "optimal") -> DataFrame:
    table = written(weights(spark, d, family), "weights")
    return lookup(written(counts(spark, d, family)[1], "probe-counts"), table, tree_depths(table, kind))


query("lookup_parts", cells_sql("lowbal", "").rstrip() + _DEPTHS + "SELECT key, n, found, depth FROM looked")(lambda spark, d: looked_up(spark, d, "lowbal"))
for _f in FAMILIES:
    query(f"replay_{_f}", cells_sql(_f, "").rstrip() + _DEPTHS + _REPLAY)(lambda spark, d, f=_f: replay_cost(looked_up(spark, d, f)))


@query("replay_equals_dp", cells_sql("lowbal", "SELECT cost::BIGINT AS dp_cost, cost::BIGINT AS replay_cost FROM cells WHERE lo = 0 AND hi = (SELECT max(idx) FROM wt)"))
def replay_equals_dp(spark: SparkSession, d: str) -> DataFrame:
    """All probes of the log looked up in the tree against the optimum of the program."""
    table = written(weights(spark, d, "lowbal"), "weights")
    program = Program(table)
    best = program.optimum().select(F.col("cost").alias("dp_cost"))
    looked = lookup(written(counts(spark, d, "lowbal")[1], "probe-counts"), table, program_depths(program))
    return best.join(F.broadcast(replay_cost(looked).select(F.col("cost").alias("replay_cost"))))


_BALANCED = """, nodes AS (SELECT 0::BIGINT AS lo, max(idx)::BIGINT AS hi, 1::BIGINT AS depth FROM wt
 UNION ALL SELECT CASE WHEN s = 0 THEN lo ELSE (lo + hi - 1) // 2 + 1 END, CASE WHEN s = 0 THEN (lo + hi - 1) // 2 ELSE hi END, depth + 1 FROM nodes, (VALUES (0), (1)) v(s) WHERE lo < hi)
SELECT sum(CASE WHEN lo = hi THEN g.miss ELSE k.hit END * depth)::BIGINT AS cost FROM nodes LEFT JOIN wt g ON g.idx = lo LEFT JOIN wt k ON lo < hi AND k.idx = (lo + hi - 1) // 2 + 1"""


def _cost_of(spark: SparkSession, d: str, family: str, kind: str) -> DataFrame:
    table = written(weights(spark, d, family), "weights")
    return table.join(tree_depths(table, kind), "idx").agg(F.sum(F.col("hit") * F.col("key_depth") + F.col("miss") * F.col("gap_depth")).alias("cost"))


for _f in ("nation", "lowbal", "pnames"):
    query(f"balanced_{_f}", f"WITH RECURSIVE {weights_sql(_f)}" + _BALANCED)(lambda spark, d, f=_f: _cost_of(spark, d, f, "balanced"))
    query(f"chain_{_f}", f"WITH {weights_sql(_f)} SELECT sum(hit * idx + miss * least(idx + 2, (SELECT max(idx) FROM wt) + 1))::BIGINT AS cost FROM wt")(lambda spark, d, f=_f: _cost_of(spark, d, f, "chain_left"))
    query(f"tree_cost_{_f}", cells_sql(_f, "SELECT cost::BIGINT AS cost FROM cells WHERE lo = 0 AND hi = (SELECT max(idx) FROM wt)"))(lambda spark, d, f=_f: _cost_of(spark, d, f, "optimal"))

@query("word_lookup_cost")
def word_lookup_cost(spark: SparkSession, d: str) -> DataFrame:
    """All words of the documents looked up in the optimal tree over all words of the benchmark: replayed cost, beside the program's and the balanced tree's."""
    table = written(weights(spark, d, "benchwords"), "weights")
    probes = written(counts(spark, d, "benchwords")[1], "probe-counts")
    out = lookup(probes, table, tree_depths(table)).groupBy("found").agg(F.count(F.lit(1)).alias("words"), F.sum("n").alias("tokens"), F.sum(F.col("n") * F.col("depth")).alias("cost"))
    kinds = [table.join(tree_depths(table, kind), "idx").agg(F.sum(F.col("hit") * F.col("key_depth") + F.col("miss") * F.col("gap_depth")).alias(f"{kind}_cost")) for kind in ("optimal", "balanced")]
    return out.join(F.broadcast(kinds[0])).join(F.broadcast(kinds[1]))


query("depth_quantiles", cells_sql("users", "").rstrip() + _DEPTHS + "SELECT quantile_cont(depth, 0.5)::DOUBLE AS median, quantile_cont(depth, 0.9)::DOUBLE AS p90, max(depth) AS height, round(avg(depth), 6) AS mean FROM looked")(
    lambda spark, d: looked_up(spark, d, "users").agg(F.percentile("depth", F.lit(0.5)).alias("median"), F.percentile("depth", F.lit(0.9)).alias("p90"), F.max("depth").alias("height"), F.round(F.avg("depth"), 6).alias("mean"))
)
query("top_shallow", cells_sql("lowbal", "").rstrip() + _DEPTHS + "SELECT key, n, depth FROM looked WHERE found ORDER BY depth, n DESC, key LIMIT 10")(
    lambda spark, d: looked_up(spark, d, "lowbal").where("found").orderBy("depth", F.desc("n"), "key").limit(10).select("key", "n", "depth")
)


@query("tree_valid", cells_sql("lowbal", "SELECT max(idx)::BIGINT AS nodes, 0::BIGINT AS orphans, 0::BIGINT AS out_of_order FROM wt"))
def tree_valid(spark: SparkSession, d: str) -> DataFrame:
    """Nodes, nodes whose parent is none or not one level up, and children on the wrong side of their parent."""
    t = written(tree_of(spark, d, "lowbal"), "tree")
    up = t.select(F.col("rank").alias("parent_rank"), F.col("depth").alias("above"))
    own = t.join(up, "parent_rank", "left")
    orphan = (F.col("side") != "root") & F.coalesce(F.col("above") + 1 != F.col("depth"), F.lit(True))
    wrong = ((F.col("side") == "left") & (F.col("rank") >= F.col("parent_rank"))) | ((F.col("side") == "right") & (F.col("rank") <= F.col("parent_rank")))
    return own.agg(F.countDistinct("rank").alias("nodes"), F.sum(orphan.cast("bigint")).alias("orphans"), F.sum(wrong.cast("bigint")).alias("out_of_order"))


@query("progressive_nation", cells_sql("nation", _CELLS))
def progressive_nation(spark: SparkSession, d: str) -> DataFrame:
    w = written(weights(spark, d, "nation"), "weights")
    return solved_progressive(w, prefix(w))


# Dictionaries, hits and misses one by one ---------------------------------------------------------
query("dict_parts", "SELECT l_partkey AS key, row_number() OVER (ORDER BY l_partkey) AS rank FROM (SELECT DISTINCT l_partkey FROM lineitem)")(
    lambda spark, d: ranked(hit_counts(load(spark, d, "lineitem"), F.col("l_partkey")).select("key"))
)
query("dict_words", f"SELECT key, row_number() OVER (ORDER BY key) AS rank FROM ({counts_sql('vocabulary')})")(lambda spark, d: ranked(counts(spark, d, "vocabulary")[0]))
query("filter_dictionary", "SELECT p_partkey AS key, p_brand FROM part WHERE p_size BETWEEN 5 AND 9 AND p_brand LIKE 'B%' AND p_name IS NOT NULL")(
    lambda spark, d: load(spark, d, "part").where(F.col("p_size").between(5, 9) & F.col("p_brand").startswith("B") & F.col("p_name").isNotNull()).select(F.col("p_partkey").alias("key"), "p_brand")
)
query("scan_pruned", "SELECT l_partkey AS key, count(*) AS n FROM lineitem WHERE l_quantity >= 40 GROUP BY l_partkey")(
    lambda spark, d: hit_counts(load(spark, d, "lineitem").where("l_quantity >= 40"), F.col("l_partkey"))
)


def _probe_sides(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    keys, own = counts(spark, d, "benchwords")
    return own, keys


_OWN_SQL = f"SELECT key, n FROM ({counts_sql('benchwords')}) WHERE own AND n > 0"
query("probe_hits", _OWN_SQL)(lambda spark, d: (lambda c, k: c.join(k, "key", "left_semi"))(*_probe_sides(spark, d)))
query("probe_misses", _OWN_SQL.replace("WHERE own AND n > 0", "WHERE NOT own"))(lambda spark, d: (lambda c, k: c.join(k, "key", "left_anti"))(*_probe_sides(spark, d)))
query("join_merge", _OWN_SQL)(lambda spark, d: (lambda c, k: c.join(k.hint("merge"), "key"))(*_probe_sides(spark, d)))


@query("miss_words", f"WITH {weights_sql('benchwords')} SELECT c.key, c.n, coalesce(keys.idx, 0) AS gap FROM (SELECT key, n FROM cnt WHERE NOT own) c ASOF LEFT JOIN keys ON keys.key <= c.key")
def miss_words(spark: SparkSession, d: str) -> DataFrame:
    """The gap of every word of the documents that the benchmark lacks, by the as-of join."""
    own, keys = _probe_sides(spark, d)
    return as_of(own.join(keys, "key", "left_anti"), ranked(keys), "key", "rank", 0).select("key", "n", F.col("rank").alias("gap"))


query("weights_hits_only", f"WITH {weights_sql('benchwords')} SELECT idx, hit, 0::BIGINT AS miss FROM wt")(lambda spark, d: weights(spark, d, "benchwords").select("idx", "hit", F.lit(0).cast("bigint").alias("miss")))
query("weights_misses_only", f"WITH {weights_sql('benchwords')} SELECT idx, 0::BIGINT AS hit, miss FROM wt")(lambda spark, d: weights(spark, d, "benchwords").select("idx", F.lit(0).cast("bigint").alias("hit"), "miss"))
query("hits_dates", "SELECT strftime(l_shipdate, '%Y-%m-%d') AS key, count(*) AS n FROM lineitem GROUP BY 1")(lambda spark, d: hit_counts(load(spark, d, "lineitem"), F.date_format("l_shipdate", "yyyy-MM-dd")))
query("rank_words", f"SELECT key, n, rank() OVER (ORDER BY n DESC) AS r, dense_rank() OVER (ORDER BY n DESC) AS dr FROM ({counts_sql('benchwords')}) WHERE own AND n > 0")(
    lambda spark, d: (lambda c, k: c.join(k, "key", "left_semi"))(*_probe_sides(spark, d)).select("key", "n", F.rank().over(Window.orderBy(F.desc("n"))).alias("r"), F.dense_rank().over(Window.orderBy(F.desc("n"))).alias("dr"))
)
_LANG = "SELECT lang, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS key FROM documents"
query("topk_per_lang", f"SELECT lang, key, n FROM (SELECT lang, key, count(*) AS n, row_number() OVER (PARTITION BY lang ORDER BY count(*) DESC, key) AS r FROM ({_LANG}) GROUP BY lang, key) WHERE r <= 5")(
    lambda spark, d: words(load(spark, d, "documents"), "lang").groupBy("lang", "key").agg(F.count(F.lit(1)).alias("n")).withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "key"))).where("r <= 5").drop("r")
)


def _vocabulary(spark: SparkSession, d: str, lang: str) -> DataFrame:
    return words(load(spark, d, "documents").where(F.col("lang") == lang)).select("key").distinct()


for _name, _op, _how in (("vocab_intersect", "INTERSECT", "left_semi"), ("vocab_except", "EXCEPT", "left_anti")):
    query(_name, f"SELECT key FROM ({_LANG}) WHERE lang = 'en' {_op} SELECT key FROM ({_LANG}) WHERE lang = 'de'")(lambda spark, d, h=_how: _vocabulary(spark, d, "en").join(_vocabulary(spark, d, "de"), "key", h))


@query("translate_ranked", f"WITH c AS (SELECT lang, key, count(*) AS n FROM ({_LANG}) WHERE lang IN ('en', 'de') GROUP BY lang, key), r AS (SELECT lang, key, row_number() OVER (PARTITION BY lang ORDER BY n DESC, key) AS r FROM c) SELECT a.key AS word, b.key AS translation FROM r a JOIN r b USING (r) WHERE a.lang = 'en' AND b.lang = 'de' AND r <= 200")
def translate_ranked(spark: SparkSession, d: str) -> DataFrame:
    """Words of equal frequency rank in two languages: the payload that a translation tree holds at its nodes."""
    c = words(load(spark, d, "documents").where("lang IN ('en', 'de')"), "lang").groupBy("lang", "key").agg(F.count(F.lit(1)).alias("n"))
    r = c.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "key"))).where("r <= 200")
    return r.where("lang = 'en'").select("r", F.col("key").alias("word")).join(r.where("lang = 'de'").select("r", F.col("key").alias("translation")), "r").drop("r")


# Plans as relations -------------------------------------------------------------------------------
def _blocks_frame(spark: SparkSession, *plan: int) -> DataFrame:
    return spark.createDataFrame([tuple(vars(b).values()) for b in g.blocks(*plan)], _BLOCKS)


def _blocks_sql(*plan: int) -> str:
    return f"({in_sql.blocks_sql(*plan)}) b"


_PLAN = (40, 5, 2)
_DEPENDS = "a.block_id <> b.block_id AND (a.r0 <= b.r1 AND b.r0 <= a.r1 AND a.c1 <= b.c1 AND a.c0 <= b.c0 OR a.c0 <= b.c1 AND b.c0 <= a.c1 AND a.r0 >= b.r0 AND a.r1 >= b.r1)"
query("block_deps_range", f"WITH RECURSIVE {weights_sql('parts40')}, {in_sql.blocks_ctes(_KEYS, *_PLAN[1:])} SELECT b.block_id::INT AS block_id, a.block_id::INT AS dep_block FROM blk b JOIN blk a ON {_DEPENDS}")(
    lambda spark, d: (lambda b: b.alias("b").join(b.alias("a"), F.expr(_DEPENDS)).select("b.block_id", F.col("a.block_id").alias("dep_block")))(_blocks_frame(spark, keys_in(spark, d, "parts40"), *_PLAN[1:]))
)
query("round_independence", "SELECT 0::BIGINT AS pairs")(
    lambda spark, d: (lambda b: b.alias("b").join(b.alias("a"), F.expr(f"a.round >= b.round AND {_DEPENDS}")).agg(F.count(F.lit(1)).alias("pairs")))(_blocks_frame(spark, *_PLAN))
)
query("blocks_per_round", f"SELECT round, count(*) AS blocks FROM {_blocks_sql(*_PLAN)} GROUP BY round")(lambda spark, d: _blocks_frame(spark, *_PLAN).groupBy("round").agg(F.count(F.lit(1)).alias("blocks")))
query("snake_mapping", f"SELECT block_id, ((row_number() OVER (ORDER BY round, r0) - 1) % 5)::BIGINT AS owner FROM {_blocks_sql(*_PLAN)}")(
    lambda spark, d: spark.createDataFrame(list(g.owners(g.blocks(*_PLAN), _PLAN[1]).items()), "block_id int, owner bigint")
)
query("extremities", f"SELECT block_id, r0 || ',' || c0 AS upper_left, r0 || ',' || c1 AS upper_right, r1 || ',' || c0 AS lower_left, r1 || ',' || c1 AS lower_right FROM {_blocks_sql(*_PLAN)}")(
    lambda spark, d: _blocks_frame(spark, *_PLAN).select("block_id", *[F.concat_ws(",", r, c).alias(n) for n, r, c in (("upper_left", "r0", "c0"), ("upper_right", "r0", "c1"), ("lower_left", "r1", "c0"), ("lower_right", "r1", "c1"))])
)
query("cell_locator", f"SELECT i::INT AS i, j::INT AS j, block_id FROM {_blocks_sql(*_PLAN)}, (SELECT unnest(range(0, 41)) AS i), (SELECT unnest(range(0, 41)) AS j) WHERE i <= j AND i BETWEEN r0 AND r1 AND j BETWEEN c0 AND c1")(
    lambda spark, d: _blocks_frame(spark, *_PLAN).select("block_id", F.explode(F.sequence("r0", "r1")).alias("i"), "c0", "c1").select("i", F.explode(F.sequence("c0", "c1")).alias("j"), "block_id").where("i <= j")
)
query("cell_deps", "SELECT i::INT AS i, j::INT AS j, (2 * (j - i))::BIGINT AS deps FROM (SELECT unnest(range(0, 13)) AS i), (SELECT unnest(range(0, 13)) AS j) WHERE i < j")(
    lambda spark, d: (lambda v: v.select(F.col("id").alias("i")).join(v.select(F.col("id").alias("j")), F.expr("i < j")).join(v.select(F.col("id").alias("k")), F.expr("i <= k AND k < j"))
    .select(F.col("i").cast("int"), F.col("j").cast("int"), F.explode(F.expr("array(struct(i AS a, k AS b), struct(k + 1 AS a, j AS b))"))).groupBy("i", "j").agg(F.countDistinct("col").alias("deps")))(spark.range(13))
)

_THEORY = "(3 + 4 * (f // 2 - 1)) / (4.0 * p) + 4 * (h + 1) * inner_sum / p + {extra} * (h + 1) / (pow(4, k) * p) + (f + f % 2) / (pow(4, k) * p)"
query("theory_time", f"SELECT n, p, k, round(n * n * ({_THEORY.format(extra=1)}), 3) AS with_term, round(n * n * ({_THEORY.format(extra=0)}), 3) AS without_term FROM (SELECT *, ceil(f / 2)::BIGINT AS h, coalesce((SELECT sum(1 / pow(4, l)) FROM (SELECT unnest(range(2, 7)) AS l) WHERE l <= k), 0) AS inner_sum FROM ({_GRID_SQL}) WHERE k > 0)")(
    lambda spark, d: spark.createDataFrame([(n, p, k, round(g.theory_time(n, p, k), 3), round(g.theory_time(n, p, k, False), 3)) for n in range(4096, 40961, 4096) for p in (32, 64, 96, 128) for k in range(1, 6)], "n bigint, p bigint, k bigint, with_term double, without_term double")
)
query("runs_cube", f"SELECT technique, p, count(*) AS runs, round(min(total_s), 6) AS least_s FROM {_RUNS_SQL} GROUP BY CUBE (technique, p)")(
    lambda spark, d: published(spark).cube("technique", "p").agg(F.count(F.lit(1)).alias("runs"), F.round(F.min("total_s"), 6).alias("least_s"))
)
query("lag_runs", f"SELECT n, k, round(total_s - lag(total_s) OVER (PARTITION BY n ORDER BY k), 6) AS gain FROM {_RUNS_SQL} WHERE technique = 'four_split' AND platform = 'A' AND p = 32")(
    lambda spark, d: published(spark).where("technique = 'four_split' AND platform = 'A' AND p = 32").select("n", "k", F.round(F.col("total_s") - F.lag("total_s").over(Window.partitionBy("n").orderBy("k")), 6).alias("gain"))
)


# Functions for SQL users --------------------------------------------------------------------------
@query("sql_functions", "SELECT p, ceil(sqrt(2 * p))::INT AS f, ceil(4097 / ceil(sqrt(2 * p)))::INT AS side FROM (SELECT unnest(range(1, 129)) AS p)")
def sql_functions(spark: SparkSession, d: str) -> DataFrame:
    register(spark)
    return spark.sql("SELECT id AS p, grid_side(id) AS f, block_side(4096, id) AS side FROM range(1, 129)")


@query("udtf_blocks", f"SELECT block_id, round, level, r0, r1, c0, c1 FROM {_blocks_sql(*_PLAN)}")
def udtf_blocks(spark: SparkSession, d: str) -> DataFrame:
    register(spark)
    return spark.sql("SELECT * FROM partition_blocks({}, {}, {})".format(*_PLAN))


@query("udaf_cost", f"WITH RECURSIVE own AS ({_NATION_CUSTS}),\n{_GROUPED}".replace("SELECT t.grp, n::INT AS n, cost::BIGINT AS cost FROM", "SELECT t.grp::INT AS n_regionkey, cost::BIGINT AS cost FROM"))
def udaf_cost(spark: SparkSession, d: str) -> DataFrame:
    """The optimal cost as an aggregate function, one small tree a region."""
    register(spark)
    c = hit_counts(load(spark, d, "customer"), F.col("c_nationkey")).withColumnRenamed("key", "n_nationkey")
    own = load(spark, d, "nation").join(c, "n_nationkey")
    return own.groupBy("n_regionkey").agg(F.expr("optimal_cost(n_nationkey, n)").alias("cost"))


# Windows over time --------------------------------------------------------------------------------
@query("sliding_weights", "SELECT strftime(w, '%Y-%m-%d') AS first_day, event_type AS key, count(*) AS n FROM (SELECT event_type, unnest([date_trunc('day', ts) - to_days(i) FOR i IN range(0, 7)]) AS w FROM events) GROUP BY 1, 2")
def sliding_weights(spark: SparkSession, d: str) -> DataFrame:
    """Weights of every seven days, one day apart; batch twin of the streaming form."""
    own = load(spark, d, "events").select("event_type", F.col("ts").cast("timestamp").alias("ts")).groupBy(F.window("ts", "7 days", "1 day").alias("w"), F.col("event_type").alias("key")).agg(F.count(F.lit(1)).alias("n"))
    return own.select(F.date_format("w.start", "yyyy-MM-dd").alias("first_day"), "key", "n")


@query("session_weights", "SELECT user_id AS key, count(*) AS sessions, max(n) AS longest FROM (SELECT user_id, s, count(*) AS n FROM (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 1 HOUR THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s) GROUP BY user_id")
def session_weights(spark: SparkSession, d: str) -> DataFrame:
    own = load(spark, d, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts")).groupBy("user_id", F.session_window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    return own.groupBy(F.col("user_id").alias("key")).agg(F.count(F.lit(1)).alias("sessions"), F.max("n").alias("longest"))
