"""Weight families of the given tables, as DataFrames and as DuckDB SQL (idx, hit, miss).

A family is a dictionary and the probes that look its keys up. ``FAMILIES`` are small enough for the dynamic
program in SQL; ``LARGE`` are dictionaries of thousands of keys, whose weights SQL can state and whose trees
tests compare with other solvers.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators.weights import hit_counts, most_frequent, weight_table
from .sources.tables import load

#: family -> (table, key in Spark, key in SQL): all distinct keys are the dictionary
_WHOLE: dict[str, tuple[str, Callable[[], Column], str]] = {
    "etype": ("events", lambda: F.col("event_type"), "event_type"),
    "nation": ("customer", lambda: F.col("c_nationkey"), "c_nationkey"),
    "hours": ("events", lambda: F.hour(F.col("ts")), "hour(ts)"),
    "psize": ("part", lambda: F.col("p_size"), "p_size"),
    "pnames": ("part", lambda: F.col("p_name"), "p_name"),
    "hosts": ("pages", lambda: F.regexp_extract("url", "^[a-z]+://([^/]+)", 1), "regexp_extract(url, '^[a-z]+://([^/]+)', 1)"),
    "months": ("orders", lambda: F.date_format("o_orderdate", "yyyy-MM"), "strftime(o_orderdate, '%Y-%m')"),
    "supp": ("lineitem", lambda: F.col("l_suppkey"), "l_suppkey"),
    "users": ("events", lambda: F.col("user_id"), "user_id"),
    "labelkeys": ("embeddings", lambda: F.col("label"), "label"),
    "parts": ("lineitem", lambda: F.col("l_partkey"), "l_partkey"),
}
#: Dictionaries of line items whose tables are cut into blocks: days of a month, quantities by flag, buckets of keys.
_CUT: dict[str, tuple[str, Callable[[], Column], str]] = {
    "days": ("lineitem", lambda: F.dayofmonth("l_shipdate"), "day(l_shipdate)"),
    "flags": ("lineitem", lambda: F.concat("l_returnflag", F.lit("-"), F.col("l_quantity").cast("int").cast("string")), "l_returnflag || '-' || l_quantity::INT"),
    "parts40": ("lineitem", lambda: F.col("l_partkey") % 40, "l_partkey % 40"),
    "orders4096": ("lineitem", lambda: F.col("l_orderkey") % 4096, "l_orderkey % 4096"),
    "orders40960": ("lineitem", lambda: F.col("l_orderkey") % 40960, "l_orderkey % 40960"),
}
#: Suppliers with a balance below this are the dictionary of ``lowbal``; every line item is a probe.
LOW_BALANCE = 4500
FAMILIES = (*(f for f in _WHOLE if f != "parts"), "lowbal")
LARGE = ("parts", "benchwords", "vocabulary")
WORDS_SQL = "SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS key FROM {}"


def words(docs: DataFrame, *keep: str) -> DataFrame:
    """(columns ``keep``, key): the words of texts."""
    return docs.select(*keep, F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("key"))


def counts(spark: SparkSession, sf_dir: str, family: str) -> tuple[DataFrame, DataFrame]:
    """(dictionary, counts) of a family."""
    if family in _WHOLE or family in _CUT:
        table, key, _ = (_WHOLE | _CUT)[family]
        own = hit_counts(load(spark, sf_dir, table), key())
        return own.select("key"), own
    if family == "lowbal":
        return load(spark, sf_dir, "supplier").where(F.col("s_acctbal") < LOW_BALANCE).select(F.col("s_suppkey").alias("key")), hit_counts(load(spark, sf_dir, "lineitem"), F.col("l_suppkey"))
    if family in ("benchwords", "vocabulary"):
        own = hit_counts(words(load(spark, sf_dir, "documents")), F.col("key"))
        return (own.select("key") if family == "vocabulary" else words(load(spark, sf_dir, "benchmark")).distinct()), own
    raise ValueError(family)


def weights(spark: SparkSession, sf_dir: str, family: str) -> DataFrame:
    return weight_table(*counts(spark, sf_dir, family))


def keys_in(spark: SparkSession, sf_dir: str, family: str) -> int:
    """How many keys the dictionary has."""
    return counts(spark, sf_dir, family)[0].distinct().count()


def vocabulary_weights(spark: SparkSession, sf_dir: str, n: int) -> DataFrame:
    """The n most frequent words of all documents against all other words: the experiments' instances."""
    own = hit_counts(words(load(spark, sf_dir, "documents")), F.col("key"))
    return weight_table(most_frequent(own, n).select("key"), own)


def all_counts(spark: SparkSession, sf_dir: str, families: tuple[str, ...] = FAMILIES) -> DataFrame:
    """(family, key, n, own) of several families in one plan: counted keys as text that sorts like the keys, and whether they are in the dictionary."""
    out: DataFrame | None = None
    for f in families:
        dictionary, own = counts(spark, sf_dir, f)
        as_text = F.col("key") if dict(own.dtypes)["key"] == "string" else F.lpad(F.col("key").cast("string"), 20, "0")
        if f in _WHOLE:
            both = own.select(as_text.alias("key"), "n", F.lit(True).alias("own"))
        else:
            marked = own.join(dictionary.distinct().withColumn("own", F.lit(True)), "key", "full_outer")
            both = marked.select(as_text.alias("key"), F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("own", F.lit(False)).alias("own"))
        both = both.select(F.lit(f).alias("family"), "key", "n", "own")
        out = both if out is None else out.unionByName(both)
    return out


def counts_sql(family: str) -> str:
    """CTE body (key, n, own): counts by key and whether the key is in the dictionary."""
    if family in _WHOLE or family in _CUT:
        table, _, key = (_WHOLE | _CUT)[family]
        return f"SELECT key, count(*) AS n, true AS own FROM (SELECT {key} AS key FROM {table}) WHERE key IS NOT NULL GROUP BY key"
    if family == "vocabulary":
        return f"SELECT key, count(*) AS n, true AS own FROM ({WORDS_SQL.format('documents')}) GROUP BY key"
    probes, dictionary = {
        "lowbal": ("SELECT l_suppkey AS key FROM lineitem", f"SELECT s_suppkey AS key FROM supplier WHERE s_acctbal < {LOW_BALANCE}"),
        "benchwords": (WORDS_SQL.format("documents"), WORDS_SQL.format("benchmark")),
    }[family]
    return f"SELECT coalesce(p.key, d.key) AS key, coalesce(n, 0) AS n, d.key IS NOT NULL AS own FROM (SELECT key, count(*) AS n FROM ({probes}) WHERE key IS NOT NULL GROUP BY key) p FULL JOIN (SELECT DISTINCT key FROM ({dictionary})) d ON p.key = d.key"


def weights_sql(family: str) -> str:
    """CTEs cnt, keys, wt (idx, key, hit, miss) of a family, without WITH."""
    return f"""cnt AS ({counts_sql(family)}),
keys AS (SELECT key, n, row_number() OVER (ORDER BY key) AS idx FROM cnt WHERE own),
gaps AS (SELECT idx, sum(n) AS n FROM (SELECT coalesce(keys.idx, 0) AS idx, c.n FROM (SELECT key, n FROM cnt WHERE NOT own) c ASOF LEFT JOIN keys ON keys.key <= c.key) GROUP BY idx),
wt AS (SELECT i.idx, k.key, coalesce(k.n, 0)::BIGINT AS hit, coalesce(g.n, 0)::BIGINT AS miss
       FROM (SELECT 0 AS idx UNION ALL SELECT idx FROM keys) i LEFT JOIN keys k ON k.idx = i.idx LEFT JOIN gaps g ON g.idx = i.idx)"""


#: CTEs from wt: pre (idx, ps, qs, miss) and cells (lo, hi, cost, split).
CELLS_SQL = """pre AS (SELECT idx, sum(hit) OVER (ORDER BY idx) AS ps, sum(miss) OVER (ORDER BY idx) AS qs, miss FROM wt),
t AS (SELECT 0 AS step, idx AS lo, idx AS hi, miss::HUGEINT AS cost, idx AS split FROM pre
 UNION ALL
 SELECT * FROM (
  WITH s AS (SELECT * FROM t WHERE step < (SELECT max(idx) FROM pre)),
  best AS (SELECT a.step + 1 AS step, a.lo, b.hi, min((a.cost + b.cost) * 1048576 + a.hi) AS m FROM s a JOIN s b ON b.lo = a.hi + 1 WHERE b.hi - a.lo = a.step + 1 GROUP BY a.step, a.lo, b.hi)
  SELECT step + 1 AS step, lo, hi, cost, split FROM s
  UNION ALL
  SELECT step, lo, hi, (m // 1048576) + y.ps - x.ps + y.qs - x.qs + x.miss, (m % 1048576)::BIGINT FROM best JOIN pre x ON x.idx = lo JOIN pre y ON y.idx = hi)),
cells AS (SELECT lo, hi, cost, split FROM t WHERE step = (SELECT max(idx) FROM pre))"""


def cells_sql(family: str, select: str) -> str:
    return f"WITH RECURSIVE {weights_sql(family)},\n{CELLS_SQL}\n{select}"
