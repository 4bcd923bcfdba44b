"""Queries of the relational surface: sources, views, joins, sets, windows, functions, and applications through trees."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .broadcasts import opened, sent
from .catalogue import _OPTIMA, _RUNS_SQL, by_families, query, tree_of
from .catalogue_use import _DEPTHS, _LANG
from .families import cells_sql, counts, counts_sql, weights, weights_sql, words
from .functions.kernel import Weights, depths_of, solve_windowed
from .operators.dynamic import solved, solved_groups
from .operators.trees import tree_depths
from .operators.weights import hit_counts
from .sources import synthetic
from .sources.files import register_views
from .sources.tables import load
from .storage import written

# Sources and views -----------------------------------------------------------------------------------
_MADE = "SELECT i AS idx, (i * 7919 + 3 * 104729) % 1009 AS draw FROM (SELECT unnest(range(0, 151)) AS i)"
for _law, _hit, _miss in (("uniform", "draw + 1", "(draw * 31 + 7) % 1009 + 1"), ("zipf", "1000000 // (draw + 1)", "1000000 // ((draw * 31 + 7) % 1009 + 1)"), ("all_hit", "draw + 1", "0"), ("all_miss", "0", "(draw * 31 + 7) % 1009 + 1")):
    query(f"synthetic_{_law}", f"SELECT idx, (CASE WHEN idx = 0 THEN 0 ELSE {_hit} END)::BIGINT AS hit, ({_miss})::BIGINT AS miss FROM ({_MADE})")(lambda spark, d, law=_law: synthetic_weights(spark, law))


def synthetic_weights(spark: SparkSession, law: str, n: int = 150, seed: int = 3) -> DataFrame:
    synthetic.register(spark)
    return spark.read.format("synthetic_weights").option("n", n).option("seed", seed).option("law", law).load()


@query("synthetic_solved", "WITH RECURSIVE wt AS (SELECT idx, (CASE WHEN idx = 0 THEN 0 ELSE 1000000 // (draw + 1) END)::BIGINT AS hit, (1000000 // ((draw * 31 + 7) % 1009 + 1))::BIGINT AS miss FROM (" + _MADE + ")),\n" + cells_sql("nation", "SELECT lo::INT AS lo, hi::INT AS hi, cost::BIGINT AS cost, split::INT AS split FROM cells").split("LEFT JOIN gaps g ON g.idx = i.idx),\n")[1])
def synthetic_solved(spark: SparkSession, d: str) -> DataFrame:
    return solved(synthetic_weights(spark, "zipf"))


@query("sql_view_tree", cells_sql("nation", "").rstrip() + _DEPTHS + "SELECT depth, count(*) AS keys, sum(n)::BIGINT AS probes FROM looked WHERE found GROUP BY depth")
def sql_view_tree(spark: SparkSession, d: str) -> DataFrame:
    """Keys and their probes by depth, asked in SQL over the views of a tree."""
    register_views(spark, tree=tree_of(spark, d, "nation"), hits=counts(spark, d, "nation")[1])
    return spark.sql("SELECT cast(depth AS bigint) AS depth, count(*) AS keys, sum(n) AS probes FROM tree JOIN hits ON tree.key = cast(hits.key AS string) GROUP BY depth")


# Joins, sets, windows ----------------------------------------------------------------------------------
@query("probe_full_outer", f"SELECT key, n, own FROM ({counts_sql('benchwords')})")
def probe_full_outer(spark: SparkSession, d: str) -> DataFrame:
    """Dictionary and probes side by side: hits, misses, and keys that nothing looks up."""
    keys, own = counts(spark, d, "benchwords")
    both = own.join(keys.withColumn("own", F.lit(True)), "key", "full_outer")
    return both.select("key", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("own", F.lit(False)).alias("own"))


def _vocabulary(spark: SparkSession, d: str, lang: str) -> DataFrame:
    return words(load(spark, d, "documents").where(F.col("lang") == lang)).select("key")


query("words_intersect", f"SELECT key FROM ({_LANG}) WHERE lang = 'en' INTERSECT SELECT key FROM ({_LANG}) WHERE lang = 'fr'")(lambda spark, d: _vocabulary(spark, d, "en").intersect(_vocabulary(spark, d, "fr")))
query("words_except", f"SELECT key FROM ({_LANG}) WHERE lang = 'en' EXCEPT SELECT key FROM ({_LANG}) WHERE lang = 'fr'")(lambda spark, d: _vocabulary(spark, d, "en").subtract(_vocabulary(spark, d, "fr")))
query("words_except_all", f"SELECT key, count(*) AS n FROM (SELECT key FROM ({_LANG}) WHERE lang = 'es' EXCEPT ALL SELECT key FROM ({_LANG}) WHERE lang = 'fr') GROUP BY key")(
    lambda spark, d: _vocabulary(spark, d, "es").exceptAll(_vocabulary(spark, d, "fr")).groupBy("key").agg(F.count(F.lit(1)).alias("n"))
)
query("ntile_words", f"SELECT key, n, ntile(10) OVER (ORDER BY n DESC, key)::BIGINT AS tenth, round(percent_rank() OVER (ORDER BY n DESC, key), 9) AS place FROM ({counts_sql('benchwords')}) WHERE own")(
    lambda spark, d: probe_full_outer(spark, d).where("own").select("key", "n", F.ntile(10).over(Window.orderBy(F.desc("n"), "key")).cast("bigint").alias("tenth"), F.round(F.percent_rank().over(Window.orderBy(F.desc("n"), "key")), 9).alias("place"))
)
query("range_frame_events", "SELECT event_type AS key, strftime(day, '%Y-%m-%d') AS day, sum(n) OVER (PARTITION BY event_type ORDER BY day RANGE BETWEEN INTERVAL 2 DAY PRECEDING AND CURRENT ROW)::BIGINT AS n FROM (SELECT event_type, date_trunc('day', ts) AS day, count(*) AS n FROM events GROUP BY 1, 2)")(
    lambda spark, d: load(spark, d, "events").groupBy(F.col("event_type").alias("key"), F.to_date("ts").alias("date")).agg(F.count(F.lit(1)).alias("c"))
    .select("key", F.date_format("date", "yyyy-MM-dd").alias("day"), F.sum("c").over(Window.partitionBy("key").orderBy(F.unix_date("date")).rangeBetween(-2, 0)).alias("n"))
)
query("runs_unpivot", f"SELECT n, k, total_s FROM {_RUNS_SQL} WHERE platform = 'A' AND p = 32 AND technique = 'four_split' AND k <= 3")(
    lambda spark, d: (lambda wide: wide.unpivot("n", ["k1", "k2", "k3"], "name", "total_s").select("n", F.substring("name", 2, 1).cast("bigint").alias("k"), "total_s"))(_pivoted(spark, d))
)


def _pivoted(spark: SparkSession, d: str) -> DataFrame:
    from .catalogue import QUERIES

    return QUERIES["runs_pivot"](spark, d)


query("approx_vocabulary", "SELECT true AS within")(
    lambda spark, d: words(load(spark, d, "documents")).agg(F.approx_count_distinct("key", 0.02).alias("a"), F.countDistinct("key").alias("c")).select((F.abs(F.col("a") - F.col("c")) <= 0.1 * F.col("c")).alias("within"))
)
query("prefix_by_hof", f"WITH {weights_sql('nation')} SELECT idx, sum(hit) OVER (ORDER BY idx)::BIGINT AS ps FROM wt")(
    lambda spark, d: weights(spark, d, "nation").agg(F.array_sort(F.collect_list(F.struct("idx", "hit"))).alias("w"))
    .select(F.explode(F.expr("transform(w, (x, i) -> struct(x.idx AS idx, aggregate(slice(w, 1, i + 1), 0L, (a, y) -> a + y.hit) AS ps))")).alias("x")).select("x.idx", "x.ps")
)


@query("interval_overlap", "SELECT x.nationkey AS a, y.nationkey AS b FROM (SELECT s_nationkey AS nationkey, min(s_suppkey) AS lo, max(s_suppkey) AS hi FROM supplier GROUP BY 1) x JOIN (SELECT s_nationkey AS nationkey, min(s_suppkey) AS lo, max(s_suppkey) AS hi FROM supplier GROUP BY 1) y ON x.lo <= y.hi AND y.lo <= x.hi")
def interval_overlap(spark: SparkSession, d: str, bucket: int = 16) -> DataFrame:
    """Pairs of nations whose ranges of supplier keys overlap: spans cut into buckets, an equi-join, and the rest of the test."""
    own = load(spark, d, "supplier").groupBy(F.col("s_nationkey").alias("nationkey")).agg(F.min("s_suppkey").alias("lo"), F.max("s_suppkey").alias("hi"))
    cut = own.withColumn("bucket", F.explode(F.expr(f"sequence(floor(lo / {bucket}), floor(hi / {bucket}))")))
    both = cut.alias("x").join(cut.alias("y"), (F.col("x.bucket") == F.col("y.bucket")) & F.expr("x.lo <= y.hi AND y.lo <= x.hi"))
    # A pair counts in the first bucket that it shares.
    return both.where(F.col("x.bucket") == F.floor(F.greatest("x.lo", "y.lo") / bucket)).select(F.col("x.nationkey").alias("a"), F.col("y.nationkey").alias("b"))


@query("udf_depth", cells_sql("lowbal", "").rstrip() + _DEPTHS + "SELECT key, depth FROM looked")
def udf_depth(spark: SparkSession, d: str) -> DataFrame:
    """Depths of probes by a vectorised function over the sorted keys: a binary search a batch."""
    table = written(weights(spark, d, "lowbal"), "weights")
    own = table.join(tree_depths(table), "idx").orderBy("idx").toPandas()  # as many rows as the dictionary has keys, which the n^2 program bounds
    model = sent(spark, (own["key"].iloc[1:].to_numpy(np.int64), own["key_depth"].to_numpy(), own["gap_depth"].to_numpy()))

    def depth_of(key: pd.Series) -> pd.Series:
        keys, hits, gaps = opened(model)
        at = np.searchsorted(keys, key.to_numpy(), side="right")
        found = (at > 0) & (keys[np.maximum(at - 1, 0)] == key.to_numpy()) if len(keys) else at > 0
        return pd.Series(np.where(found, hits[at], gaps[at]))

    probes = counts(spark, d, "lowbal")[1]
    return probes.select("key", F.pandas_udf(depth_of, "long")("key").alias("depth"))


@query("saving_balanced", "SELECT family, round(100 * (1 - optimum / greatest(1, cost)), 6) AS saving FROM (SELECT o.family AS family, o.cost AS optimum, b.cost AS cost FROM (" + _OPTIMA + ") o JOIN (" + " UNION ALL ".join(
    f"(SELECT * FROM (WITH RECURSIVE {weights_sql(f)}, nodes AS (SELECT 0::BIGINT AS lo, max(idx)::BIGINT AS hi, 1::BIGINT AS depth FROM wt UNION ALL SELECT CASE WHEN s = 0 THEN lo ELSE (lo + hi - 1) // 2 + 1 END, CASE WHEN s = 0 THEN (lo + hi - 1) // 2 ELSE hi END, depth + 1 FROM nodes, (VALUES (0), (1)) v(s) WHERE lo < hi) "
    f"SELECT '{f}' AS family, sum(CASE WHEN lo = hi THEN g.miss ELSE k.hit END * depth)::BIGINT AS cost FROM nodes LEFT JOIN wt g ON g.idx = lo LEFT JOIN wt k ON lo < hi AND k.idx = (lo + hi - 1) // 2 + 1))" for f in ("nation", "psize", "pnames", "lowbal", "users")) + ") b USING (family))")
def saving_balanced(spark: SparkSession, d: str) -> DataFrame:
    """What the optimal tree saves against the height-balanced one, in per cent of the latter's cost."""

    def rows_of(family: str, w: Weights, best: int) -> list[tuple]:
        keys, gaps = depths_of(lambda a, b: (a + b - 1) // 2, w.n)
        cost = int((keys * w.hit).sum() + (gaps * w.miss).sum())
        return [(family, round(100 * (1 - best / max(1, cost)), 6))]

    return by_families(spark, d, ("nation", "psize", "pnames", "lowbal", "users"), rows_of, "family string, saving double")


# Applications through trees ------------------------------------------------------------------------------
_BIGRAMS = "SELECT prev, key, count(*) AS n FROM (SELECT w[i] AS prev, w[i + 1] AS key FROM (SELECT w, unnest(range(1, len(w))) AS i FROM (SELECT regexp_extract_all(lower(text), '[a-z]+') AS w FROM conversations))) GROUP BY prev, key"


def bigrams(spark: SparkSession, d: str) -> DataFrame:
    """(prev, key, n): words of the conversations by the word before them."""
    w = load(spark, d, "conversations").select(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0)).alias("w"))
    pairs = w.select(F.explode(F.expr("transform(slice(w, 2, greatest(size(w) - 1, 0)), (x, i) -> struct(w[i] AS prev, x AS key))")).alias("b"))
    return pairs.groupBy("b.prev", "b.key").agg(F.count(F.lit(1)).alias("n"))


@query("next_word_prefix", f"SELECT prev, prefix, min(rank) AS first_rank, max(rank) AS last_rank, min((-n, key))[2] AS best, sum(n)::BIGINT AS n FROM (SELECT prev, key, n, key[1:1] AS prefix, row_number() OVER (PARTITION BY prev ORDER BY key) AS rank FROM ({_BIGRAMS})) GROUP BY prev, prefix")
def next_word_prefix(spark: SparkSession, d: str) -> DataFrame:
    """For each previous word and typed letter: the interval of key ranks in the word's tree that the prefix stands for, and the likeliest word in it."""
    own = bigrams(spark, d).withColumn("rank", F.row_number().over(Window.partitionBy("prev").orderBy("key")).cast("bigint")).withColumn("prefix", F.substring("key", 1, 1))
    return own.groupBy("prev", "prefix").agg(F.min("rank").alias("first_rank"), F.max("rank").alias("last_rank"), F.min(F.struct((-F.col("n")).alias("c"), "key")).getField("key").alias("best"), F.sum("n").alias("n"))


@query("next_word_trees")
def next_word_trees(spark: SparkSession, d: str) -> DataFrame:
    """(grp, n, cost): one optimal tree of next words for each previous word."""
    return solved_groups(bigrams(spark, d).select(F.col("prev").alias("grp"), "key", F.col("n").alias("hit")), "grp")


@query("translate_tree")
def translate_tree(spark: SparkSession, d: str, most: int = 500) -> DataFrame:
    """(lang, word, translation, rank, depth, n): one tree a language over its most frequent words; a node holds the word of equal rank in English."""
    c = words(load(spark, d, "documents"), "lang").groupBy("lang", "key").agg(F.count(F.lit(1)).alias("n"))
    top = written(c.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "key"))).where(F.col("r") <= most), "frequent")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        own = pdf.sort_values("key").reset_index(drop=True)
        w = Weights(np.concatenate([[0], own["n"].to_numpy()]), np.zeros(len(own) + 1, np.int64))
        split = solve_windowed(w).split
        keys, _ = depths_of(lambda a, b: int(split[a, b]), w.n)
        return pd.DataFrame({"lang": own["lang"], "word": own["key"], "r": own["r"], "rank": range(1, w.n + 1), "depth": keys[1:], "n": own["n"]})

    trees = top.where("lang <> 'en'").groupBy("lang").applyInPandas(run, "lang string, word string, r int, rank long, depth long, n long")
    return trees.join(top.where("lang = 'en'").select("r", F.col("key").alias("translation")), "r").drop("r")


@query("embedding_keys", "SELECT key, count(*) AS n FROM (SELECT round(embedding[1] * 100)::BIGINT AS key FROM embeddings) GROUP BY key")
def embedding_keys(spark: SparkSession, d: str) -> DataFrame:
    """Hits of numeric keys: the first component in hundredths."""
    return hit_counts(load(spark, d, "embeddings"), F.round(F.get("embedding", F.lit(0)) * 100).cast("bigint"))


@query("clean_vocabulary", f"SELECT key, count(*) AS n FROM (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS key FROM documents JOIN labels USING (doc_id) WHERE quality = 1 AND toxic = 0) GROUP BY key")
def clean_vocabulary(spark: SparkSession, d: str) -> DataFrame:
    """Words of the documents that are labelled good and not toxic."""
    good = load(spark, d, "labels").where("quality = 1 AND toxic = 0").select("doc_id")
    return hit_counts(words(load(spark, d, "documents").join(good, "doc_id")), F.col("key"))
