"""The registered queries of the text operators, each over its whole table, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import context_tree, decontaminate, exact_dedup, html_extract, license_scan, near_dedup, packing, quality, secret_scan, toxicity
from .common import LOWER, UPPER, load


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return context_tree.language_model_scores(load(spark, sf_dir, "documents"))


def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_duplicates(load(spark, sf_dir, "documents"))


def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.license_scan(load(spark, sf_dir, "documents")).drop("placements")


def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contamination(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark")).drop("items", "spans", "near")


def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity_scores(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels")).drop("passages")


def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(load(spark, sf_dir, "documents"), shingle=3, percent=85).drop("n_class")


def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.best_fit_packing(load(spark, sf_dir, "documents"), tokenizer_path())


def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_scores(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels")).drop("log_odds")


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.extract_main_text(load(spark, sf_dir, "pages"))


def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.secret_scan(load(spark, sf_dir, "documents")).drop("secrets", "n_markov")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_context_tree_scores": op1,
    "op2_exact_dedup": op2,
    "op3_license_scan": op3,
    "op4_decontamination": op4,
    "op5_toxic_segments": op5,
    "op6_near_dedup": op6,
    "op7_packing": op7,
    "op8_quality": op8,
    "op9_html_text": op9,
    "op10_secret_scan": op10,
}

_WORDS = rf"regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

ORACLE_SQL: dict[str, str] = {
    "op2_exact_dedup": r"""
WITH t AS (SELECT doc_id, length(coalesce(text, '')) AS points, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', '', 'g') AS norm FROM documents)
SELECT doc_id, first_value(doc_id) OVER w AS keep_id, count(*) OVER (PARTITION BY norm) AS group_size,
  doc_id = first_value(doc_id) OVER w AS kept, sha256(norm) AS text_sha256
FROM t WINDOW w AS (PARTITION BY norm ORDER BY points DESC, doc_id)
""",
    "op4_decontamination": rf"""
WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
b AS (SELECT item_id, {_WORDS} AS w FROM benchmark),
bw AS (SELECT DISTINCT item_id, least(len(w), 13) AS n, array_to_string(w[i : i + 12], ' ') AS g
       FROM (SELECT item_id, w, unnest(range(1, greatest(1, len(w) - 12) + 1)) AS i FROM b WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT doc_id, n, i, array_to_string(w[i : i + n - 1], ' ') AS g
       FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, sizes WHERE len(w) >= n)),
m AS (SELECT doc_id, i, dw.n AS n, item_id FROM dw JOIN bw ON dw.n = bw.n AND dw.g = bw.g),
hit AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM (SELECT DISTINCT doc_id, i, n FROM m)) GROUP BY doc_id),
items AS (SELECT doc_id, count(DISTINCT item_id) AS n_items, string_agg(DISTINCT item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS ids FROM m GROUP BY doc_id),
terms AS (SELECT item_id, word, min(i) AS first FROM (SELECT item_id, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS i FROM b) GROUP BY item_id, word),
places AS (SELECT doc_id, word, i FROM (SELECT doc_id, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS i FROM d) WHERE word IN (SELECT word FROM terms)),
often AS (SELECT word, count(*) AS n FROM places GROUP BY word),
rare AS (SELECT item_id, word, count(*) OVER (PARTITION BY item_id) AS k FROM (SELECT item_id, terms.word AS word, row_number() OVER (PARTITION BY item_id ORDER BY coalesce(n, 0), first) AS r FROM terms LEFT JOIN often ON often.word = terms.word) WHERE r <= 4),
stands AS (SELECT doc_id, item_id, k, rare.word AS word, i FROM rare JOIN places ON places.word = rare.word),
latest AS (SELECT x.doc_id, x.item_id, x.k, x.i AS stop, y.word, max(y.i) AS i FROM stands x JOIN stands y ON y.doc_id = x.doc_id AND y.item_id = x.item_id AND y.i <= x.i AND x.i - y.i < 20 GROUP BY ALL),
near AS (SELECT doc_id, count(DISTINCT item_id) AS n_near FROM (SELECT doc_id, item_id, stop FROM latest GROUP BY doc_id, item_id, k, stop HAVING count(*) = k) GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items, sha256(coalesce(ids, '')) AS items_sha256,
  coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated, coalesce(n_near, 0)::BIGINT AS n_near
FROM d LEFT JOIN hit USING (doc_id) LEFT JOIN items USING (doc_id) LEFT JOIN near USING (doc_id)
""",
    "op6_near_dedup": rf"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, hash(array_to_string(w[i : i + 2], ' ')) AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(1, len(w) - 2) + 1)) AS i FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
e AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 85 * (x.n + y.n - c)),
both_ways AS (SELECT a, b FROM e UNION ALL SELECT b, a FROM e),
reach AS (SELECT doc_id, doc_id AS r FROM d UNION SELECT reach.doc_id, both_ways.b FROM reach JOIN both_ways ON both_ways.a = reach.r),
c AS (SELECT doc_id, min(r) AS component_id FROM reach GROUP BY doc_id)
SELECT doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, component_id, doc_id = component_id AS kept FROM c LEFT JOIN n USING (doc_id)
""",
}
