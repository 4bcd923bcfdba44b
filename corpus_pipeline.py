"""A corpus pipeline of text operators: quality, exact and near copies, benchmark passages, packing.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; each works on all that its
predecessor kept. All but the last keep the columns of ``documents``. A decision holds for a row, not
for its id: ids may repeat or be null.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from optbst.llm import decontaminate, exact_dedup, near_dedup, packing, quality
from optbst.llm.common import load
from optbst.llm.queries import tokenizer_path
from optbst.storage import drop_since, made, written


def _read_once(docs: DataFrame) -> bool:
    """Whether ``docs`` is nothing but files of one source, each listed once, so that places in files are keys."""
    plan = docs._jdf.queryExecution().analyzed()
    if plan.nodeName() != "LogicalRelation" or plan.relation().getClass().getSimpleName() != "HadoopFsRelation":
        return False
    files = list(plan.relation().location().inputFiles())
    return len(files) == len(set(files))


def _keyed(docs: DataFrame) -> tuple[DataFrame, str]:
    """``docs`` with a key of its own for each row, and the name of that column.

    Ids may repeat or be null. The key must be the same when the rows are read again: in files it is the
    number of the file and the place in it; anything else, also a source read twice, is written first.
    """
    row = "_row"
    while row in (c.lower() for c in docs.columns):
        row += "_"
    if not _read_once(docs):
        return written(docs.withColumn(row, F.monotonically_increasing_id()), "keyed"), row
    path, at = row + "path", row + "at"
    paths = sorted(r[0] for r in docs.select("_metadata.file_path").distinct().collect())
    files = docs.sparkSession.createDataFrame([(x, k << 40) for k, x in enumerate(paths)], f"{path} string, {row} long")
    placed = docs.select("*", F.col("_metadata.file_path").alias(path), F.col("_metadata.row_index").alias(at)).join(F.broadcast(files), path)
    return placed.select(*docs.columns, (F.col(row) + F.col(at)).alias(row)), row


def _keep(docs: DataFrame, row: str, kept: DataFrame) -> DataFrame:
    """Rows of ``docs`` whose key is in ``kept(row)``, without the key."""
    return docs.join(kept, row, "left_semi").drop(row)


def _by_id(row: str) -> Column:
    """Order of rows that may stand for each other: the smallest id, null ids last, then the row's key."""
    return F.struct(F.col("doc_id").isNull().alias("no_id"), F.col("doc_id").alias("id"), F.col(row).alias("row"))


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier predicts to be good."""
    docs, row = _keyed(docs)
    return _keep(docs, row, quality.quality_scores(docs, load(spark, sf_dir, "labels"), carry=(row,)).where("predicted = 1").select(row))


def without_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of texts that are equal without white space, also of rows that repeat an id."""
    docs, row = _keyed(docs)
    verdicts = exact_dedup.exact_duplicates(docs.select(_by_id(row).alias("by_id"), "text"), key="by_id")
    return _keep(docs, row, verdicts.where("kept").select(F.col("doc_id.row").alias(row)))


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each component of near copies (five words, similarity 0.8 or more): that of the smallest id."""
    docs, row = _keyed(docs)
    verdicts = near_dedup.near_duplicates(docs, key=row, shingle=5, percent=80).select(F.col("doc_id").alias(row), "component_id")
    best = verdicts.join(docs.select("doc_id", row), row).groupBy("component_id").agg(F.min(_by_id(row)).alias("best"))
    return _keep(docs, row, best.select(F.col("best.row").alias(row)))


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that benchmark passages do not contaminate."""
    docs, row = _keyed(docs)
    return _keep(docs, row, decontaminate.contamination(docs, load(spark, sf_dir, "benchmark"), key=row).where("NOT contaminated").select(F.col("doc_id").alias(row)))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents in sequences of 4096 tokens."""
    return packing.best_fit_packing(docs, tokenizer_path())


STAGES = [
    ("quality", good_quality),
    ("exact copies", without_copies),
    ("near copies", without_near_copies),
    ("benchmark", without_benchmark),
    ("packing", packed),
]

#: The classifier and the tokenizer have no SQL form; tests compare stages with brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order on the table ``documents``, each written and read again; what a stage wrote on its way then goes."""
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        mark = made(spark)
        docs = written(stage(spark, docs, sf_dir), "stage-" + name.replace(" ", "-"))
        drop_since(spark, mark, but_last=1)
    return STAGES[-1][1](spark, docs, sf_dir)
