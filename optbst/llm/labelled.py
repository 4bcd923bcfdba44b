"""A bounded sample of labelled documents for fitting classifiers."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import written
from .common import fold_of, two_columns

#: Most labelled rows that a classifier is fitted on.
SAMPLE_ROWS = 20_000


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, modulus: int, held_out: int, key: str = "doc_id", text: str = "text", rows: int = SAMPLE_ROWS) -> DataFrame:
    """(doc_id, text, label) of at most ``rows`` labelled documents outside the held-out fold.

    Rows with a null id or label are left out; an id with several labels has the largest. The sample is
    the ids with the smallest hashes, so it is the same in every run. Only these ids are broadcast, so
    the broadcast has a proven bound and the texts are never shuffled.
    """
    own = labels.select(F.col(key).alias("doc_id"), F.col(label).cast("int").alias("label")).where("doc_id IS NOT NULL AND label IS NOT NULL")
    ids = own.where(fold_of(F.col("doc_id"), modulus) != held_out).groupBy("doc_id").agg(F.max("label").alias("label"))
    ids = written(ids.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows), "sample-ids")
    return two_columns(docs, key, text).join(F.broadcast(ids), "doc_id")


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))
