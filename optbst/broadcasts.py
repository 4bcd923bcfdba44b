"""Objects of this package in broadcasts.

A broadcast pickles classes by reference, so workers that have no copy of the package could not open it;
functions travel by value. Here an object is pickled as functions are, and opened once a worker.
"""

from __future__ import annotations

import pickle

from pyspark import cloudpickle
from pyspark.core.broadcast import Broadcast
from pyspark.sql import SparkSession


def sent(spark: SparkSession, thing: object) -> Broadcast:
    """A broadcast of ``thing`` with the code of its class; the caller bounds its size."""
    return spark.sparkContext.broadcast(cloudpickle.dumps(thing))


def opened(broadcast: Broadcast) -> object:
    """The object of a broadcast made by ``sent``: one for all tasks of a worker process."""
    if not hasattr(broadcast, "_opened"):
        broadcast._opened = pickle.loads(broadcast.value)
    return broadcast._opened
