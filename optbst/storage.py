"""Reliable intermediate tables in the folder that the cluster shares.

Iterative plans cut their lineage by writing a table and reading it again. The folder is
``spark.checkpoint.dir`` of the running session; only a local session (tests, a laptop) may leave it
unset and then gets a temporary folder, as executors elsewhere could not read each other's disks.
Written tables outlive lost executors. ``drop_since`` removes those that a finished step no longer
needs; in a cluster's folder what is left stays until the folder is cleaned.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_OWN: dict[str, str] = {}
_MADE: dict[str, list[str]] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder for intermediate tables of this session."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    app = spark.sparkContext.applicationId
    if app not in _OWN:
        _OWN[app] = tempfile.mkdtemp(prefix="optbst-")
        atexit.register(shutil.rmtree, _OWN[app], ignore_errors=True)
    return _OWN[app]


def new_path(spark: SparkSession, name: str) -> str:
    """A path for a new table, remembered for ``drop_since``."""
    own = _MADE.setdefault(spark.sparkContext.applicationId, [])
    own.append(f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}")
    return own[-1]


def written(df: DataFrame, name: str, *partition_by: str, options: dict[str, object] | None = None) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and return the table read back."""
    spark = df.sparkSession
    path = new_path(spark, name)
    writer = df.write.options(**(options or {}))
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def made(spark: SparkSession) -> int:
    """How many tables this session has written: a mark for ``drop_since``."""
    return len(_MADE.get(spark.sparkContext.applicationId, ()))


def drop_since(spark: SparkSession, mark: int, but_last: int = 0) -> None:
    """Remove the tables begun after ``mark``, but for the last ``but_last`` of them.

    Only for tables that no later plan reads: the results made from them must have been written.
    """
    own, jvm = _MADE.get(spark.sparkContext.applicationId, []), spark.sparkContext._jvm
    conf, end = spark._jsparkSession.sessionState().newHadoopConf(), len(own) - but_last
    for path in own[mark:end]:
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(conf).delete(at, True)
    own[mark:end] = []
