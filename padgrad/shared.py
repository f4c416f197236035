"""Tables written in the cluster's shared folder to cut lineage.

The folder is the one the session names in ``spark.checkpoint.dir``. Where that is unset, a
session on one machine uses its temporary folder; a session on a cluster is refused.
"""

from __future__ import annotations

import contextlib
import contextvars
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """URI of the folder that the driver and all executors share."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = f"file://{tempfile.gettempdir()}/checkpoints"
    return found.rstrip("/")


#: Paths given out to this session, for ``clean_up``.
_given: list[tuple[str, str]] = []


def fresh_path(spark: SparkSession, tag: str) -> str:
    path = f"{shared_root(spark)}/padgrad/{tag}-{uuid.uuid4().hex}"
    _given.append((spark.sparkContext.applicationId, path))
    return path


def clean_up(spark: SparkSession) -> int:
    """Deletes everything that this session wrote through ``fresh_path``; to be called when its results have been read. Gives the number of paths."""
    own = [p for app, p in _given if app == spark.sparkContext.applicationId]
    for path in own:
        drop_path(spark, path)
    _given[:] = [x for x in _given if x[1] not in set(own)]
    return len(own)


#: Paths written within the innermost open ``scratch`` block of this thread.
_open_block: contextvars.ContextVar[list[str] | None] = contextvars.ContextVar("open_block", default=None)


@contextlib.contextmanager
def scratch(spark: SparkSession):
    """Tables that ``written`` makes in the block are deleted at its end; what should stay goes to ``stored``."""
    paths: list[str] = []
    before = _open_block.set(paths)
    try:
        yield
    finally:
        _open_block.reset(before)
        for path in paths:
            drop_path(spark, path)


def stored(df: DataFrame, tag: str) -> DataFrame:
    """Like ``written``, but kept by an enclosing ``scratch`` block."""
    path = fresh_path(df.sparkSession, tag)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def written(df: DataFrame, tag: str) -> DataFrame:
    """``df`` written as a Parquet table in the shared folder and read back.

    The result no longer depends on executors' memory or shuffle files, so a lost
    executor costs nothing that was written.
    """
    path = fresh_path(df.sparkSession, tag)
    if (block := _open_block.get()) is not None:
        block.append(path)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def drop_path(spark: SparkSession, path: str) -> None:
    """Deletes a folder through Spark's own file system layer."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
