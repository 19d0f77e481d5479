"""Tables in the folder that driver and executors share, and what is cut off there."""

from __future__ import annotations

import atexit
import contextlib
import shutil
import tempfile
import threading
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

_local_dir: str | None = None


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share (``spark.checkpoint.dir``).

    Where the setting is absent, as in tests on one machine, a temporary folder
    serves; a session on a cluster without the setting is refused.
    """
    global _local_dir
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    if _local_dir is None:
        _local_dir = tempfile.mkdtemp(prefix="binsketch-")
        atexit.register(shutil.rmtree, _local_dir, ignore_errors=True)
    return f"file://{_local_dir}"


def fresh_path(spark: SparkSession, what: str) -> str:
    """A new place in this application's part of the shared folder."""
    return f"{shared_dir(spark)}/binsketch-{spark.sparkContext.applicationId}/{what}-{uuid.uuid4().hex}"


def written(df: DataFrame, what: str) -> DataFrame:
    """Cut lineage: the rows as a table in the shared folder, read again.

    It goes with the ``scratch`` block that this thread is in, else when the application ends.
    """
    spark = df.sparkSession
    path = fresh_path(spark, what)
    df.write.parquet(path)
    blocks = _blocks()
    if blocks:
        blocks[-1].paths.append(path)
    else:
        _last(spark)
    out = spark.read.schema(df.schema).parquet(path)
    out._written_at = path
    return out


def remove(spark: SparkSession, path: str) -> None:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


_ends: set[str] = set()


def _last(spark: SparkSession) -> None:
    """What outlives all blocks goes at the end of the process, if the session is still there."""
    folder = f"{shared_dir(spark)}/binsketch-{spark.sparkContext.applicationId}"
    if folder in _ends:
        return
    _ends.add(folder)

    def end() -> None:
        with contextlib.suppress(Exception):
            if spark.sparkContext._jsc is not None:
                remove(spark, folder)

    atexit.register(end)


class Scratch:
    """Tables written within a ``scratch`` block; all but those of ``keep`` go at its end."""

    def __init__(self):
        self.paths: list[str] = []

    def keep(self, df: DataFrame) -> DataFrame:
        """A table made by ``written``: it belongs to the block around this one."""
        self.paths.remove(df._written_at)
        blocks = _blocks()
        if len(blocks) > 1:
            blocks[-2].paths.append(df._written_at)
        else:
            _last(df.sparkSession)
        return df


_local = threading.local()


def _blocks() -> list[Scratch]:
    """The open blocks of this thread: queries that run beside each other don't touch each other's tables."""
    if not hasattr(_local, "blocks"):
        _local.blocks = []
    return _local.blocks


@contextlib.contextmanager
def scratch(spark: SparkSession) -> Iterator[Scratch]:
    """Intermediate tables take room in the shared folder only until their consumers are written."""
    own = Scratch()
    _blocks().append(own)
    try:
        yield own
    finally:
        _blocks().remove(own)
        for path in own.paths:
            remove(spark, path)
