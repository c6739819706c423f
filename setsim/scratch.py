"""Shared intermediate storage.

Operators that read an intermediate result more than once, or that iterate, write it as Parquet below the folder
that the session names in ``spark.checkpoint.dir`` (all executors and the driver share it), and read it back. A
lost executor then costs one re-read. A private folder is made only where the setting is absent and the master is
local (tests, notebooks); on a cluster an absent setting is an error.

The shuffle files behind a written table are removed as soon as it is complete: nothing reads them again. What is
left of the tables is deleted at the end of the Python process.
"""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_MADE: list[Scratch] = []


def scratch_root(spark: SparkSession) -> str:
    """The shared folder of the session; a temporary one for a local master where none is configured."""
    configured = spark.conf.get("spark.checkpoint.dir", None)
    if configured:
        return configured.rstrip("/")
    master = spark.sparkContext.master
    if not (master == "local" or master.startswith("local[")):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    own = getattr(spark, "_setsim_scratch", None)
    if own is None:
        own = "file://" + tempfile.mkdtemp(prefix="setsim-")
        spark._setsim_scratch = own
    return own


@contextlib.contextmanager
def _shuffles_removed(spark: SparkSession):
    """What runs inside leaves no shuffle files; the session's own setting is put back."""
    before = spark.conf.get(_CLEANUP, None)
    spark.conf.set(_CLEANUP, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(_CLEANUP)
        else:
            spark.conf.set(_CLEANUP, before)


class Scratch:
    """Tables of one operator call, each under its own name."""

    def __init__(self, spark: SparkSession, tag: str):
        self.spark = spark
        self.base = f"{scratch_root(spark)}/{tag}-{uuid.uuid4().hex}"
        _MADE.append(self)

    def save(self, df: DataFrame, name: str, *, codec: str | None = None, by: str | None = None) -> DataFrame:
        """Write ``df`` and return a DataFrame that reads what was written; ``by`` gives each value of a column a folder."""
        path = f"{self.base}/{name}"
        with _shuffles_removed(self.spark):
            df.write.parquet(path, partitionBy=by, compression=codec)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, *names: str) -> None:
        """Delete tables that nothing reads any more; without names, all of them."""
        jvm, conf = self.spark._jvm, self.spark._jsc.hadoopConfiguration()
        for path in [f"{self.base}/{name}" for name in names] or [self.base]:
            path = jvm.org.apache.hadoop.fs.Path(path)
            path.getFileSystem(conf).delete(path, True)


@atexit.register
def _clear() -> None:
    for scratch in _MADE:
        with contextlib.suppress(Exception):  # the session may be gone, and its folder with it
            scratch.drop()
