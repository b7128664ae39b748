"""Written intermediate tables in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_own_dir: str | None = None


def shared_dir(spark: SparkSession) -> str:
    """The session's spark.checkpoint.dir; a temporary folder only where none is set and the session is a local one."""
    global _own_dir
    if named := spark.conf.get("spark.checkpoint.dir", None):
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    if _own_dir is None:
        _own_dir = tempfile.mkdtemp(prefix="poslp-")
    return f"file://{_own_dir}"


def materialise(df: DataFrame, name: str) -> DataFrame:
    path = f"{shared_dir(df.sparkSession)}/poslp/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.written_path = path
    return out


#: Spark keeps shuffle files until the driver collects garbage; with this set they go when the query that wrote them ends.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def cleaned(spark: SparkSession) -> Iterator[None]:
    """Inside, shuffle files are deleted as each query ends, unless the session says itself what to do with them."""
    own = spark.conf.get(CLEANUP, None) is None
    if own:
        spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        if own:
            spark.conf.unset(CLEANUP)


def discard(*tables: DataFrame | None) -> None:
    """Deletes written tables that nothing lazy depends on any more."""
    for df in tables:
        if path := getattr(df, "written_path", None):
            at = df.sparkSession._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(at, True)
