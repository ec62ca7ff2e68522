"""Tables that cut lineage: written to the folder every executor shares.

The folder is the session's ``spark.checkpoint.dir``. Only where that is unset and all of Spark runs in this process's
machine (``local[...]``) a temporary folder is used instead; on a cluster that is refused.
"""

from __future__ import annotations

import tempfile
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_OWN: dict[str, str] = {}
#: Whether a query's shuffle files are removed at its end.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_dir(spark: SparkSession) -> str:
    """The session's shared folder; a process-wide temporary one only where none is set and Spark is local."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        found = spark.sparkContext.getCheckpointDir()
        base = found.rsplit("/", 1)[0] if found else None
    if not base:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise RuntimeError(f"set spark.checkpoint.dir to a folder that all machines of {master} share")
        if "dir" not in _OWN:
            _OWN["dir"] = tempfile.mkdtemp(prefix="eventpulse-")
        base = _OWN["dir"]
    return base.rstrip("/")


def new_dir(spark: SparkSession, tag: str) -> str:
    """A fresh folder in the session's shared place; it goes when the driver ends."""
    path = f"{shared_dir(spark)}/eventpulse/{tag}-{uuid.uuid4().hex}"
    p, fs = hadoop_path(spark, path)
    fs.mkdirs(p)
    fs.deleteOnExit(p)
    return path


def hadoop_path(spark: SparkSession, path: str):
    """A path and its file system, on the driver's JVM."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p, p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def materialize(df: DataFrame, tag: str, codec: str = "snappy") -> DataFrame:
    """Write ``df`` as a Parquet table in the shared folder and return a scan of it.

    Unlike a block-manager copy the table outlives lost executors. It is removed when
    the driver ends, or earlier by :func:`discard`. The shuffle files of the write go when it ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/eventpulse/{tag}-{uuid.uuid4().hex}"
    kept = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.parquet(path, compression=codec)
    finally:
        spark.conf.set(CLEANUP, kept) if kept is not None else spark.conf.unset(CLEANUP)
    p, fs = hadoop_path(spark, path)
    fs.deleteOnExit(p)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


def discard(df: DataFrame | None) -> None:
    """Delete a table made by :func:`materialize` that no later plan reads."""
    path = getattr(df, "_scratch_path", None)
    if path:
        p, fs = hadoop_path(df.sparkSession, path)
        fs.delete(p, True)


def ship(spark: SparkSession) -> None:
    """Let Python workers import this package when the driver runs from elsewhere.

    On a cluster the package is installed or sent with ``--py-files``; the entry added
    here is then merely an unused search path.
    """
    root = str(Path(__file__).resolve().parents[2])
    env = spark.sparkContext.environment
    if root not in env.get("PYTHONPATH", "").split(":"):
        env["PYTHONPATH"] = ":".join(x for x in (root, env.get("PYTHONPATH", "")) if x)
