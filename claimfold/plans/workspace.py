"""Tables in the folder that the session names in spark.checkpoint.dir: lineage ends there.

Every executor can reach that folder, so a lost executor costs its running tasks only.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_written: list[tuple[SparkSession, str]] = []


def workspace(spark: SparkSession) -> str:
    """The shared folder; a local one only where the session has none (tests)."""
    have = spark.conf.get("spark.checkpoint.dir", None)
    if not have:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        have = "file://" + tempfile.mkdtemp(prefix="claimfold-")
        spark.conf.set("spark.checkpoint.dir", have)
    return have.rstrip("/")


def partitions(df: DataFrame) -> int:
    """The session's shuffle partitions, for steps that make few bytes into much work: what is named isn't merged at run time."""
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def settle(df: DataFrame, name: str) -> DataFrame:
    """Write df into the shared folder and read it back."""
    spark = df.sparkSession
    path = f"{workspace(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _written.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


def release(df: DataFrame) -> None:
    """Delete a settled table that nothing will read again."""
    for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        for spark, known in list(_written):
            if path.split(":", 1)[-1].lstrip("/") == known.split(":", 1)[-1].lstrip("/"):
                _delete(spark, known)
                _written.remove((spark, known))


def _delete(spark: SparkSession, path: str) -> None:
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


@atexit.register
def _sweep() -> None:
    """Remove what this process has written, where the session still lives."""
    for spark, path in _written:
        try:
            _delete(spark, path)
        except Exception:  # the gateway is gone at exit; nothing else to do
            return
