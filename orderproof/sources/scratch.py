"""Tables written down between steps: lineage is cut in the folder that all executors share."""

from __future__ import annotations

import atexit
import contextlib
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def folder(spark: SparkSession) -> str:
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):  # each machine of a cluster would have a folder of its own
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        root = tempfile.mkdtemp(prefix="orderproof-")
        spark.sparkContext.setCheckpointDir(root)
    return str(root).rstrip("/")


def _delete(spark: SparkSession, path: str) -> None:
    with contextlib.suppress(Exception):
        p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


_scopes: list[list[str]] = []  # paths of the tables made in each open scope, innermost last


def written(df: DataFrame) -> DataFrame:
    """df as a Parquet table, removed when the scope it is made in closes, or when the driver ends."""
    path = f"{folder(df.sparkSession)}/step-{uuid.uuid4().hex}"
    if _scopes:
        _scopes[-1].append(path)
    atexit.register(_delete, df.sparkSession, path)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@contextlib.contextmanager
def scope(spark: SparkSession):
    """Tables written inside go at its end, but for what the function it gives returns: a result as a table of the scope around."""
    own: list[str] = []
    _scopes.append(own)

    def kept(df: DataFrame) -> DataFrame:
        _scopes.pop()  # scopes close in the order they were opened, so this one is the innermost
        try:
            return written(df)
        finally:
            _scopes.append(own)

    try:
        yield kept
    finally:
        _scopes.pop()
        for path in own:
            _delete(spark, path)
