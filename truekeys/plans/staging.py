"""Intermediate tables in the cluster's shared folder: they cut lineage and survive lost executors."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

#: Open scratch contexts: the paths that each has to delete.
_OPEN: list[list[str]] = []


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; without it, a folder of our own on local masters, as in tests, else an error.

    A machine-local folder on a cluster would scatter a table's files over the executors.
    """
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        folder = getattr(spark, "_truekeys_folder", None)
        if folder is None:
            folder = spark._truekeys_folder = "file://" + tempfile.mkdtemp(prefix="truekeys-")
    return folder.rstrip("/")


def staged(df: DataFrame) -> DataFrame:
    """df written as a table in the shared folder and read again."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/staged-{uuid.uuid4().hex}"
    for paths in _OPEN:
        paths.append(path)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._staged_path = path
    return out


def _delete(spark: SparkSession, path: str) -> None:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def discard(*tables: DataFrame) -> None:
    """Deletes staged tables that nothing reads any more, such as an earlier round of a loop; others are left alone."""
    for t in tables:
        path = getattr(t, "_staged_path", None)
        if path:
            _delete(t.sparkSession, path)


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Deletes at its end whatever was staged inside; write the results that are to stay before that."""
    own: list[str] = []
    _OPEN.append(own)
    try:
        yield
    finally:
        _OPEN[:] = [paths for paths in _OPEN if paths is not own]
        for path in own:
            _delete(spark, path)
