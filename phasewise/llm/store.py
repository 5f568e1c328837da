"""Intermediate tables in the shared folder of the cluster.

Lineage is cut by writing a Parquet table below ``spark.checkpoint.dir`` and
reading it back: unlike cached or locally checkpointed blocks, such a table
survives the loss of any executor.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import threading
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_LOCAL = threading.local()


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors share.

    The session's ``spark.checkpoint.dir`` is used as it is.  Only where it is unset on a
    local master (tests) a temporary folder is made, kept in the session's settings and removed
    when the process ends.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        base = spark.conf.get("phasewise.shared.dir", None)
        if not base:
            if not spark.conf.get("spark.master", "local").startswith("local"):
                raise ValueError("set spark.checkpoint.dir to a folder that the cluster shares")
            path = tempfile.mkdtemp(prefix="phasewise-")
            atexit.register(shutil.rmtree, path, ignore_errors=True)
            base = "file://" + path
            spark.conf.set("phasewise.shared.dir", base)
    return base.rstrip("/")


def new_path(spark: SparkSession, tag: str) -> str:
    path = f"{shared_dir(spark)}/phasewise-{tag}-{uuid.uuid4().hex}"
    getattr(_LOCAL, "made", []).append(path)
    return path


def stored(df: DataFrame, tag: str, **options) -> DataFrame:
    """Writes ``df`` once and returns the written table."""
    spark = df.sparkSession
    path = new_path(spark, tag)
    df.write.options(**options).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def delete(spark: SparkSession, paths: list[str]) -> None:
    for path in paths:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


@contextmanager
def stage(docs: DataFrame) -> Iterator[None]:
    """One stage of a pipeline whose stages' results are written and read again.

    The tables that the stage before made in this thread go as the next stage begins: its result,
    ``docs``, is a written table then.  They stay where ``docs`` is not read from files, or is read
    from them."""
    files = docs.inputFiles()
    old = [p for p in getattr(_LOCAL, "done", []) if files and not any(p.rsplit("/", 1)[1] in f for f in files)]
    delete(docs.sparkSession, old)
    kept = [p for p in getattr(_LOCAL, "done", []) if p not in old]
    _LOCAL.made = []
    try:
        yield
    finally:
        _LOCAL.done = kept + _LOCAL.made
        del _LOCAL.made


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
