"""Tables in the folder that the cluster shares: ``spark.checkpoint.dir``.

Lineage is cut by writing a Parquet table and reading it back; it survives the loss of any executor."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` as it is; only where it is unset on a local master (tests) a temporary
    folder, removed when the process ends."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        base = spark.conf.get("phasewise.tables.dir", None)
        if not base:
            if not spark.conf.get("spark.master", "local").startswith("local"):
                raise ValueError("set spark.checkpoint.dir to a folder that the cluster shares")
            path = tempfile.mkdtemp(prefix="phasewise-")
            atexit.register(shutil.rmtree, path, ignore_errors=True)
            base = "file://" + path
            spark.conf.set("phasewise.tables.dir", base)
    return base.rstrip("/")


def new_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/phasewise-{tag}-{uuid.uuid4().hex}"


def written(df: DataFrame, path: str) -> DataFrame:
    """``df`` written to ``path`` (what a broken attempt left there is replaced) and read back."""
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def stored(df: DataFrame, tag: str) -> DataFrame:
    return written(df, new_path(df.sparkSession, tag))
