"""Session helpers: cutting lineage, shipping the package, plan sizes."""

from __future__ import annotations

import gc
import os
import re
import tempfile
import uuid
import zipfile

from pyspark.sql import DataFrame, SparkSession


def checkpoint_folder(spark: SparkSession) -> str:
    """The shared folder that the cluster names; one of our own only where none is set (tests)."""
    jsc = spark.sparkContext._jsc.sc()
    if jsc.getCheckpointDir().isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named:
            if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
                raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
            named = tempfile.mkdtemp(prefix="motifmill-checkpoints-")
        spark.sparkContext.setCheckpointDir(named)
    return jsc.getCheckpointDir().get()


def cut(df: DataFrame) -> DataFrame:
    """Materialise df in the shared checkpoint folder and forget how it was made."""
    checkpoint_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def keep(df: DataFrame, name: str) -> DataFrame:
    """df written as a compressed table in the shared folder, and read from there: what cut()
    does, for large results (checkpoints are not compressed)."""
    path = f"{checkpoint_folder(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def sweep(spark: SparkSession) -> None:
    """Let Spark's cleaner drop the shuffle files of results that nothing refers to any more."""
    gc.collect()
    spark._jvm.System.gc()


ARROW_BATCH_BYTES = 4 << 20


def ship(spark: SparkSession) -> None:
    """Give this package to Python workers, which may not see the driver's folders: Spark's
    own file server hands the archive out, no worker reads the path it was made at.

    Also bounds Arrow batches in bytes, unless the session says otherwise: their default
    bound counts rows only, which very long texts outgrow.
    """
    sc = spark.sparkContext
    if spark.conf.get("spark.sql.execution.arrow.maxBytesPerBatch", None) is None:
        spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", ARROW_BATCH_BYTES)
    if getattr(sc, "_motifmill_shipped", False):
        return
    here = os.path.dirname(os.path.abspath(__file__))
    path = os.path.join(tempfile.mkdtemp(prefix="motifmill-"), "motifmill_package.zip")
    with zipfile.ZipFile(path, "w") as out:
        for folder, _, names in os.walk(here):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(folder, name)
                    out.write(full, os.path.relpath(full, os.path.dirname(here)))
    sc.addPyFile(path)
    sc._motifmill_shipped = True


def plan_bytes(df: DataFrame) -> int:
    """Catalyst's estimate of df's size; no job runs."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
