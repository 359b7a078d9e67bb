"""Tables that cut lineage, written to the folder all executors share.

The folder is the one the cluster names in ``spark.checkpoint.dir``.  Only where that is unset (tests on one machine)
a temporary folder is made and set.
"""

from __future__ import annotations

import sys
import tempfile
import types
import uuid

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def worker_cache() -> dict:
    """What a Python worker keeps between tasks (loaded vocabularies); never pickled."""
    return sys.modules.setdefault("_worker_cache", types.ModuleType("_worker_cache")).__dict__


def scratch_root(spark: SparkSession) -> str:
    """URI of the shared folder; never a machine-local one when the session names a folder."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    context = spark.sparkContext
    held = context._jsc.sc().getCheckpointDir()
    if held.isDefined():
        return str(held.get()).rstrip("/")
    made = "file://" + tempfile.mkdtemp(prefix="signedcluster-")
    context.setCheckpointDir(made)
    return str(context._jsc.sc().getCheckpointDir().get()).rstrip("/")


def new_path(spark: SparkSession, label: str) -> str:
    return f"{scratch_root(spark)}/{label}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, label: str = "table") -> DataFrame:
    """Write ``df`` as Parquet to the shared folder and return the frame that reads it.

    Unlike a local checkpoint, what is read back survives the loss of any executor, has column pruning, and has a size
    that the optimizer knows when it picks joins.
    """
    spark = df.sparkSession
    path = new_path(spark, label)
    df.write.parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    back.shared_path = path
    return back


def measured(df: DataFrame, label: str, *values) -> tuple[DataFrame, dict]:
    """:func:`materialize`, and aggregates (aliased columns; the number of rows as ``rows``) that the same job takes of what
    it writes, so that no other job reads it again for them."""
    seen = Observation()
    back = materialize(df.observe(seen, F.count(F.lit(1)).alias("rows"), *values), label)
    return back, seen.get


def discard(df: DataFrame | None) -> None:
    """Delete the files of a frame made by :func:`materialize` that nothing reads any more."""
    path = getattr(df, "shared_path", None)
    if path is None:
        return
    session = df.sparkSession
    target = session._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(session._jsc.hadoopConfiguration()).delete(target, True)
