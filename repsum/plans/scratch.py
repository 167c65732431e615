"""Shared scratch storage and worker set-up.

Intermediate tables that several later stages read are written as Parquet below the
folder that the session names in ``spark.checkpoint.dir``. A written table cuts lineage
and survives the loss of any executor. Only where that setting is absent in a single local
process (tests, a local shell) a folder of our own is set; on a cluster its absence is an error.
"""

from __future__ import annotations

import atexit
import os
import uuid

from pyspark.sql import DataFrame, SparkSession

_LOCAL_DEFAULT = "/tmp/checkpoints"
_OPENED: dict[str, SparkSession] = {}


def scratch_root(spark: SparkSession) -> str:
    """Folder for this application's intermediate tables, on storage all executors share."""
    sc = spark.sparkContext
    base = sc.getConf().get("spark.checkpoint.dir")
    if not base:
        if not (sc.master == "local" or sc.master.startswith("local[")):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = f"file://{_LOCAL_DEFAULT}"
        if sc._jsc.sc().getCheckpointDir().isEmpty():
            sc.setCheckpointDir(base)
    root = f"{base.rstrip('/')}/repsum-{sc.applicationId}"
    if root not in _OPENED:
        _OPENED[root] = spark
    return root


def new_path(spark: SparkSession, name: str) -> str:
    return f"{scratch_root(spark)}/{name}-{uuid.uuid4().hex[:12]}"


def materialise(df: DataFrame, name: str, options: dict | None = None) -> DataFrame:
    """Write ``df`` to the shared folder and read it back under the same schema."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.options(**(options or {})).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: Bytes of an Arrow batch on its way to a Python worker; both sides hold one or two at a time.
ARROW_BATCH = 8 << 20


def ship_package(spark: SparkSession) -> None:
    """Let Python workers import this package when it is not installed on them, and keep their batches small."""
    held = spark.conf.get("spark.sql.execution.arrow.maxBytesPerBatch").lower().rstrip("b")
    if held.endswith(("m", "g")) or held.isdigit() and int(held) > ARROW_BATCH:
        spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", ARROW_BATCH)
    here = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    env = spark.sparkContext.environment
    if here not in env.get("PYTHONPATH", "").split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (here, env.get("PYTHONPATH", "")) if x)


@atexit.register
def _sweep() -> None:
    for root, spark in _OPENED.items():
        try:
            sc = spark.sparkContext
            path = sc._jvm.org.apache.hadoop.fs.Path(root)
            path.getFileSystem(sc._jsc.hadoopConfiguration()).delete(path, True)
        except Exception:  # the session has already ended; the folder carries its application id
            pass
