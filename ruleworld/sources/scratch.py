"""Intermediate tables in the folder that all executors share.

The folder is ``spark.checkpoint.dir`` of the session. Where that is unset (tests on one machine) a
temporary folder is made and set as checkpoint folder. What is written here goes when the driver ends.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_own: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """URI of a fresh folder below the shared checkpoint folder."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        base = tempfile.mkdtemp(prefix="ruleworld-")
        atexit.register(shutil.rmtree, base, ignore_errors=True)
        base = f"file://{base}"
        spark.sparkContext.setCheckpointDir(base)
    if "://" not in base:
        base = f"file://{base}" if base.startswith("/") else base.replace("file:", "file://", 1)
    where = f"{base}/ruleworld-{uuid.uuid4().hex}"
    if not _own:
        atexit.register(_clean, spark)
    _own.append(where)
    return where


def _clean(spark: SparkSession) -> None:
    try:
        jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
        for where in _own:
            path = jvm.org.apache.hadoop.fs.Path(where)
            path.getFileSystem(conf).delete(path, True)
    except Exception:  # noqa: BLE001  the session may be gone already; leftovers are harmless
        pass


def settle(frame: DataFrame) -> DataFrame:
    """Write a frame to the shared folder and read it back: cuts lineage, survives lost executors."""
    where = shared_dir(frame.sparkSession)
    frame.write.parquet(where)
    return frame.sparkSession.read.schema(frame.schema).parquet(where)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
