"""Tables written to the folder that driver and executors share."""

from __future__ import annotations

import atexit
import shutil
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Removes a write's shuffle files when it has ended; what is written needs them no more. A setting of the session.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
#: Settings during a write: that, and small batches to and from Python, so that many long values at once take no memory.
DURING = {CLEANUP: "true", "spark.sql.execution.arrow.maxBytesPerBatch": "8m"}
_OWN: dict[str, str] = {}


def scratch_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session. Where that is unset, as in tests: a folder in the warehouse, which a cluster shares
    too; it is removed when this process ends, if it is a local one. The session's own checkpoint folder is left as it is."""
    sc = spark.sparkContext
    named = sc.getConf().get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not named:
        if sc.applicationId not in _OWN:
            _OWN[sc.applicationId] = f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/scratch-{uuid.uuid4().hex}"
            if _OWN[sc.applicationId].startswith(("file:", "/")):
                atexit.register(shutil.rmtree, "/" + _OWN[sc.applicationId].removeprefix("file:").lstrip("/"), ignore_errors=True)
        named = _OWN[sc.applicationId]
    return named.rstrip("/")


def written(df: DataFrame, name: str, path: str | None = None) -> DataFrame:
    """df, written once and read back: its lineage is cut and a lost executor loses nothing."""
    spark = df.sparkSession
    path = path or f"{scratch_dir(spark)}/{name}-{uuid.uuid4().hex}"
    before = {k: spark.conf.get(k) for k in DURING}
    try:
        for k, v in DURING.items():
            spark.conf.set(k, v)
        df.write.mode("overwrite").parquet(path)
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)
    out = spark.read.schema(df.schema).parquet(path)
    out.scratch_path = path
    return out


def remove(spark: SparkSession, path: str) -> None:
    """Deletes a folder, if it is there."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def forget(*tables: DataFrame) -> None:
    """Deletes tables made by written(), once nothing reads them any more."""
    for df in tables:
        remove(df.sparkSession, df.scratch_path)
