"""Session helpers: local sessions, worker import path, and tables that cut lineage."""

from __future__ import annotations

import atexit
import gc
import os
import shutil
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

ROOT = str(Path(__file__).resolve().parent.parent)


def local_session(cores: str | int = "*", shuffle_partitions: int = 8, memory: str = "8g") -> SparkSession:
    """A session for tests and benches; a cluster brings its own."""
    return (
        SparkSession.builder.master(f"local[{cores}]").appName("mlcurate")
        .config("spark.sql.shuffle.partitions", str(shuffle_partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", memory)
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.execution.arrow.pyspark.enabled", "true")
        .getOrCreate()
    )


#: Rows and bytes of an Arrow batch; the default of ten thousand long texts fills workers for nothing.
ARROW_ROWS, ARROW_BYTES = 1000, 8 << 20


def prepare(spark: SparkSession) -> SparkSession:
    """Let Python workers import this package, whatever the driver's own path looks like, and send them texts in small batches."""
    if spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch", "10000") == "10000":
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(ARROW_ROWS))
        spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(ARROW_BYTES))
    env = spark.sparkContext.environment
    if ROOT not in env.get("PYTHONPATH", "").split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (ROOT, env.get("PYTHONPATH", "")) if x)
    return spark


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster shares for intermediate tables (spark.checkpoint.dir); a temporary one only where all runs on this machine."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        own = tempfile.mkdtemp(prefix="mlcurate-")
        atexit.register(shutil.rmtree, own, ignore_errors=True)
        named = f"file://{own}"
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(named)
    return named.rstrip("/")


_FOLDERS: dict[str, str] = {}


def _delete(jvm, conf, path: str) -> None:
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(conf).delete(at, True)


def _delete_quietly(jvm, conf, path: str) -> None:
    try:
        _delete(jvm, conf, path)
    except Exception:  # noqa: BLE001  the virtual machine may be gone before this process ends
        pass


def new_path(spark: SparkSession, name: str) -> str:
    """A new place below this application's own part of the shared folder, which goes when the driver's process ends."""
    app = spark.sparkContext.applicationId
    if app not in _FOLDERS:
        _FOLDERS[app] = f"{shared_dir(spark)}/mlcurate-{app}-{uuid.uuid4().hex[:8]}"
        atexit.register(_delete_quietly, spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration(), _FOLDERS[app])
    return f"{_FOLDERS[app]}/{name}-{uuid.uuid4().hex}"


def settle(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back: lineage ends there, and a lost executor costs nothing."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.settled_at = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete settled tables that nothing reads any more: all that was made from them is itself settled."""
    for t in tables:
        if path := getattr(t, "settled_at", None):
            _delete(t.sparkSession.sparkContext._jvm, t.sparkSession.sparkContext._jsc.hadoopConfiguration(), path)


def release(spark: SparkSession) -> None:
    """Let go of the shuffle files behind tables that are written by now; without a collection on the driver they stay on the executors' disks."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()
