"""Access to settings of the running session: the shared folder, tables written to it, sizes of plans, code for workers."""

from __future__ import annotations

import tempfile
import threading
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession


_once = threading.RLock()


def shared_dir(spark: SparkSession) -> str:
    """Folder that the driver and all executors share, from ``spark.checkpoint.dir``.

    Where none is set, a folder of this machine is made, but only for a local master: on a cluster it would be another one
    on each executor.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not base:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = getattr(shared_dir, "_own", None) or tempfile.mkdtemp(prefix="navgraph-")
        shared_dir._own = base
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(base)
    return base


def _session_dir(spark: SparkSession) -> str:
    """This application's own folder below the shared one. Hadoop deletes it when the driver's JVM ends."""
    sc = spark.sparkContext
    with _once:
        if not getattr(sc, "_navgraph_dir", None):
            made = f"{shared_dir(spark).rstrip('/')}/navgraph-{uuid.uuid4().hex}"
            path = sc._jvm.org.apache.hadoop.fs.Path(made)
            system = path.getFileSystem(sc._jsc.hadoopConfiguration())
            system.mkdirs(path)
            system.deleteOnExit(path)
            sc._navgraph_dir = made
    return sc._navgraph_dir


def scratch_path(spark: SparkSession, name: str) -> str:
    """A new path below the shared folder."""
    return f"{_session_dir(spark)}/{name}-{uuid.uuid4().hex}"


def discard(spark: SparkSession, path: str) -> None:
    """Deletes a path that scratch_path() gave."""
    if path.startswith(_session_dir(spark) + "/"):
        at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` written once below the shared folder and read back: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def plan_bytes(df: DataFrame) -> int | None:
    """Catalyst's estimate of the size of ``df`` from file sizes, without reading anything; None where it has none."""
    n = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return n if n < 1 << 60 else None


def ship(spark: SparkSession) -> None:
    """Sends this package to the Python workers, once per Spark context, so that they needn't have it installed."""
    sc = spark.sparkContext
    with _once:
        if getattr(sc, "_navgraph_shipped", False):
            return
        root = Path(__file__).resolve().parent
        if root.is_dir():
            target = Path(tempfile.mkdtemp(prefix="navgraph-")) / "navgraph.zip"
            with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
                for p in sorted(root.rglob("*.py")):
                    z.write(p, f"navgraph/{p.relative_to(root)}")
            sc.addPyFile(str(target))
        sc._navgraph_shipped = True
