"""Session helpers that work with a session somebody else started."""

from __future__ import annotations

import os
import tempfile
import threading
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_LOCK = threading.Lock()
_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> SparkSession:
    """Send this package to the executors once per application, so that Python
    functions resolve there whatever their working directory is."""
    sc = spark.sparkContext
    with _LOCK:
        if sc.applicationId not in _SHIPPED:
            root = Path(__file__).resolve().parent
            target = os.path.join(tempfile.mkdtemp(prefix="ship"), f"{root.name}_code.zip")
            with zipfile.ZipFile(target, "w") as z:
                for p in sorted(root.rglob("*.py")):
                    z.write(p, p.relative_to(root.parent))
            sc.addPyFile(target)
            _SHIPPED.add(sc.applicationId)
    return spark


def shared_dir(spark: SparkSession) -> str:
    """The reliable folder of this application: the one the cluster names. Where none is named, a local
    master gets one of its own; on a cluster that is an error, as machines share no local folder."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not sc.master.startswith("local"):
            raise RuntimeError("name a folder that all machines share in spark.checkpoint.dir")
        sc.setCheckpointDir(named or os.path.join(tempfile.gettempdir(), "kgflow-checkpoints"))
    return sc._jsc.sc().getCheckpointDir().get()


def settled(df: DataFrame) -> DataFrame:
    """Cut the lineage of df in the shared folder: survives lost executors."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame) -> DataFrame:
    """As settled(), as a compressed table of the shared folder."""
    spark = df.sparkSession
    place = f"{shared_dir(spark)}/table-{uuid.uuid4().hex}"
    df.write.parquet(place)
    return spark.read.schema(df.schema).parquet(place)


def removed(spark: SparkSession, place: str) -> None:
    """Delete a folder that an earlier step wrote and no later one reads."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(place)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def width(spark: SparkSession) -> int:
    """Number of shuffle partitions that the cluster is set to."""
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))
