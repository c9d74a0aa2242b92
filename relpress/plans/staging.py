"""Written intermediates: iterative plans cut their lineage with tables in the folder that all executors share."""

from __future__ import annotations

import io
import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The session's checkpoint folder; one of our own only where none is set and all tasks run on this machine."""
    sc = spark.sparkContext
    found = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not found:
        if not (sc.master == "local" or sc.master.startswith("local[")):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="relpress-"))
        found = sc.getCheckpointDir()
    return found.rstrip("/")


def drop_at_exit(spark: SparkSession, path: str) -> None:
    """Delete a written intermediate when the session's JVM ends, unless it is deleted before."""
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(p.getParent())


def staged(df: DataFrame, name: str = "stage") -> DataFrame:
    """Write ``df`` and read it back."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/relpress-{uuid.uuid4().hex}/{name}"
    df.write.parquet(path)
    drop_at_exit(spark, path)
    return spark.read.schema(df.schema).parquet(path)


def ship(spark: SparkSession) -> None:
    """Make this package importable in Python workers: sent through the shared folder, unless they find it by themselves.

    Workers find it on PYTHONPATH, or, on a local master, in the folder they were started from.
    """
    sc = spark.sparkContext
    if getattr(sc, "_relpress_shipped", False):
        return
    root = Path(__file__).resolve().parents[2]
    places = [p for p in os.environ.get("PYTHONPATH", "").split(os.pathsep) if p] + ([os.getcwd()] if sc.master.startswith("local[") or sc.master == "local" else [])
    if not any(Path(p).resolve() == root for p in places):
        data = io.BytesIO()
        with zipfile.ZipFile(data, "w", zipfile.ZIP_DEFLATED) as z:
            for f in sorted((root / "relpress").rglob("*.py")):
                z.write(f, f.relative_to(root))
        target = f"{shared_dir(spark)}/relpress-{uuid.uuid4().hex}/relpress-package.zip"
        path = sc._jvm.org.apache.hadoop.fs.Path(target)
        out = path.getFileSystem(sc._jsc.hadoopConfiguration()).create(path)
        out.write(bytearray(data.getvalue()))
        out.close()
        sc.addPyFile(target)
    sc._relpress_shipped = True
