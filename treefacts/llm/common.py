"""Helpers shared by the operators: reading, shared folders, shipping the package to workers."""

from __future__ import annotations

import atexit
import gc
import os
import shutil
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

ROOT = Path(__file__).resolve().parents[2]
_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Makes this package importable on the workers where neither PYTHONPATH nor the working folder does."""
    known = {os.path.realpath(p) for p in os.environ.get("PYTHONPATH", "").split(os.pathsep) if p}
    app = spark.sparkContext.applicationId
    if str(ROOT) in known | {os.path.realpath(os.getcwd())} or app in _shipped:
        return
    _shipped.add(app)
    folder = Path(tempfile.mkdtemp(prefix="treefacts"))
    atexit.register(shutil.rmtree, folder, True)
    with zipfile.ZipFile(folder / "treefacts.zip", "w") as z:
        for p in (ROOT / "treefacts").rglob("*.py"):
            z.write(p, p.relative_to(ROOT))
    spark.sparkContext.addPyFile(str(folder / "treefacts.zip"))


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir; a temporary one only where that is unset."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        folder = tempfile.mkdtemp(prefix="treefacts-shared")
        atexit.register(shutil.rmtree, folder, True)
        spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


def new_folder(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Writes df as Parquet in the shared folder and reads it back: lineage ends there and lost executors cost nothing."""
    folder = new_folder(df.sparkSession, name)
    df.write.parquet(folder)
    out = df.sparkSession.read.schema(df.schema).parquet(folder)
    out._treefacts_folder = folder
    return out


def discard(*tables: DataFrame | None) -> None:
    """Deletes what materialise() wrote, once nothing reads it any more."""
    for df in tables:
        folder = getattr(df, "_treefacts_folder", None)
        if folder:
            sc = df.sparkSession.sparkContext
            path = sc._jvm.org.apache.hadoop.fs.Path(folder)
            path.getFileSystem(sc._jsc.hadoopConfiguration()).delete(path, True)


def free(spark: SparkSession) -> None:
    """Lets Spark delete the shuffle files of tables that are out of use: it does when the driver has collected garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def id_type(df: DataFrame, column: str) -> str:
    return df.schema[column].dataType.simpleString()
