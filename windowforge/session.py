"""Shared state between rounds: written to the cluster's checkpoint folder and read again, so lineage ends and work resumes."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from collections.abc import Callable
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

PACKAGE = Path(__file__).resolve().parent
#: Lists of the paths made since each open ``distilled`` began, innermost last.
_OPEN: list[list[str]] = []


def state_dir(spark: SparkSession) -> str:
    """The cluster's checkpoint folder; a temporary one only where no cluster names any."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = held.get() if held.isDefined() else None
    if not base:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="windowforge-")
        spark.sparkContext.setCheckpointDir(base)
    return base.rstrip("/")


def fresh_path(spark: SparkSession, label: str) -> str:
    """A new path in the state folder; it goes when the ``distilled`` around it ends."""
    path = f"{state_dir(spark)}/{label}-{uuid.uuid4().hex}"
    if _OPEN:
        _OPEN[-1].append(path)
    return path


def settled(df: DataFrame, label: str) -> DataFrame:
    """A stage written as Parquet in the state folder, and read back: lineage ends there and lost executors cost nothing."""
    path = fresh_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def remove(spark: SparkSession, path: str) -> None:
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)


def distilled(spark: SparkSession, label: str, build: Callable[[], DataFrame]) -> DataFrame:
    """What ``build`` returns, settled; all other paths that it made are removed, whether it succeeds or not."""
    target, made = fresh_path(spark, label), []
    _OPEN.append(made)
    try:
        df = build()
        df.write.parquet(target)
        schema = df.schema
    finally:
        _OPEN.remove(made)
        for path in made:
            remove(spark, path)
    return spark.read.schema(schema).parquet(target)


def ship(spark: SparkSession) -> None:
    """Gives executors this package's source, once for each Spark context."""
    sc = spark.sparkContext
    if getattr(sc, "_windowforge_shipped", False):
        return
    target = os.path.join(tempfile.mkdtemp(prefix="windowforge-src-"), "windowforge_src.zip")
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted(PACKAGE.rglob("*.py")):
            z.write(p, p.relative_to(PACKAGE.parent))
    sc.addPyFile(target)
    sc._windowforge_shipped = True
