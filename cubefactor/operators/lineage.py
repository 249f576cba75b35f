"""Cutting lineage through tables in the folder that driver and executors share."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_SHIPPED: set[str] = set()


def ship_package(spark: SparkSession) -> None:
    """Send this package's sources to the executors once per application, for Python workers to import."""
    context = spark.sparkContext
    if context.applicationId in _SHIPPED:
        return
    root = Path(__file__).resolve().parents[2]
    target = Path(tempfile.mkdtemp(prefix="ship_")) / "cubefactor_engine.zip"
    with zipfile.ZipFile(target, "w") as archive:
        for path in sorted((root / "cubefactor").rglob("*.py")):
            archive.write(path, path.relative_to(root))
    context.addPyFile(str(target))
    _SHIPPED.add(context.applicationId)


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or a local folder where a session on one machine sets none."""
    configured = spark.conf.get("spark.checkpoint.dir", None)
    if configured:
        return configured
    if not spark.sparkContext.master.startswith("local["):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    fallback = os.path.join(tempfile.gettempdir(), "cubefactor-checkpoints")
    os.makedirs(fallback, exist_ok=True)
    return f"file://{fallback}"


def written(frame: DataFrame, name: str) -> DataFrame:
    """Write the rows to the shared folder and read them back: later steps survive the loss of any executor."""
    spark = frame.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    frame.write.parquet(path)
    return spark.read.schema(frame.schema).parquet(path)
