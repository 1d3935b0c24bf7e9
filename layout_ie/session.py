"""Sending this package to the Python workers."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession


def ship(spark: SparkSession) -> None:
    """Let workers import the package wherever they run: its sources go along once per application."""
    context = spark.sparkContext
    if getattr(context, "_layout_ie_shipped", False):
        return
    root = Path(__file__).resolve().parent
    if root.is_dir():  # nothing to send where the package was itself sent as an archive
        folder = tempfile.mkdtemp(prefix="package-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        with zipfile.ZipFile(f"{folder}/{root.name}.zip", "w", zipfile.ZIP_DEFLATED) as archive:
            for file in sorted(root.rglob("*.py")):
                archive.write(file, file.relative_to(root.parent))
        context.addPyFile(f"{folder}/{root.name}.zip")
    context._layout_ie_shipped = True


def shipped(df: DataFrame) -> DataFrame:
    """``df``, for operators whose workers import this package."""
    ship(df.sparkSession)
    return df
