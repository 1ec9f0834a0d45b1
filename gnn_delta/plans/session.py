"""What a running session needs before Python functions of this package reach its executors."""

from __future__ import annotations

import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = Path(__file__).resolve().parents[1]


def ship(spark: SparkSession) -> SparkSession:
    """Send this package to all executors, once per Spark context."""
    context = spark.sparkContext
    if getattr(context, "_gnn_delta_shipped", False):
        return spark
    target = Path(tempfile.mkdtemp(prefix="gnn-delta-")) / "gnn_delta.zip"
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
        for file in sorted(ROOT.rglob("*.py")):
            z.write(file, Path(ROOT.name) / file.relative_to(ROOT))
    context.addPyFile(str(target))
    context._gnn_delta_shipped = True
    return spark
