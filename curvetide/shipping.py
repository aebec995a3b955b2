"""Sends the package to Python workers that can't import it from where they run."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_SENT = "_curvetide_sent"


def ship(spark: SparkSession) -> None:
    """Once for each Spark context, as one zip through Spark's own file server."""
    context = spark.sparkContext
    if getattr(context, _SENT, False):
        return
    root = Path(__file__).resolve().parent
    path = os.path.join(tempfile.mkdtemp(prefix="curvetide-"), "curvetide.zip")
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
        for f in sorted(root.rglob("*.py")):
            z.write(f, f.relative_to(root.parent))
    context.addPyFile(path)
    setattr(context, _SENT, True)
