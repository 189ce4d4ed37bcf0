"""Bringing the package to executors that don't share the driver's folders."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Add the package as a zip file to the session's Python path, once per application."""
    sc = spark.sparkContext
    if sc.applicationId in _shipped:
        return
    root = Path(__file__).resolve().parents[2]
    target = os.path.join(tempfile.mkdtemp(prefix="pointtree-"), "pointtree.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
        for p in [*sorted((root / "pointtree").rglob("*.py")), *sorted(root.glob("corpus_pipeline.py"))]:
            z.write(p, p.relative_to(root))
    sc.addPyFile(target)
    _shipped.add(sc.applicationId)
