"""Gives the executors the package where they cannot import it by themselves."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = Path(__file__).resolve().parents[2]
_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Add the package to the session's files, once for each application.

    Nothing is done where the workers inherit a path that holds it.
    """
    context = spark.sparkContext
    known = [os.getcwd(), *os.environ.get("PYTHONPATH", "").split(os.pathsep)]
    if context.applicationId in _shipped or any(p and Path(p).resolve() == ROOT for p in known):
        return
    path = Path(tempfile.mkdtemp(prefix="cellcluster-ship-")) / "cellcluster.zip"
    with zipfile.ZipFile(path, "w") as out:
        for f in [*(ROOT / "cellcluster").rglob("*.py"), *ROOT.glob("corpus_pipeline.py")]:
            out.write(f, f.relative_to(ROOT))
    context.addPyFile(str(path))
    _shipped.add(context.applicationId)
