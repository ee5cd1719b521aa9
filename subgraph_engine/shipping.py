"""Makes the package importable by Python workers that were not started beside it."""

from __future__ import annotations

import os
import shutil
import tempfile
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = Path(__file__).resolve().parents[1]
_shipped: set[str] = set()


def reach_workers(spark: SparkSession) -> None:
    """Adds the package to the job, unless PYTHONPATH or the working folder already leads workers to it."""
    context = spark.sparkContext
    paths = {os.path.realpath(p) for p in os.environ.get("PYTHONPATH", "").split(os.pathsep) if p}
    if str(ROOT) in paths or os.path.realpath(os.getcwd()) == str(ROOT) or context.applicationId in _shipped:
        return
    folder = tempfile.mkdtemp(prefix="subgraph_engine_zip_")
    archive = shutil.make_archive(f"{folder}/subgraph_engine_package", "zip", ROOT, "subgraph_engine")
    context.addPyFile(archive)
    _shipped.add(context.applicationId)
