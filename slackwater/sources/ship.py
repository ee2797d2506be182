"""Gets this package to executors that would not find it."""

from __future__ import annotations

import os
import tempfile
import zipfile
from collections.abc import Callable
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

ROOT = Path(__file__).resolve().parents[2]
_sent: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Adds the package to the session's files once, unless the workers' path holds it: by PYTHONPATH, or by the folder
    that a local session was started in. Spark hands the archive from the driver to every executor."""
    context = spark.sparkContext
    found = str(ROOT) in os.environ.get("PYTHONPATH", "").split(os.pathsep) or (context.master.startswith("local[") and Path.cwd() == ROOT)
    if found or context.applicationId in _sent:
        return
    _sent.add(context.applicationId)
    archive = os.path.join(tempfile.mkdtemp(), f"{ROOT.name}.zip")
    with zipfile.ZipFile(archive, "w") as z:
        for path in (ROOT / "slackwater").rglob("*.py"):
            z.write(path, path.relative_to(ROOT))
    context.addPyFile(archive)


def shipped(query: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return query(spark, sf_dir)

    return run
