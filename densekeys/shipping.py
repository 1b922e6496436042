"""The package travels with the job: executors get it as an archive, wherever they run."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import weakref
import zipfile
from collections.abc import Callable
from functools import wraps
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_sent: weakref.WeakSet = weakref.WeakSet()


def ship(spark: SparkSession) -> None:
    """Once for each context. The driver serves the archive to executors from its own folder until it ends."""
    context = spark.sparkContext
    if context in _sent:
        return
    root = Path(__file__).resolve().parent
    folder = tempfile.mkdtemp(prefix="densekeys-")
    atexit.register(shutil.rmtree, folder, ignore_errors=True)
    archive = Path(folder) / "densekeys.zip"
    with zipfile.ZipFile(archive, "w", zipfile.ZIP_DEFLATED) as out:
        for path in sorted(root.rglob("*.py")):
            out.write(path, str(path.relative_to(root.parent)))
    context.addPyFile(str(archive))
    _sent.add(context)


def shipped(query: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    @wraps(query)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return query(spark, sf_dir)

    return run
