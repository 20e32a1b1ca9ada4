"""Makes the package importable in Python workers whatever way the session was started."""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import zipfile
from functools import wraps
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = Path(__file__).resolve().parent.parent
_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Sends a zip of the package to the executors once per application, unless their path has it."""
    if str(ROOT) in os.environ.get("PYTHONPATH", "").split(os.pathsep):
        return
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    folder = tempfile.mkdtemp()  # the driver serves the zip while the application runs
    atexit.register(shutil.rmtree, folder, ignore_errors=True)
    path = Path(folder) / "rangegraph.zip"
    with zipfile.ZipFile(path, "w") as z:
        for f in [*(ROOT / "rangegraph").rglob("*.py"), *ROOT.glob("corpus_pipeline.py")]:
            z.write(f, f.relative_to(ROOT))
    spark.sparkContext.addPyFile(str(path))
    _shipped.add(app)


def shipped(query):
    """The query, with the package sent first."""

    @wraps(query)
    def run(spark, sf_dir):
        ship(spark)
        return query(spark, sf_dir)

    return run
