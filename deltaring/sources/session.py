"""What a session needs before Python functions of this package run on executors."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession


def ship(spark: SparkSession) -> SparkSession:
    """Send the package to the executors' Python workers, once per Spark context."""
    sc = spark.sparkContext
    if getattr(sc, "_deltaring_shipped", False):
        return spark
    top = Path(__file__).resolve().parents[1]
    fd, name = tempfile.mkstemp(prefix="deltaring-", suffix=".zip")
    os.close(fd)
    with zipfile.ZipFile(name, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(top.rglob("*.py")):
            z.write(p, p.relative_to(top.parent).as_posix())
    sc.addPyFile(name)
    sc._deltaring_shipped = True
    return spark
