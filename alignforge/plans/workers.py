"""Makes the library importable in Python workers, wherever the driver was started."""

from __future__ import annotations

import os
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = str(Path(__file__).resolve().parents[2])


def visible(spark: SparkSession) -> SparkSession:
    """Adds the library's folder to the PYTHONPATH that Python functions of this session carry with them.

    For workers that see the driver's folders; on other clusters ship the package with --py-files.
    """
    env = spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if ROOT not in paths:
        env["PYTHONPATH"] = os.pathsep.join([ROOT, *paths])
    return spark
