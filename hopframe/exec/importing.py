"""Lets Python workers import this package where it is not installed."""

from __future__ import annotations

import os
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = str(Path(__file__).resolve().parents[2])


def importable(spark: SparkSession) -> None:
    """Puts the package's folder on the path of workers started from now on; a remote session is left as it is."""
    environment = getattr(getattr(spark, "_sc", None), "environment", None)
    if environment is not None:
        paths = environment.get("PYTHONPATH", "").split(os.pathsep)
        if ROOT not in paths:
            environment["PYTHONPATH"] = os.pathsep.join([ROOT, *(p for p in paths if p)])
