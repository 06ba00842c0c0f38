"""Spark-native motion-agreement forensics, with operators for training-data preparation."""

from __future__ import annotations

import os

_ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def ready(spark) -> None:
    """Lets Python workers import this package from where the driver has it. Where executors don't see that folder, ship the package with addPyFile()."""
    env = spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if _ROOT not in paths:
        env["PYTHONPATH"] = os.pathsep.join([_ROOT, *paths])
