"""Spark-native tuplewise statistics: averages of a kernel over pairs and tuples of rows."""

from __future__ import annotations

import os


def workers_find_us(spark) -> None:
    """Let Python workers import this package from where the driver has it.

    Workers that share the driver's file system (local mode, a mounted repository) get its root on
    their path with every function shipped from now on; elsewhere the package has to be shipped
    (--py-files) and the extra entry is ignored."""
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    env = spark.sparkContext.environment
    have = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if root not in have:
        env["PYTHONPATH"] = os.pathsep.join([*have, root])
