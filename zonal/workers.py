"""Python workers must find this package when it isn't installed on the executors."""

from __future__ import annotations

from pathlib import Path

from pyspark.sql import SparkSession


def let_workers_import(spark: SparkSession) -> None:
    """Put the folder that holds this package on the import path of workers started later.

    For a checkout on a path that driver and executors share; elsewhere install the package
    or ship it with ``--py-files``.
    """
    root = str(Path(__file__).resolve().parent.parent)
    env = spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", "").split(":") if p]
    if root not in paths:
        env["PYTHONPATH"] = ":".join([root, *paths])
